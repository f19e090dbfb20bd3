import hashlib
import struct

import numpy as np
import pytest
import zstandard
from pyspark.sql import functions as F

import corpus_pipeline
from deltamatch.llm import ann, queries, warc
from deltamatch.llm.common import shared_dir

PAGES = "page_id bigint, url string, html string, digest string, first_id int"


def odd_pages(spark):
    long = "<p>long</p>" * 200_000
    rows = [(1, "http://a", "x" * 100), (2, None, "x" * 100), (3, "http://c\r\nEvil: 1", "x" * 99), (4, "http://d", "x" * 99), (5, "http://e", None), (6, "http://f", ""), (7, "http://g", long), (8, "http://h", long), (8, "http://h", long), (9, "é", "é\r\n\r\nWARC/1.1" * 50), (None, "n", "x" * 100)]
    return spark.createDataFrame([(*r, "d", 1) for r in rows], PAGES)


def test_round_trip_equals_the_contract(spark):
    got = {(r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.round_trip(spark, odd_pages(spark)).collect()}
    want = set()
    rows = [(r.page_id, (r.html or "").encode()) for r in odd_pages(spark).collect()]
    for page, body in rows:
        first = min(p for p, b in rows if b == body and p is not None)
        again = len(body) >= 100 and page != first
        want.add((page, len(body), hashlib.sha256(body).hexdigest(), "revisit" if again else "response", first if again else None))
    assert got == want
    assert warc.round_trip(spark, odd_pages(spark).limit(0)).count() == 0


def test_archives_are_plain_zstandard_with_a_leading_dictionary(spark):
    path = f"{shared_dir(spark)}/plain-archives"
    warc.write_archives(odd_pages(spark), path, archive_bytes=1 << 20)
    files = [bytes(r.content) for r in spark.read.format("binaryFile").load(path).where("length > 0").collect()]
    total = 0
    for data in files:
        magic, size = struct.unpack_from("<II", data)
        assert magic == warc.DICTIONARY_MAGIC
        whole = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(data[8 : 8 + size])).stream_reader(data, read_across_frames=True).read()
        total += whole.count(b"WARC-Record-ID")
        assert whole == b"".join(warc.frames(data))
    assert total == odd_pages(spark).count() and len(files) > 1


def test_records_are_dated_typed_and_named_apart(spark):
    path = f"{shared_dir(spark)}/dated-archives"
    warc.write_archives(odd_pages(spark), path, date="2020-01-02T03:04:05Z")
    got = warc.read_archives(spark, path).cache()
    assert got.select("record_id").distinct().count() == got.count() == odd_pages(spark).count()
    assert warc.unresolved(got).count() == 0
    assert warc.unresolved(got.where("page_id <> 1 OR page_id IS NULL")).count() == 2
    assert {r.url for r in got.where("page_id IN (2, 3)").collect()} == {None, "http://c%0D%0AEvil:%201"}
    for r in spark.read.format("binaryFile").load(path).where("length > 0").collect():
        for raw in warc.frames(bytes(r.content)):
            headers, _ = warc.parse(raw)
            assert headers["warc-date"] == "2020-01-02T03:04:05Z" and headers["content-type"] == "application/http;msgtype=response"
            assert (headers["warc-type"] == "revisit") == ("warc-refers-to-target-uri" in headers)
    assert {len(r.payload) for r in got.where("record_type = 'revisit'").collect()} == {0}


def test_broken_archives_are_refused():
    body = b"hello"
    good = warc.record("urn:uuid:1", "2020-01-02T03:04:05Z", 1, "u", body, hashlib.sha256(body).hexdigest())
    assert warc.payload_of(*warc.parse(good)) == body
    size = len(warc.parse(good)[1])
    for bad in (good.replace(b"WARC/1.1", b"WARC/9"), good.replace(b"Content-Length: %d" % size, b"Content-Length: %d" % (size - 1)), good.replace(b"WARC-Date", b"Date"), good.replace(b"2020-01-02T03", b"yesterday"), good.replace(b"WARC-Type", b"WARC Type"), good[:-2], b""):
        with pytest.raises(warc.BadArchive):
            warc.parse(bad)
    data = warc.archive([good, good])
    with pytest.raises(warc.BadArchive):
        list(warc.frames(data[:-3]))
    broken = bytearray(data)
    broken[-20] ^= 255
    with pytest.raises(warc.BadArchive):
        list(warc.frames(bytes(broken)))


def plain_nearest(vectors, queries_, k):
    out = {}
    for q, x in vectors.items():
        if q in queries_:
            far = sorted((float(np.sqrt(((y - x) ** 2).sum())), v) for v, y in vectors.items() if v != q)[:k]
            out[q] = far
    return out


def test_search_recall_and_scores(spark, sf):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    vectors = {r.vec_id: np.array(r.embedding, dtype=float) for r in rows}
    got = queries.op9_cross_polytope(spark, sf).collect()
    want = plain_nearest(vectors, {v for v in vectors if v % 100 == 0}, 10)
    hit = 0
    for q, near in want.items():
        mine = sorted((r for r in got if r.query_id == q), key=lambda r: r.rank)
        assert [r.rank for r in mine] == list(range(1, 11))
        assert all(r.score == pytest.approx(float(np.sqrt(((vectors[r.vec_id] - vectors[q]) ** 2).sum())), abs=1e-12) for r in mine)
        hit += len({r.vec_id for r in mine} & {v for _, v in near})
    assert hit / (10 * len(want)) >= 0.9


def test_search_odd_rows(spark):
    schema = "vec_id bigint, embedding array<float>, cell int, v string"
    good = [(i, [float(i % 5), 1.0, 2.0]) for i in range(30)]
    bad = [(100, None), (101, [0.0, 0.0, 0.0]), (102, [1.0, None, 2.0]), (103, [float("nan"), 1.0, 1.0]), (104, [float("inf"), 1.0, 1.0]), (105, []), (None, [1.0, 1.0, 1.0])]
    df = spark.createDataFrame([(*r, 1, "v") for r in good + bad], schema)
    got = ann.search(df, F.col("vec_id") % 10 == 0).collect()
    want = plain_nearest({i: np.array(v) for i, v in good}, {0, 10, 20}, 10)
    assert {q: [(r.score, r.vec_id) for r in sorted(got, key=lambda r: r.rank) if r.query_id == q] for q in want} == {q: [(pytest.approx(d), v) for d, v in near] for q, near in want.items()}
    few = ann.search(df.where("vec_id < 4"), F.col("vec_id") == 0).collect()
    assert sorted((r.rank, r.vec_id) for r in few) == [(1, 1), (2, 2), (3, 3)]
    assert ann.search(df.limit(0), F.col("vec_id") == 0).count() == 0
    same = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(300)], "vec_id bigint, embedding array<double>")
    got = ann.search(same, F.col("vec_id") == 200).collect()
    assert sorted((r.rank, r.vec_id, r.score) for r in got) == [(i + 1, i, 0.0) for i in range(10)]


def test_crowded_cells_are_split_without_loss(spark, monkeypatch):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((600, 8))
    df = spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    want = plain_nearest(dict(enumerate(x)), set(range(20)), 10)
    want = {(q, v) for q, near in want.items() for _, v in near}
    every = (ann.Plan(1, 1, 16), ann.Plan(2, 1, 256))  # all cells of one table
    found = lambda plan: {(r.query_id, r.vec_id) for r in ann.search(df, F.col("vec_id") < 20, plan=plan).collect()}
    assert all(found(plan) == want for plan in every)
    monkeypatch.setattr(ann, "CELL", 7)
    assert all(found(plan) == want for plan in every)


def test_probes_come_in_the_order_of_their_loss():
    rng = np.random.default_rng(4)
    x = rng.standard_normal((5, 8))
    plan = ann.Plan(2, 1, 40)
    turned = [ann.rotate(x, j, 11) for j in (0, 1)]
    signed = [np.concatenate([t, -t], axis=1) for t in turned]
    for i, (lead, last) in enumerate(ann.probed(x, 0, 11, plan, 40)):
        loss = (signed[0][i].max() - signed[0][i])[:, None] ** 2 + (signed[1][i].max() - signed[1][i]) ** 2
        assert len(set(zip(lead.tolist(), last.tolist()))) == 40
        assert loss[lead, last] == pytest.approx(np.sort(loss.ravel())[:40])
        assert (lead[0], last[0]) == tuple(int(a[0]) for a in ann.probed(x, 0, 11, plan, 1)[i])


def test_pairs_of_axes_find_most_of_the_nearest_in_a_small_share_of_random_rows():
    """The hard case: random directions, of which even the nearest is far off."""
    rng = np.random.default_rng(5)
    n, asked = 30_000, 40
    x = rng.standard_normal((n, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    plan = ann.plan_for(n)
    seen = np.zeros((asked, n), dtype=bool)
    for t in range(plan.tables):
        cells = np.array([lead[0] * 128 + last[0] for lead, last in ann.probed(x, t, 11, plan, 1)])
        for i, (lead, last) in enumerate(ann.probed(x[:asked], t, 11, plan, plan.probes)):
            seen[i] |= np.isin(cells, lead * 128 + last)
    near = np.argsort(-(x[:asked] @ x.T), axis=1)[:, 1:11]
    assert np.take_along_axis(seen, near, 1).mean() >= 0.9
    assert seen.mean() <= 0.16


def test_plan_does_not_follow_the_rows(spark, monkeypatch):
    plans, hashed = [], ann._hashed
    monkeypatch.setattr(ann, "_hashed", lambda rows, plan, probes, seed: (plans.append((plan, probes)), hashed(rows, plan, probes, seed))[1])
    for n in (30, 4200):
        rows = spark.range(n).selectExpr("id AS vec_id", "array(sin(id), cos(id), sin(3 * id), cos(7 * id)) AS embedding")
        assert ann.search(rows, F.col("vec_id") < 2).count() == 20
    assert plans[:2] == plans[2:]


def test_packed_vectors_keep_their_direction():
    rng = np.random.default_rng(6)
    x = rng.standard_normal((20, 64)) * 10.0 ** rng.integers(-30, 30, (20, 1))
    back = ann.unpacked([ann.packed(v) for v in x])
    assert (np.abs(back - x) <= np.abs(x).max(axis=1, keepdims=True) / 253).all()


def test_stages(spark, odd, none):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "near_duplicates", "secret_scan", "source_mixing", "byte_bpe"]
    for docs in (odd, none):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            assert stage(spark, docs, "").columns == docs.columns
        for _, stage in corpus_pipeline.STAGES:
            assert stage(spark, docs, "").count() >= 0


def test_pipeline_end_to_end(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = corpus_pipeline.run(spark, sf).collect()
    ids = {r.doc_id for r in out}
    assert 0 < len(ids) < docs.count() and len(out) >= len(ids)
    texts = {r.doc_id: r.text for r in docs.collect()}
    untouched = [r for r in out if r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()]
    assert len(untouched) > 0.8 * len(out)
    assert all(len(r.ids) == 4 * r.n_tokens for r in out)
