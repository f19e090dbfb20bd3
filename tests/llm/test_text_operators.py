import hashlib
import re
from collections import Counter

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from deltamatch.llm import bpe, licenses, mixing, quality_knn, quality_rules, secrets, simhash, toxicity
from deltamatch.llm.common import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="session")
def codec():
    return bpe.public_codec()


@pytest.fixture(scope="session")
def reference():
    import public_tokenizers
    import tiktoken

    ranks = bpe.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


# Byte-level BPE


def test_codec_equals_the_library_and_decodes_back(codec, reference, spark, sf):
    for row in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect():
        ids = codec.encode(row.text or "")
        assert np.frombuffer(ids, "<u4").tolist() == reference.encode_ordinary(row.text or "")
        assert codec.decode(ids) == (row.text or "").encode()


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet=st.characters(exclude_categories=["Cs"]), max_size=60))
def test_codec_on_any_text(text):
    import public_tokenizers
    import tiktoken

    global _pair
    if "_pair" not in globals():
        ranks = bpe.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
        _pair = bpe.public_codec(), tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    assert np.frombuffer(_pair[0].encode(text), "<u4").tolist() == _pair[1].encode_ordinary(text)


def test_perfect_hash_fills_every_slot():
    keys = {f"key{i}".encode(): i for i in range(2000)}
    table = bpe.PerfectHash.build(keys)
    assert table.slots == len(keys) == len(set(table.keys))
    assert all(table.get(k) == v for k, v in keys.items())
    assert table.get(b"other") == -1
    assert bpe.PerfectHash.build({}).get(b"") == -1


def test_encode_odd_rows(odd, none, codec):
    got = bpe.encode_digests(odd, codec).collect()
    assert len(got) == odd.count() and bpe.encode_digests(none, codec).count() == 0
    empty = hashlib.sha256(b"").hexdigest()
    assert [(r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in got if r.doc_id in (1, 2)] == [(0, empty, empty)] * 2
    assert bpe.encode_documents(odd, codec).count() == odd.count()


# SimHash


def plain_fingerprint(text, width=3):
    words = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_groups(ids_prints, bits):
    parent = {p: p for _, p in ids_prints}

    def find(p):
        while parent[p] != p:
            p = parent[p]
        return p

    names = list(parent)
    for i, a in enumerate(names):
        for b in names[i + 1 :]:
            if (a ^ b).bit_count() <= bits:
                parent[find(b)] = find(a)
    least = {}
    for d, p in ids_prints:
        least[find(p)] = min(least.get(find(p), 1 << 62), d)
    return sorted((d, least[find(p)]) for d, p in ids_prints)


def test_simhash_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    prints = [(r.doc_id, plain_fingerprint(r.text)) for r in docs.collect()]
    got = simhash.near_duplicates(docs).collect()
    assert {r.doc_id: r.fingerprint for r in got} == {d: f"{p:016x}" for d, p in prints}
    assert sorted((r.doc_id, r.component_id) for r in got) == plain_groups(prints, 3)


def test_crowded_buckets_keep_every_link(spark):
    rng = np.random.default_rng(5)
    base = int(rng.integers(0, 1 << 62))
    prints = [(i, base ^ sum(1 << int(b) for b in rng.choice(60, int(rng.integers(0, 5)), replace=False))) for i in range(400)]
    prints += [(1000 + i, int(rng.integers(0, 1 << 62))) for i in range(50)]
    df = spark.createDataFrame(prints, "doc_id bigint, fp bigint")
    got = simhash.groups(df, crowd=8).select("doc_id", "component_id").collect()
    assert sorted(map(tuple, got)) == plain_groups(prints, 3)


def test_forest_spans_the_groups_of_all_pairs():
    rng = np.random.default_rng(1)
    values = np.unique(rng.integers(0, 1 << 12, 200))
    edges = simhash.forest(values, 1)
    assert all((a ^ b).bit_count() <= 1 for a, b in edges)
    groups = {c for _, c in plain_groups([(i, int(v)) for i, v in enumerate(values)], 1)}
    assert len(values) - len(edges) == len(groups)


def test_simhash_odd_rows(odd, none):
    got = {(r.doc_id, r.component_id) for r in simhash.near_duplicates(odd).collect()}
    assert {(1, 1), (2, 1), (7, 1)} <= got and {(4, 4), (5, 4)} <= got
    assert simhash.near_duplicates(none).count() == 0


def test_deduplicate_keeps_one_of_each_group(spark, sf, odd, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text or "" for r in docs.collect()}

    def shingles(t):
        words = t.encode().lower().split()
        return {b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()

    sets = {d: shingles(t) for d, t in texts.items()}
    kept = {r.doc_id for r in simhash.deduplicate(docs).collect()}
    alike = [(a, b) for a in sets for b in sets if a < b and (sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]))]
    assert not [p for p in alike if set(p) <= kept]
    near = {x for p in alike for x in p}
    assert set(texts) - kept <= near
    out = simhash.deduplicate(odd)
    assert out.columns == odd.columns
    ids = Counter(r.doc_id for r in out.collect())
    assert ids[4] == 1 and ids[5] == 0 and ids[None] == 1 and ids[1] == 1 and ids[2] == ids[7] == 0 or ids[7] == 1
    assert simhash.deduplicate(none).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (102, 100), (7, 7)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()))
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100, 102: 100}
    assert components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


# Licenses


def test_license_base_equals_brute_force(spark, sf, odd, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    for r in licenses.scan(docs).collect():
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in texts[r.doc_id]))
        places = sorted((i, label) for p, label in licenses.PHRASES.items() for i in range(len(words)) if words[i : i + len(p.split())] == p.split())
        assert (r.n_words, r.n_base, r.base_labels) == (len(words), len(places), ",".join(sorted({x for _, x in places})))
        assert (r.first_word, r.last_word) == ((places[0][0], places[-1][0]) if places else (None, None))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert licenses.scan(odd).count() == odd.count() and licenses.scan(none).count() == 0


def test_template_join_equals_all_pairs():
    rng = np.random.default_rng(2)
    words = [f"w{i}" for i in range(30)]
    templates = [(f"t{i}", " ".join(rng.choice(words, int(rng.integers(1, 14)), replace=False))) for i in range(16)]
    ready = licenses.Templates(templates, {w.encode(): int(rng.integers(0, 50)) for w in words}, 0.7)
    for _ in range(300):
        block = [w.encode() for w in rng.choice(words, int(rng.integers(1, 25)))]
        want = {}
        for label, text in templates:
            t = {w.encode() for w in text.split()}
            if len(t & set(block)) >= 0.7 * len(t) - 1e-9:
                want[label] = len(t & set(block)) / len(t)
        assert ready.matches(block) == want


def test_license_notice_without_a_phrase(spark):
    text = "hello\n\nRedistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions are met\n\nend"
    row = licenses.scan(spark.createDataFrame([(1, text)], "doc_id bigint, text string")).first()
    assert row.labels == "bsd" and row.n_base == 0 and row.score == 1.0


def test_license_blocks_cover_lines_paragraphs_and_neighbours():
    got = [b" ".join(b).decode() for b in licenses.blocks("A b\nc\n\n \nd\n\ne f\n")]
    assert got == ["a b", "c", "a b c", "d", "a b c d", "e f", "d e f"]
    assert list(licenses.blocks(None)) == list(licenses.blocks("\n \n")) == []


def test_license_notice_across_an_empty_line_with_changes(spark):
    text = "x\n\nThis program is free software: you may redistribute it and/or change it under the\n\nterms of the GNU General Public Licence as published by the Free Software Foundation\n\ny"
    rows = spark.createDataFrame([(1, text), (2, "released under the terms of a license\n\nmit"), (3, None)], "doc_id bigint, text string")
    assert {r.doc_id: (r.labels, r.n_base) for r in licenses.scan(rows).collect()} == {1: ("gpl,lgpl", 0), 2: ("", 0), 3: ("", 0)}


# Secrets


def plain_spans(text):
    found = [(m.start(), 0, m.end()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.ASCII | re.IGNORECASE) if len(m[2]) >= 12]
    found += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 18]
    found += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 16]
    return [(a, b, secrets.KINDS[k]) for a, k, b in sorted(found)]


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=list("AKIAtoken=:'\" 0123abcdefXYZ_.-ſK"), max_size=80))
def test_base_spans_equal_the_plain_forms(text):
    assert secrets.base_spans(text) == plain_spans(text)


def test_secret_scan(spark, sf, odd, none, codec):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    for r in secrets.scan(docs, codec).collect():
        want = plain_spans(texts[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, b, k in want).encode()).hexdigest()
    assert secrets.scan(odd, codec).count() == odd.count() and secrets.scan(none, codec).count() == 0


def test_token_efficiency_tells_random_strings(codec):
    found = lambda t: [t[a:b] for a, b, k in secrets.secret_spans(t, codec)[1] if k == "random"]
    key = "q9X4vL0zT7mB2kR8wE5yU1sH"
    assert found(f"use {key} here") == [key]
    assert not found("internationalization_of_configuration_parameters and AbstractSingletonProxyFactoryBean")
    assert not found("550e8400-e29b-41d4-a716-446655440000 D41D8CD98F00B204E9800998ECF8427E 12345678901234567890123")


def test_redaction_masks_and_keeps_rows(odd, codec):
    out = {r.doc_id: r for r in secrets.redact(odd, codec).collect()}
    assert len(secrets.redact(odd, codec).collect()) == odd.count()
    assert "AKIA" not in out[9].text and out[9].text.count("[SECRET]") == 3 and out[9].n_chars == len(out[9].text)
    assert out[2].text is None


# Quality rules


def plain_counts(text):
    words = WORD.findall(text or "")
    triples = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = Counter(triples)
    covered = {j for i, t in enumerate(triples) if often[t] > 1 for j in (i, i + 1, i + 2)}
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), dup, len(covered)


def test_quality_counts_equal_brute_force(spark, sf, odd, none):
    for docs in (spark.read.parquet(f"{sf}/documents.parquet"), odd.where("doc_id is not null").dropDuplicates(["doc_id"])):
        texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
        rows = quality_rules.quality_verdicts(docs).collect()
        assert len(rows) == len(texts)
        for r in rows:
            want = plain_counts(texts[r.doc_id])
            assert tuple(r[c] for c in quality_rules.COUNTS) == want
            assert r.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0])
            assert not (r.base_failed and r.kept)
    assert quality_rules.quality_verdicts(none).count() == 0


def test_quality_filter_agrees_with_the_verdicts(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = sorted(r.doc_id for r in quality_rules.quality_verdicts(docs).where("kept").collect())
    out = quality_rules.filter_documents(docs)
    assert out.columns == docs.columns and sorted(r.doc_id for r in out.collect()) == want


def test_quality_runs_no_python(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plan = quality_rules.with_counts(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


# Mixing


def test_mix_meets_weights_and_keeps_all(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = mixing.mix_report(docs, max_repeats=2.0).collect()
    assert {r.doc_id for r in out} == {r.doc_id for r in docs.collect()}
    assert len({(r.doc_id, r.epoch) for r in out}) == len(out)
    total = sum(r.n_tokens for r in out)
    for source in {r.source for r in out}:
        rows = [r for r in out if r.source == source]
        assert sum(r.n_tokens for r in rows) / total == pytest.approx(rows[0].weight, abs=0.05)
    assert all(0 <= r.position < 1 for r in out)


def test_mix_limits(spark):
    rows = [(i, "a" if i % 4 else "b", "w " * (1 + i % 7)) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id bigint, source string, text string")
    out = mixing.mix_report(docs, max_repeats=1.5).collect()
    count = Counter((r.doc_id) for r in out)
    assert max(count.values()) == 2 and min(count.values()) == 1
    tokens = Counter()
    for r in out:
        tokens[r.source] += r.n_tokens
    own = {s: sum(1 + i % 7 for i, t, _ in rows if t == s) for s in "ab"}
    assert tokens["a"] == own["a"] and 1.4 * own["b"] < tokens["b"] <= 1.5 * own["b"] + 1
    even = mixing.mix_report(docs, entropy=1.0, max_repeats=None)
    sums = {r.source: r[1] for r in even.groupBy("source").sum("n_tokens").collect()}
    assert sums["a"] == pytest.approx(sums["b"], rel=0.05)
    half = mixing.mix_report(docs, max_repeats=1.0, budget=sum(own.values()) / 2).collect()
    assert sum(r.n_tokens for r in half) == pytest.approx(sum(own.values()) / 2, rel=0.05)


def test_exponent_meets_its_targets(spark):
    tokens = {"a": 5000, "b": 1200, "c": 90, "d": 7, None: 333, "empty": 0}
    shares = mixing.sources(spark.createDataFrame(list(tokens.items()), "source string, n_tokens bigint"))
    p = np.array([n for n in tokens.values() if n]) / sum(tokens.values())

    def entropy(a):
        w = p**a / (p**a).sum()
        return -(w * np.log(w)).sum()

    own = entropy(1.0) / np.log(len(p))
    for target in (0.5, 0.8, 0.95):
        a = mixing.exponent(shares, entropy=target)
        assert own < target and entropy(a) / np.log(len(p)) == pytest.approx(target, abs=1e-6)
        assert mixing.mix_entropy(shares, a) == pytest.approx(entropy(a))
    assert mixing.exponent(shares, entropy=own / 2) == 1.0 and mixing.exponent(shares, entropy=1.0) < 1e-4
    for limit in (1.0, 2.0, 50.0):
        assert (p.max() / p.min()) ** (1 - mixing.exponent(shares, max_repeats=limit)) == pytest.approx(limit)
    assert mixing.exponent(shares, max_repeats=1e6) == 0.0
    assert mixing.exponent(shares, entropy=0.95, max_repeats=2.0) == mixing.exponent(shares, max_repeats=2.0)
    assert mixing.exponent(shares.limit(0), entropy=0.9, max_repeats=2.0) == 1.0


def test_mix_odd_rows(odd, none):
    out = mixing.mix_documents(odd)
    assert out.columns == odd.columns and out.count() >= odd.count()
    assert mixing.mix_documents(none).count() == 0


# Classifiers


def held_out_accuracy(spark, sf, rows, label):
    truth = {r.doc_id: r[label] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    held = [r for r in rows if r.held_out and truth.get(r.doc_id) is not None]
    return sum(r.predicted == truth[r.doc_id] for r in held) / len(held)


def test_quality_neighbours(spark, odd, none):
    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    rows = quality_knn.classify(docs, labels).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.7) for r in rows)
    assert held_out_accuracy(spark, sf, rows, "quality") >= 0.95
    assert quality_knn.classify(odd, labels).count() == odd.count() and quality_knn.classify(none, labels).count() == 0
    assert {r.score for r in quality_knn.classify(odd, labels.limit(0)).collect()} == {0.5}


def test_toxicity(spark, odd, none):
    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.classify(docs, labels).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)
    assert held_out_accuracy(spark, sf, rows, "toxic") >= 0.88
    assert toxicity.classify(odd, labels).count() == odd.count() and toxicity.classify(none, labels).count() == 0
    assert {r.score for r in toxicity.classify(odd, labels.limit(0)).collect()} == {0.0}


def test_kernel_equals_plain_subsequences():
    def plain(a, b):
        def features(w):
            out = Counter()
            w = "".join(filter(str.isalpha, w))
            for i in range(len(w)):
                for j in range(i + 1, min(len(w), i + toxicity.SPAN)):
                    for k in range(j + 1, min(len(w), i + toxicity.SPAN)):
                        out[w[i] + w[j] + w[k]] += toxicity.DECAY ** (k - i + 1)
            return out

        x, y = features(a), features(b)
        dot = lambda p, q: sum(v * q[t] for t, v in p.items())
        return dot(x, y) / max((dot(x, x) * dot(y, y)) ** 0.5, 1e-12)

    marks = toxicity.Landmarks(["idiot", "worthless"])
    words = ["idiot", "id*iot", "i.d.i.o.t", "idioot", "worthlesss", "harmless", "id***iot", "i--d--i--o--t", "i**d**i**o**t", "ixdxixoxt", "--", "a-b"]
    marks.compare(words)
    for w in words:
        want = [plain(w, m) for m in marks.words]
        got = marks.close[w] if marks.close[w] is not None else np.zeros(2)
        assert got == pytest.approx([k**3 if k >= toxicity.FLOOR else 0 for k in want], abs=1e-5)
    assert all(marks.close[w][0] == pytest.approx(1, abs=1e-5) for w in ("id*iot", "id***iot", "i--d--i--o--t", "i**d**i**o**t"))
    assert all("idiot" in toxicity.words_of(f"what an {w} you are") for w in ("i d i o t", "i  d  i  o  t", "i__d__i__o__t"))
    assert toxicity.words_of("_ " * 50_000 + "x") == {"x"} and toxicity.words_of("_" * 100_000) == set()


# Near-duplicate groups keep every link


def plain_similar(rows, width=5):
    sets = {}
    for d, t in rows:
        words = t.encode().lower().split()
        sets[d] = {b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))} if words else set()
    root = {d: d for d in sets}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    for a in sets:
        for b in sets:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                low, high = sorted((find(a), find(b)))
                root[high] = low
    return sorted((d, find(d)) for d in sets)


def similar(spark, rows):
    return sorted(map(tuple, simhash.similar_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()))


def test_copies_of_one_original_all_meet_it(spark):
    rng = np.random.default_rng(3)
    base = [f"w{x}" for x in rng.integers(0, 5000, 300)]
    rows = [(1000, " ".join(base))]
    for i in range(60):
        words = list(base)
        for at in rng.choice(300, 6, replace=False):
            words[at] = f"n{rng.integers(0, 10**9)}"
        rows.append((i if i % 2 else 2000 + i, " ".join(words)))
    assert similar(spark, rows) == plain_similar(rows)


def test_block_edits_are_found(spark):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(60):
        words = [f"w{x}" for x in rng.integers(0, 3000, int(rng.integers(80, 400)))]
        n = len(words)
        more = [f"x{x}" for x in rng.integers(0, 3000, n // 6)]
        edited = (words[: n - n // 6], words + more, words[: n // 2] + words[n // 2 + n // 7 :], more + words)[i % 4]
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(edited))]
    want = plain_similar(rows)
    assert sum(d != c for d, c in want) > 50
    assert similar(spark, rows) == want


def test_a_crowd_changes_no_pair(spark):
    """Pairs 6 to 10 bits apart in a crowd of over 1024 texts that share most words, as alone."""
    rng = np.random.default_rng(6)
    stock = [f"w{x}" for x in range(120)]
    rows = []
    for i in range(700):
        words = [stock[x] for x in rng.permutation(120)]
        edited = words[:-14] + [f"n{rng.integers(0, 10**9)}" for _ in range(6)]
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(edited))]
    want = sorted((d, d - d % 2) for d, _ in rows)
    assert plain_similar(rows[:200]) == want[:200]
    assert similar(spark, rows) == want


def test_secret_scan_takes_linear_time_on_very_long_runs(codec):
    """A single run of a million characters, of whatever classes, ends soon; an ambiguous pattern would take ages on forty."""
    import time

    letters = "abcdefghijklmnopqrstuvwxyz"
    for run in ("7" * 10**6 + "a1", letters * 40_000 + "B", "camelCase" * 110_000, "a1" * 50_000, "Ab1" * 40_000 + "c"):
        began = time.perf_counter()
        secrets.secret_spans(f"x {run} y", codec)
        assert time.perf_counter() - began < 10


def test_names_are_told_from_keys_as_by_the_ambiguous_form():
    """The unambiguous pattern accepts what its plain reading does: words of two letters or more, in one case or capitalised, numbers and joints."""
    import random
    import re

    plain, draw = re.compile("(?:[A-Z]?[a-z]{2,}|[A-Z]{2,}|[0-9]{1,8}|[+/_=-])+"), random.Random(5)
    for _ in range(50_000):
        run = "".join(draw.choices("aabbABC12-_", k=draw.randint(0, 10)))
        assert bool(plain.fullmatch(run)) == bool(secrets._NAME.fullmatch(run)), run


def test_wide_fingerprints_pass_all_alike_pairs():
    """Sets at the least similarity, of any size that is judged, stay within the allowed bits; unlike ones mostly don't."""
    rng = np.random.default_rng(8)
    most, passed = simhash.widest(0.8), 0
    apart = lambda a, b: sum(((x ^ y) & (1 << 64) - 1).bit_count() for x, y in zip(simhash.wide_fingerprint(a), simhash.wide_fingerprint(b)))
    for n in (18, 45, 90, 900):
        for _ in range(150):
            both, left, right, other = (rng.integers(-(1 << 62), 1 << 62, k) for k in (n * 8 // 9, n // 9, n // 9, n))
            assert apart(np.concatenate([both, left]), np.concatenate([both, right])) <= most
            passed += apart(np.concatenate([both, left]), other) <= most
    assert not passed


def test_an_order_from_a_full_table_misses_no_pair(spark, monkeypatch):
    """Shingles that share a cell, as in a table too small for its corpus, only change the order."""
    real = simhash.commonness
    monkeypatch.setattr(simhash, "commonness", lambda rows, width: real(rows, width, share=1, least=1, cells_log2=6))
    rng = np.random.default_rng(9)
    rows = []
    for i in range(80):
        words = [f"w{x}" for x in rng.integers(0, 400, 120)]
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(words[:-8] + ["new"]))]
    want = plain_similar(rows)
    assert sum(d != c for d, c in want) >= 80
    assert similar(spark, rows) == want


def test_pairs_whose_first_member_differs_are_still_met(spark):
    """Three texts of the same words: one shuffled, the other two one swap apart."""
    words = [f"w{x}" for x in range(200)]
    swapped = words[:100] + [words[101], words[100]] + words[102:]
    rows = [(1, " ".join(sorted(words))), (2, " ".join(words)), (3, " ".join(swapped))]
    assert similar(spark, rows) == [(1, 1), (2, 2), (3, 2)]


def test_near_copies_come_from_the_pigeonhole_blocks(spark, monkeypatch):
    """Pairs within three bits are found by the blocks, with or without the prefix join, and verified; those further apart by the join."""
    rng = np.random.default_rng(10)
    draw = lambda n: [f"w{x}" for x in rng.integers(0, 10**6, n)]
    hashes = lambda words: np.array(simhash.shingle_hashes(" ".join(words), 5), dtype=np.int64)
    bits = lambda a, b: ((simhash.wide_fingerprint(hashes(a))[0] ^ simhash.wide_fingerprint(hashes(b))[0]) & (1 << 64) - 1).bit_count()
    pairs = []
    for n, edits in [(400, 1)] * 20 + [(60, 6)] * 20:
        words = draw(n)
        pairs.append((words, words[:-edits] + draw(edits)))
    unlike = None
    while unlike is None:  # within three bits, but only 50 of 70 shingles alike
        words = draw(64)
        other = words[:20] + draw(1) + words[21:40] + draw(1) + words[41:]
        unlike = (words, other) if bits(words, other) <= 3 else None
    pairs.append(unlike)
    rows = [(2 * i + j, " ".join(words)) for i, pair in enumerate(pairs) for j, words in enumerate(pair)]
    close = [bits(*pair) <= 3 for pair in pairs]
    assert sum(close[:40]) >= 10 and not all(close[:40])
    want = [(2 * i + j, 2 * i + j * (i == 40)) for i in range(41) for j in (0, 1)]
    assert plain_similar(rows) == want
    used, links = [], simhash.links
    monkeypatch.setattr(simhash, "links", lambda fps, **options: (used.append(options), links(fps, **options))[1])
    assert similar(spark, rows) == want
    assert used == [{"max_bits": 3, "blocks": 6}]
    monkeypatch.setattr(simhash, "_heads", lambda *_: spark.createDataFrame([], "key bigint, id bigint, at int"))
    assert similar(spark, rows) == [(d, c if close[d // 2] else d) for d, c in want]


def test_blocked_candidates_connect_what_all_pairs_would(spark):
    rng = np.random.default_rng(11)
    bases = [int(x) for x in rng.integers(0, 1 << 62, 30)]
    prints = [(i, base ^ sum(1 << int(b) for b in rng.choice(64, int(rng.integers(0, 4)), replace=False))) for i, base in enumerate(bases * 6)]
    signed = [(i, 5, p - (1 << 64) if p >= 1 << 63 else p) for i, p in prints]
    got = simhash._blocked(spark.createDataFrame([*signed, (900, 0, 0), (901, 0, 0)], "first bigint, size int, f0 bigint"), 3, 6)
    found = dict(map(tuple, components(got.select(got.x.alias("a"), got.y.alias("b"))).collect()))
    assert sorted((d, found.get(d, d)) for d, _ in prints) == plain_groups(prints, 3)
    assert not {900, 901} & set(found)


def test_quality_verdicts_equal_their_twin(spark, sf, odd):
    """Counts, quartiles, fences and verdicts against exact quartiles in SQL, on the tables and on odd rows."""
    from collections import Counter

    import duckdb

    from deltamatch.llm import queries, quality_rules

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    names = ["doc_id", *quality_rules.COUNTS, "base_failed", "kept"]
    whole = queries.op6_adaptive_quality(spark, sf)
    sql = f"SELECT {', '.join(names)} FROM ({queries.ORACLES['op6_adaptive_quality']})"
    got = Counter(tuple(r) for r in whole.select(*names).collect())
    assert got == Counter(con.execute(sql).fetchall()) and {r[-1] for r in got} == {True, False}
    con.execute("DROP VIEW documents")
    con.register("documents", odd.select("doc_id", "lang", "source", "text").toArrow())
    assert Counter(tuple(r) for r in quality_rules.quality_verdicts(odd).select(*names).collect()) == Counter(con.execute(sql).fetchall())
