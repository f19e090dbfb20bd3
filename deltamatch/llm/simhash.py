"""SimHash near-dedup: fingerprints, pigeonhole blocks, verified links, groups.

Fingerprint: each word shingle is hashed (XXH64, seed 42); a bit is set if it is set in
over half of the hashes. Two fingerprints within `max_bits` bits agree on all but
`max_bits` of the blocks the 64 bits are split into, so joining on every choice of
`blocks - max_bits` blocks finds all of them. A bucket of fingerprints that share a key
yields a spanning forest of its links (at most one row per member), never all its pairs.
A bucket over `crowd` fingerprints is split again by the same argument on the bits its
key left open; what then still shares a key differs in at most 16 bits, so no group that
one task gathers holds over 65,536 fingerprints, however many copies the input holds.

`near_duplicates` groups by these links alone. `similar_groups` and `deduplicate`, for a
Jaccard similarity, start from the same links, verify them by the shingle sets and go on
to the pairs that lie further apart.

Null and empty texts have fingerprint zero, linked like any other. Repeated rows are
copies of each other. Rows with a null id keep their fingerprint and group.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import components, cut, map_rows, rekeyed

_CHUNK = 1 << 16


def fingerprint(text: str | None, width: int = 3) -> int:
    """Signed 64-bit fingerprint of a whole text; fewer words than width count as one shingle."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # on bytes: ASCII case and ASCII white space
    if not words:
        return 0
    if len(words) <= width:
        shingles = [b" ".join(words)]
    else:
        shingles = list(map(b" ".join, zip(*(words[i:] for i in range(width)))))
    ones, n = np.zeros(64, dtype=np.int64), len(shingles)
    for at in range(0, n, _CHUNK):
        part = shingles[at : at + _CHUNK]
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, part, repeat(42)), dtype="<u8", count=len(part))
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, *, width: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp bigint) of every row."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            yield {"doc_id": got["key"], "fp": [fingerprint(t, width) for t in got["body"]]}

    return map_rows(docs, [F.col(id_col).cast("bigint").alias("key"), F.col(text_col).alias("body")], "doc_id bigint, fp bigint", run)


def forest(values: np.ndarray, max_bits: int) -> list[tuple[int, int]]:
    """Links of a spanning forest: same connected groups as all pairs within max_bits bits."""
    left, out = values.astype("<i8").view("<u8"), []  # the count of set bits is that of the absolute value where signed
    while len(left):
        ready, left = [left[0]], left[1:]
        while ready and len(left):
            at = ready.pop()
            near = np.bitwise_count(left ^ at) <= max_bits
            if near.any():
                out += [(int(at.view("<i8")), int(x)) for x in left[near].view("<i8")]
                ready += list(left[near])
                left = left[~near]
    return out


def _splits(bits: list[list[int]], drop: int) -> list[int]:
    """Masks over all choices of len(bits) - drop blocks; each block is a list of bit numbers."""
    return [sum(1 << b for block in chosen for b in block) for chosen in combinations(bits, len(bits) - drop)]


def _deal(bits: list[int], parts: int) -> list[list[int]]:
    return [list(map(int, x)) for x in np.array_split(bits, parts)]


def _signed(mask: int) -> Column:
    return F.lit(mask - (1 << 64) if mask >= 1 << 63 else mask).cast("bigint")


def _keyed(rows: DataFrame, masks: list[int], first: Column) -> DataFrame:
    """A row (part, key, fp) for each mask; `first` numbers the table the row comes from."""
    keys = F.array(*[F.struct((first * len(masks) + i).cast("int").alias("part"), F.col("fp").bitwiseAND(_signed(m)).alias("key")) for i, m in enumerate(masks)])
    return rows.select("fp", F.explode(keys).alias("k")).select("k.part", "k.key", "fp")


def _linked(buckets: DataFrame, max_bits: int) -> DataFrame:
    """Forest links (a, b) of each bucket (fps array)."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            found = [x for fps in got["fps"] for x in forest(np.array(fps, dtype="<i8"), max_bits)]
            yield {"a": [x[0] for x in found], "b": [x[1] for x in found]}

    return map_rows(buckets, ["fps"], "a bigint, b bigint", run)


def links(fps: DataFrame, *, max_bits: int = 3, blocks: int = 6, crowd: int = 1024) -> DataFrame:
    """Links (a, b) that connect distinct fingerprints (fp) exactly as all pairs within max_bits bits would.

    `blocks` sets the key length: 64 * (blocks - max_bits) / blocks bits, in C(blocks, max_bits)
    tables. 6 blocks (32 bits, 20 tables) keep chance buckets small up to about 10**9 distinct
    fingerprints, 9 blocks (43 bits, 84 tables) up to 10**12.
    """
    if not 0 < max_bits < blocks <= 16:
        raise ValueError("1 <= max_bits < blocks <= 16 is required")
    masks = _splits(_deal(list(range(64)), blocks), max_bits)
    keyed = _keyed(fps, masks, F.lit(0))
    many = keyed.groupBy("part", "key").agg(F.count("*").alias("n")).where("n > 1").select("part", rekeyed("key"), "n")
    met = cut(keyed.join(many, ["part", "key"]))
    small = met.where(F.col("n") <= crowd).repartition("part", "key").groupBy("part", "key").agg(F.collect_list("fp").alias("fps"))
    found = _linked(small, max_bits)
    crowded = met.where(F.col("n") > crowd)
    if crowded.isEmpty():
        return found
    # The open bits of each table, split until at most 16 of them stay open.
    rows = None
    for t, mask in enumerate(masks):
        open_bits = [b for b in range(64) if not mask >> b & 1]
        finer = max_bits + 1
        while len(_deal(open_bits, finer)[0]) * max_bits > 16:
            finer += 1
        sub = [mask | m for m in _splits(_deal(open_bits, finer), max_bits)]
        own = _keyed(crowded.where(F.col("part") == t).select("fp"), sub, F.lit(t))
        rows = own if rows is None else rows.union(own)
    fine = rows.groupBy("part", "key").agg(F.collect_set("fp").alias("fps")).where(F.size("fps") > 1)
    return found.union(_linked(fine, max_bits))


def groups(prints: DataFrame, *, max_bits: int = 3, blocks: int = 6, crowd: int = 1024) -> DataFrame:
    """(doc_id, fp, component_id) for prints (doc_id, fp): component_id is the smallest doc_id reachable over links."""
    prints = cut(prints)
    each = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components(links(each.select("fp"), max_bits=max_bits, blocks=blocks, crowd=crowd))
    found = each.join(found, each.fp == found.node, "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    roots = found.groupBy("root").agg(F.min("least").alias("component_id")).select(rekeyed("root"), "component_id")
    named = found.join(roots, "root").select(rekeyed("fp"), "component_id")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def near_duplicates(docs: DataFrame, *, width: int = 3, max_bits: int = 3, blocks: int = 6) -> DataFrame:
    """(doc_id, fingerprint as 16 hex digits, component_id) of every document."""
    out = groups(fingerprints(docs, width=width), max_bits=max_bits, blocks=blocks)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def shingle_hashes(text: str | None, width: int) -> list[int]:
    """Hashes of the distinct word shingles."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    joined = [b" ".join(words)] if len(words) <= width else map(b" ".join, zip(*(words[i:] for i in range(width))))
    return np.fromiter({xxhash.xxh64_intdigest(x) for x in joined}, dtype="<u8").view("<i8").tolist() if words else []


_SLACK = 1e-6
#: Ids that a worker holds to pick its texts.
_HELD = 1 << 22
#: Ids that are broadcast to drop their rows.
_SENT = 1 << 21
#: Bits of a wide fingerprint, in 64-bit words; texts of fewer shingles aren't judged by it.
_WORDS, _FEW = 4, 20
_SIGS = [f"f{i}" for i in range(_WORDS)]


def wide_fingerprint(hashes: np.ndarray) -> list[int]:
    """SimHash of a set of shingle hashes in `_WORDS` signed words, each from a remix of the hashes."""
    out = []
    for word in range(_WORDS):
        ones = np.zeros(64, dtype=np.int64)
        for at in range(0, len(hashes), _CHUNK):
            mixed = hashes[at : at + _CHUNK].view("<u8") + np.uint64(0x9E3779B97F4A7C15 * (word + 1) & (1 << 64) - 1)
            mixed = (mixed ^ (mixed >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            mixed = (mixed ^ (mixed >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            ones += np.unpackbits((mixed ^ (mixed >> np.uint64(31))).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out.append(int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0]))
    return out


def widest(similarity: float, deviations: float = 7.0) -> int:
    """Differing bits of wide fingerprints that sets of at least that Jaccard similarity stay within: expected ones plus seven standard deviations, which about one pair in 10**11 exceeds."""
    share, bits = math.acos(2 * similarity / (1 + similarity)) / math.pi, 64 * _WORDS
    return math.ceil(bits * share + deviations * math.sqrt(bits * share * (1 - share)))


class Commonness:
    """How common shingles are, by powers of two, in a table of fixed size: cells of four bits, 16 to a word.

    Shingles that share a cell count as common as the commonest of them. Any such table gives
    a global order, which is all that `prefix` needs to miss no pair; a better one meets fewer others.
    """

    def __init__(self, cells_log2: int, words: dict[int, int]):
        self.cells_log2 = cells_log2
        self.cells = np.zeros(max(1, (1 << cells_log2) // 16), dtype="<u8")
        if words:
            self.cells[list(words)] = np.array([w & (1 << 64) - 1 for w in words.values()], dtype="<u8")

    def of(self, hashes: np.ndarray) -> np.ndarray:
        at = hashes.view("<u8") >> np.uint64(64 - self.cells_log2)
        return (self.cells[(at >> np.uint64(4)).astype(np.int64)] >> ((at & np.uint64(15)) * np.uint64(4))) & np.uint64(15)


def commonness(rows: DataFrame, width: int, *, share: int = 8, least: int = 4, cells_log2: int = 24) -> Commonness:
    """Counted over one of `share` texts, chosen by a hash of their ids; shingles seen there `least` times or more count as common. The driver and each worker hold 2 ** cells_log2 / 2 bytes, whatever the corpus."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            for text in got["text"]:
                yield {"key": shingle_hashes(text, width)}

    some = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(share)) == 0)
    often = map_rows(some, ["text"], "key bigint", run).groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    cell = F.shiftrightunsigned("key", 64 - cells_log2)
    each = often.groupBy(cell.alias("cell")).agg(F.max(F.least(F.floor(F.log2("n")), F.lit(15)).cast("bigint")).alias("c"))
    # At most 2 ** cells_log2 / 16 rows.
    words = each.groupBy(F.shiftrightunsigned("cell", 4).alias("word")).agg(F.bit_or(F.expr("shiftleft(c, cast(4 * (cell & 15) as int))")).alias("w")).toArrow()
    return Commonness(cells_log2, dict(zip(words["word"].to_pylist(), words["w"].to_pylist())))


def prefix(hashes: np.ndarray, similarity: float, common: Commonness) -> np.ndarray:
    """The first shingles of a set, rare ones first: two sets of at least that Jaccard similarity share one of them."""
    if not len(hashes):
        return hashes
    return hashes[np.lexsort((hashes, common.of(hashes)))][: len(hashes) - math.ceil(similarity * len(hashes) - _SLACK) + 1]


def _may(similarity: float, a: str, b: str) -> Column:
    """Whether the sets of structs a and b (id, size, at, words of the wide fingerprint) that meet at these places of theirs can be similar enough."""
    n, m, at, other = F.col(f"{a}.size"), F.col(f"{b}.size"), F.col(f"{a}.at"), F.col(f"{b}.at")
    long_enough = F.least(n, m) >= similarity * F.greatest(n, m) - _SLACK
    room = F.least(n - at, m - other) >= similarity / (1 + similarity) * (n + m) - _SLACK
    apart = sum(F.bit_count(F.col(f"{a}.{f}").bitwiseXOR(F.col(f"{b}.{f}"))) for f in _SIGS)
    return long_enough & room & ((apart <= widest(similarity)) | (F.least(n, m) < _FEW))


def _alike(rows: DataFrame, pairs: DataFrame, width: int, similarity: float) -> DataFrame:
    """Those of the pairs (x, y) whose shingle sets are similar enough, as (a, b). Texts aren't shuffled unless over `_HELD` are asked for."""
    asked = pairs.select(F.col("x").alias("doc_id")).union(pairs.select("y")).distinct()
    held = asked.limit(_HELD + 1).toArrow()["doc_id"].to_numpy()
    every = len(held) > _HELD
    held = np.zeros(0, dtype=np.int64) if every else np.sort(held)

    def hashed(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            ids = np.array(got["doc_id"], dtype=np.int64)
            fine = np.arange(len(ids)) if every else np.flatnonzero(np.searchsorted(held, ids, "right") > np.searchsorted(held, ids))
            for at in range(0, len(fine), 512):
                yield {"id": ids[fine[at : at + 512]], "hashes": [shingle_hashes(got["text"][i], width) for i in fine[at : at + 512].tolist()]}

    texts = rows.join(asked, "doc_id", "left_semi") if every else rows
    # One row for an id, should several rows carry it; both joins read the same exchange of them.
    sets = map_rows(texts, ["doc_id", "text"], "id bigint, hashes array<bigint>", hashed).groupBy("id").agg(F.first("hashes").alias("hashes"))
    left, right = sets.select(F.col("id").alias("x"), F.col("hashes").alias("hx")), sets.select(F.col("id").alias("y"), F.col("hashes").alias("hy"))
    both = F.size(F.array_intersect("hx", "hy"))
    return cut(pairs.join(left, "x").join(right, "y").where(both >= similarity * (F.size("hx") + F.size("hy") - both)).select(F.col("x").alias("a"), F.col("y").alias("b")))


def _blocked(firsts: DataFrame, max_bits: int, blocks: int) -> DataFrame:
    """Candidates (x, y) by the pigeonhole blocks over f0, the sets' 64-bit fingerprint: they connect sets (first, size, f0) exactly as all pairs within max_bits bits would. Sets without shingles take no part."""
    prints = cut(firsts.where("size > 0").groupBy(F.col("f0").alias("fp")).agg(F.min("first").alias("least"), F.count("*").alias("n")))
    linked = links(prints.select("fp"), max_bits=max_bits, blocks=blocks)
    left, right = prints.select(F.col("fp").alias("a"), F.col("least").alias("x")), prints.select(F.col("fp").alias("b"), F.col("least").alias("y"))
    apart = linked.join(left, "a").select("x", rekeyed("b")).join(right, "b").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))
    equal = firsts.where("size > 0").join(prints.where("n > 1"), F.col("f0") == F.col("fp")).where("first <> least").select(F.col("least").alias("x"), F.col("first").alias("y"))
    return apart.union(equal).where("x <> y")


def _heads(rows: DataFrame, again: DataFrame, width: int, similarity: float) -> DataFrame:
    """(key, id, at): the prefix shingles of each text but those of the ids in `again`, and their places."""
    common = commonness(rows, width)
    copies = again.limit(_HELD + 1).toArrow()["doc_id"].to_numpy()
    shuffled = len(copies) > _HELD
    copies = np.zeros(0, dtype=np.int64) if shuffled else np.sort(copies)

    def keyed(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            ids = np.array(got["doc_id"], dtype=np.int64)
            fine = np.flatnonzero(np.searchsorted(copies, ids, "right") == np.searchsorted(copies, ids))
            for start in range(0, len(fine), 256):
                chosen = fine[start : start + 256]
                found = [prefix(np.array(shingle_hashes(got["text"][i], width), dtype=np.int64), similarity, common) for i in chosen.tolist()]
                yield {"key": np.concatenate(found), "id": np.repeat(ids[chosen], list(map(len, found))), "at": np.concatenate([np.arange(len(x), dtype=np.int32) for x in found])}

    texts = rows.join(again, "doc_id", "left_anti") if shuffled else rows
    return map_rows(texts, ["doc_id", "text"], "key bigint, id bigint, at int", keyed)


def similar_groups(docs: DataFrame, *, width: int = 5, similarity: float = 0.8, max_bits: int = 3, blocks: int = 6) -> DataFrame:
    """(doc_id, component_id): groups of texts whose sets of word shingles have a Jaccard similarity of at least `similarity`, linked by all such pairs.

    Equal sets fall together by digest; texts without words have equal, empty sets. The others
    go the way of `near_duplicates`: fingerprints of 64 bits, pigeonhole blocks, links within
    `max_bits` bits, verified by the shingle sets, and groups. That is only certain for a few
    differing bits, and this similarity allows far more, so an exact way for the rest goes
    with it, in which blocks are shingles: two sets that alike share one of their prefixes,
    rare shingles first, and meet under it. Length, the place of the shingle and the Hamming
    distance of wide fingerprints then drop pairs that can't be alike; what is left is verified
    together with the links. Each key's members first meet its least edited one (that with the
    fewest rarer shingles, as an original has against its copies), then those that this and
    the links left in different groups meet each other. Work on texts that share their
    prefixes without being alike still grows with the square of their number, but
    makes no rows. Rows with a null doc_id aren't grouped.
    """
    rows = docs.where("doc_id is not null").select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    own = lambda got: [np.sort(np.array(shingle_hashes(t, width), dtype=np.int64)) for t in got["text"]]
    digests = lambda sets: [hashlib.md5(x.tobytes()).hexdigest() for x in sets]

    def printed(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            sets = own(got)
            wide = [wide_fingerprint(x) for x in sets]
            yield {"doc_id": got["doc_id"], "digest": digests(sets), "size": list(map(len, sets))} | {f: [w[i] for w in wide] for i, f in enumerate(_SIGS)}

    prints = cut(map_rows(rows, ["doc_id", "text"], "doc_id bigint, digest string, size int, " + ", ".join(f"{f} bigint" for f in _SIGS), printed))
    # One row for a set; sets that occur once, most of them, needn't be looked up.
    firsts = cut(prints.groupBy("digest").agg(F.min("doc_id").alias("first"), F.count("*").alias("n"), F.first("size").alias("size"), *[F.first(f).alias(f) for f in _SIGS]))
    again = prints.join(firsts.where("n > 1").select("digest", "first"), "digest").where("doc_id <> first").select("doc_id").distinct()
    # Pairs that the pigeonhole blocks link; then the rest, by shared prefixes.
    linked = _blocked(firsts, max_bits, blocks)
    heads = _heads(rows, again, width, similarity)
    place = F.struct("at", "id")
    several = heads.groupBy("key").agg(F.min(place).alias("top"), F.max(place).alias("last")).where("top.id <> last.id").select(rekeyed("key"), "top")
    met = cut(heads.join(several, "key").where("id <> top.id").select("key", "id", "at", "top"))
    sized = firsts.where("size > 0").select(F.col("first").alias("sized"), F.struct("size", *_SIGS).alias("s"))
    full = lambda of, at: F.struct(F.col("s.size").alias("size"), F.col(at).alias("at"), *[F.col(f"s.{f}").alias(f) for f in _SIGS]).alias(of)
    # The first shingle that two sets share has the least place in both.
    first_met = met.groupBy(F.col("top.id").alias("x"), F.col("id").alias("y")).agg(F.min("top.at").alias("there"), F.min("at").alias("at"))
    pairs = first_met.join(sized, F.col("y") == F.col("sized")).select(rekeyed("x"), "y", "there", full("a", "at"))
    tried = pairs.join(sized, F.col("x") == F.col("sized")).select("x", "y", "a", full("b", "there")).where(_may(similarity, "a", "b"))
    tried = cut(tried.select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).union(linked).distinct())
    found = _alike(rows, tried, width, similarity)
    joined = cut(components(found))
    # Pairs of a key besides its first member, where they aren't in one group yet.
    all_met = met.select("key", "id", "at").union(met.select("key", F.col("top.id"), F.col("top.at")).distinct())
    named = all_met.join(joined, F.col("id") == joined.node, "left").select("key", "id", "at", F.coalesce("root", "id").alias("own"))
    mixed = named.groupBy("key").agg(F.min("own").alias("low"), F.max("own").alias("high"), F.count("*").alias("n")).where("low <> high AND n > 2").select(rekeyed("key"))
    rest = cut(named.join(mixed, "key", "left_semi").join(sized, F.col("id") == F.col("sized")).select("key", "id", "own", full("a", "at")))
    other = rest.select(rekeyed("key"), F.col("id").alias("y"), F.col("own").alias("its"), F.col("a").alias("b"))
    pairs = rest.join(other, (rest["key"] == other["key"]) & (F.col("id") < F.col("y")) & (F.col("own") != F.col("its")) & _may(similarity, "a", "b"))
    pairs = pairs.select(F.col("id").alias("x"), "y").distinct()
    pairs = cut(pairs.join(tried, ["x", "y"], "left_anti"))
    if not pairs.isEmpty():
        joined = components(found.union(_alike(rows, pairs, width, similarity)))
    named = firsts.join(joined, firsts["first"] == joined.node, "left").select("digest", F.coalesce("root", "first").alias("component_id"))
    return prints.join(named.select(F.concat("digest", F.lit("")).alias("digest"), "component_id"), "digest").select("doc_id", "component_id")


def deduplicate(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs, with their own columns, of which one stays for each group: that with the smallest doc_id. Rows that repeat it count once; null ids stay."""
    grouped = cut(similar_groups(docs, **options))
    gone = grouped.where("doc_id <> component_id").select("doc_id").distinct()
    again = grouped.groupBy("doc_id").count().where("count > 1").select("doc_id")
    if gone.limit(_SENT + 1).count() <= _SENT:  # then the texts needn't be shuffled
        gone = F.broadcast(gone)
    left = docs.join(gone, "doc_id", "left_anti").select(docs.columns)
    if again.isEmpty():
        return left
    # Few ids are ever repeated; only their rows are compared.
    single = left.join(again, "doc_id", "left_anti").select(docs.columns)
    return single.union(left.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(docs.columns))
