"""Byte-level BPE: encode with a two-tier lookup, decode back.

A text is cut into pre-tokens by the vocabulary's pattern. Tier one is a minimal perfect
hash over the whole vocabulary, stored in exactly one slot per entry: a pre-token that is
itself an entry costs one hash and one comparison. Tier two merges the bytes of the other
pre-tokens: neighbours form a linked list and a heap hands out the lowest rank, leftmost
first, so n bytes take O(n log n). Results equal those of the public tiktoken library.

Null text counts as empty: no ids, the digests of nothing. Repeated rows stay.
"""

from __future__ import annotations

import base64
import heapq
import sys
from array import array
from collections.abc import Iterator
from dataclasses import dataclass, field
from hashlib import sha256

import numpy as np
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows

#: White space as the pattern language of rank files has it; the class of the Python library also holds \x1c-\x1f.
_SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def compile_pattern(pattern: str) -> regex.Pattern:
    """The split pattern with its white-space classes spelt out."""
    return regex.compile(pattern.replace(r"[^\s", f"[^{_SPACE}").replace(r"\s", f"[{_SPACE}]").replace(r"\S", f"[^{_SPACE}]"))


@dataclass
class PerfectHash:
    """Minimal perfect hash: keys fall into small groups, and each group has a shift that sends its keys to free slots."""

    slots: int
    groups: int
    shift: list[int]
    keys: list[bytes] = field(repr=False)
    values: list[int] = field(repr=False)

    @staticmethod
    def _parts(key: bytes) -> tuple[int, int, int]:
        h = xxhash.xxh3_128_intdigest(key)
        return h & 0xFFFFFFFF, (h >> 32) & 0xFFFFFFFF, (h >> 64) & 0xFFFFFFFF

    @classmethod
    def build(cls, entries: dict[bytes, int]) -> PerfectHash:
        keys = list(entries)
        n = max(1, len(keys))
        groups = n // 3 + 1
        parts = np.array([cls._parts(k) for k in keys], dtype=np.int64).reshape(-1, 3)
        members: dict[int, list[int]] = {}
        for i, g in enumerate((parts[:, 0] % groups).tolist()):
            members.setdefault(g, []).append(i)
        free = np.ones(n, dtype=bool)
        shift, at = [0] * groups, np.zeros(len(keys), dtype=np.int64)
        for g, own in sorted(members.items(), key=lambda x: -len(x[1])):
            turn = 0
            while True:  # shift = turn * n + step; a turn remixes the keys, a step moves them all
                base = (parts[own, 1] + turn * parts[own, 2]) % n
                if len(set(base.tolist())) == len(own) and (step := cls._step(free, base)) >= 0:
                    break
                turn += 1
                if turn > 10_000:
                    raise ValueError("two keys have the same hash")
            shift[g] = turn * n + step
            at[own] = (base + step) % n
            free[at[own]] = False
        placed, values = [b""] * n, [-1] * n
        for i, s in enumerate(at.tolist()):
            placed[s], values[s] = keys[i], entries[keys[i]]
        return cls(n, groups, shift, placed, values)

    @staticmethod
    def _step(free: np.ndarray, base: np.ndarray) -> int:
        """The first step that moves all of base to free slots, or -1."""
        n, at = len(free), 0
        for span in (256, 8192, n):
            tries = np.arange(at, min(n, at + span), dtype=np.int64)
            fits = free[(base[0] + tries) % n]
            for b in base[1:]:
                fits &= free[(b + tries) % n]
            if len(fits) and fits[step := int(fits.argmax())]:
                return at + step
            at += span
        return -1

    def get(self, key: bytes) -> int:
        """The value of key, or -1."""
        a, b, c = self._parts(key)
        turn, step = divmod(self.shift[a % self.groups], self.slots)
        slot = (b + turn * c + step) % self.slots
        return self.values[slot] if self.keys[slot] == key else -1


def merge_bytes(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of a piece that is no entry itself."""
    n = len(piece)
    rank_of = ranks.get
    ids = [ranks[piece[i : i + 1]] for i in range(n)]
    after, before, end = list(range(1, n + 1)), list(range(-1, n - 1)), list(range(1, n + 1))
    heap = []
    for i in range(n - 1):
        rank = rank_of(piece[i : i + 2])
        if rank is not None:
            heap.append((rank, i, i + 1, i + 2))
    heapq.heapify(heap)
    while heap:
        rank, i, mid, stop = heapq.heappop(heap)
        if end[i] != mid:
            continue
        j = after[i]
        if j >= n or end[j] != stop:  # one of the two was merged meanwhile
            continue
        ids[i], end[i], end[j] = rank, stop, -1
        j = after[i] = after[j]
        if j < n:
            before[j] = i
            rank = rank_of(piece[i : end[j]])
            if rank is not None:
                heapq.heappush(heap, (rank, i, stop, end[j]))
        j = before[i]
        if j >= 0:
            rank = rank_of(piece[j:stop])
            if rank is not None:
                heapq.heappush(heap, (rank, j, i, stop))
    out, i = [], 0
    while i < n:
        out.append(ids[i])
        i = after[i]
    return out


class ByteCodec:
    """Encoder and decoder over one rank file; small enough to travel with each task."""

    MEMO = 1 << 18

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.pattern = pattern
        self.hash = PerfectHash.build(ranks)
        self.ranks = ranks
        self.words = [b""] * (max(ranks.values(), default=-1) + 1)
        for word, rank in ranks.items():
            self.words[rank] = word
        self._open()

    def _open(self) -> None:
        self.find = compile_pattern(self.pattern).findall
        self.memo: dict[str, bytes] = {}

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("find", "memo")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        self._open()

    def piece(self, text: str) -> bytes:
        """Ids of one pre-token as little-endian 32-bit integers."""
        raw = text.encode()
        whole = self.hash.get(raw)
        ids = array("I", [whole] if whole >= 0 else merge_bytes(raw, self.ranks))
        if sys.byteorder == "big":
            ids.byteswap()
        return ids.tobytes()

    def encode(self, text: str) -> bytes:
        memo, out = self.memo, []
        for piece in self.find(text):
            ids = memo.get(piece)
            if ids is None:
                if len(memo) >= self.MEMO:
                    memo.clear()
                ids = self.piece(piece)
                if len(piece) < 64:
                    memo[piece] = ids
            out.append(ids)
        return b"".join(out)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.words.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


def encode_documents(docs: DataFrame, codec: ByteCodec) -> DataFrame:
    """(doc_id, source, n_tokens, ids binary, decoded_sha256): little-endian 32-bit ids of every whole text, and a digest of what they decode to."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            for at in range(0, len(got["key"]), 512):  # ids take more room than the text
                ids = [codec.encode(t or "") for t in got["body"][at : at + 512]]
                yield {
                    "doc_id": got["key"][at : at + 512], "source": got["source"][at : at + 512], "n_tokens": [len(x) // 4 for x in ids],
                    "ids": ids, "decoded_sha256": [sha256(codec.decode(x)).hexdigest() for x in ids],
                }

    columns = [F.col("doc_id").cast("bigint").alias("key"), F.col("source").cast("string").alias("source"), F.col("text").alias("body")]
    return map_rows(docs, columns, "doc_id bigint, source string, n_tokens bigint, ids binary, decoded_sha256 string", run)


def encode_digests(docs: DataFrame, codec: ByteCodec) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) without moving ids or texts back to the JVM."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            out: dict[str, list] = {"doc_id": got["key"], "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
            for text in got["body"]:
                ids = codec.encode(text or "")
                out["n_tokens"].append(len(ids) // 4)
                out["ids_sha256"].append(sha256(ids).hexdigest())
                out["decoded_sha256"].append(sha256(codec.decode(ids)).hexdigest())
            yield out

    return map_rows(docs, [F.col("doc_id").cast("bigint").alias("key"), F.col("text").alias("body")], "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string", run)


def public_codec(name: str = "byte_bpe_multi_50k.tiktoken") -> ByteCodec:
    import public_tokenizers

    return ByteCodec(read_ranks(public_tokenizers.path(name)), public_tokenizers.PATTERN)
