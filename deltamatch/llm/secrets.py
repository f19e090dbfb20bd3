"""Secret scans: known forms of credentials, and strings a tokenizer finds inefficient.

Base spans are maximal matches of three forms (assignments, access keys, hexadecimal
runs). The token-efficiency test then looks at the other unbroken runs of 20 or more
characters from the alphabets of keys: text that a vocabulary knows takes few tokens, a
random string takes one for every one or two characters. Runs that a digest or an
identifier explains (hexadecimal of a digest's length, UUIDs, numbers, words joined by
separators, paths) are left out first. Ratios come from the byte-level codec of `bpe`.

Null text counts as empty: no spans. Offsets are code points, ends exclusive. Repeated
rows are scanned alike; other columns pass through `redact` untouched.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from hashlib import sha256

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import ByteCodec
from .common import map_rows, small_batches

KINDS = ("assign", "access", "hex", "random")
_ASSIGN = re.compile(r"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
# Maximal runs, so a bound on their length drops the same matches as a later filter would.
_ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
_HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{16,}")
_RUN = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
_DIGEST_LENGTHS = frozenset((32, 40, 56, 64, 96, 128))
_ALL_HEX = re.compile(r"[0-9a-fA-F]+")
_UUID = re.compile(r"[0-9a-fA-F]{8}(?:-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}")
#: Words, in one case or capitalised, and numbers, side by side or joined. Each branch takes a whole run of its class for good, so a test takes linear time.
_NAME = re.compile(r"(?:[A-Z]*+[a-z]{2,}+|[A-Z]{2,}+|[0-9]++|[+/_=-]++)++")
_CLASSES = (re.compile("[0-9]"), re.compile("[a-z]"), re.compile("[A-Z]"))
_PADDED_NUMBER = re.compile(r"[0-9+/_=-]+")


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base forms, by start, then by the order of KINDS."""
    found = [(m.start(), m.end(), "assign") for m in _ASSIGN.finditer(text) if m.end() - m.start(1) >= 12]
    found += [(m.start(), m.end(), "access") for m in _ACCESS.finditer(text)]
    found += [(m.start(), m.end(), "hex") for m in _HEX.finditer(text)]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


def is_explained(run: str) -> bool:
    """A known digest or an identifier, not a random string."""
    if _ALL_HEX.fullmatch(run) and len(run) in _DIGEST_LENGTHS or _UUID.fullmatch(run) or _PADDED_NUMBER.fullmatch(run):
        return True
    if _NAME.fullmatch(run):  # names switch between classes seldom, keys all the time
        switches = sum(1 for _ in re.finditer(r"[A-Z]?[a-z]+|[A-Z]+|[0-9]+", run))
        return switches * 4 <= len(run)
    return False


def random_spans(text: str, taken: list[tuple[int, int, str]], codec: ByteCodec, most_per_token: float = 2.2) -> list[tuple[int, int, str]]:
    """Runs outside `taken` (by start) with at most most_per_token characters for each token."""
    found, at, reached = [], 0, 0  # taken spans before `at` start before the end of this run and end by `reached`
    for m in _RUN.finditer(text):
        while at < len(taken) and taken[at][0] < m.end():
            reached = max(reached, taken[at][1])
            at += 1
        if reached > m.start():
            continue
        run = m.group()
        if sum(1 for c in _CLASSES if c.search(run)) < 2 or is_explained(run):
            continue
        if len(run) * 4 <= most_per_token * len(codec.encode(run)):  # four bytes an id
            found.append((m.start(), m.end(), "random"))
    return found


def secret_spans(text: str | None, codec: ByteCodec) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """Base spans, and all spans."""
    base = base_spans(text or "")
    more = random_spans(text or "", base, codec)
    return base, sorted(base + more, key=lambda x: (x[0], KINDS.index(x[2])))


def _joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


def scan(docs: DataFrame, codec: ByteCodec) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every whole text."""

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            found = [secret_spans(t, codec) for t in got["body"]]
            count = lambda kind: [sum(s[2] == kind for s in base) for base, _ in found]
            yield {
                "doc_id": got["key"], "n_assign": count("assign"), "n_access": count("access"), "n_hex": count("hex"),
                "base_sha256": [sha256(_joined(base).encode()).hexdigest() for base, _ in found], "spans": [_joined(every) for _, every in found],
            }

    return map_rows(docs, [F.col("doc_id").cast("bigint").alias("key"), F.col("text").alias("body")], "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string", run)


def mask(text: str, spans: list[tuple[int, int, str]], mark: str = "[SECRET]") -> str:
    """text with every union of overlapping spans replaced by one mark."""
    out, at = [], 0
    for start, end, _ in spans:
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, codec: ByteCodec, mark: str = "[SECRET]") -> DataFrame:
    """docs with every secret in `text` replaced by mark, and `n_chars`, where there is one, counted again; no row goes."""
    import pyarrow as pa

    names = docs.columns
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.names.index("text")
            texts = [t if t is None else mask(t, secret_spans(t, codec)[1], mark) for t in batch.column(at).to_pylist()]
            columns = list(batch.columns)
            columns[at] = pa.array(texts, batch.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    out = docs.mapInArrow(run, docs.schema)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in names else out
