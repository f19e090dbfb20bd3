"""Quality classifier: nearest-neighbour voting in a latent-semantic space.

Terms are byte trigrams of the whole text, hashed into a fixed number of columns, and a
few shape terms (repeated neighbours, repeated lines, case, symbols), each damped by a
logarithm. A truncated singular value decomposition of the weighted term counts of a
bounded sample of labelled rows gives the latent space. The labelled vectors of that
sample, at most `most_labelled` of them, travel to every task; each document is compared
with all of them by blocked matrix products, and its nearest neighbours vote with their
similarity as weight. Votes are mapped so that 0.7 is the cut that separates the labelled
sample best when each of its rows is scored without itself.

Null texts count as empty; empty texts get the share of label 1. Repeated rows get the same
score. Without labelled rows every score is 0.5. Labels, languages, sources and ids are no
inputs of a score. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_rows

COLUMNS_LOG2 = 12
SHAPES = 10


def remainder(parts: int) -> Column:
    """crc32 of doc_id as text, modulo parts."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % parts, F.lit(-1))


def term_counts(text: str | None) -> np.ndarray:
    """Damped counts of the hashed byte trigrams and of the shape terms."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    out = np.zeros((1 << COLUMNS_LOG2) + SHAPES, dtype=np.float32)
    if not raw.strip():
        return out
    b = np.frombuffer(raw, dtype=np.uint8).astype(np.uint32)
    if len(b) >= 3:
        for at in range(0, len(b) - 2, 1 << 20):
            part = b[at : at + (1 << 20) + 2]
            code = ((part[:-2] << 16) | (part[1:-1] << 8) | part[2:]) * np.uint32(0x9E3779B1) >> np.uint32(32 - COLUMNS_LOG2)
            out[: 1 << COLUMNS_LOG2] += np.bincount(code, minlength=1 << COLUMNS_LOG2)
    np.log1p(out, out=out)
    scale = np.sqrt(float((out**2).sum())) or 1.0
    words, lines = raw.split(), raw.split(b"\n")
    n = len(words)
    same = sum(map(bytes.__eq__, words, words[1:])) / n
    kinds = np.bincount(np.array(_CLASSES)[b.astype(np.uint8)], minlength=5) / len(b)
    shapes = [same, 1 - len(set(words)) / n, 1 - len(set(lines)) / len(lines), *kinds, len(raw) / n / 20, min(n, 200) / 200]
    out[1 << COLUMNS_LOG2 :] = np.array(shapes, dtype=np.float32)[:SHAPES] * scale
    return out


#: byte -> class: other, upper-case letter, digit, symbol, white space
_CLASSES = [4 if c in b" \t\n\r\x0b\x0c" else 1 if 65 <= c <= 90 else 2 if 48 <= c <= 57 else 3 if 33 <= c <= 126 and not chr(c).isalpha() else 0 for c in range(256)]


@dataclass
class NeighbourModel:
    """What travels to the tasks: term weights, latent axes, labelled vectors and the map of votes."""

    weight: np.ndarray
    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    neighbours: int
    cut: float
    share: float

    def latent(self, counts: np.ndarray) -> np.ndarray:
        z = (counts * self.weight) @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def votes(self, z: np.ndarray, alone: bool = False) -> np.ndarray:
        """Weighted share of label 1 among the nearest neighbours; alone: rows are the labelled ones, without themselves."""
        near = z @ self.vectors.T
        if alone:
            np.fill_diagonal(near, -2.0)
        k = min(self.neighbours, near.shape[1] - alone)
        top = np.argpartition(-near, k - 1, axis=1)[:, :k]
        w = np.maximum(np.take_along_axis(near, top, 1), 1e-6) ** 4
        return (w * self.labels[top]).sum(1) / w.sum(1)

    def scores(self, texts: list[str | None]) -> np.ndarray:
        counts = np.stack([term_counts(t) for t in texts])
        s = self.votes(self.latent(counts))
        s[~counts.any(axis=1)] = self.share
        return _bent(s, self.cut)


def _bent(s: np.ndarray, cut: float) -> np.ndarray:
    """Monotone map of [0, 1] that sends cut to 0.7."""
    return np.clip(np.where(s < cut, 0.7 * s / cut, 0.7 + 0.3 * (s - cut) / max(1e-9, 1 - cut)), 0.0, 1.0)


def labelled_counts(docs: DataFrame, labels: DataFrame, target: str, rest: Column, most: int, counts, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of at most `most` labelled rows, picked by hash; the picked ids are bounded, so they may be broadcast."""
    picked = labels.where(rest & F.col(target).isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("l_id"), F.col(target).cast("int").alias("l_label")).dropDuplicates(["l_id"]).orderBy(F.xxhash64("l_id"), "l_id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), F.col("doc_id") == F.col("l_id"))

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            yield {"id": got["doc_id"], "label": got["l_label"], "x": [counts(t).astype(np.float16).tobytes() for t in got["text"]]}

    found = sorted(map_rows(rows, ["doc_id", "l_label", "text"], "id bigint, label int, x binary", run).collect(), key=lambda r: (r["id"], bytes(r["x"])))
    found = found[:most]
    x = np.frombuffer(b"".join(bytes(r["x"]) for r in found), dtype=np.float16).reshape(-1, width).astype(np.float32)
    return x, np.array([r["label"] for r in found], dtype=np.float32)


def fit(x: np.ndarray, y: np.ndarray, *, dimensions: int = 96, neighbours: int = 15) -> NeighbourModel | None:
    if len(y) < 2:
        return None
    weight = np.log((1 + len(x)) / (1 + (x > 0).sum(0))).astype(np.float32) + 0.2
    weight[-SHAPES:] = 2.0
    counts = x * weight
    counts /= np.maximum(np.linalg.norm(counts, axis=1, keepdims=True), 1e-12)
    gram = (counts @ counts.T).astype(np.float64)
    values, left = np.linalg.eigh(gram)
    keep = [i for i in np.argsort(-values)[:dimensions] if values[i] > 1e-8 * values[-1]]
    axes = (counts.T @ left[:, keep] / np.sqrt(values[keep])).astype(np.float32)
    model = NeighbourModel(weight, axes, np.zeros((0, len(keep)), np.float32), y, neighbours, 0.5, float(y.mean()))
    model.vectors = model.latent(x)
    model.cut = best_cut(model.votes(model.vectors, alone=True), y)
    return model


def best_cut(s: np.ndarray, y: np.ndarray) -> float:
    """The cut with the best mean of both labels' accuracies, in the middle of its gap."""
    levels = np.unique(s)
    if len(levels) < 2 or len(set(y.tolist())) < 2:
        return 0.5
    cuts = (levels[1:] + levels[:-1]) / 2
    good = [((s[y == 1] >= c).mean() + (s[y == 0] < c).mean()) for c in cuts]
    return float(min(max(cuts[int(np.argmax(good))], 0.02), 0.98))


def classify(docs: DataFrame, labels: DataFrame, *, held_out: int = 2, parts: int = 4, most_labelled: int = 2000) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document; rows of the held-out part never lend their labels."""
    x, y = labelled_counts(docs, labels, "quality", remainder(parts) != held_out, most_labelled, term_counts, (1 << COLUMNS_LOG2) + SHAPES)
    model = fit(x, y)

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            for at in range(0, len(got["key"]), 256):
                texts = got["body"][at : at + 256]
                s = model.scores(texts) if model else np.full(len(texts), 0.5)
                yield {"doc_id": got["key"][at : at + 256], "held_out": got["held"][at : at + 256], "score": s.astype(float).tolist(), "predicted": (s >= 0.7).astype(int).tolist()}

    return map_rows(docs, [F.col("doc_id").cast("bigint").alias("key"), F.col("text").alias("body"), (remainder(parts) == held_out).alias("held")], "doc_id bigint, held_out boolean, score double, predicted int", run)
