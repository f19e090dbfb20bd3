"""Toxicity: a support vector machine over a gap-weighted subsequence kernel with Nyström landmarks.

Words (and spelt-out runs of single letters, joined) are compared by the subsequences of
three letters they share, each weighted by decay ** span, spans up to `SPAN` letters;
characters that aren't letters don't count, so "id***iot" and "i--d--i--o--t" equal "idiot",
and inserted letters leave gaps. The kernel is normalised and cubed (products of kernels are kernels), which keeps
near matches only. Landmarks are the words that tell the labelled sentences apart best, by
their counts in a bounded labelled sample. A text is the maximum over its words of the
kernel against each landmark, mapped by the inverse root of the landmarks' own kernel
matrix; a linear support vector machine on that map and a logistic curve on its held-back
margins give the score.

Most words share too few subsequences with any landmark to matter: an upper bound of the
kernel, exact in direction, drops them before the comparison. Whole texts are scored. Null
texts count as empty; an empty text has no matches and gets the score of that. Repeated
rows get the same score. Without labelled rows of both kinds all scores are the share of
label 1. Labels, languages, sources and ids are no inputs of a score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows
from .quality_knn import remainder

SPAN = 6
DECAY = 0.6
LONGEST = 48
FLOOR = 0.5
_CODES = 1 << 15
#: Offsets of the second and third letter within the span, and their weights.
_OFFSETS = [(i, j, DECAY ** (j + 1)) for i in range(1, SPAN - 1) for j in range(i + 1, SPAN)]
_STRIP = ".,;:!?#$%&*|\"'()<>[]{}-_/\\"
_SPELT = re.compile(r"(?<!\S)[^\W_](?:[ .*_-]{1,3}[^\W_]){3,}(?!\S)")
_LOOKALIKE = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s"}


def _class_table() -> np.ndarray:
    """Code point -> 1..26 for Latin letters and look-alikes, 27..31 for other letters, 0 for the rest."""
    out = np.zeros(0x10000, dtype=np.uint8)
    for c in range(0x10000):
        if chr(c).isalpha():
            out[c] = 27 + c % 5
    for c in range(97, 123):
        out[c] = out[c - 32] = c - 96
    for c, like in _LOOKALIKE.items():
        out[ord(c)] = ord(like) - 96
    return out


def words_of(text: str | None) -> set[str]:
    """Distinct lower-case words, without punctuation around them; longer ones in overlapping parts."""
    text = (text or "").lower()
    found = {w.strip(_STRIP) for w in set(text.split())}
    found.update("".join(filter(str.isalnum, m.group())) for m in _SPELT.finditer(text))
    found.discard("")
    for w in [w for w in found if len(w) > LONGEST]:
        found.discard(w)
        found.update(w[at : at + LONGEST] for at in range(0, len(w), LONGEST // 2))
    return found


def subsequences(words: list[str], table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word number, code, weight) of the gapped letter triples, weights of equal triples summed; other characters between letters don't widen a gap."""
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    points = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype="<u4")
    letters = np.where(points < 0x10000, table[np.minimum(points, 0xFFFF)], 27).astype(np.int64)
    owner = np.repeat(np.arange(len(words)), lengths)[letters > 0]
    letters = letters[letters > 0]
    keys, weights = [], []
    for i, j, w in _OFFSETS:
        if len(letters) <= j:
            break
        a, b, c = letters[: len(letters) - j], letters[i : len(letters) - j + i], letters[j:]
        fine = owner[: len(letters) - j] == owner[j:]
        keys.append((owner[: len(letters) - j][fine] << 15) | (a[fine] << 10) | (b[fine] << 5) | c[fine])
        weights.append(np.full(int(fine.sum()), w))
    if not keys:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    key, weight = np.concatenate(keys), np.concatenate(weights)
    order = np.argsort(key, kind="stable")
    key, weight = key[order], weight[order]
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)
    total = np.add.reduceat(weight, starts) if len(starts) else np.zeros(0)
    key = key[starts]
    return key >> 15, key & (_CODES - 1), total


class Landmarks:
    """Landmark words and the kernel of other words against them."""

    MEMO = 1 << 19

    def __init__(self, words: list[str]):
        self.words = words
        self._open()

    def __getstate__(self) -> dict:
        return {"words": self.words}

    def __setstate__(self, state: dict) -> None:
        self.words = state["words"]
        self._open()

    def _open(self) -> None:
        self.table = _class_table()
        owner, code, weight = subsequences(self.words, self.table)
        norm = np.sqrt(np.bincount(owner, weight**2, minlength=len(self.words)))
        known = np.unique(code)
        self.column = np.full(_CODES, -1)
        self.column[known] = np.arange(len(known))
        self.profile = np.zeros((len(known), len(self.words)), dtype=np.float32)
        self.profile[self.column[code], owner] = weight / np.maximum(norm[owner], 1e-12)
        self.most = np.zeros(_CODES)
        self.most[known] = self.profile.max(axis=1) if self.words else 0
        self.close: dict[str, np.ndarray | None] = {}

    def compare(self, words: list[str]) -> None:
        """Adds the kernels of new words to `close`; None where all are below FLOOR."""
        owner, code, weight = subsequences(words, self.table)
        n = len(words)
        norm = np.maximum(np.sqrt(np.bincount(owner, weight**2, minlength=n)), 1e-12)
        bound = np.bincount(owner, weight * self.most[code], minlength=n) / norm
        maybe = np.flatnonzero(bound >= FLOOR)
        self.close.update(dict.fromkeys(words))
        if not len(maybe):
            return
        place = np.full(n, -1)
        place[maybe] = np.arange(len(maybe))
        fine = (place[owner] >= 0) & (self.column[code] >= 0)
        row, code, weight = place[owner[fine]], self.column[code[fine]], weight[fine]
        for at in range(0, len(maybe), 1024):
            lo, hi = np.searchsorted(row, (at, at + 1024))
            part = maybe[at : at + 1024]
            dense = np.zeros((len(part), len(self.profile)), dtype=np.float32)
            dense[row[lo:hi] - at, code[lo:hi]] = weight[lo:hi]
            kernel = dense @ self.profile / norm[part, None].astype(np.float32)
            for i in np.flatnonzero(kernel.max(axis=1) >= FLOOR).tolist():
                self.close[words[part[i]]] = np.where(kernel[i] >= FLOOR, kernel[i], 0.0) ** 3

    def features(self, texts: list[str | None]) -> np.ndarray:
        """Per text the maximum over its words of the cubed kernel against each landmark."""
        out = np.zeros((len(texts), len(self.words)), dtype=np.float32)
        held: list[set[str]] = []
        new: set[str] = set()
        if len(self.close) > self.MEMO:
            self.close.clear()
        for at, text in enumerate(texts):
            held.append(words_of(text))
            new.update(w for w in held[-1] if w not in self.close)
            if len(new) < 1 << 14 and at + 1 < len(texts):
                continue
            if new:
                self.compare(list(new))
            for row, own in zip(out[at + 1 - len(held) : at + 1], held):
                if near := [k for w in own if (k := self.close[w]) is not None]:
                    np.max(near, axis=0, out=row)
            held, new = [], set()
            if len(self.close) > self.MEMO:
                self.close.clear()
        return out


@dataclass
class SubsequenceModel:
    landmarks: Landmarks
    root: np.ndarray
    weights: np.ndarray
    bias: float
    slope: float
    offset: float

    def scores(self, texts: list[str | None]) -> np.ndarray:
        margin = self.landmarks.features(texts) @ self.root @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.offset, -30, 30)))


def choose(rows: list[tuple[list[str], int]], most: int) -> list[str]:
    """Words whose presence speaks most for either label, by their smoothed log odds times what it is based on; three quarters for label 1."""
    positive, every = Counter(), Counter()
    for words, label in rows:
        every.update(words)
        if label:
            positive.update(words)
    n1 = max(1, sum(label for _, label in rows))
    n0 = max(1, len(rows) - n1)

    def evidence(w: str) -> float:
        a, b = positive[w], every[w] - positive[w]
        odds = math.log((a + 0.5) / (n1 - a + 0.5)) - math.log((b + 0.5) / (n0 - b + 0.5))
        return odds / math.sqrt(1 / (a + 0.5) + 1 / (b + 0.5))

    strength = {w: evidence(w) for w, n in every.items() if n >= 3 and len(w) >= 4}
    for_one = sorted((w for w in strength if strength[w] > 3.0), key=lambda w: (-strength[w], w))[: 3 * most // 4]
    against = sorted((w for w in strength if strength[w] < 0), key=lambda w: (strength[w], w))[: most - 3 * most // 4]
    return sorted(for_one + against)


def train_margin(x: np.ndarray, y: np.ndarray, *, c: float = 4.0, rounds: int = 60) -> tuple[np.ndarray, float]:
    """Linear support vector machine, squared hinge loss, labels weighted to equal sums, by Newton steps on the active rows."""
    sign = np.where(y > 0, 1.0, -1.0)
    cost = c * len(y) / 2 / np.where(y > 0, max(1, (y > 0).sum()), max(1, (y <= 0).sum()))
    z = np.c_[x.astype(float), np.ones(len(x))]
    ridge = np.eye(z.shape[1])
    ridge[-1, -1] = 1e-6
    w = np.zeros(z.shape[1])
    for _ in range(rounds):
        active = sign * (z @ w) < 1
        a = z[active]
        new = np.linalg.solve(ridge + 2 * a.T @ (cost[active, None] * a), 2 * a.T @ (cost[active] * sign[active]))
        if np.abs(new - w).max() < 1e-9:
            break
        w = 0.5 * (w + new) if _ > 10 else new
    return w[:-1], float(w[-1])


def logistic(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the curve that turns margins into probabilities."""
    a, b = 1.0, 0.0
    n1, n0 = (y > 0).sum(), (y <= 0).sum()
    t = np.where(y > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g = np.array([((p - t) * margin).sum() + 1e-3 * a, (p - t).sum()])
        q = np.maximum(p * (1 - p), 1e-9)
        h = np.array([[(q * margin**2).sum() + 1e-3, (q * margin).sum()], [(q * margin).sum(), q.sum() + 1e-9]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(max(a, 1e-3)), float(b)


def fit(rows: list[tuple[list[str], int]], *, most_landmarks: int = 128) -> SubsequenceModel | None:
    """rows: distinct words and label of each labelled text."""
    y = np.array([label for _, label in rows])
    if len(set(y.tolist())) < 2:
        return None
    folds = np.arange(len(rows)) % 3

    def solved(train: np.ndarray) -> SubsequenceModel | None:
        words = choose([rows[i] for i in np.flatnonzero(train)], most_landmarks)
        if not words:
            return None
        marks = Landmarks(words)
        own = marks.features(words).astype(float)
        own = (own + own.T) / 2
        values, vectors = np.linalg.eigh(own)
        root = vectors @ np.diag(1 / np.sqrt(np.maximum(values, 0.05))) @ vectors.T
        x = marks.features([" ".join(rows[i][0]) for i in np.flatnonzero(train)]) @ root
        w, bias = train_margin(x, y[train])
        return SubsequenceModel(marks, root, w, bias, 1.0, 0.0)

    margins = np.zeros(len(rows))
    for k in range(3):
        part = solved(folds != k)
        if part is None:
            return None
        held = np.flatnonzero(folds == k)
        margins[held] = part.landmarks.features([" ".join(rows[i][0]) for i in held]) @ part.root @ part.weights + part.bias
    model = solved(np.ones(len(rows), dtype=bool))
    if model:
        model.slope, model.offset = logistic(margins, y)
    return model


def labelled_words(docs: DataFrame, labels: DataFrame, rest, most: int) -> list[tuple[list[str], int]]:
    """Distinct words and label of at most `most` labelled rows, picked by hash; ids picked are bounded and so may be broadcast."""
    usable = labels.where(rest & F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("l_id"), F.col("toxic").cast("int").alias("l_label")).dropDuplicates(["l_id"])
    # Toxic rows are few: each label fills its own half where it can.
    picked = usable.where("l_label = 1").orderBy(F.xxhash64("l_id"), "l_id").limit(most // 2).union(usable.where("l_label <> 1").orderBy(F.xxhash64("l_id"), "l_id").limit(most - most // 2))
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), F.col("doc_id") == F.col("l_id"))

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            yield {"id": got["doc_id"], "label": got["l_label"], "words": [" ".join(sorted(words_of(t))) for t in got["text"]]}

    found = map_rows(rows, ["doc_id", "l_label", "text"], "id bigint, label int, words string", run).collect()
    return [(r["words"].split(), r["label"]) for r in sorted(found, key=lambda r: (r["id"], r["words"]))]


def classify(docs: DataFrame, labels: DataFrame, *, held_out: int = 0, parts: int = 5, most_labelled: int = 3000) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document; rows of the held-out part never lend their labels."""
    rows = labelled_words(docs, labels, remainder(parts) != held_out, most_labelled)
    model = fit(rows)
    share = sum(label for _, label in rows) / len(rows) if rows else 0.0

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            s = model.scores(got["body"]) if model else np.full(len(got["key"]), share)
            yield {"doc_id": got["key"], "held_out": got["held"], "score": s.astype(float).tolist(), "predicted": (s >= 0.5).astype(int).tolist()}

    return map_rows(docs, [F.col("doc_id").cast("bigint").alias("key"), F.col("text").alias("body"), (remainder(parts) == held_out).alias("held")], "doc_id bigint, held_out boolean, score double, predicted int", run)
