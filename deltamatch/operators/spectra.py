"""Laplacian spectra of packed graphs: dense solves, stacked by size in Arrow batches."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamatch.session import cut

#: A query value must exceed a data value by this share before a rejection: solves aren't exact.
EPSILON = 1e-7


def laplacian(n: int, edges: list[tuple[int, int]]) -> np.ndarray:
    out = np.zeros((n, n))
    for a, b in edges:
        out[a, b] = out[b, a] = -1.0
    np.fill_diagonal(out, -out.sum(1))
    return out


def _stack(nv: np.ndarray, ends: list[np.ndarray]) -> dict[int, tuple[list[int], np.ndarray]]:
    """Laplacians of equal size together: size -> (row numbers, stacked matrices). Vertices without edges only add zeros and stay out."""
    by_size: dict[int, tuple[list[int], list[np.ndarray]]] = {}
    for i, e in enumerate(ends):
        pairs = np.asarray(e, dtype=np.int64).reshape(-1, 2)
        names, at = np.unique(pairs, return_inverse=True)
        at = at.reshape(-1, 2)
        m = np.zeros((len(names), len(names)))
        m[at[:, 0], at[:, 1]] = m[at[:, 1], at[:, 0]] = -1.0
        m[np.diag_indices(len(names))] = -m.sum(1)
        rows, held = by_size.setdefault(len(names), ([], []))
        rows.append(i)
        held.append(m)
    return {n: (rows, np.stack(held)) for n, (rows, held) in by_size.items()}


def spectra_of(nv: np.ndarray, ends: list[np.ndarray], r: int | None) -> list[np.ndarray]:
    """Descending eigenvalues of each graph, padded with zeros to r; r None: all nv of them."""
    out: list[np.ndarray] = [np.zeros(0)] * len(ends)
    for n, (rows, matrices) in _stack(nv, ends).items():
        values = np.linalg.eigvalsh(matrices)[:, ::-1] if n else np.zeros((len(rows), 0))
        for i, v in zip(rows, values):
            width = int(nv[i]) if r is None else r
            padded = np.zeros(width)
            padded[: min(width, len(v))] = np.maximum(v[:width], 0.0)
            out[i] = padded
    return out


def laplacian_spectrum(packed: DataFrame, r: int | None = 4, key: str = "center") -> DataFrame:
    """packed (key, nv, ends) with spec ARRAY<DOUBLE>."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({key: b[key], "nv": b["nv"], "spec": spectra_of(b["nv"].to_numpy(), list(b["ends"]), r)})

    return packed.mapInPandas(run, f"{key} bigint, nv bigint, spec array<double>")


def closed_walks(packed: DataFrame, k: int = 3, key: str = "center") -> DataFrame:
    """(key, walks): closed walks of length k in each packed graph."""

    def count(e: np.ndarray) -> int:
        pairs = np.asarray(e, dtype=np.int64).reshape(-1, 2)
        names, at = np.unique(pairs, return_inverse=True)
        at = at.reshape(-1, 2)
        m = np.zeros((len(names), len(names)), dtype=np.int64)
        m[at[:, 0], at[:, 1]] = m[at[:, 1], at[:, 0]] = 1
        return int(np.trace(np.linalg.matrix_power(m, k))) if len(names) else 0

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({key: b[key], "walks": [count(e) for e in b["ends"]]})

    return packed.mapInPandas(run, f"{key} bigint, walks bigint")


def iterative_spectrum(m: np.ndarray, r: int, start: np.ndarray | None = None, tolerance: float = 1e-9, most: int = 2000) -> tuple[np.ndarray, np.ndarray, int]:
    """Leading r eigenvalues by block power iteration from `start`, the vectors reached and the rounds used; the baseline a direct solve beats.

    Vectors of an older matrix may be orthogonal to one that a change has brought in, so a
    little noise is added to a start.
    """
    values, x, rounds = iterative_spectra(m[None], r, None if start is None else start[None], tolerance, most)
    return values[0], x[0], int(rounds[0])


def iterative_spectra(stack: np.ndarray, r: int, starts: np.ndarray | None = None, tolerance: float = 1e-9, most: int = 2000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """`iterative_spectrum` of matrices of equal size together; each leaves the stack when its own values stand still."""
    k, n = stack.shape[:2]
    noise = np.random.default_rng(3).standard_normal((n, min(r, n)))
    x = starts + 1e-2 * noise if starts is not None else np.repeat(noise[None], k, axis=0)
    found, vectors, rounds = np.zeros((k, x.shape[2])), x.copy(), np.full(k, most)
    at, m, before = np.arange(k), stack, np.zeros((k, x.shape[2]))
    for turn in range(1, most + 1):
        x, _ = np.linalg.qr(m @ x + 1e-12 * x)
        values, turned = np.linalg.eigh(x.transpose(0, 2, 1) @ m @ x)
        x, values = x @ turned[:, :, ::-1], values[:, ::-1]
        still = np.abs(values - before).max(axis=1) < tolerance
        if still.any() or turn == most:
            done = still | (turn == most)
            found[at[done]], vectors[at[done]], rounds[at[done]] = values[done], x[done], turn
            at, m, x, values = at[~done], m[~done], x[~done], values[~done]
            if not len(at):
                break
        before = values
    return found, vectors, rounds


def _relabelled(pairs: DataFrame) -> DataFrame:
    """(n, before, after, balls): pairs whose vertices, numbered in the order of their ids, have the same edges, once; balls counts them."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for old, new in zip(b["before"], b["after"]):
                names, at = np.unique(np.concatenate([old, new]).astype(np.int64), return_inverse=True)
                at = at.ravel().astype(np.int32)
                rows.append((len(names), at[: len(old)], at[len(old) :]))
            yield pd.DataFrame(rows, columns=["n", "before", "after"])

    forms = pairs.select("before", "after").mapInPandas(run, "n int, before array<int>, after array<int>")
    return forms.groupBy("n", "before", "after").agg(F.count("*").alias("balls"))


#: Matrices solved together, which bounds a worker's memory.
_STACK = 256


def solver_costs(pairs: DataFrame, r: int = 4, tolerance: float = 1e-8) -> DataFrame:
    """(solver, balls, rounds, micros, worst) over balls (center, before, after: flat arrays of edge ends): the direct solver, and the iterative one from a random start and from the vectors it reached for `before`; worst is the largest distance from the direct values.

    Balls with the same matrices are solved once and count as often as they occur, in micros
    too. Matrices of equal size are solved in one stack, by each of the solvers.
    """

    def matrices(n: int, ends: list) -> np.ndarray:
        out = np.zeros((len(ends), n, n))
        for m, e in zip(out, ends):
            a, b = np.asarray(e, dtype=np.int64).reshape(-1, 2).T
            m[a, b] = m[b, a] = -1.0
            m[np.diag_indices(n)] = -m.sum(1)
        return out

    def run(part: pd.DataFrame) -> pd.DataFrame:
        n, often = int(part["n"].iloc[0]), part["balls"].to_numpy()
        out = []
        for low in range(0, len(part), _STACK):
            some, times = part.iloc[low : low + _STACK], often[low : low + _STACK]
            m0, m1 = matrices(n, list(some["before"])), matrices(n, list(some["after"]))
            began = time.perf_counter()
            exact = np.linalg.eigvalsh(m1)[:, ::-1][:, :r]
            took = [("direct", exact, np.ones(len(some), dtype=np.int64), time.perf_counter() - began)]
            _, vectors, _ = iterative_spectra(m0, r, tolerance=tolerance)
            for name, starts in (("cold", None), ("warm", vectors)):
                began = time.perf_counter()
                values, _, rounds = iterative_spectra(m1, r, starts, tolerance)
                took.append((name, values, rounds, time.perf_counter() - began))
            # A stack's time falls to its matrices by their rounds.
            out += [(name, int(times.sum()), int((rounds * times).sum()), 1e6 * seconds * float((rounds * times).sum() / rounds.sum()), float(np.abs(values - exact).max())) for name, values, rounds, seconds in took]
        return pd.DataFrame(out, columns=["solver", "balls", "rounds", "micros", "worst"])

    # Rows are few bytes and much work, so tasks follow the cores and not the bytes. Sizes are dealt into blocks of a stack each.
    forms = cut(_relabelled(pairs))
    blocks = F.broadcast(forms.groupBy("n").agg(F.ceil(F.count("*") / _STACK).cast("int").alias("blocks")))  # a row a size
    dealt = forms.join(blocks, "n").select("n", F.pmod(F.xxhash64("before", "after"), F.col("blocks")).alias("block"), "before", "after", "balls")
    dealt = dealt.repartition(4 * pairs.sparkSession.sparkContext.defaultParallelism, "n", "block")
    each = dealt.groupBy("n", "block").applyInPandas(run, "solver string, balls bigint, rounds bigint, micros double, worst double")
    every = pairs.sparkSession.createDataFrame([("direct",), ("cold",), ("warm",)], "solver string").join(each, "solver", "left").na.fill(0)
    return every.groupBy("solver").agg(F.sum("balls").alias("balls"), F.sum("rounds").alias("rounds"), F.sum("micros").alias("micros"), F.max("worst").alias("worst"))


def wide(spectra: DataFrame, r: int) -> DataFrame:
    """spec as columns l1..lr, whose file statistics a reader can use to skip."""
    return spectra.select(*[c for c in spectra.columns if c != "spec"], *[F.col("spec")[i].alias(f"l{i + 1}") for i in range(r)])
