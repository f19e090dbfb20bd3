"""Arrow functions and table functions for SQL users."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType

from deltamatch.operators.spectra import spectra_of

from . import bounds


@pandas_udf(ArrayType(DoubleType()))
def laplacian_top(ends: pd.Series, r: pd.Series) -> pd.Series:
    """Leading r eigenvalues of the graph whose edges are the flat array a0, b0, a1, b1, ..."""
    flat = [np.asarray(e if e is not None else [], dtype=np.int64) for e in ends]
    most = int(r.max()) if len(r) else 0
    return pd.Series([s[: int(k)] for s, k in zip(spectra_of(np.array([len(set(e.tolist())) for e in flat]), flat, most), r)])


@pandas_udf(ArrayType(DoubleType()))
def ball_spectrum(a: pd.Series, b: pd.Series) -> list[float]:
    """Grouped: all eigenvalues of the graph with the group's edges (a, b)."""
    flat = np.stack([a.to_numpy(), b.to_numpy()], axis=1).ravel()
    return spectra_of(np.array([len(set(flat.tolist()))]), [flat], None)[0].tolist()


@udtf(returnType="u INT, near INT, depth INT")
class expand_query:
    """Rows (u, near, depth) of a query given as text "0-1,1-2": its edges in both directions, with u's distance from vertex 0."""

    def eval(self, edges: str) -> Iterator[tuple[int, int, int]]:
        pairs = [tuple(map(int, e.split("-"))) for e in (edges or "").split(",") if e]
        near: dict[int, list[int]] = {}
        for a, b in pairs:
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        depth, ready = {0: 0}, deque([0])
        while ready:
            u = ready.popleft()
            for w in near.get(u, []):
                if w not in depth:
                    depth[w] = depth[u] + 1
                    ready.append(w)
        for u in sorted(near):
            for w in near[u]:
                yield u, w, depth.get(u, -1)


def register(spark: SparkSession) -> None:
    """laplacian_top, ball_spectrum, expand_query and the bound functions for SQL."""
    spark.udf.register("laplacian_top", laplacian_top)
    spark.udf.register("ball_spectrum", ball_spectrum)
    spark.udtf.register("expand_query", expand_query)
    bounds.register(spark)
