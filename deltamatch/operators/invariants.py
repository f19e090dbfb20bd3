"""Subgraph-monotone invariants of balls, and the degree sequences they are compared with."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def counts(ball: DataFrame, edges: DataFrame, key: str = "center") -> DataFrame:
    """(key, nv, ne)."""
    ne = edges.groupBy(key).agg(F.count("*").alias("ne"))
    return ball.groupBy(key).agg(F.count("*").alias("nv")).join(ne, key, "left").select(key, "nv", F.coalesce("ne", F.lit(0)).cast("bigint").alias("ne"))


def triangles(edges: DataFrame, key: str = "center") -> DataFrame:
    """(key, tri) of the balls that hold a triangle; edges have a < b, so each is met once as a < b < c."""
    ab = edges.select(key, "a", "b")
    bc = edges.select(key, F.col("a").alias("b"), F.col("b").alias("c"))
    ac = edges.select(key, "a", F.col("b").alias("c"))
    return ab.join(bc, [key, "b"]).join(ac, [key, "a", "c"]).groupBy(key).agg(F.count("*").alias("tri"))


def all_counts(ball: DataFrame, edges: DataFrame, key: str = "center") -> DataFrame:
    """(key, nv, ne, tri)."""
    return counts(ball, edges, key).join(triangles(edges, key), key, "left").select(key, "nv", "ne", F.coalesce("tri", F.lit(0)).cast("bigint").alias("tri"))


def ball_degrees(edges: DataFrame, key: str = "center") -> DataFrame:
    """(key, member, degree): degrees inside the ball, of members with an edge."""
    ends = edges.select(key, F.col("a").alias("member")).union(edges.select(key, "b"))
    return ends.groupBy(key, "member").agg(F.count("*").alias("degree"))


def conjugate_degrees(edges: DataFrame, t: int = 4, key: str = "center") -> DataFrame:
    """(key, d1..dt): d_i is the number of members of degree at least i; their sums bound the leading eigenvalues' sums."""
    each = ball_degrees(edges, key)
    return each.groupBy(key).agg(*[F.sum((F.col("degree") >= i).cast("bigint")).alias(f"d{i}") for i in range(1, t + 1)])


@dataclass(frozen=True)
class Invariant:
    """A monotone invariant: column of the data side, value on the query side, and the slack of a rejection."""

    name: str
    query_value: Callable[[int, list[tuple[int, int]]], float]
    exact: bool = True


def query_triangles(n: int, edges: list[tuple[int, int]]) -> int:
    near = [set() for _ in range(n)]
    for a, b in edges:
        near[a].add(b)
        near[b].add(a)
    return sum(len(near[a] & near[b]) for a, b in edges) // 3


REGISTRY = {
    "nv": Invariant("nv", lambda n, e: n),
    "ne": Invariant("ne", lambda n, e: len(e)),
    "tri": Invariant("tri", query_triangles),
}
