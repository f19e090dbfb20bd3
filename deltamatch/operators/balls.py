"""Capped balls around vertices and edges, their induced edges, and packed forms for solvers.

A center one of whose members within distance h - 1 has `cap` or more neighbours has more
than `cap` members: that member's closed neighbourhood lies inside. Such centers overflow
before their last hop is expanded, so a hop never makes more than cap rows per member.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamatch.session import cut

from .graph import both_ways, degrees


def vertex_balls(adj: DataFrame, centers: DataFrame, h: int = 2, cap: int | None = 64) -> DataFrame:
    """(center, member, dist) of the balls with at most cap members; centers (v) that overflow are absent.

    adj: v, w of all edges in both directions. Without cap every ball is kept.
    """
    hops = adj.select("v", "w").distinct()
    ball = centers.select(F.col("v").alias("center"), F.col("v").alias("member"), F.lit(0).alias("dist")).distinct()
    degree = degrees(hops) if cap is not None else None
    for step in range(1, h + 1):
        if cap is not None:
            rich = ball.join(degree.where(F.col("degree") >= cap), ball.member == degree.v, "left_semi").select("center").distinct()
            ball = ball.join(rich, "center", "left_anti")
        far = ball.where(F.col("dist") == step - 1).join(hops, F.col("member") == F.col("v")).select("center", F.col("w").alias("member"), F.lit(step).alias("dist"))
        # Each hop reads the ball several times, so it is written out.
        ball = cut(ball.union(far).groupBy("center", "member").agg(F.min("dist").alias("dist")))
        if cap is not None:
            over = ball.groupBy("center").agg(F.count("*").alias("n")).where(F.col("n") > cap).select("center")
            ball = ball.join(over, "center", "left_anti")
    return ball


def induced_edges(ball: DataFrame, adj: DataFrame) -> DataFrame:
    """(center, a, b) with a < b: the edges inside each ball."""
    inside = ball.select("center", F.col("member").alias("a"))
    edges = adj.where("v < w").select(F.col("v").alias("a"), F.col("w").alias("b")).distinct()
    other = ball.select("center", F.col("member").alias("b"))
    return inside.join(edges, "a").join(other, ["center", "b"], "left_semi").select("center", "a", "b")


def sizes(ball: DataFrame) -> DataFrame:
    return ball.groupBy("center").agg(F.count("*").alias("nv"))


def overflow(centers: DataFrame, ball: DataFrame) -> DataFrame:
    """Centers (v) without a ball."""
    return centers.join(ball.select(F.col("center").alias("v")).distinct(), "v", "left_anti")


def degree_screen(adj: DataFrame, cap: int) -> DataFrame:
    """(v, over): whether v's own two-hop ball must exceed cap, from degrees alone."""
    degree = degrees(adj.select("v", "w").distinct())
    rich = degree.where(F.col("degree") >= cap).select("v")
    near = adj.select("v", "w").join(rich.withColumnRenamed("v", "w"), "w", "left_semi").select("v").union(rich).distinct()
    return degree.select("v").join(near.withColumn("over", F.lit(True)), "v", "left").select("v", F.coalesce("over", F.lit(False)).alias("over"))


def edge_balls(updates: DataFrame, versions: DataFrame, rho: int, cap: int | None = 64, *, before: bool = False) -> DataFrame:
    """(seq, member, dist) of the vertices within rho of either end of each update.

    The graph is that with the inserted edge, or, with `before`, that which still holds the
    deleted one. A lifetime test goes with the equi-join on the vertex. Updates whose ball
    would exceed cap are absent: they pass every test.
    """
    at = F.col("seq") - 1 if before else F.col("seq")
    hops = both_ways(versions)
    ball = updates.select("seq", F.explode(F.array("src", "dst")).alias("member"), F.lit(0).alias("dist")).distinct()
    for step in range(1, rho + 1):
        far = ball.where(F.col("dist") == step - 1).join(hops, F.col("member") == F.col("v")).where((F.col("valid_from") <= at) & (at < F.col("valid_to")))
        far = far.select("seq", F.col("w").alias("member"), F.lit(step).alias("dist"))
        ball = cut(ball.union(far).groupBy("seq", "member").agg(F.min("dist").alias("dist")))
        if cap is not None:
            over = ball.groupBy("seq").agg(F.count("*").alias("n")).where(F.col("n") > cap).select("seq")
            ball = ball.join(over, "seq", "left_anti")
    return ball


def edge_ball_edges(ball: DataFrame, versions: DataFrame, *, before: bool = False) -> DataFrame:
    """(seq, a, b): edges alive at the update inside its ball."""
    at = F.col("seq") - 1 if before else F.col("seq")
    inside = ball.select("seq", F.col("member").alias("a"))
    edges = versions.select(F.col("src").alias("a"), F.col("dst").alias("b"), "valid_from", "valid_to")
    met = inside.join(edges, "a").where((F.col("valid_from") <= at) & (at < F.col("valid_to")))
    return met.join(ball.select("seq", F.col("member").alias("b")), ["seq", "b"], "left_semi").select("seq", "a", "b")


def packed(ball: DataFrame, edges: DataFrame, key: str = "center") -> DataFrame:
    """(key, nv, ends): ends is one flat array a0, b0, a1, b1, ... of the ball's edges."""
    held = edges.groupBy(key).agg(F.flatten(F.array_sort(F.collect_list(F.array("a", "b")))).alias("ends"))
    return ball.groupBy(key).agg(F.count("*").alias("nv")).join(held, key, "left").select(key, "nv", F.coalesce("ends", F.array().cast("array<bigint>")).alias("ends"))
