"""Anchored gates: skip an update if no label-compatible query edge can have a match through it.

A query edge's sub-query within rho must embed into the data ball within rho of the updated
edge; a monotone invariant that is larger on the query side disproves it. Tests run from
cheap to dear, and each stage only sees mappings that the stages before left open; updates
with a capped ball pass. Updates without any compatible query edge are reported apart.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamatch.functions.bounds import EPSILON
from deltamatch.plans.query import Query, invariant_values
from deltamatch.session import OPEN_END, cut

from .balls import edge_ball_edges, edge_balls, packed
from .graph import ANY, offered
from .invariants import all_counts
from .spectra import laplacian_spectrum

PHIS = ("nv", "ne", "tri", "spec")


def register(spark: SparkSession, queries: list[Query], rhos: tuple[int, ...] = (1, 2), r: int = 4) -> DataFrame:
    """(query_id, u, w, lu, lw, rho, q_nv, q_ne, q_tri, q_spec) of both directions of every query edge; a few rows."""
    rows = []
    for q in queries:
        for a, b in q.edges:
            for rho in rhos:
                n, edges = q.anchored(a, b, rho)
                x = invariant_values(n, edges, r)
                rows += [(q.name, u, w, q.labels[u], q.labels[w], rho, x["nv"], x["ne"], x["tri"], x["spec"]) for u, w in ((a, b), (b, a))]
    return spark.createDataFrame(rows, "query_id string, u int, w int, lu int, lw int, rho int, q_nv bigint, q_ne bigint, q_tri bigint, q_spec array<double>")


def data_side(updates: DataFrame, versions: DataFrame, rho: int, cap: int | None, *, before: bool = False, cheap: bool = False) -> tuple[DataFrame, DataFrame]:
    """(seq, nv, ne, tri) of each update's ball, and the ball packed for a solver."""
    ball = cut(edge_balls(updates, versions, rho, cap, before=before))
    if cheap:
        return ball.groupBy("seq").agg(F.count("*").alias("nv")), ball
    edges = cut(edge_ball_edges(ball, versions, before=before))
    return all_counts(ball, edges, "seq"), packed(ball, edges, "seq")


def decide(queries: list[Query], versions: DataFrame, vertices: DataFrame, *, sign: int = 1, rhos: tuple[int, ...] = (1, 2), phis: tuple[str, ...] = PHIS, cap: int | None = 64, r: int = 4, since: int = 0) -> DataFrame:
    """(query_id, seq, decision, killers): decision is "skip", "pass" or "label_skip"; killers has bit 4 (rho - 1) + i for each invariant i that disproved a mapping."""
    spark = versions.sparkSession
    before = sign < 0
    at, other = (("valid_to", F.col("valid_to") < OPEN_END) if before else ("valid_from", F.col("valid_from") > 0))
    updates = cut(versions.where(other & (F.col(at) > since)).select(F.col(at).alias("seq"), "src", "dst"))
    reg = register(spark, queries, rhos, r)
    ends = vertices.select("id", F.coalesce("label", F.lit(-1)).alias("label"))
    known = updates.join(ends.withColumnsRenamed({"id": "src", "label": "l1"}), "src", "left").join(ends.withColumnsRenamed({"id": "dst", "label": "l2"}), "dst", "left")
    known = known.select("seq", "l2", offered("l1").alias("lu")).select("seq", "lu", offered("l2").alias("lw"))
    asked = reg.select("query_id", "u", "w", F.coalesce("lu", F.lit(ANY)).alias("lu"), F.coalesce("lw", F.lit(ANY)).alias("lw")).distinct()
    mappings = cut(known.join(F.broadcast(asked), ["lu", "lw"]).select("seq", "query_id", "u", "w"))
    key = ["seq", "query_id", "u", "w"]
    killed = None
    left = mappings
    for rho in rhos:
        open_updates = updates.join(left.select("seq").distinct(), "seq", "left_semi")
        counted, held = data_side(open_updates, versions, rho, cap, before=before, cheap=phis == ("nv",))
        asked = F.broadcast(reg.where(F.col("rho") == rho).drop("rho", "lu", "lw"))
        met = left.join(asked, ["query_id", "u", "w"]).join(counted, "seq", "left")
        bits = F.lit(0)
        for i, phi in enumerate(("nv", "ne", "tri")):
            if phi in phis:
                bits = bits + F.when(F.coalesce(F.col(f"q_{phi}") > F.col(phi), F.lit(False)), 1 << (4 * (rho - 1) + i)).otherwise(0)
        tested = cut(met.select(*key, "q_spec", bits.alias("killers")))
        found = tested.where("killers > 0").select(*key, "killers")
        if "spec" in phis:
            undecided = tested.where("killers = 0")
            balls = held.join(undecided.select("seq").distinct(), "seq", "left_semi")
            spectra = laplacian_spectrum(balls, r, "seq").select("seq", "spec")
            low = F.exists(F.zip_with("q_spec", "spec", lambda q, d: q > d + EPSILON * F.greatest(F.lit(1.0), q)), lambda b: b)
            found = found.union(undecided.join(spectra, "seq").where(low).select(*key, F.lit(1 << (4 * (rho - 1) + 3))))
        found = cut(found)
        killed = found if killed is None else killed.union(found)
        left = cut(left.join(found, key, "left_anti"))
    by = mappings.join(killed.groupBy(*key).agg(F.bit_or("killers").alias("killers")), key, "left").groupBy("query_id", "seq")
    decided = by.agg(F.bool_and(F.col("killers").isNotNull()).alias("all"), F.coalesce(F.bit_or("killers"), F.lit(0)).cast("int").alias("killers"))
    names = F.broadcast(spark.createDataFrame([(q.name,) for q in queries], "query_id string"))
    every = updates.select("seq", F.explode(F.lit([q.name for q in queries])).alias("query_id"))
    return every.join(names, "query_id", "left_semi").join(decided, ["query_id", "seq"], "left").select("query_id", "seq", F.when(F.col("all").isNull(), "label_skip").when(F.col("all"), "skip").otherwise("pass").alias("decision"), F.coalesce("killers", F.lit(0)).alias("killers"))


def open_mappings(queries: list[Query], versions: DataFrame, vertices: DataFrame, **options) -> DataFrame:
    """(query_id, seq) with at least one mapping left."""
    return decide(queries, versions, vertices, **options).where("decision = 'pass'").select("query_id", "seq")


def skips(log: DataFrame) -> DataFrame:
    return log.where("decision = 'skip'").select("query_id", "seq")


def rates(log: DataFrame, matches: DataFrame) -> DataFrame:
    """(query_id, processed, skipped, label_skipped, wrong): wrong counts skipped updates that a control run finds matches for; it must be 0."""
    wrong = log.where("decision <> 'pass'").join(matches.select("query_id", "seq").distinct(), ["query_id", "seq"], "left_semi").groupBy("query_id").agg(F.count("*").alias("wrong"))
    out = log.groupBy("query_id").agg(F.sum((F.col("decision") != "label_skip").cast("bigint")).alias("processed"), F.sum((F.col("decision") == "skip").cast("bigint")).alias("skipped"), F.sum((F.col("decision") == "label_skip").cast("bigint")).alias("label_skipped"))
    return out.join(wrong, "query_id", "left").select("query_id", "processed", "skipped", "label_skipped", F.coalesce("wrong", F.lit(0)).alias("wrong"))
