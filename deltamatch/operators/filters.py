"""Candidate filters: label and degree, neighbour labels, ball size, interlacing, propagation; and their attribution."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltamatch.functions.bounds import EPSILON
from deltamatch.plans.query import Query, padded_spectrum, query_vertices
from deltamatch.session import cut

from .graph import offered
from .invariants import ball_degrees


def label_degree(queries: list[Query], vertices: DataFrame, degree: DataFrame) -> DataFrame:
    """(query_id, u, v): vertices with u's label and at least its degree. The query side is a few rows."""
    wanted = query_vertices(vertices.sparkSession, queries)
    rows = vertices.join(degree, vertices.id == degree.v).select("v", "degree", offered("label").alias("q_label"))
    return rows.join(F.broadcast(wanted), "q_label").where("degree >= q_degree").select("query_id", "u", "v")


def label_neighbour(cand: DataFrame, queries: list[Query], profile: DataFrame) -> DataFrame:
    """Candidates with at least as many neighbours of each label as u has in its query: none of the needs is short."""
    spark = cand.sparkSession
    needs = [(q.name, u, label, n) for q in queries for u in range(q.size) for label, n in q.needs(u).items()]
    if not needs:
        return cand
    need = F.broadcast(spark.createDataFrame(needs, "query_id string, u int, w_label int, need bigint"))
    asked = cand.join(need, ["query_id", "u"])
    short = asked.join(profile, ["v", "w_label"], "left").where(F.coalesce("n", F.lit(0)) < F.col("need")).select("query_id", "u", "v").distinct()
    return cand.join(short, ["query_id", "u", "v"], "left_anti")


def query_values(queries: list[Query], h: int, r: int) -> list[tuple]:
    """(query_id, u, ball size, leading eigenvalues of the query ball) on the driver."""
    out = []
    for q in queries:
        for u in range(q.size):
            n, edges = q.ball(u, h)
            out.append((q.name, u, n, padded_spectrum(n, edges, r)))
    return out


def ball_tests(cand: DataFrame, queries: list[Query], spectra: DataFrame, h: int = 2, r: int = 4) -> DataFrame:
    """cand with killers: bit 0 where the data ball is too small, bit t where eigenvalue t is too low.

    spectra: (v, nv, spec) of deployed vertices; others pass. Version rows keep their seq_from
    and seq_to, with a result for each. One broadcast of the query side, one join by v.
    """
    times = [c for c in ("seq_from", "seq_to") if c in spectra.columns]
    asked = cand.sparkSession.createDataFrame(query_values(queries, h, r), "query_id string, u int, q_nv int, q_spec array<double>")
    met = cand.join(F.broadcast(asked), ["query_id", "u"]).join(spectra.select("v", "nv", "spec", *times), "v", "left")
    bits = F.when(F.col("nv") < F.col("q_nv"), 1).otherwise(0)
    for t in range(r):
        q, d = F.col("q_spec")[t], F.col("spec")[t]
        bits = bits + F.when(q > d + EPSILON * F.greatest(F.lit(1.0), q), 1 << (t + 1)).otherwise(0)
    return met.select("query_id", "u", "v", "nv", F.coalesce(F.when(F.col("spec").isNotNull(), bits), F.lit(0)).cast("int").alias("killers"), *times)


def passed(tested: DataFrame, *, size_only: bool = False) -> DataFrame:
    """Pairs that pass, with the times they do if tested on version rows."""
    fine = F.col("killers").bitwiseAND(1) == 0 if size_only else F.col("killers") == 0
    return tested.where(fine).select("query_id", "u", "v", *[c for c in ("seq_from", "seq_to") if c in tested.columns])


def attribution(tested: DataFrame, r: int = 4) -> DataFrame:
    """(component, first, any): rejections by eigenvalue, as the first that fires and at all; component 0 is the size test."""
    bits = F.explode(F.array(*[F.struct(F.lit(t).alias("component"), F.col("killers").bitwiseAND(1 << t).alias("bit"), F.col("killers").bitwiseAND((1 << t) - 1).alias("lower")) for t in range(r + 1)]))
    rows = tested.where("killers > 0").select("killers", bits.alias("b")).where("b.bit > 0")
    return rows.groupBy(F.col("b.component").alias("component")).agg(F.sum((F.col("b.lower") == 0).cast("bigint")).alias("first"), F.count("*").alias("any"))


def hub_excluded(ball_edges: DataFrame, q_max: int, r: int = 4) -> DataFrame:
    """(center, component): components that can't reject, since the component-th degree inside the ball is at least q_max + component - 1."""
    rank = F.row_number().over(Window.partitionBy("center").orderBy(F.desc("degree"), "member"))
    ranked = ball_degrees(ball_edges).withColumn("component", rank).where(F.col("component") <= r)
    return ranked.where(F.col("degree") >= F.lit(q_max - 1) + F.col("component")).select("center", "component")


def propagate(cand: DataFrame, queries: list[Query], adj: DataFrame, mode: str = "arc", most_rounds: int = 12) -> DataFrame:
    """Candidates that keep, for neighbours of u, an adjacent candidate.

    Modes: "none"; "tree" and "dag": one pass towards and one away from vertex 0 over a
    spanning tree or all edges; "arc": all edges until nothing changes; "assign": arc,
    then distinct neighbours for each (at least as many candidates around v as u has neighbours).
    """
    if mode == "none":
        return cand
    spark = cand.sparkSession
    rounds: list[list[tuple[str, int, int]]] = []
    if mode in ("tree", "dag"):
        down, up = [], []
        for q in queries:
            depth = q.distances(0)
            for x, y in q.edges:
                a, b = sorted((x, y), key=lambda v: (depth[v], v))
                if mode == "dag" or a == min((p for p in q.near(b)), key=lambda p: (depth[p], p)):
                    up.append((q.name, a, b))
                    down.append((q.name, b, a))
        rounds = [up, down]
    else:
        rounds = [[(q.name, *e) for q in queries for a, b in q.edges for e in ((a, b), (b, a))]] * most_rounds
    hops = adj.select("v", "w").distinct()
    before = None
    for need in rounds:
        needs = F.broadcast(spark.createDataFrame(need, "query_id string, u int, other int"))
        # v stays for u if each needed neighbour has an adjacent candidate.
        seen = cand.join(needs, ["query_id", "u"]).join(hops, "v").select("query_id", "u", "v", "other", "w")
        held = seen.join(cand.select("query_id", F.col("u").alias("other"), F.col("v").alias("w")), ["query_id", "other", "w"], "left_semi")
        met = held.groupBy("query_id", "u", "v").agg(F.count_distinct("other").alias("met"), F.count_distinct("w").alias("around"))
        asked = needs.groupBy("query_id", "u").agg(F.count("*").alias("asked"))
        state = cand.join(F.broadcast(asked), ["query_id", "u"], "left").join(met, ["query_id", "u", "v"], "left")
        fine = F.coalesce("met", F.lit(0)) >= F.coalesce("asked", F.lit(0))
        if mode == "assign":
            fine = fine & (F.coalesce("around", F.lit(0)) >= F.coalesce("asked", F.lit(0)))
        cand = cut(state.where(fine).select("query_id", "u", "v"))
        if mode in ("arc", "assign"):
            now = cand.count()
            if now == before:
                break
            before = now
    return cand


def dominance(cand: DataFrame, queries: list[Query], profile: DataFrame, degree: DataFrame) -> DataFrame:
    """Candidates whose vector (degree, then the sum of the neighbours' degrees) dominates the query vertex's, both monotone."""
    spark = cand.sparkSession
    rows = [(q.name, u, len(q.near(u)), sum(len(q.near(w)) for w in q.near(u))) for q in queries for u in range(q.size)]
    asked = F.broadcast(spark.createDataFrame(rows, "query_id string, u int, q1 bigint, q2 bigint"))
    vector = profile.select("v", "w").join(degree.withColumnsRenamed({"v": "w", "degree": "dw"}), "w").groupBy("v").agg(F.count("*").alias("d1"), F.sum("dw").alias("d2"))
    return cand.join(asked, ["query_id", "u"]).join(vector, "v").where("d1 >= q1 AND d2 >= q2").select("query_id", "u", "v")


def pipeline(cand: DataFrame, *steps) -> DataFrame:
    return reduce(lambda c, step: step(c), steps, cand)
