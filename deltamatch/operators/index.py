"""Local spectra index: exact leading eigenvalues of small balls, kept as version rows.

Life of a vertex: undeployed (passes every test) until a candidate list first asks for it;
deployed with exact values, solved anew at each update that changes its ball; evicted for
good once its ball outgrows the cap, and passing again. Granularities: "update" makes one
version row per change, exact at every moment; "batch" makes one upper bound for a whole
batch from the union of all its edges, which monotonicity makes safe for each moment in it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltamatch.plans.query import Query
from deltamatch.session import OPEN_END, cut

from .balls import induced_edges, packed, vertex_balls
from .filters import ball_tests
from .graph import both_ways
from .spectra import laplacian_spectrum


def consult(adj: DataFrame, asked: DataFrame, known: DataFrame | None = None, *, h: int = 2, r: int = 4, cap: int | None = 64) -> DataFrame:
    """(v, nv, spec, state) of the vertices asked (v) that known doesn't hold yet: "deployed", or "evicted" with nulls."""
    new = asked.select("v").distinct()
    if known is not None:
        new = new.join(known, "v", "left_anti")
    new = cut(new)
    ball = cut(vertex_balls(adj, new, h, cap))
    solved = laplacian_spectrum(packed(ball, induced_edges(ball, adj)), r)
    return new.join(solved.withColumnRenamed("center", "v"), "v", "left").select("v", "nv", "spec", F.when(F.col("spec").isNull(), "evicted").otherwise("deployed").alias("state"))


def envelope(versions: DataFrame, asked: DataFrame, *, h: int = 2, r: int = 4, cap: int | None = 64) -> DataFrame:
    """consult on every edge that lives at any time in versions: an upper bound at each of those times."""
    return consult(both_ways(versions.select("src", "dst").distinct()), asked, h=h, r=r, cap=cap)


def reverse(ball: DataFrame) -> DataFrame:
    """(member, center, dist): in which balls a vertex lies."""
    return ball.select("member", "center", "dist")


def touched(updates: DataFrame, rev: DataFrame, h: int = 2, mode: str = "exact") -> DataFrame:
    """(seq, center) of the balls an update concerns, from membership before it.

    "exact": both ends lie in the ball with the new edge: both did already, or one lies
    within h - 1 and draws the other in. "either": one end lies in it, the naive superset.
    """
    near = lambda end: updates.select("seq", F.col(end).alias("member")).join(rev, "member").select("seq", "center", F.col("dist").alias(f"d_{end}"))
    met = near("src").join(near("dst"), ["seq", "center"], "full")
    if mode == "exact":
        met = met.where(f"(d_src IS NOT NULL AND d_dst IS NOT NULL) OR d_src <= {h - 1} OR d_dst <= {h - 1}")
    return met.select("seq", "center")


def touched_at(updates: DataFrame, versions: DataFrame, h: int = 2, mode: str = "exact") -> DataFrame:
    """`touched` against the balls as they stand just before each update (seq, src, dst), an insertion or a deletion.

    Distance is symmetric, so the centers whose balls hold an end are the ball around that
    end: work follows the updates and not the number of centers.
    """
    ends = updates.select("seq", F.posexplode(F.array("src", "dst")).alias("end", "center"))
    ball = balls_at(ends.select((2 * F.col("seq") + F.col("end")).alias("key"), "center", (F.col("seq") - 1).alias("at")), versions, h, None)
    near = lambda end: F.min(F.when(F.col("key") % 2 == end, F.col("dist")))
    met = ball.groupBy(F.shiftright("key", 1).alias("seq"), F.col("member").alias("center")).agg(near(0).alias("d_src"), near(1).alias("d_dst"))
    if mode == "exact":
        met = met.where(f"(d_src IS NOT NULL AND d_dst IS NOT NULL) OR d_src <= {h - 1} OR d_dst <= {h - 1}")
    return met.select("seq", "center")


def balls_at(pairs: DataFrame, versions: DataFrame, h: int, cap: int | None) -> DataFrame:
    """(key, member, dist) of the ball of `center` in the graph at `at`, for pairs (key, center, at); beyond cap absent."""
    hops = both_ways(versions)
    ball = pairs.select("key", "at", F.col("center").alias("member"), F.lit(0).alias("dist"))
    for step in range(1, h + 1):
        far = ball.where(F.col("dist") == step - 1).join(hops, F.col("member") == F.col("v")).where("valid_from <= at AND at < valid_to").select("key", "at", F.col("w").alias("member"), F.lit(step).alias("dist"))
        ball = cut(ball.union(far).groupBy("key", "at", "member").agg(F.min("dist").alias("dist")))
        if cap is not None:
            ball = ball.join(ball.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > cap).select("key"), "key", "left_anti")
    return ball


def _solved_at(pairs: DataFrame, versions: DataFrame, h: int, r: int, cap: int | None) -> DataFrame:
    """pairs with nv and spec, null where the ball exceeds cap."""
    ball = cut(balls_at(pairs, versions, h, cap))
    inside = ball.select("key", "at", F.col("member").alias("a"))
    edges = inside.join(versions.select(F.col("src").alias("a"), F.col("dst").alias("b"), "valid_from", "valid_to"), "a").where("valid_from <= at AND at < valid_to")
    edges = edges.join(ball.select("key", F.col("member").alias("b")), ["key", "b"], "left_semi").select("key", "a", "b")
    solved = laplacian_spectrum(packed(ball.select("key", "member"), edges, "key"), r, "key")
    return pairs.join(solved, "key", "left")


def maintain(versions: DataFrame, deployed: DataFrame, *, h: int = 2, r: int = 4, cap: int = 64, redeploy: bool = False) -> DataFrame:
    """Version rows (v, seq_from, seq_to, nv, state, spec) of the vertices deployed (v) over a whole stream.

    A center is solved anew at the updates that change its ball as it then stands. From the
    first moment beyond cap on a vertex is evicted, unless `redeploy` lets it come back.
    """
    changes = versions.where("valid_from > 0").select(F.col("valid_from").alias("seq"), "src", "dst").union(versions.where(F.col("valid_to") < OPEN_END).select("valid_to", "src", "dst"))
    both = touched_at(changes, versions, h).join(deployed.select(F.col("v").alias("center")).distinct(), "center", "left_semi").select("center", F.col("seq").alias("at"))
    pairs = deployed.select(F.col("v").alias("center"), F.lit(0).cast("bigint").alias("at")).union(both).distinct()
    pairs = cut(pairs.withColumn("key", F.monotonically_increasing_id()))
    solved = _solved_at(pairs, versions, h, r, cap)
    by = Window.partitionBy("center").orderBy("at")
    rows = solved.withColumn("out", F.max(F.col("spec").isNull().cast("int")).over(by.rowsBetween(Window.unboundedPreceding, 0)))
    held = F.col("spec").isNotNull() if redeploy else F.col("out") == 0
    rows = rows.withColumn("state", F.when(held, "deployed").otherwise("evicted")).withColumn("spec", F.when(held, F.col("spec"))).withColumn("nv", F.when(held, F.col("nv")))
    same = F.lag(F.struct("state", "nv", F.transform("spec", lambda x: F.round(x, 9)))).over(by).eqNullSafe(F.struct("state", "nv", F.transform("spec", lambda x: F.round(x, 9))))
    rows = rows.withColumn("same", same).where("NOT same OR at = 0")
    return rows.select(F.col("center").alias("v"), F.col("at").alias("seq_from"), F.coalesce(F.lead("at").over(by), F.lit(OPEN_END)).alias("seq_to"), "nv", "state", "spec")


def spectra_at(rows: DataFrame, seq: int) -> DataFrame:
    """What the index holds at one moment."""
    return rows.where((F.col("seq_from") <= seq) & (F.col("seq_to") > seq)).select("v", "nv", "state", "spec")


def anomaly_scores(rows: DataFrame) -> DataFrame:
    """(v, seq, jump): how far the leading values move at each version, for other consumers of local spectra."""
    by = Window.partitionBy("v").orderBy("seq_from")
    before = F.lag("spec").over(by)
    jump = F.aggregate(F.zip_with("spec", before, lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: s + x)
    return rows.select("v", F.col("seq_from").alias("seq"), jump.alias("jump")).where("jump IS NOT NULL")


def resync(queries: list[Query], cand: DataFrame, before: DataFrame, after: DataFrame, *, h: int = 2, r: int = 4, gated: bool = True) -> DataFrame:
    """(query_id, u, v, change): candidate pairs that new spectra admit again ("+") or reject ("-"), of all label-matching pairs cand.

    gated: only vertices whose kept values changed are tested again.
    """
    if gated:
        moved = after.join(before.select("v", F.col("spec").alias("old")), "v", "left").where(~F.transform("spec", lambda x: F.round(x, 9)).eqNullSafe(F.transform("old", lambda x: F.round(x, 9)))).select("v")
        cand = cand.join(moved.distinct(), "v", "left_semi")
    old = ball_tests(cand, queries, before, h, r).select("query_id", "u", "v", (F.col("killers") == 0).alias("was"))
    new = ball_tests(cand, queries, after, h, r).select("query_id", "u", "v", (F.col("killers") == 0).alias("now"))
    return old.join(new, ["query_id", "u", "v"]).where("was <> now").select("query_id", "u", "v", F.when(F.col("now"), "+").otherwise("-").alias("change"))


def compact(rev: DataFrame, live: DataFrame) -> DataFrame:
    """Reverse rows of live centers (v) only."""
    return rev.join(live.select(F.col("v").alias("center")), "center", "left_semi").select("member", "center", "dist")


def check_complete(bindings: DataFrame, cand: DataFrame) -> DataFrame:
    """Bindings (query_id, u, v) of true matches that the candidates lack; empty if no test is wrong."""
    return bindings.join(cand, ["query_id", "u", "v"], "left_anti")


def bindings(matches: DataFrame) -> DataFrame:
    """(query_id, u, v) of matches (query_id, bind)."""
    return matches.select("query_id", F.posexplode("bind").alias("u", "v")).distinct()


def footprint(spectra: DataFrame, rev: DataFrame, profile: DataFrame, r: int = 4) -> DataFrame:
    """(spectra_bytes, reverse_bytes, profile_bytes): fixed widths times rows."""
    n = spectra.where("state = 'deployed'").agg((F.count("*") * (8 + 8 * r)).alias("spectra_bytes"))
    return n.crossJoin(rev.agg((F.count("*") * 16).alias("reverse_bytes"))).crossJoin(profile.agg((F.count("*") * 16).alias("profile_bytes")))  # single rows


def write_layout(spectra: DataFrame, path: str, r: int = 4) -> None:
    """Wide rows sorted by the leading value within buckets of vertices, so that `l1 >= x` skips row groups."""
    wide = spectra.select("v", "nv", "state", *[F.col("spec")[i].alias(f"l{i + 1}") for i in range(r)])
    wide.repartition("v").sortWithinPartitions("l1").write.mode("overwrite").parquet(path)
