"""Experiments: every test on and off with the same engine and order, and the measures that compare them."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamatch.functions.bounds import RULES, exceeds, mass_cost
from deltamatch.operators import balls, engines, filters, gate, graph, index, invariants, spectra
from deltamatch.plans.query import Query
from deltamatch.session import cut
from deltamatch.sources.streams import alive_at


@dataclass(frozen=True)
class Config:
    """Which tests a run uses; the engine and its order stay the same."""

    vertex: bool = False
    phis: tuple[str, ...] = ()
    engine: str = "a"
    r: int = 4
    cap: int = 64


#: The control, each test alone, both, and the gate without the vertex layer.
CONFIGS = {
    "control": Config(),
    "vertex": Config(vertex=True),
    "laplacian_gate": Config(phis=("nv", "ne", "spec")),
    "triangle_gate": Config(phis=gate.PHIS),
    "vertex_gate": Config(vertex=True, phis=gate.PHIS),
    "vertex_gate_b": Config(vertex=True, phis=gate.PHIS, engine="b"),
    "control_b": Config(engine="b"),
}


def base_candidates(queries: list[Query], edges: DataFrame, vertices: DataFrame) -> DataFrame:
    adj = graph.adjacency(edges, vertices)
    return cut(filters.label_neighbour(filters.label_degree(queries, vertices, graph.degrees(adj)), queries, graph.label_profile(adj)))


def run(queries: list[Query], versions: DataFrame, vertices: DataFrame, config: Config, sign: int = 1, seconds: float | None = None) -> tuple[engines.Run, DataFrame, DataFrame | None]:
    """The run, its candidates and its gate log. Candidates come from the union of all edges, so they are safe at every update."""
    union = versions.select("src", "dst").distinct()
    cand = base_candidates(queries, union, vertices)
    if config.vertex:
        held = cut(index.envelope(versions, cand, r=config.r, cap=config.cap))
        cand = cut(filters.passed(filters.ball_tests(cand, queries, held, r=config.r)))
    log = cut(gate.decide(queries, versions, vertices, sign=sign, phis=config.phis, cap=config.cap, r=config.r)) if config.phis else None
    skips = gate.skips(log) if log is not None else None
    if config.engine == "b":
        return engines.delta_reduced(queries, versions, vertices, cand=cand, skips=skips, sign=sign), cand, log
    return engines.delta(queries, versions, vertices, cand=cand, skips=skips, sign=sign, seconds=seconds), cand, log


def matrix(queries: list[Query], versions: DataFrame, vertices: DataFrame, names: tuple[str, ...] = ("control", "vertex", "triangle_gate")) -> DataFrame:
    """(test, candidates, skipped, intermediates, matches, seconds) per configuration."""
    spark, rows = versions.sparkSession, []
    for name in names:
        result, cand, log = run(queries, versions, vertices, CONFIGS[name])
        made = result.levels.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        rows.append((name, cand.count(), gate.skips(log).count() if log is not None else 0, made, result.matches.count(), result.seconds))
    return spark.createDataFrame(rows, "test string, candidates bigint, skipped bigint, intermediates bigint, matches bigint, seconds double")


def modes(queries: list[Query], versions: DataFrame, vertices: DataFrame, names: tuple[str, ...] = ("off", "gate_only", "eager"), r: int = 4, cap: int = 64) -> DataFrame:
    """(mode, init_seconds, refresh_seconds, run_seconds, refreshes, index_rows, index_bytes, skipped, intermediates, matches).

    "off" runs no test; "gate_only" tests each update and keeps no index; "eager" also solves
    every asked ball at the start and again at each update that changes it, and takes
    candidates as they stand at each update.
    """
    spark, rows = versions.sparkSession, []
    base = base_candidates(queries, versions.select("src", "dst").distinct(), vertices)
    for name in names:
        init = refresh = 0.0
        refreshes = kept = skipped = 0
        cand, skips = base, None
        if name == "eager":
            began = time.monotonic()
            cut(index.consult(graph.both_ways(alive_at(versions, 0)), base, r=r, cap=cap))
            init, began = time.monotonic() - began, time.monotonic()
            held = cut(index.maintain(versions, base.select("v").distinct(), r=r, cap=cap))
            kept, refreshes = held.agg(F.count("*"), F.count_if(F.col("seq_from") > 0)).first()
            cand = cut(filters.passed(filters.ball_tests(base, queries, held, r=r)))
            refresh = time.monotonic() - began
        began = time.monotonic()
        if name != "off":
            skips = cut(gate.skips(gate.decide(queries, versions, vertices, cap=cap, r=r)))
            skipped = skips.count()
        run = engines.delta(queries, versions, vertices, cand=cand, skips=skips)
        made, found = run.levels.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0], run.matches.count()
        rows.append((name, init, refresh, time.monotonic() - began, refreshes, kept, kept * (24 + 8 * r), skipped, made, found))
    return spark.createDataFrame(rows, "mode string, init_seconds double, refresh_seconds double, run_seconds double, refreshes bigint, index_rows bigint, index_bytes bigint, skipped bigint, intermediates bigint, matches bigint")


def power(queries: list[Query], edges: DataFrame, vertices: DataFrame, r: int = 8, cap: int | None = 64) -> DataFrame:
    """Tests of all base candidates: (query_id, u, v, nv, killers)."""
    cand = base_candidates(queries, edges, vertices)
    held = cut(index.consult(graph.both_ways(edges), cand, r=r, cap=cap))
    return cut(filters.ball_tests(cand, queries, held, r=r))


def utility(tested: DataFrame) -> DataFrame:
    """(bucket, tested, rejected) by ball size, after the size test."""
    bucket = F.when(F.col("nv") <= 8, "01-08").when(F.col("nv") <= 16, "09-16").when(F.col("nv") <= 32, "17-32").when(F.col("nv") <= 64, "33-64").otherwise("65-")
    fine = tested.where(F.col("killers").bitwiseAND(1) == 0)
    return fine.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("tested"), F.sum((F.col("killers") > 0).cast("bigint")).alias("rejected"))


def coverage(tested: DataFrame, sizes: DataFrame, caps: tuple[int, ...] = (16, 32, 64, 128)) -> DataFrame:
    """(cap, deployed, vertices, retained, rejections) for each cap."""
    every = F.explode(F.array(*map(F.lit, caps))).alias("cap")
    held = sizes.select("nv", every).groupBy("cap").agg(F.sum((F.col("nv") <= F.col("cap")).cast("bigint")).alias("deployed"), F.count("*").alias("vertices"))
    kept = tested.where("killers > 1").select("nv", every).groupBy("cap").agg(F.sum((F.col("nv") <= F.col("cap")).cast("bigint")).alias("retained"), F.count("*").alias("rejections"))
    return held.join(kept, "cap", "left").na.fill(0)


def headroom(edges: DataFrame, cap: int = 64, t: int = 4) -> DataFrame:
    """(q25, median, q75) of the share the leading eigenvalues reach of what inner degrees allow."""
    adj = graph.both_ways(edges)
    ball = cut(balls.vertex_balls(adj, adj.select("v").distinct(), 2, cap))
    inside = cut(balls.induced_edges(ball, adj))
    found = spectra.laplacian_spectrum(balls.packed(ball, inside), t).join(invariants.conjugate_degrees(inside, t), "center")
    total = F.aggregate("spec", F.lit(0.0), lambda s, x: s + x)
    share = found.select((total / sum(F.col(f"d{i}") for i in range(1, t + 1))).alias("share"))
    return share.agg(*[F.expr(f"percentile(share, {p})").alias(n) for p, n in ((0.25, "q25"), (0.5, "median"), (0.75, "q75"))])


def retention(queries: list[Query], versions: DataFrame, vertices: DataFrame, taus: tuple[int, ...] = (1, 2, 4, 8), r: int = 8, cap: int = 64) -> DataFrame:
    """(tau, rule, base, retained, unsafe) after tau touching insertions.

    base counts pairs that exact values reject both at the start and after the touches;
    unsafe counts pairs a rule rejects although exact values admit them. The rule named
    per_update counts updates instead of edges, and may be unsafe.
    """
    initial = alive_at(versions, 0)
    adj0 = graph.both_ways(initial)
    cand = base_candidates(queries, versions.select("src", "dst").distinct(), vertices)
    stale = cut(index.consult(adj0, cand, r=r, cap=cap).where("state = 'deployed'"))
    ball0 = cut(balls.vertex_balls(adj0, stale.select("v"), 2, cap))
    before = cut(balls.induced_edges(ball0, adj0).withColumnRenamed("center", "v"))
    rejected = cut(filters.ball_tests(cand, queries, stale, r=r).where("killers > 1").select("query_id", "u", "v"))
    centers = rejected.select("v").distinct()
    inserts = versions.where("valid_from > 0")
    ever = graph.both_ways(versions.select("src", "dst").distinct())
    reach = cut(balls.vertex_balls(ever, centers, 2, None))
    met = inserts.join(reach.select(F.col("member").alias("src"), "center"), "src").join(reach.select(F.col("member").alias("dst"), "center"), ["dst", "center"]).select("center", F.col("valid_from").alias("at")).distinct()
    pairs = cut(met.withColumn("key", F.monotonically_increasing_id()))
    # Which of them lie in the ball as it is then.
    ball = cut(index.balls_at(pairs, versions, 2, cap))
    held = pairs.join(inserts.select(F.col("valid_from").alias("at"), "src", "dst"), "at").join(ball.select("key", F.col("member").alias("src")), ["key", "src"], "left_semi").join(ball.select("key", F.col("member").alias("dst")), ["key", "dst"], "left_semi")
    from pyspark.sql import Window

    numbered = held.select("key", "center", "at").distinct().withColumn("tau", F.row_number().over(Window.partitionBy("center").orderBy("at"))).where(F.col("tau").isin(list(taus)))
    numbered = cut(numbered)
    exact = cut(index._solved_at(numbered.select("key", "center", "at"), versions, 2, r, cap).where("spec IS NOT NULL"))
    inside = ball.select("key", "at", F.col("member").alias("a")).join(versions.select(F.col("src").alias("a"), F.col("dst").alias("b"), "valid_from", "valid_to"), "a").where("valid_from <= at AND at < valid_to").join(ball.select("key", F.col("member").alias("b")), ["key", "b"], "left_semi")
    # Edges that the ball has gained; deletions don't make up for them.
    gained = inside.join(numbered.select("key", F.col("center").alias("v")), "key").join(before, ["v", "a", "b"], "left_anti").groupBy("key").agg(F.count("*").alias("k"))
    at_tau = numbered.select("key", "tau").join(exact.select("key", F.col("center").alias("v"), F.col("spec").alias("now")), "key").join(gained, "key", "left").na.fill(0, ["k"])
    sides = versions.sparkSession.createDataFrame([(n, u, s) for n, u, _, s in filters.query_values(queries, 2, r)], "query_id string, u int, q array<double>")
    rows = rejected.join(F.broadcast(sides), ["query_id", "u"]).join(stale.select("v", F.col("spec").alias("d")), "v").join(at_tau, "v")
    q, d, k = F.col("q"), F.col("d"), F.col("k")
    rules = [F.struct(F.lit(n).alias("rule"), rule(q, d, k).alias("rejects")) for n, rule in RULES.items()] + [F.struct(F.lit("per_update").alias("rule"), exceeds(q, F.transform(d, lambda x: x + 2 * F.col("tau"))).alias("rejects"))]
    told = rows.select("tau", exceeds(q, F.col("now")).alias("truth"), F.explode(F.array(*rules)).alias("x"))
    return told.groupBy("tau", F.col("x.rule").alias("rule")).agg(F.sum(F.col("truth").cast("bigint")).alias("base"), F.sum((F.col("truth") & F.col("x.rejects")).cast("bigint")).alias("retained"), F.sum((~F.col("truth") & F.col("x.rejects")).cast("bigint")).alias("unsafe"))


def margins(queries: list[Query], edges: DataFrame, vertices: DataFrame, r: int = 8) -> DataFrame:
    """(n, q10, median, q90) of the mass that rejected pairs lack."""
    cand = base_candidates(queries, edges, vertices)
    held = cut(index.consult(graph.both_ways(edges), cand, r=r))
    sides = edges.sparkSession.createDataFrame([(n, u, s) for n, u, _, s in filters.query_values(queries, 2, r)], "query_id string, u int, q array<double>")
    cost = cand.join(F.broadcast(sides), ["query_id", "u"]).join(held.where("state = 'deployed'"), "v").select(mass_cost(F.col("q"), F.col("spec")).alias("cost")).where("cost > 1e-6")
    return cost.agg(F.count("*").alias("n"), *[F.expr(f"percentile(cost, {p})").alias(n) for p, n in ((0.1, "q10"), (0.5, "median"), (0.9, "q90"))])


def triggers(versions: DataFrame, deployed: DataFrame, h: int = 2, cap: int = 64) -> DataFrame:
    """(updates, exact, either): touched deployed vertices by both rules, on balls of the union of all edges."""
    ever = graph.both_ways(versions.select("src", "dst").distinct())
    rev = cut(index.reverse(balls.vertex_balls(ever, deployed, h, cap)))
    updates = versions.where("valid_from > 0").select(F.col("valid_from").alias("seq"), "src", "dst")
    both = index.touched(updates, rev, 0).agg(F.count("*").alias("exact"))
    either = index.touched(updates, rev, h, "either").agg(F.count("*").alias("either"))
    return updates.agg(F.count("*").alias("updates")).crossJoin(both).crossJoin(either)  # single rows


def overlap(tested: DataFrame, visited: DataFrame) -> DataFrame:
    """(query_id, rejected, visited, overlap, doomed) of pairs (u, v), accumulated over a stream.

    tested: ball tests on version rows; visited: a run's log of every binding. overlap counts
    pairs rejected at some time and visited at some time; doomed counts those visited while
    rejected. The others were visited only while admitted: their state flipped in the stream.
    """
    pair = ["query_id", "u", "v"]
    gone = cut(tested.where("killers > 0").select(*pair, "seq_from", "seq_to"))
    ever = gone.select(*pair).distinct()
    seen = visited.select(*pair).distinct()
    doomed = visited.join(gone, pair).where("seq_from <= seq AND seq < seq_to").select(*pair).distinct()
    count = lambda df, name: df.groupBy("query_id").agg(F.count("*").alias(name))
    out = count(ever, "rejected").join(count(seen, "visited"), "query_id", "full")
    for df, name in ((ever.join(seen, pair, "left_semi"), "overlap"), (doomed, "doomed")):
        out = out.join(count(df, name), "query_id", "left")
    return out.na.fill(0)


def budgets(queries: list[Query], versions: DataFrame, vertices: DataFrame, cand: DataFrame, seconds: float, factors: tuple[int, ...] = (1, 5, 10), batches: int = 4) -> list[tuple]:
    """(query_id, budget, factor, seconds, last_seq, intermediates, matches, solved): one run a query under the largest budget, read off for each."""
    last = versions.agg(F.max("valid_from")).first()[0] or 0
    out = []
    for q in queries:
        rows = engines.paced(q, versions, vertices, seconds=seconds * max(factors), cand=cand, batches=batches)
        for factor in factors:
            done = [r for i, r in enumerate(rows) if i == 0 or rows[i - 1][1] <= seconds * factor]
            spent, at = (done[-1][1], done[-1][0]) if done else (0.0, 0)
            out.append((q.name, seconds, factor, spent, at, sum(r[2] for r in done), sum(r[3] for r in done), at >= last and spent <= seconds * factor))
    return out


def static_costs(queries: list[Query], edges: DataFrame, vertices: DataFrame, r: int = 8) -> DataFrame:
    """(test, query_id, candidates, scans): construction with and without the spectral test."""
    adj = graph.both_ways(edges)
    base = base_candidates(queries, edges, vertices)
    held = cut(index.consult(adj, base, r=r))
    tested = cut(filters.passed(filters.ball_tests(base, queries, held, r=r)))
    out = None
    for name, cand in (("off", base), ("on", tested)):
        _, scans = engines.candidate_space(queries, cand, adj)
        rows = cand.groupBy("query_id").agg(F.count("*").alias("candidates")).join(scans, "query_id", "left").select(F.lit(name).alias("test"), "query_id", "candidates", F.coalesce("scans", F.lit(0)).alias("scans"))
        out = rows if out is None else out.union(rows)
    return out


def advise(engine: str, standing: bool) -> str:
    """Where aggregate tests pay: "full" for static, batch and list-driven engines and index builds, "gate" or "off" for adjacency-guided delta engines."""
    if engine in ("static", "batch", "list"):
        return "full"
    return "gate" if standing else "off"
