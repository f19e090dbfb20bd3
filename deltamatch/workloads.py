"""Registered queries: each method, baseline and measure on the given tables. Their SQL twins are in `oracles`."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamatch import experiments as X
from deltamatch.functions import bounds
from deltamatch.operators import balls, engines, filters, gate, graph, index, invariants, meetings, spectra
from deltamatch.plans.query import Query, pattern, sample
from deltamatch.session import cut
from deltamatch.sources import graphs, streams

CAP, R = 64, 4
#: Patterns with labels 0..3 of the co-purchase graph (p_size modulo 4).
LABELLED = (
    Query("labelled_path", (0, 1, 2), ((0, 1), (1, 2))),
    Query("labelled_triangle", (0, 1, 2), ((0, 1), (0, 2), (1, 2))),
    Query("labelled_diamond", (0, 1, 2, 3), ((0, 1), (0, 2), (1, 2), (1, 3), (2, 3))),
)
PATTERNS = ("triangle", "diamond", "clique4", "cycle4", "tailed_triangle")
RING = Query("trade_ring", (0, 1, 2, 1), ((0, 1), (1, 2), (2, 3), (0, 3)))


def _edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut(graphs.copurchase_edges(spark, sf_dir))


def _inserts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut(streams.edge_versions(streams.insert_stream(_edges(spark, sf_dir))))


def _mixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut(streams.edge_versions(streams.mixed_stream(_edges(spark, sf_dir))))


def _vertices(spark: SparkSession, sf_dir: str, labels: int = 4) -> DataFrame:
    return graphs.part_vertices(spark, sf_dir, labels)


def _balls(edges: DataFrame, h: int = 2, cap: int | None = CAP) -> tuple[DataFrame, DataFrame]:
    adj = graph.both_ways(edges)
    ball = cut(balls.vertex_balls(adj, adj.select("v").distinct(), h, cap))
    return ball, balls.induced_edges(ball, adj)


def _dense(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (8,), count: int = 2, labels: int = 8) -> tuple[list[Query], DataFrame, DataFrame]:
    edges = _edges(spark, sf_dir)
    vertices = cut(_vertices(spark, sf_dir, labels))
    return [q for n in sizes for q in sample(edges, vertices, "dense", n, count)], edges, vertices


# Graphs and streams


def copurchase_edges(spark, sf_dir):
    return graphs.copurchase_edges(spark, sf_dir)


def copurchase_stream_90_10(spark, sf_dir):
    return streams.insert_stream(_edges(spark, sf_dir))


def mixed_stream_70_30(spark, sf_dir):
    return streams.mixed_stream(_edges(spark, sf_dir))


def edge_versions(spark, sf_dir):
    return _mixed(spark, sf_dir)


def degree_table(spark, sf_dir):
    return graph.degrees(graph.both_ways(graphs.copurchase_edges(spark, sf_dir)))


def label_profile(spark, sf_dir):
    return graph.label_profile(graph.adjacency(graphs.copurchase_edges(spark, sf_dir), _vertices(spark, sf_dir)))


def temporal_user_edges(spark, sf_dir):
    edges = graphs.temporal_edges(spark, sf_dir)
    return edges.select("src", "dst", graphs.micros(edges, "ts").alias("us"))


def sliding_window_edges(spark, sf_dir):
    rows = graphs.table(spark, sf_dir, "events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return rows.select(graphs.micros(rows, "w.start").alias("start_us"), "n")


def event_sessions(spark, sf_dir):
    rows = graphs.table(spark, sf_dir, "events").where("user_id IS NOT NULL AND ts IS NOT NULL")
    found = rows.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return found.select("user_id", graphs.micros(found, "w.start").alias("start_us"), "n")


def asof_version_lookup(spark, sf_dir):
    """The version each deletion ends, looked up as the latest one opened before it."""
    updates = cut(streams.mixed_stream(_edges(spark, sf_dir)))
    gone = updates.where("op = '-'").select("seq", "src", "dst")
    opened = updates.where("op = '+'").select("src", "dst", F.col("seq").alias("from_seq"))
    return gone.join(opened, ["src", "dst"]).where("from_seq < seq").groupBy("seq", "src", "dst").agg(F.max("from_seq").alias("valid_from"))


# Filters


def ldf_candidates(spark, sf_dir):
    adj = graph.adjacency(_edges(spark, sf_dir), _vertices(spark, sf_dir))
    return filters.label_degree(list(LABELLED), _vertices(spark, sf_dir), graph.degrees(adj))


def nlf_candidates(spark, sf_dir):
    return X.base_candidates(list(LABELLED), _edges(spark, sf_dir), _vertices(spark, sf_dir))


def propagation_two_rounds(spark, sf_dir):
    edges = _edges(spark, sf_dir)
    cand = X.base_candidates(list(LABELLED), edges, _vertices(spark, sf_dir))
    return filters.propagate(cand, list(LABELLED), graph.both_ways(edges), "arc", 2).groupBy("query_id", "u").agg(F.count("*").alias("n"))


def candidate_space_scans(spark, sf_dir):
    edges = _edges(spark, sf_dir)
    cand = X.base_candidates(list(LABELLED), edges, _vertices(spark, sf_dir))
    return engines.candidate_space(list(LABELLED), cand, graph.both_ways(edges))[1]


def list_scan_cost(spark, sf_dir):
    edges, vertices = _edges(spark, sf_dir), _vertices(spark, sf_dir)
    cand = X.base_candidates([LABELLED[2]], edges, vertices)
    return engines.list_scan_cost(engines.static([LABELLED[2]], edges, vertices, cand), [LABELLED[2]], cand)


def dominance_candidates(spark, sf_dir):
    """Label and degree candidates whose degree and sum of neighbours' degrees dominate the query vertex's."""
    edges, vertices = _edges(spark, sf_dir), _vertices(spark, sf_dir)
    adj = graph.both_ways(edges)
    degree = graph.degrees(adj)
    return filters.dominance(filters.label_degree(list(LABELLED), vertices, degree), list(LABELLED), adj, degree)


def _list_driven(spark, sf_dir):
    edges = _edges(spark, sf_dir)
    cand = X.base_candidates(list(LABELLED), edges, _vertices(spark, sf_dir))
    return engines.list_driven(list(LABELLED), cand, graph.both_ways(edges))


def list_driven_matches(spark, sf_dir):
    """Matches of the engine that intersects materialised candidate lists."""
    return _list_driven(spark, sf_dir)[0].matches.groupBy("query_id").agg(F.count("*").alias("matches"))


def list_driven_scans(spark, sf_dir):
    """List entries it reads for the labelled triangle."""
    return _list_driven(spark, sf_dir)[1].where("query_id = 'labelled_triangle'")


def propagation_modes(spark, sf_dir):
    """(mode, query_id, n): candidates each way of propagating leaves, as the context indexes do."""
    edges = _edges(spark, sf_dir)
    cand, adj = X.base_candidates(list(LABELLED), edges, _vertices(spark, sf_dir)), graph.both_ways(edges)
    out = None
    for mode in ("none", "tree", "dag", "arc", "assign"):
        rows = filters.propagate(cand, list(LABELLED), adj, mode).groupBy(F.lit(mode).alias("mode"), "query_id").agg(F.count("*").alias("n"))
        out = rows if out is None else out.union(rows)
    return out


# Balls and invariants


def ball_sizes_h1(spark, sf_dir):
    return balls.sizes(_balls(_edges(spark, sf_dir), 1, None)[0])


def ball_sizes_h2(spark, sf_dir):
    return balls.sizes(_balls(_edges(spark, sf_dir))[0])


def ball_edge_counts(spark, sf_dir):
    return invariants.counts(*_balls(_edges(spark, sf_dir)))


def ball_triangles(spark, sf_dir):
    return invariants.all_counts(*_balls(_edges(spark, sf_dir))).select("center", "tri")


def degree_overflow_screen(spark, sf_dir):
    return balls.degree_screen(graph.both_ways(_edges(spark, sf_dir)), 8)


def hub_excluded_components(spark, sf_dir):
    return filters.hub_excluded(_balls(_edges(spark, sf_dir))[1], 6, R)


def conjugate_degree_ceiling(spark, sf_dir):
    return invariants.conjugate_degrees(_balls(_edges(spark, sf_dir))[1], R)


def spectral_moments(spark, sf_dir):
    """Sums of the first three powers of all eigenvalues of each ball, rounded: integers in theory."""
    found = spectra.laplacian_spectrum(balls.packed(*_balls(_edges(spark, sf_dir))), None)
    power = lambda k: F.round(F.aggregate("spec", F.lit(0.0), lambda s, x: s + F.pow(x, F.lit(k)))).cast("bigint").alias(f"m{k}")
    return found.select("center", power(1), power(2), power(3))


def closed_walks_are_triangles(spark, sf_dir):
    """(center, walks) of length three: six for each triangle."""
    return spectra.closed_walks(balls.packed(*_balls(_edges(spark, sf_dir))), 3)


def reverse_index_fanout(spark, sf_dir):
    return index.reverse(_balls(_edges(spark, sf_dir))[0]).groupBy("member").agg(F.count("*").alias("centers"))


def reverse_compaction(spark, sf_dir):
    """(rows, live_rows): the reverse index of all balls, and what compaction leaves of it once those beyond the cap are evicted."""
    ball = _balls(_edges(spark, sf_dir), 2, None)[0]
    live = balls.sizes(ball).where(F.col("nv") <= CAP).select(F.col("center").alias("v"))
    count = lambda rev, name: rev.agg(F.count("*").alias(name))
    rev = index.reverse(ball)
    return count(rev, "rows").crossJoin(count(index.compact(rev, live), "live_rows"))  # single rows


def coverage_by_cap(spark, sf_dir):
    sizes = balls.sizes(_balls(_edges(spark, sf_dir), 2, None)[0])
    rows = sizes.select("nv", F.explode(F.array(*map(F.lit, (8, 16, 32, 64, 128)))).alias("cap"))
    return rows.groupBy("cap").agg(F.sum((F.col("nv") <= F.col("cap")).cast("bigint")).alias("deployed"), F.count("*").alias("vertices"))


def utility_bucket_sizes(spark, sf_dir):
    sizes = balls.sizes(_balls(_edges(spark, sf_dir), 2, None)[0])
    return sizes.groupBy(F.when(F.col("nv") <= 8, "01-08").when(F.col("nv") <= 16, "09-16").when(F.col("nv") <= 32, "17-32").when(F.col("nv") <= 64, "33-64").otherwise("65-").alias("bucket")).agg(F.count("*").alias("n"))


def report_rollup(spark, sf_dir):
    degree = graph.degrees(graph.both_ways(_edges(spark, sf_dir)))
    rows = degree.join(_vertices(spark, sf_dir), degree.v == F.col("id")).select("label", F.least(F.col("degree"), F.lit(5)).alias("bucket"))
    return rows.rollup("label", "bucket").agg(F.count("*").alias("n"))


# Bound rules, on integer degree vectors in place of spectra, so that results are exact

QUERY_SIDE = [9.0, 6.0, 5.0, 4.0]


def _degree_vectors(spark, sf_dir):
    inside = _balls(_edges(spark, sf_dir))[1]
    top = invariants.ball_degrees(inside).withColumn("t", F.row_number().over(Window.partitionBy("center").orderBy(F.desc("degree"), "member"))).where("t <= 4")
    wide = top.groupBy("center").agg(*[F.coalesce(F.max(F.when(F.col("t") == t, F.col("degree"))), F.lit(0)).cast("double").alias(f"d{t}") for t in range(1, 5)])
    return wide.select("center", F.array("d1", "d2", "d3", "d4").alias("d"))


def mass_cost(spark, sf_dir):
    q = F.array(*map(F.lit, QUERY_SIDE))
    return _degree_vectors(spark, sf_dir).select("center", bounds.mass_cost(q, F.col("d")).cast("bigint").alias("cost"))


def ceilings_vs_lattice(spark, sf_dir):
    c = bounds.ceilings(F.col("d"), F.lit(2))
    return _degree_vectors(spark, sf_dir).select("center", *[c[i].cast("bigint").alias(f"c{i + 1}") for i in range(4)])


def bound_rules(spark, sf_dir):
    """(k, rule, rejected): centers each rule rejects after k insertions."""
    q = F.array(*map(F.lit, QUERY_SIDE))
    rows = _degree_vectors(spark, sf_dir).select("d", F.explode(F.array(*map(F.lit, (0, 1, 2, 3)))).alias("k"))
    rules = [F.struct(F.lit(n).alias("rule"), rule(q, F.col("d"), F.col("k")).alias("x")) for n, rule in bounds.RULES.items()]
    return rows.select("k", F.explode(F.array(*rules)).alias("r")).groupBy("k", F.col("r.rule").alias("rule")).agg(F.sum(F.col("r.x").cast("bigint")).alias("rejected"))


# Delta enumeration


def _delta_of(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark, sf_dir):
        run = engines.delta([pattern(name)], _inserts(spark, sf_dir), _vertices(spark, sf_dir))
        return engines.match_counts(run).select("seq", "sign", "matches")

    return query


def delta_mixed_signs(spark, sf_dir):
    versions, vertices = _mixed(spark, sf_dir), _vertices(spark, sf_dir)
    both = [engines.match_counts(engines.delta([pattern("triangle")], versions, vertices, sign=s)) for s in (1, -1)]
    return both[0].union(both[1]).select("seq", "sign", "matches")


def delta_labelled(spark, sf_dir):
    run = engines.delta(list(LABELLED), _inserts(spark, sf_dir), _vertices(spark, sf_dir))
    return engines.match_counts(run).select("query_id", "seq", "matches")


def match_lifetimes(spark, sf_dir):
    return engines.lifetimes(pattern("triangle"), _mixed(spark, sf_dir), _vertices(spark, sf_dir))


def static_matches(spark, sf_dir):
    edges, vertices = _edges(spark, sf_dir), _vertices(spark, sf_dir)
    run = engines.static(list(LABELLED), edges, vertices, X.base_candidates(list(LABELLED), edges, vertices))
    return run.matches.groupBy("query_id").agg(F.count("*").alias("matches"))


def level_intermediates_control(spark, sf_dir):
    run = engines.delta([LABELLED[2]], _inserts(spark, sf_dir), _vertices(spark, sf_dir))
    return run.levels.groupBy("query_id", "level").agg(F.sum("n").alias("n"))


def level_intermediates_nlf(spark, sf_dir):
    versions, vertices = _inserts(spark, sf_dir), _vertices(spark, sf_dir)
    cand = X.base_candidates([LABELLED[2]], versions.select("src", "dst"), vertices)
    run = engines.delta([LABELLED[2]], versions, vertices, cand=cand)
    return run.levels.groupBy("query_id", "level").agg(F.sum("n").alias("n"))


def trade_rings(spark, sf_dir):
    """Customers whose two orders hold the same part: (customer, rings as the engine counts them)."""
    edges = cut(graphs.trade_edges(spark, sf_dir))
    found = engines.brute(RING, edges, graphs.trade_vertices(edges))
    return found.groupBy(F.col("m0").alias("customer")).agg(F.count("*").alias("rings"))


# Gates


def gate_counts_fire(spark, sf_dir):
    log = gate.decide([pattern("clique4")], _inserts(spark, sf_dir), _vertices(spark, sf_dir), rhos=(1,), phis=("nv", "ne", "tri"))
    return log.select("seq", "decision")


def gate_fire_by_label(spark, sf_dir):
    log = gate.decide([LABELLED[1]], _inserts(spark, sf_dir), _vertices(spark, sf_dir), rhos=(1,), phis=("nv", "ne", "tri"))
    return log.groupBy("decision").agg(F.count("*").alias("n"))


def exact_vs_naive_triggers(spark, sf_dir):
    """(seq, exact, either): deployed balls, of the graph with all edges, that hold both ends or one end of an update."""
    versions = _inserts(spark, sf_dir)
    rev = index.reverse(_balls(versions.select("src", "dst"))[0])
    updates = versions.where("valid_from > 0").select(F.col("valid_from").alias("seq"), "src", "dst")
    count = lambda mode, name: index.touched(updates, rev, 0, mode).groupBy("seq").agg(F.count("*").alias(name))
    out = updates.select("seq").join(count("exact", "exact"), "seq", "left").join(count("either", "either"), "seq", "left")
    return out.select("seq", F.coalesce("exact", F.lit(0)).alias("exact"), F.coalesce("either", F.lit(0)).alias("either"))


def decoy_workload(spark, sf_dir):
    """The constructed exception: the vertex-count screen skips all decoys and the true region keeps its matches."""
    vertices, updates = graphs.order_decoys(spark, sf_dir)
    versions = cut(streams.edge_versions(updates))
    q = [pattern("near_clique8_tail", (0,) * 10)]
    log = cut(gate.decide(q, versions, vertices, phis=("nv",)))
    run = engines.delta(q, versions, vertices, skips=gate.skips(log))
    return log.agg(F.count("*").alias("updates"), F.sum((F.col("decision") == "skip").cast("bigint")).alias("skipped")).withColumn("matches", F.lit(run.matches.count()).cast("bigint"))


def decoy_control(spark, sf_dir):
    """(test, intermediates, matches) of the constructed exception without the gate and with it: on is less than a hundredth of off."""
    vertices, updates = graphs.order_decoys(spark, sf_dir)
    versions = cut(streams.edge_versions(updates))
    q = [pattern("near_clique8_tail", (0,) * 10)]
    out = None
    for name, skips in (("off", None), ("on", gate.skips(gate.decide(q, versions, vertices, phis=("nv",))))):
        run = engines.delta(q, versions, vertices, skips=skips)
        rows = engines.intermediates(run, q).select(F.lit(name).alias("test"), F.col("all_levels").alias("intermediates"), F.lit(run.matches.count()).cast("bigint").alias("matches"))
        out = rows if out is None else out.union(rows)
    return out


def update_triggers(spark, sf_dir):
    """(seq, exact, either): two-hop balls that each insertion or deletion changes, as they stand then, against those that merely hold one of its ends."""
    versions = _mixed(spark, sf_dir)
    updates = cut(versions.where("valid_from > 0").select(F.col("valid_from").alias("seq"), "src", "dst").union(versions.where(F.col("valid_to") < engines.OPEN_END).select("valid_to", "src", "dst")))
    count = lambda mode: index.touched_at(updates, versions, 2, mode).groupBy("seq").agg(F.count("*").alias(mode))
    return count("either").join(count("exact"), "seq").select("seq", "exact", "either")


def intermediates_per_update(spark, sf_dir):
    """(query_id, seq, n): bindings beyond the anchor that each update causes."""
    run = engines.delta([LABELLED[2]], _inserts(spark, sf_dir), _vertices(spark, sf_dir))
    return run.levels.groupBy("query_id", "seq").agg(F.sum("n").alias("n"))


def homomorphic_matches(spark, sf_dir):
    """(query_id, matches) if query vertices may share a data vertex."""
    qs = [pattern("cycle4"), LABELLED[0]]
    edges, vertices = _edges(spark, sf_dir), _vertices(spark, sf_dir)
    run = engines.static(qs, edges, vertices, engines.label_candidates(qs, vertices), injective=False)
    return run.matches.groupBy("query_id").agg(F.count("*").alias("matches"))


def distinct_subgraphs(spark, sf_dir):
    """(query_id, seq, n): data subgraphs born at each update, each once and not once for each symmetry of the query."""
    qs = [pattern(p) for p in PATTERNS]
    run = engines.delta(qs, _inserts(spark, sf_dir), _vertices(spark, sf_dir))
    return engines.subgraphs(run.matches, qs).groupBy("query_id", "seq").agg(F.count("*").alias("n"))


def periodic_checks(spark, sf_dir):
    """(at, matches, found) of triangles at every tenth update of the mixed stream."""
    versions = _mixed(spark, sf_dir)
    last = versions.agg(F.max("valid_from")).first()[0] or 0
    return engines.periodic(engines.lifetimes(pattern("triangle"), versions, _vertices(spark, sf_dir)), 10, last)


def pruned_visited_overlap(spark, sf_dir):
    """(query_id, u, rejected, anchored, visited): label-degree candidates that the neighbour-label filter rejects, and those of them that the run without it binds, at the anchor and beyond it, whether or not a match comes of it."""
    versions, vertices = _inserts(spark, sf_dir), _vertices(spark, sf_dir)
    edges = versions.select("src", "dst")
    adj = graph.adjacency(edges, vertices)
    base = cut(filters.label_degree(list(LABELLED), vertices, graph.degrees(adj)))
    kept = filters.label_neighbour(base, list(LABELLED), graph.label_profile(adj))
    gone = cut(base.join(kept, ["query_id", "u", "v"], "left_anti"))
    bound = engines.delta(list(LABELLED), versions, vertices, log=True).visited.groupBy("query_id", "u", "v").agg(F.max("anchored").alias("a"), F.min("anchored").alias("b"))
    met = gone.join(bound, ["query_id", "u", "v"], "left")
    total = lambda c, name: F.sum(F.coalesce(c, F.lit(False)).cast("bigint")).alias(name)
    return met.groupBy("query_id", "u").agg(F.count("*").alias("rejected"), total(F.col("a"), "anchored"), total(~F.col("b"), "visited"))


# Breaches of what must hold: each is a count that has to be 0


def _breaches(df: DataFrame, condition) -> DataFrame:
    return df.where(condition).agg(F.count("*").alias("violations"))


def interlacing_violations(spark, sf_dir):
    """Vertices of true matches that the spectral test rejects."""
    queries, edges, vertices = _dense(spark, sf_dir)
    cand = X.base_candidates(queries, edges, vertices)
    held = cut(index.consult(graph.both_ways(edges), cand, r=8))
    kept = filters.passed(filters.ball_tests(cand, queries, held, r=8))
    run = engines.static(queries, edges, vertices, cand)
    return index.check_complete(index.bindings(run.matches), kept).agg(F.count("*").alias("violations"))


def majorisation_violations(spark, sf_dir):
    """Partial sums of eigenvalues beyond those of the conjugate degrees."""
    ball, inside = _balls(_edges(spark, sf_dir))
    inside = cut(inside)
    rows = spectra.laplacian_spectrum(balls.packed(ball, inside), R).join(invariants.conjugate_degrees(inside, R), "center")
    bad = F.lit(False)
    for t in range(1, R + 1):
        bad = bad | (sum(F.col("spec")[i] for i in range(t)) > sum(F.col(f"d{i + 1}") for i in range(t)) + 1e-6)
    return _breaches(rows, bad)


def ceiling_violations(spark, sf_dir):
    """Closed form against stepwise bounds, and bounds below flat ones."""
    rows = _degree_vectors(spark, sf_dir).select("d", F.explode(F.array(*map(F.lit, range(7)))).alias("k"))
    closed, steps, flat = bounds.ceilings(F.col("d"), F.col("k")), bounds.ceilings_stepwise(F.col("d"), F.col("k")), bounds.flat(F.col("d"), F.col("k"))
    return _breaches(rows.select(closed.alias("c"), steps.alias("s"), flat.alias("f")), (F.col("c") != F.col("s")) | F.exists(F.zip_with("c", "f", lambda a, b: a > b), lambda x: x))


def gate_wrong_skips(spark, sf_dir):
    """Updates that the full gate skips although the control finds matches, in both directions."""
    versions, vertices = _mixed(spark, sf_dir), _vertices(spark, sf_dir)
    qs = [pattern("clique4"), LABELLED[2]]
    out = None
    for sign in (1, -1):
        rows = gate.rates(gate.decide(qs, versions, vertices, sign=sign), engines.delta(qs, versions, vertices, sign=sign).matches)
        out = rows if out is None else out.union(rows)
    return out.agg(F.sum("wrong").alias("violations"))


def envelope_violations(spark, sf_dir):
    """Versions of the exact index above the batch envelope."""
    versions = _mixed(spark, sf_dir)
    every = graph.both_ways(versions.select("src", "dst")).select("v").distinct()
    exact = index.maintain(versions, every).where("state = 'deployed'")
    upper = index.envelope(versions, every).where("state = 'deployed'").select("v", F.col("spec").alias("top"))
    return _breaches(exact.join(upper, "v"), F.exists(F.zip_with("spec", "top", lambda a, b: a > b + 1e-7), lambda x: x))


# Results that SQL can't express


def vertex_spectra(spark, sf_dir):
    return spectra.wide(spectra.laplacian_spectrum(balls.packed(*_balls(_edges(spark, sf_dir))), R), R)


def interlace_candidates(spark, sf_dir):
    """(query_id, base, kept): candidates before and after the spectral test."""
    queries, edges, vertices = _dense(spark, sf_dir, (8, 12), 3)
    tested = X.power(queries, edges, vertices)
    return tested.groupBy("query_id").agg(F.count("*").alias("base"), F.sum((F.col("killers") == 0).cast("bigint")).alias("kept"))


def component_attribution(spark, sf_dir):
    queries, edges, vertices = _dense(spark, sf_dir, (8, 12), 3)
    return filters.attribution(X.power(queries, edges, vertices), 8)


def utility_by_ball_size(spark, sf_dir):
    queries, edges, vertices = _dense(spark, sf_dir, (8, 12, 16), 2)
    return X.utility(X.power(queries, edges, vertices, cap=None))


def retained_by_cap(spark, sf_dir):
    """(cap, deployed, vertices, retained, rejections): vertices that a cap deploys, and the rejections of uncapped balls that are left under it."""
    queries, edges, vertices = _dense(spark, sf_dir, (8, 12), 3)
    return X.coverage(X.power(queries, edges, vertices, cap=None), balls.sizes(_balls(edges, 2, None)[0]))


def retention_with_deletions(spark, sf_dir):
    """(tau, rule, base, retained, unsafe) over the stream of 70 % insertions and 30 % deletions; a safe rule is never unsafe."""
    queries, edges, vertices = _dense(spark, sf_dir, (12,), 2)
    return X.retention(queries, cut(streams.edge_versions(streams.mixed_stream(edges, 0.7))), vertices)


def gate_configurations(spark, sf_dir):
    """The matrix of the gate without triangles and of both layers, beside the control."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 1)
    return X.matrix(queries, cut(streams.edge_versions(streams.insert_stream(edges))), vertices, ("control", "laplacian_gate", "vertex_gate"))


def retention_curve(spark, sf_dir):
    queries, edges, vertices = _dense(spark, sf_dir, (12, 16), 2)
    return X.retention(queries, cut(streams.edge_versions(streams.insert_stream(edges, 0.7))), vertices)


def rejection_margins(spark, sf_dir):
    return X.margins(*_dense(spark, sf_dir, (12,), 3))


def laplacian_gate(spark, sf_dir):
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    return gate.decide(queries, versions, vertices, phis=("nv", "ne", "spec")).groupBy("query_id", "decision").agg(F.count("*").alias("n"))


def headroom_ratio(spark, sf_dir):
    return X.headroom(_edges(spark, sf_dir))


def envelope_index(spark, sf_dir):
    versions = _mixed(spark, sf_dir)
    return index.envelope(versions, graph.both_ways(versions.select("src", "dst")).select("v").distinct()).groupBy("state").agg(F.count("*").alias("n"))


def exact_index(spark, sf_dir):
    """(state, versions, vertices) of the index maintained update by update on all vertices."""
    versions = _mixed(spark, sf_dir)
    every = graph.both_ways(versions.select("src", "dst")).select("v").distinct()
    return index.maintain(versions, every).groupBy("state").agg(F.count("*").alias("versions"), F.count_distinct("v").alias("vertices"))


def static_construction(spark, sf_dir):
    return X.static_costs(*_dense(spark, sf_dir, (12, 16), 2))


def replication_matrix(spark, sf_dir):
    """Control, vertex test and gate with the same engine: candidates, skips, intermediates and matches."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    return X.matrix(queries, cut(streams.edge_versions(streams.insert_stream(edges))), vertices)


def second_engine(spark, sf_dir):
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    return X.matrix(queries, cut(streams.edge_versions(streams.insert_stream(edges))), vertices, ("control_b", "vertex_gate_b"))


def sparse_queries(spark, sf_dir):
    """Tree-like walk queries, where the spectral test has next to nothing to reject."""
    edges = _edges(spark, sf_dir)
    vertices = cut(_vertices(spark, sf_dir, 8))
    tested = X.power(sample(edges, vertices, "walk", 8, 3), edges, vertices)
    return tested.groupBy("query_id").agg(F.count("*").alias("base"), F.sum((F.col("killers") == 0).cast("bigint")).alias("kept"))


def admission(spark, sf_dir):
    edges = _edges(spark, sf_dir)
    return engines.admit(list(LABELLED), X.base_candidates(list(LABELLED), edges, _vertices(spark, sf_dir)))


# Other graphs, label rules and configurations


def shared_line_edges(spark, sf_dir):
    return graphs.shared_line_edges(spark, sf_dir)


def neighbour_graph(spark, sf_dir):
    """Each vector's three nearest by cosine, as edges."""
    return graphs.neighbour_edges(spark, sf_dir)


def page_link_fanout(spark, sf_dir):
    """(page, links): distinct link targets of each page."""
    return graphs.link_edges(spark, sf_dir).groupBy(F.col("src").alias("page")).agg(F.count("*").alias("links"))


def trade_degrees(spark, sf_dir):
    """(kind, vertices, most): sizes and hubs of the trade graph."""
    degree = graph.degrees(graph.both_ways(graphs.trade_edges(spark, sf_dir)))
    return degree.groupBy(F.floor(F.col("v") / graphs.KIND).cast("int").alias("kind")).agg(F.count("*").alias("vertices"), F.max("degree").alias("most"))


def zipf_label_counts(spark, sf_dir):
    ids = graphs.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
    return graphs.zipf_labels(ids, 4).groupBy("label").agg(F.count("*").alias("n"))


def renewed_stream_births(spark, sf_dir):
    """(seq, matches) of triangles over a stream in which every fifth insertion is taken back and renewed."""
    versions = cut(streams.edge_versions(streams.renewed_stream(_edges(spark, sf_dir))))
    run = engines.delta([pattern("triangle")], versions, _vertices(spark, sf_dir))
    return engines.match_counts(run).select("seq", "matches")


def temporal_triangles(spark, sf_dir):
    """(matches) triangle births over the stream of user edges that expire after a day; users with equal events are met once, as a class, and edges are made from events in windows of two days."""
    return meetings.triangle_matches(graphs.twin_events(spark, sf_dir), 3600 * 10**6, 24 * 3600 * 10**6)


def deletion_gate(spark, sf_dir):
    """(decision, n) of the count gate before deletions."""
    log = gate.decide([pattern("clique4")], _mixed(spark, sf_dir), _vertices(spark, sf_dir), sign=-1, rhos=(1,), phis=("nv", "ne", "tri"))
    return log.groupBy("decision").agg(F.count("*").alias("n"))


def _versioned_tests(spark, sf_dir):
    """Queries, versions, vertices, base candidates, and their spectral tests at every version of the exact index."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    base = X.base_candidates(queries, edges, vertices)
    held = cut(index.maintain(versions, base.select("v").distinct(), r=8))
    return queries, versions, vertices, base, cut(filters.ball_tests(base, queries, held, r=8))


def spectral_overlap(spark, sf_dir):
    """(test, query_id, rejected, visited, overlap, doomed): bindings the exact index ever rejects against all that the engine performs, without the test and with candidates as they stand at each update; doomed is 0 with it."""
    queries, versions, vertices, base, tested = _versioned_tests(spark, sf_dir)
    out = None
    for name, cand in (("off", base), ("on", filters.passed(tested))):
        run = engines.delta(queries, versions, vertices, cand=cand, log=True)
        rows = X.overlap(tested, run.visited).select(F.lit(name).alias("test"), "*")
        out = rows if out is None else out.union(rows)
    return out


def versioned_match_changes(spark, sf_dir):
    """Updates whose match count with candidates of each update's own spectra differs from the control's."""
    queries, versions, vertices, base, tested = _versioned_tests(spark, sf_dir)
    count = lambda cand: engines.match_counts(engines.delta(queries, versions, vertices, cand=cand))
    off, on = count(base), count(filters.passed(tested)).withColumnRenamed("matches", "found")
    both = off.join(on, ["query_id", "seq", "sign"], "full")
    return _breaches(both, ~F.col("matches").eqNullSafe(F.col("found")))


def order_feedback(spark, sf_dir):
    """(query_id, order, bindings, matches): orders from the query alone against orders from candidate counts; matches agree, bindings may not."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    cand = X.base_candidates(queries, edges, vertices)
    sizes: dict[str, dict[int, int]] = {q.name: dict.fromkeys(range(q.size), 0) for q in queries}
    for r in cand.groupBy("query_id", "u").count().collect():  # a row per query vertex
        sizes[r.query_id][r.u] = r["count"]
    out = None
    for name, by in (("query", None), ("counts", sizes)):
        run = engines.delta(queries, versions, vertices, cand=cand, sizes=by)
        found = run.matches.groupBy("query_id").agg(F.count("*").alias("matches"))
        rows = engines.intermediates(run, queries).join(found, "query_id", "left").select("query_id", F.lit(name).alias("order"), F.col("all_levels").alias("bindings"), F.coalesce("matches", F.lit(0)).alias("matches"))
        out = rows if out is None else out.union(rows)
    return out


def index_footprint(spark, sf_dir):
    edges = _edges(spark, sf_dir)
    adj = graph.both_ways(edges)
    asked = adj.select("v").distinct()
    held = cut(index.consult(adj, asked))
    rev = index.reverse(balls.vertex_balls(adj, asked, 2, CAP))
    return index.footprint(held, rev, graph.label_profile(graph.adjacency(edges, _vertices(spark, sf_dir))))


def resync_changes(spark, sf_dir):
    """(change, n): candidate pairs that the spectra after the whole stream admit again or reject, against those before it."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    cand = X.base_candidates(queries, edges, vertices)
    before = cut(index.consult(graph.both_ways(streams.alive_at(versions, 0)), cand))
    after = cut(index.consult(graph.both_ways(edges), cand))
    return index.resync(queries, cand, before, after).groupBy("change").agg(F.count("*").alias("n"))


def budgeted_run(spark, sf_dir):
    """(query_id, budget, factor, seconds, last_seq, intermediates, matches, solved): queries under 1, 5 and 10 times a budget of 5 s, checked between batches of updates."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    cand = X.base_candidates(queries, edges, vertices)
    schema = "query_id string, budget double, factor int, seconds double, last_seq bigint, intermediates bigint, matches bigint, solved boolean"
    return spark.createDataFrame(X.budgets(queries, versions, vertices, cand, 5.0), schema)


def _generated_utility(spark, sf_dir, generator):
    """Rejection by ball size on a generated graph between the parts of the co-purchase graph, with their labels."""
    ids = cut(graph.both_ways(graphs.copurchase_edges(spark, sf_dir)).select(F.col("v").alias("id")).distinct())
    edges = cut(graphs.placed(generator(spark, max(1, ids.count())), ids))
    vertices = cut(_vertices(spark, sf_dir).join(ids, "id", "left_semi"))
    return X.utility(X.power(sample(edges, vertices, "dense", 12, 2), edges, vertices, cap=None))


def random_graph_utility(spark, sf_dir):
    """Rejection by ball size on a generated sparse graph of the co-purchased parts."""
    return _generated_utility(spark, sf_dir, graphs.random_edges)


def small_world_utility(spark, sf_dir):
    """Rejection by ball size on a rewired ring of the co-purchased parts, whose balls are alike in size."""
    return _generated_utility(spark, sf_dir, graphs.small_world_edges)


def candidates_by_size(spark, sf_dir):
    """(size, queries, base, kept): candidates before and after the spectral test, five dense queries of each size."""
    queries, edges, vertices = _dense(spark, sf_dir, (16, 24, 32), 5)
    tested = X.power(queries, edges, vertices)
    of = F.broadcast(spark.createDataFrame([(q.name, q.size) for q in queries], "query_id string, size int"))
    return tested.join(of, "query_id").groupBy("size").agg(F.count_distinct("query_id").alias("queries"), F.count("*").alias("base"), F.count_if(F.col("killers") == 0).alias("kept"))


def index_modes(spark, sf_dir):
    """No test, gate alone and eagerly maintained index over the same stream."""
    queries, edges, vertices = _dense(spark, sf_dir, (8,), 2)
    return X.modes(queries, cut(streams.edge_versions(streams.insert_stream(edges))), vertices)


def solver_costs(spark, sf_dir):
    """Direct, cold and warm solver on the balls that the insert stream changes, from their first to their last form."""
    versions = _inserts(spark, sf_dir)
    was, now = graph.both_ways(streams.alive_at(versions, 0)), graph.both_ways(versions.select("src", "dst"))
    packed = lambda adj: balls.packed(*(lambda b: (b, balls.induced_edges(b, adj)))(balls.vertex_balls(adj, adj.select("v").distinct(), 2, CAP)))
    pairs = packed(was).select("center", F.col("ends").alias("before")).join(packed(now).select("center", F.col("ends").alias("after")), "center").where("before <> after")
    return spectra.solver_costs(pairs, R)


STRICT = [
    shared_line_edges, page_link_fanout, trade_degrees, zipf_label_counts, renewed_stream_births, deletion_gate,
    copurchase_edges, copurchase_stream_90_10, mixed_stream_70_30, edge_versions, degree_table, label_profile, temporal_user_edges, sliding_window_edges, event_sessions, asof_version_lookup,
    ldf_candidates, nlf_candidates, propagation_two_rounds, candidate_space_scans, list_scan_cost, dominance_candidates, list_driven_matches, list_driven_scans, ball_sizes_h1, ball_sizes_h2, ball_edge_counts, ball_triangles, degree_overflow_screen,
    hub_excluded_components, conjugate_degree_ceiling, spectral_moments, closed_walks_are_triangles, reverse_index_fanout, reverse_compaction, coverage_by_cap, utility_bucket_sizes, report_rollup, mass_cost, ceilings_vs_lattice, bound_rules,
    delta_mixed_signs, delta_labelled, match_lifetimes, static_matches, level_intermediates_control, level_intermediates_nlf, trade_rings, gate_counts_fire, gate_fire_by_label, exact_vs_naive_triggers, decoy_workload,
    decoy_control, update_triggers, intermediates_per_update, homomorphic_matches, distinct_subgraphs, periodic_checks,
    pruned_visited_overlap, versioned_match_changes, interlacing_violations, majorisation_violations, ceiling_violations, gate_wrong_skips, envelope_violations,
]
ROWS_ONLY = [
    vertex_spectra, interlace_candidates, component_attribution, utility_by_ball_size, retained_by_cap, retention_curve, retention_with_deletions, gate_configurations, rejection_margins, laplacian_gate, headroom_ratio, envelope_index, exact_index,
    spectral_overlap, order_feedback, index_footprint, resync_changes, budgeted_run, random_graph_utility, temporal_triangles, neighbour_graph,
    static_construction, replication_matrix, second_engine, sparse_queries, admission, propagation_modes,
    small_world_utility, candidates_by_size, index_modes, solver_costs,
]
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in STRICT} | {f"delta_{p}": _delta_of(p) for p in PATTERNS} | {f.__name__: f for f in ROWS_ONLY}
