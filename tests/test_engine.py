import itertools
import math
import random
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from deltamatch import experiments as X
from deltamatch import workloads
from deltamatch.functions import bounds, udfs
from deltamatch.operators import balls, engines, filters, gate, graph, index, invariants, spectra
from deltamatch.plans.query import Query, invariant_values, padded_spectrum, pattern, sample
from deltamatch.session import cut
from deltamatch.sources import graphs, streams


def edge_frame(spark, pairs):
    return graph.canonical_edges(spark.createDataFrame([tuple(map(int, p)) for p in pairs], "src bigint, dst bigint"))


def labelled(spark, n, labels=1):
    return spark.createDataFrame([(i, i % labels) for i in range(n)], "id bigint, label int")


@pytest.fixture(scope="module")
def g1(spark, sf):
    return graphs.copurchase_edges(spark, sf).cache(), graphs.part_vertices(spark, sf, 4).cache()


# Spectra


@pytest.mark.parametrize("n", [2, 5, 9])
def test_closed_form_spectra(n):
    path = [(i, i + 1) for i in range(n - 1)]
    cycle = path + [(0, n - 1)]
    clique = list(itertools.combinations(range(n), 2))
    star = [(0, i) for i in range(1, n)]
    assert padded_spectrum(n, path, n) == pytest.approx(sorted((2 - 2 * math.cos(math.pi * k / n) for k in range(n)), reverse=True), abs=1e-9)
    if n > 2:
        assert padded_spectrum(n, cycle, n) == pytest.approx(sorted((2 - 2 * math.cos(2 * math.pi * k / n) for k in range(n)), reverse=True), abs=1e-9)
    assert padded_spectrum(n, clique, n) == pytest.approx([n] * (n - 1) + [0], abs=1e-9)
    assert padded_spectrum(n, star, n) == pytest.approx([n] + [1] * (n - 2) + [0], abs=1e-9)


def test_equal_degrees_but_other_spectra():
    six = [(i, (i + 1) % 6) for i in range(6)]
    three = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5)]
    assert padded_spectrum(6, six, 1) == pytest.approx([4.0]) and padded_spectrum(6, three, 1) == pytest.approx([3.0])


def test_distributed_spectra_equal_local_ones(spark):
    rng = random.Random(4)
    pairs = {tuple(sorted(rng.sample(range(30), 2))) for _ in range(45)}
    edges = edge_frame(spark, pairs)
    adj = graph.both_ways(edges)
    ball = balls.vertex_balls(adj, adj.select("v").distinct(), 2, None)
    got = {r.center: r.spec for r in spectra.laplacian_spectrum(balls.packed(ball, balls.induced_edges(ball, adj)), 5).collect()}
    q = Query("all", (None,) * 30, tuple(pairs))
    for v, spec in got.items():
        assert spec == pytest.approx(padded_spectrum(*q.ball(v, 2), 5), abs=1e-9)


def test_iterative_solver_agrees_and_warm_start_helps():
    m = spectra.laplacian(12, [(i, j) for i in range(12) for j in range(i + 1, 12) if (i * j) % 3])
    exact = np.linalg.eigvalsh(m)[::-1][:3]
    values, vectors, cold = spectra.iterative_spectrum(m, 3)
    assert values == pytest.approx(exact, abs=1e-5)
    assert spectra.iterative_spectrum(m, 3, vectors)[2] <= cold


@settings(max_examples=60, deadline=None)
@given(st.integers(4, 9), st.data())
def test_monotone_invariants(n, data):
    pairs = list(itertools.combinations(range(n), 2))
    big = data.draw(st.lists(st.sampled_from(pairs), unique=True, min_size=1))
    part = big[: data.draw(st.integers(0, len(big)))]
    low, high = invariant_values(n, part, n), invariant_values(n, big, n)
    assert all(low[k] <= high[k] for k in ("nv", "ne", "tri"))
    assert all(a <= b + 1e-9 for a, b in zip(low["spec"], high["spec"]))
    assert sum(high["spec"]) - sum(low["spec"]) == pytest.approx(2 * (len(big) - len(part)), abs=1e-8)


# Bounds


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(0, 12), min_size=1, max_size=4), st.lists(st.integers(0, 12), min_size=4, max_size=4), st.integers(0, 4))
def test_tightest_rule_is_optimal_in_the_relaxation(d, q, k):
    d, q = sorted(d, reverse=True), sorted(q[: len(d)], reverse=True)
    top = [min(d[i - j] + 2 * (k - j) for j in range(min(k, i) + 1)) for i in range(len(d))]
    steps = list(d)
    for _ in range(k):
        steps = [steps[0] + 2] + [min(a, b + 2) for a, b in zip(steps, steps[1:])]
    assert steps == top
    rejects = sum(max(0, a - b) for a, b in zip(q, d)) > 2 * k or any(a > c for a, c in zip(q, top))
    assert rejects != bounds.feasible(q, d, k)
    reachable = any(all(d[i] + x[i] <= top[i] and d[i] + x[i] >= q[i] for i in range(len(d))) and sum(x) <= 2 * k and all(d[i] + x[i] >= d[i + 1] + x[i + 1] for i in range(len(d) - 1)) for x in itertools.product(range(2 * k + 1), repeat=len(d)))
    assert rejects != reachable


def test_bound_columns_and_sql(spark):
    udfs.register(spark)
    rows = [([9.0, 4.0, 2.0, 1.0], 2), ([5.0, 5.0, 0.0, 0.0], 0), ([7.0, 1.0, 1.0, 0.0], 5)]
    df = spark.createDataFrame(rows, "d array<double>, k int")
    d, k = F.col("d"), F.col("k")
    for r in df.select("d", "k", bounds.ceilings(d, k).alias("c"), bounds.ceilings_stepwise(d, k).alias("s"), bounds.rank_shift(d, k).alias("r"), bounds.flat(d, k).alias("f"), F.expr("spectrum_ceilings(d, k)").alias("q"), F.expr("spectrum_flat(d, k)").alias("qf")).collect():
        want = [min(r.d[i - j] + 2 * (r.k - j) for j in range(min(r.k, i) + 1)) for i in range(4)]
        assert r.c == r.s == r.q == want and r.f == r.qf == [x + 2 * r.k for x in r.d]
        assert all(a <= b for a, b in zip(r.c, r.r)) and all(a <= b for a, b in zip(r.c, r.f))
    one = spark.sql("SELECT spectrum_mass_cost(array(5D, 3D), array(4D, 4D)) AS m, spectrum_interlaces(array(5D), array(4D)) AS i, laplacian_top(array(0L, 1L, 1L, 2L), 2) AS t").first()
    assert one.m == 1.0 and one.i is False and one.t == pytest.approx([3.0, 1.0])
    assert spark.sql("SELECT * FROM expand_query('0-1,1-2')").count() == 4
    assert spark.createDataFrame([], "d array<double>, k int").select(bounds.tightest(d, d, k)).count() == 0


def test_counting_updates_instead_of_edges_is_unsafe(spark):
    # Vertex 9 enters the ball of 0 with several edges by one update.
    base = [(0, 1), (0, 2), (0, 3), (9, 1), (9, 2)]
    before = padded_spectrum(4, [(0, 1), (0, 2), (0, 3)], 4)
    after = padded_spectrum(5, [(0, 1), (0, 2), (0, 3), (4, 1), (4, 2), (4, 0)], 4)
    assert any(a > b + 2 for a, b in zip(after, before)) or sum(after) - sum(before) > 2 + 1e-9
    assert all(a <= b + 2 * 3 + 1e-9 for a, b in zip(after, before)) and base


# Filters


def test_no_filter_loses_a_match(spark, g1):
    edges, vertices = g1
    adj = graph.both_ways(edges)
    queries = sample(edges, vertices, "dense", 5, 2) + sample(edges, vertices, "walk", 5, 1) + [Query("t", (0, 1, 2), ((0, 1), (0, 2), (1, 2)))]
    cand = X.base_candidates(queries, edges, vertices)
    held = index.consult(adj, cand, r=8)
    kept = filters.passed(filters.ball_tests(cand, queries, held, r=8))
    degree = graph.degrees(adj)
    run = engines.static(queries, edges, vertices, filters.label_degree(queries, vertices, degree))
    pairs = index.bindings(run.matches).cache()
    assert pairs.count() > 0
    for tested in (cand, kept, filters.propagate(cand, queries, adj, "arc"), filters.propagate(cand, queries, adj, "tree"), filters.propagate(cand, queries, adj, "dag"), filters.propagate(cand, queries, adj, "assign"), filters.dominance(cand, queries, adj, degree)):
        assert index.check_complete(pairs, tested).count() == 0
        assert tested.exceptAll(cand).count() == 0


def test_hub_exclusion_never_hides_a_rejection(spark, g1):
    edges, vertices = g1
    queries = sample(edges, vertices, "dense", 6, 3)
    tested = X.power(queries, edges, vertices, r=4)
    adj = graph.both_ways(edges)
    ball = balls.vertex_balls(adj, adj.select("v").distinct(), 2, 64)
    dead = {(r.center, r.component) for r in filters.hub_excluded(balls.induced_edges(ball, adj), 6, 4).collect()}
    assert dead
    for r in tested.where("killers > 1").collect():
        assert not [t for t in range(1, 5) if r.killers >> t & 1 and (r.v, t) in dead]


# Engines and gates


def test_engines_agree(spark, g1):
    edges, vertices = g1
    versions = streams.edge_versions(streams.mixed_stream(edges)).cache()
    for q in (pattern("diamond"), pattern("tailed_triangle"), Query("l", (0, 1, 2, None), ((0, 1), (0, 2), (1, 2), (2, 3)))):
        lives = engines.lifetimes(q, versions, vertices).cache()
        for sign, at, open_ in ((1, "born", F.col("born") > 0), (-1, "dies", F.col("dies") < 2**62)):
            want = Counter(r[at] for r in lives.where(open_).collect())
            run = engines.delta([q], versions, vertices, sign=sign)
            assert {r.seq: r.matches for r in engines.match_counts(run).collect()} == want
            cand = X.base_candidates([q], versions.select("src", "dst"), vertices)
            reduced = engines.delta_reduced([q], versions, vertices, cand=cand, sign=sign)
            assert {r.seq: r.matches for r in engines.match_counts(reduced).collect()} == want
            # Engine B counts before it verifies the other edges: never fewer than its own matches.
            assert engines.intermediates(reduced, [q]).first().all_levels >= reduced.matches.count()
        last = streams.alive_at(versions, 2**62)
        cand = X.base_candidates([q], last, vertices)
        found = engines.brute(q, last, vertices).count()
        assert engines.static([q], last, vertices, cand).matches.count() == found
        for longest in (4096, 1) if q.name == "diamond" else (4096,):  # lists in one part each, and split to the utmost
            run, scans = engines.list_driven([q], cand, graph.both_ways(last), longest=longest)
            assert run.matches.count() == found == run.matches.distinct().count()
            assert scans.count() == q.size - 2


def test_insert_then_delete_is_net_zero_and_renewal_counts_again(spark, g1):
    edges, vertices = g1
    q = pattern("triangle")
    versions = streams.edge_versions(streams.renewed_stream(edges)).cache()
    born = engines.delta([q], versions, vertices).matches.count()
    gone = engines.delta([q], versions, vertices, sign=-1).matches.count()
    total = engines.brute(q, edges, vertices).count()
    start = engines.brute(q, streams.alive_at(versions, 0), vertices).count()
    assert start + born - gone == total and gone > 0
    assert streams.noop_updates(streams.renewed_stream(edges)).count() == 0


def test_gate_skips_nothing_that_matters(spark, g1):
    edges, vertices = g1
    versions = streams.edge_versions(streams.mixed_stream(edges)).cache()
    queries = [pattern("clique4"), Query("l", (0, 1, 2, 3), pattern("diamond").edges)]
    for sign in (1, -1):
        control = engines.delta(queries, versions, vertices, sign=sign)
        log = gate.decide(queries, versions, vertices, sign=sign).cache()
        assert all(r.wrong == 0 for r in gate.rates(log, control.matches).collect())
        assert log.where("decision = 'skip'").count() > 0
        gated = engines.delta(queries, versions, vertices, sign=sign, skips=gate.skips(log))
        assert gated.matches.groupBy("query_id").count().exceptAll(control.matches.groupBy("query_id").count()).count() == 0
        on, off = (r.levels.agg(F.sum("n")).first()[0] or 0 for r in (gated, control))
        skipped = control.levels.join(gate.skips(log), ["query_id", "seq"], "left_semi").agg(F.sum("n")).first()[0] or 0
        assert off - on == skipped
        few = gate.decide(queries, versions, vertices, sign=sign, phis=("nv",))
        assert gate.skips(few).exceptAll(gate.skips(log)).count() == 0


def test_capped_balls_pass(spark):
    star = edge_frame(spark, [(0, i) for i in range(1, 40)])
    versions = streams.edge_versions(streams.insert_stream(star))
    log = gate.decide([pattern("triangle")], versions, labelled(spark, 40), cap=8)
    assert {r.decision for r in log.collect()} == {"pass"}


def test_constructed_exception_is_detected(spark):
    vertices, updates = graphs.decoys(spark, 2)
    versions = streams.edge_versions(updates).cache()
    q = [pattern("near_clique8_tail", (0,) * 10)]
    log = gate.decide(q, versions, vertices, phis=("nv",)).cache()
    assert sorted(r.decision for r in log.collect()) == ["pass", "skip", "skip"]
    on = engines.delta(q, versions, vertices, skips=gate.skips(log))
    off = engines.delta(q, versions, vertices)
    assert on.matches.count() == off.matches.count() == 720
    made = [r.levels.agg(F.sum("n")).first()[0] for r in (on, off)]
    assert made[0] < 0.2 * made[1]


# Index


def test_exact_index_equals_spectra_of_each_moment(spark, g1):
    edges, _ = g1
    versions = streams.edge_versions(streams.mixed_stream(edges)).cache()
    some = graph.both_ways(edges).where("v % 6 = 0").select("v").distinct()
    rows = index.maintain(versions, some).cache()
    for seq in (0, 7, 23, 10**6):
        adj = graph.both_ways(streams.alive_at(versions, seq))
        want = {r.v: r.spec for r in index.consult(adj, some).where("state = 'deployed'").collect()}
        got = {r.v: r.spec for r in index.spectra_at(rows, seq).where("state = 'deployed'").collect()}
        for v, spec in got.items():
            assert spec == pytest.approx(want.get(v, [0.0] * 4), abs=1e-6)
    upper = {r.v: r.spec for r in index.envelope(versions, some).where("state = 'deployed'").collect()}
    for r in rows.where("state = 'deployed'").collect():
        assert r.v not in upper or all(a <= b + 1e-7 for a, b in zip(r.spec, upper[r.v]))
    assert index.anomaly_scores(rows).where("jump < 0").count() == 0


def test_eviction_is_permanent_unless_redeployed(spark):
    pairs = [(0, i) for i in range(1, 4)]
    ops = [(0, "+", *p) for p in pairs] + [(i, "+", 0, 10 + i) for i in range(1, 5)] + [(10 + i, "-", 0, 10 + i) for i in range(1, 5)]
    versions = streams.edge_versions(spark.createDataFrame(ops, "seq bigint, op string, src bigint, dst bigint")).cache()
    zero = spark.createDataFrame([(0,)], "v bigint")
    rows = index.maintain(versions, zero, cap=6)
    assert index.spectra_at(rows, 0).first().state == "deployed"
    assert index.spectra_at(rows, 4).first().state == "evicted" and index.spectra_at(rows, 14).first().state == "evicted"
    assert index.spectra_at(index.maintain(versions, zero, cap=6, redeploy=True), 14).first().state == "deployed"


def test_resync_restores_a_raised_candidate(spark):
    q = pattern("triangle")
    before = index.consult(graph.both_ways(edge_frame(spark, [(0, 1), (1, 2)])), labelled(spark, 3).select(F.col("id").alias("v")))
    after = index.consult(graph.both_ways(edge_frame(spark, [(0, 1), (1, 2), (0, 2)])), labelled(spark, 3).select(F.col("id").alias("v")))
    cand = spark.createDataFrame([("triangle", u, v) for u in range(3) for v in range(3)], "query_id string, u int, v bigint")
    got = index.resync([q], cand, before, after).collect()
    assert got and {r.change for r in got} == {"+"}
    assert {r.change for r in index.resync([q], cand, after, before).collect()} == {"-"}
    assert index.resync([q], cand, after, after).count() == 0


def test_triggers(spark, g1):
    edges, _ = g1
    versions = streams.edge_versions(streams.insert_stream(edges))
    adj = graph.both_ways(edges)
    row = X.triggers(versions, adj.select("v").distinct()).first()
    assert 0 < row.exact < row.either


# Experiments


def test_tests_change_candidates_but_hardly_intermediates(spark, g1):
    edges, vertices = g1
    queries = sample(edges, vertices, "dense", 6, 2)
    versions = streams.edge_versions(streams.insert_stream(edges)).cache()
    rows = {r.test: r for r in X.matrix(queries, versions, vertices, ("control", "vertex", "triangle_gate")).collect()}
    control = rows["control"]
    for r in rows.values():
        assert r.matches == control.matches and r.candidates <= control.candidates and r.intermediates <= control.intermediates


def test_retention_is_safe_and_ordered(spark, g1):
    edges, vertices = g1
    queries = sample(edges, vertices, "dense", 8, 2)
    versions = streams.edge_versions(streams.insert_stream(edges, 0.6)).cache()
    rows = X.retention(queries, versions, vertices, taus=(1, 2)).collect()
    kept = {(r.tau, r.rule): r.retained for r in rows}
    assert all(r.unsafe == 0 for r in rows if r.rule != "per_update")
    for tau in {r.tau for r in rows}:
        assert kept[tau, "tightest"] >= max(kept[tau, "ceilings"], kept[tau, "mass"]) and kept[tau, "ceilings"] >= max(kept[tau, "flat"], kept[tau, "rank_shift"])


def test_static_costs_follow_candidates(spark, g1):
    rows = X.static_costs(sample(*g1, "dense", 8, 2), *g1).collect()
    off, on = ({r.query_id: r for r in rows if r.test == t} for t in ("off", "on"))
    assert all(on[k].scans <= off[k].scans and on[k].candidates <= off[k].candidates for k in on)


def test_generated_graphs_and_readers(spark, tmp_path):
    assert graphs.random_edges(spark, 300).where("src >= dst").count() == 0
    ring = graphs.small_world_edges(spark, 100, 4, 0.0)
    assert ring.count() == 200 and graph.degrees(graph.both_ways(ring)).where("degree <> 4").count() == 0
    labels = {r.label: r["count"] for r in graphs.zipf_labels(spark.range(4000), 4).groupBy("label").count().collect()}
    assert labels[1] > labels[2] > labels[3] > labels[4]
    path = tmp_path / "edges.txt"
    path.write_text("# comment\n3\t1\n1\t3\n2\t2\n4\t5\n")
    assert sorted(map(tuple, graphs.read_edge_list(spark, str(path)).collect())) == [(1, 3), (4, 5)]
    assert X.advise("static", False) == "full" and X.advise("delta", True) == "gate" and X.advise("delta", False) == "off"
    assert invariants.REGISTRY["tri"].query_value(4, list(itertools.combinations(range(4), 2))) == 4


def test_index_queries_take_every_vertex(spark, monkeypatch):
    taken, maintain = [], workloads.index.maintain
    monkeypatch.setattr(workloads.index, "maintain", lambda versions, some, **k: (taken.append((versions, some)), maintain(versions, some, **k))[1])
    path = "/root/testdata/sf0.001"
    workloads.exact_index(spark, path)
    workloads.envelope_violations(spark, path)
    assert len(taken) == 2
    for versions, some in taken:
        assert some.count() == graph.both_ways(versions.select("src", "dst")).select("v").distinct().count()


def test_utility_tests_large_balls_too(spark, monkeypatch):
    held = []
    monkeypatch.setattr(workloads.X, "utility", lambda tested: held.append(tested) or tested)
    workloads.utility_by_ball_size(spark, "/root/testdata/sf0.01")
    assert held[0].where("nv > 64").count() > 0 and held[0].where("nv IS NULL").count() == 0


def test_neighbours_across_blocks(spark, tmp_path):
    rng = np.random.default_rng(2)
    vectors = rng.standard_normal((90, 8))
    rows = [(i, v.tolist()) for i, v in enumerate(vectors)] + [(100, None), (101, [0.0] * 8)]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {tuple(r) for r in graphs.neighbour_edges(spark, str(tmp_path), 3, block=20).select("src", "dst").collect()}
    unit = vectors.astype("f4").astype("f8")
    near = (unit := unit / np.linalg.norm(unit, axis=1, keepdims=True)) @ unit.T
    np.fill_diagonal(near, -2)
    want = {tuple(sorted((a, int(b)))) for a in range(90) for b in np.argsort(-near[a])[:3]}
    assert got == want


def test_log_holds_every_binding_and_budgets_read_off(spark):
    pairs = [(0, 1), (1, 2), (2, 3), (3, 4), (0, 2)]
    versions = spark.createDataFrame([(a, b, i, 2**63 - 1) for i, (a, b) in enumerate(pairs)], "src bigint, dst bigint, valid_from bigint, valid_to bigint")
    query = pattern("triangle", (0, 0, 0))
    run = engines.delta([query], versions, labelled(spark, 5), log=True)
    got = {(r.u, r.v, r.seq, r.anchored) for r in run.visited.collect()}
    anchored = {(u, v, s, True) for s, e in enumerate(pairs) if s for v in e for u in range(3)}
    assert got == anchored | {(u, 1, 4, False) for u in range(3)}
    assert run.matches.count() == 6
    # Vertex 1 is a candidate before the closing edge only, so nothing may bind it there.
    cand = spark.createDataFrame([("triangle", u, v, 0, 4 if v == 1 else 99) for u in range(3) for v in range(5)], "query_id string, u int, v bigint, seq_from bigint, seq_to bigint")
    assert engines.delta([query], versions, labelled(spark, 5), cand=cand).matches.count() == 0
    rows = X.budgets([query], versions, labelled(spark, 5), None, 1e6, factors=(1,), batches=2)
    assert [(r[4], r[5], r[6], r[7]) for r in rows] == [(4, 6, 6, True)]
    assert X.budgets([query], versions, labelled(spark, 5), None, 0.0, factors=(1,), batches=2)[0][4:] == (2, 0, 0, False)


def test_symmetry_breaks_keep_one_of_each_orbit():
    for name, group in (("triangle", 6), ("diamond", 4), ("clique4", 24), ("cycle4", 8), ("tailed_triangle", 2)):
        q = pattern(name)
        assert len(q.automorphisms()) == group
        kept = [p for p in itertools.permutations(range(q.size)) if all(p[u] < p[w] for u, w in q.symmetry_breaks())]
        assert len(kept) * group == math.factorial(q.size)


def test_decoy_bindings_by_plain_search(spark):
    """The bindings of the true region, which the twin of decoy_control states."""
    _, updates = graphs.decoys(spark)
    rows = [(r.src, r.dst, r.seq) for r in updates.where("src >= 5000").collect()]
    old = {frozenset(r[:2]) for r in rows if r[2] == 0}
    (a, b), *more = [r[:2] for r in rows if r[2] > 0]
    assert not more
    q, made, found = pattern("near_clique8_tail", (0,) * 10), 0, 0
    ids = sorted({v for e in old for v in e})

    def grow(held, order):
        nonlocal made, found
        if len(held) == q.size:
            found += 1
            return
        x = order[len(held)]
        for v in ids:
            if v not in held.values() and all(frozenset((v, held[y])) in old for y in q.near(x) if y in held):
                made += 1
                grow({**held, x: v}, order)

    for u, w in q.edges:
        for s, t in ((u, w), (w, u)):
            grow({s: a, t: b}, q.order(s, t))
    assert (made, found) == (36870, 720)


def test_periodic_checks_see_what_lives_then(spark):
    lives = spark.createDataFrame([(0, 5), (3, 10), (10, 11), (11, 19), (4, 100)], "born bigint, dies bigint")
    assert [tuple(r) for r in engines.periodic(lives, 10, 39).orderBy("at").collect()] == [(0, 1, True), (10, 2, True), (20, 1, True), (30, 1, True)]
    assert [r.found for r in engines.periodic(lives.where("dies = 19"), 10, 19).collect()] == [False, False]


def test_triggers_as_balls_stand_at_each_update(spark, g1):
    """A center is named exactly if its induced ball before and after the update differ."""
    versions = streams.edge_versions(streams.mixed_stream(g1[0])).cache()
    rows = [tuple(r) for r in versions.collect()]
    changes = [(f, a, b) for a, b, f, t in rows if f > 0] + [(t, a, b) for a, b, f, t in rows if t < engines.OPEN_END]
    got = {(r.seq, r.center) for r in index.touched_at(spark.createDataFrame(changes, "seq bigint, src bigint, dst bigint"), versions).collect()}

    def shape(near, c):
        ball = {c} | near.get(c, set())
        ball |= {w for v in list(ball) for w in near.get(v, ())}
        return {frozenset((v, w)) for v in ball for w in near.get(v, ()) if w in ball}

    want = set()
    for seq, a, b in changes:
        sides = []
        for at in (seq - 1, seq):
            near: dict = {}
            for s, d, f, t in rows:
                if f <= at < t:
                    near.setdefault(s, set()).add(d)
                    near.setdefault(d, set()).add(s)
            sides.append(near)
        want |= {(seq, c) for c in sides[0].keys() | sides[1].keys() if shape(sides[0], c) != shape(sides[1], c)}
    assert got == want


def test_warm_start_agrees_with_direct_solves(spark):
    rows = [(1, [0, 1, 1, 2], [0, 1, 1, 2, 0, 2]), (2, [0, 1], [0, 1, 2, 3, 2, 4, 2, 5])]
    got = {r.solver: r for r in spectra.solver_costs(spark.createDataFrame(rows, "center bigint, before array<bigint>, after array<bigint>")).collect()}
    assert {r.balls for r in got.values()} == {2} and max(r.worst for r in got.values()) < 1e-3


def test_solver_costs_solve_equal_balls_once(spark, monkeypatch, tmp_path):
    rows = [(100 * i, [x + 100 * i for x in e0], [x + 100 * i for x in e1]) for i in range(40) for e0, e1 in (([0, 1, 1, 2], [0, 1, 1, 2, 0, 2]), ([0, 1], [0, 1, 2, 3, 2, 4, 2, 5]))]
    real = spectra.iterative_spectra

    def noted(stack, *a, **k):
        with open(f"{tmp_path}/solved", "a") as f:
            f.write(f"{len(stack)}\n")
        return real(stack, *a, **k)

    monkeypatch.setattr(spectra, "iterative_spectra", noted)
    schema = "center bigint, before array<bigint>, after array<bigint>"
    many = {r.solver: r for r in spectra.solver_costs(spark.createDataFrame(rows, schema)).collect()}
    assert sum(map(int, open(f"{tmp_path}/solved"))) == 2 * 3  # two forms: before, cold and warm
    once = {r.solver: r for r in spectra.solver_costs(spark.createDataFrame(rows[:2], schema)).collect()}
    assert {n: (r.balls, r.rounds, r.worst) for n, r in many.items()} == {n: (40 * r.balls, 40 * r.rounds, r.worst) for n, r in once.items()}


def test_stacked_solves_equal_single_ones():
    rng = np.random.default_rng(2)
    stack = np.stack([spectra.laplacian(7, [(i, j) for i in range(7) for j in range(i + 1, 7) if rng.random() < 0.5]) for _ in range(20)])
    values, vectors, rounds = spectra.iterative_spectra(stack, 3)
    assert len(set(rounds.tolist())) > 1
    for i, m in enumerate(stack):
        own, x, turns = spectra.iterative_spectrum(m, 3)
        assert own == pytest.approx(values[i], abs=1e-9) and turns == rounds[i]


def test_modes_agree_on_matches(spark, g1):
    edges, vertices = g1
    versions = cut(streams.edge_versions(streams.insert_stream(edges)))
    rows = {r["mode"]: r for r in X.modes([workloads.LABELLED[1]], versions, vertices).collect()}
    assert len({r.matches for r in rows.values()}) == 1
    assert rows["off"].skipped == rows["off"].refreshes == rows["gate_only"].index_rows == 0 < rows["eager"].refreshes
