"""Enumeration: delta engines over edge versions, static and list-driven engines, counters.

The interpreted plan runs all queries and anchors together, one join a level. Partial
matches carry `bind`, an array with one slot per query vertex. A level explodes the bound
neighbours of the next vertex, meets each with the edges alive at the update, and keeps
data vertices met by all of them: the pool is the common neighbourhood, counted after
labels, candidates and injectivity. Every level is written out, since counters and the
next level read it.
"""

from __future__ import annotations

import time
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamatch.plans.query import Query
from deltamatch.session import OPEN_END, cut

from .graph import ANY, both_ways, offered

PARTIAL = "query_id string, anchor int, seq bigint, bind array<bigint>"


@dataclass
class Run:
    """What a run made: matches (query_id, seq, sign, bind), counters per level, its status and, if logged, every binding (query_id, u, v, seq, anchored)."""

    matches: DataFrame
    levels: DataFrame
    solved: bool = True
    seconds: float = 0.0
    visited: DataFrame | None = None


def _anchors(queries: list[Query], sizes: dict[str, dict[int, int]] | None = None) -> list[tuple]:
    """(query_id, anchor, u, w, label_u, label_w): both directions of each query edge, with their matching orders."""
    out = []
    for q in queries:
        for i, (a, b) in enumerate(q.edges):
            for j, (u, w) in enumerate(((a, b), (b, a))):
                out.append((q.name, 2 * i + j, u, w, q.labels[u], q.labels[w], q.order(u, w, sizes[q.name] if sizes else None)))
    return out


def _seeds(spark: SparkSession, queries: list[Query], anchors: list[tuple], changed: DataFrame, labels: DataFrame) -> DataFrame:
    """Partial matches of the anchor edge alone; changed: (seq, src, dst)."""
    size = {q.name: q.size for q in queries}
    known_as = lambda label: ANY if label is None else label
    rows = [(n, a, u, w, known_as(lu), known_as(lw), size[n]) for n, a, u, w, lu, lw, _ in anchors]
    asked = F.broadcast(spark.createDataFrame(rows, "query_id string, anchor int, u int, w int, lu int, lw int, size int"))
    ends = labels.select(F.col("id"), F.coalesce("label", F.lit(-1)).alias("label"))
    known = changed.join(ends.withColumnsRenamed({"id": "src", "label": "l1"}), "src", "left").join(ends.withColumnsRenamed({"id": "dst", "label": "l2"}), "dst", "left")
    known = known.select("seq", "src", "dst", "l2", offered("l1").alias("lu")).select("seq", "src", "dst", "lu", offered("l2").alias("lw"))
    # Both directions of an edge are anchors of their own, so the data edge is taken in one.
    bind = F.transform(F.sequence(F.lit(0), F.col("size") - 1), lambda i: F.when(i == F.col("u"), F.col("src")).when(i == F.col("w"), F.col("dst")))
    return known.join(asked, ["lu", "lw"]).select("query_id", "anchor", "seq", bind.alias("bind"))


def _admitted(rows: DataFrame, cand: DataFrame, u: str, v: str, sign: int = 1) -> DataFrame:
    """rows whose vertex v is a candidate of u; candidates with seq_from and seq_to count only while they hold, before a deletion or after an insertion."""
    known = cand.withColumnsRenamed({"query_id": "__q", "u": "__u", "v": "__v"})
    on = (F.col("query_id") == F.col("__q")) & (F.col(u) == F.col("__u")) & (F.col(v) == F.col("__v"))
    if "seq_from" in cand.columns:
        at = F.col("seq") - (0 if sign > 0 else 1)
        on = on & (F.col("seq_from") <= at) & (at < F.col("seq_to"))
    return rows.join(known, on, "left_semi")


def _level(partials: DataFrame, steps: DataFrame, adj: DataFrame, cand: DataFrame | None, sign: int = 1, injective: bool = True) -> DataFrame:
    """One more vertex for each partial match; steps: (query_id, anchor, x, x_label, back ARRAY<INT>)."""
    rows = partials.join(steps, ["query_id", "anchor"]).select("query_id", "anchor", "seq", "bind", "x", "x_label", F.size("back").alias("need"), F.explode("back").alias("b"))
    rows = rows.withColumn("v", F.get("bind", F.col("b")))
    alive = (F.col("valid_from") < F.col("seq")) & (F.col("valid_to") > F.col("seq"))
    met = rows.join(adj, "v").where(alive & F.coalesce(F.col("x_label") == F.col("w_label"), F.lit(True)))
    if injective:
        met = met.where(~F.array_contains(F.filter("bind", lambda y: y.isNotNull()), F.col("w")))
    single = met.where("need = 1").select("query_id", "anchor", "seq", "bind", "x", "w")
    several = met.where("need > 1").groupBy("query_id", "anchor", "seq", "bind", "x", "w", "need").agg(F.count("*").alias("n")).where("n = need").select("query_id", "anchor", "seq", "bind", "x", "w")
    pool = single.union(several)
    if cand is not None:
        pool = _admitted(pool, cand, "x", "w", sign)
    return pool.select("query_id", "anchor", "seq", F.transform("bind", lambda y, i: F.when(i == F.col("x"), F.col("w")).otherwise(y)).alias("bind"))


def _verified(tried: DataFrame, rest: DataFrame, adj: DataFrame) -> DataFrame:
    """Partial matches whose newest vertex also has the edges of rest: (query_id, anchor, x, rest ARRAY<INT>); those with nothing to verify stay."""
    rows = tried.join(rest, ["query_id", "anchor"])
    key = ["query_id", "anchor", "seq", "bind"]
    asked = rows.where(F.size("rest") > 0).select(*key, F.get("bind", F.col("x")).alias("w"), F.size("rest").alias("need"), F.explode("rest").alias("b")).withColumn("v", F.get("bind", F.col("b")))
    alive = (F.col("valid_from") < F.col("seq")) & (F.col("valid_to") > F.col("seq"))
    held = asked.join(adj.select("v", "w", "valid_from", "valid_to"), ["v", "w"]).where(alive).groupBy(*key, "need").agg(F.count("*").alias("n")).where("n = need")
    return rows.where(F.size("rest") == 0).select(*key).union(held.select(*key))


def delta(queries: list[Query], versions: DataFrame, vertices: DataFrame, *, cand: DataFrame | None = None, skips: DataFrame | None = None, sign: int = 1, sizes: dict[str, dict[int, int]] | None = None, seconds: float | None = None, since: int = 0, until: int = OPEN_END, late: bool = False, log: bool = False) -> Run:
    """Engine A: matches born (sign 1) or gone (sign -1) at each update, anchored at the changed edge.

    An update's matches use it as their newest edge: all other edges are older and alive, so
    each match appears once. skips: (query_id, seq) that a gate has ruled out. cand restricts
    every vertex; with columns seq_from and seq_to, only at updates in between. sizes makes
    matching orders follow candidate counts. The budget is checked between levels; a run over
    it is flagged, never trimmed. Only updates after `since` and up to `until` count. With
    `log` the run keeps each binding it performs, the anchor's ends included and marked. With `late` a level grows along one edge and is counted before its other edges are verified.
    """
    spark, began = versions.sparkSession, time.monotonic()
    at, other = (("valid_from", F.col("valid_from") > 0) if sign > 0 else ("valid_to", F.col("valid_to") < OPEN_END))
    changed = versions.where(other & (F.col(at) > since) & (F.col(at) <= until)).select(F.col(at).alias("seq"), "src", "dst")
    anchors = _anchors(queries, sizes)
    labels = vertices.select("id", F.coalesce("label", F.lit(-1)).alias("w_label"))
    adj = cut(both_ways(versions).join(labels.withColumnRenamed("id", "w"), "w", "left").select("v", "w", F.coalesce("w_label", F.lit(-1)).alias("w_label"), "valid_from", "valid_to"))
    partials = _seeds(spark, queries, anchors, changed, vertices)
    if skips is not None:
        partials = partials.join(skips.select("query_id", "seq").distinct(), ["query_id", "seq"], "left_anti")
    if cand is not None:  # the anchor's own ends are candidates too
        for end in (0, 1):
            ends = F.broadcast(spark.createDataFrame([(n, a, (u, w)[end]) for n, a, u, w, *_ in anchors], "query_id string, anchor int, u int"))
            partials = _admitted(partials.join(ends, ["query_id", "anchor"]).withColumn("v", F.get("bind", F.col("u"))), cand, "u", "v", sign).select("query_id", "anchor", "seq", "bind")
    by_name = {q.name: q for q in queries}
    done, levels, solved = [], [], True
    depth, partials = 2, cut(partials)
    seen = []
    if log:  # one slot for each end
        held = partials.select("query_id", "seq", F.posexplode("bind").alias("u", "v")).where("v IS NOT NULL")
        seen.append(held.select("query_id", "u", "v", "seq", F.lit(True).alias("anchored")).distinct())
    while True:
        full = [q.name for q in queries if q.size == depth]
        if full:
            done.append(partials.where(F.col("query_id").isin(full)).select("query_id", "seq", F.lit(sign).alias("sign"), "bind"))
        going = [q.name for q in queries if q.size > depth]
        if not going:
            break
        if seconds is not None and time.monotonic() - began > seconds:
            solved = False
            break
        rows = []
        for n, a, u, w, _, _, order in anchors:
            if n in going:
                x = order[depth]
                rows.append((n, a, x, by_name[n].labels[x], [y for y in order[:depth] if y in by_name[n].near(x)]))
        grown = [(*row[:4], row[4][:1]) for row in rows] if late else rows
        steps = F.broadcast(spark.createDataFrame(grown, "query_id string, anchor int, x int, x_label int, back array<int>"))
        partials = cut(_level(partials, steps, adj, cand, sign))
        depth += 1
        if log:
            seen.append(partials.join(steps, ["query_id", "anchor"]).select("query_id", F.col("x").alias("u"), F.get("bind", F.col("x")).alias("v"), "seq", F.lit(False).alias("anchored")).distinct())
        levels.append(partials.groupBy("query_id", "seq").agg(F.count("*").alias("n")).withColumn("level", F.lit(depth)))
        if late:
            rest = spark.createDataFrame([(n, a, x, back[1:]) for n, a, x, _, back in rows], "query_id string, anchor int, x int, rest array<int>")
            partials = cut(_verified(partials, F.broadcast(rest), adj))
    none = spark.createDataFrame([], "query_id string, seq bigint, sign int, bind array<bigint>")
    matches = none
    for part in done:
        matches = matches.union(part)
    counted = spark.createDataFrame([], "query_id string, seq bigint, n bigint, level int")
    for part in levels:
        counted = counted.unionByName(part)
    visited = cut(reduce(DataFrame.union, seen).distinct()) if log else None
    return Run(matches, counted, solved, time.monotonic() - began, visited)


def paced(query: Query, versions: DataFrame, vertices: DataFrame, *, seconds: float, cand: DataFrame | None = None, batches: int = 8) -> list[tuple[int, float, int, int]]:
    """(last seq, seconds so far, intermediates, matches) of each batch of updates of one query, in stream order.

    The budget is checked between batches: the batch that crosses it is completed and is
    the last. A run that reaches the last update has solved its query if its time is within
    the budget; every smaller budget can be read off the same rows.
    """
    last = versions.agg(F.max(F.greatest("valid_from", F.when(F.col("valid_to") < OPEN_END, F.col("valid_to"))))).first()[0] or 0
    marks = sorted({last * (i + 1) // batches for i in range(batches)} - {0})
    out, spent, since = [], 0.0, 0
    for mark in marks:
        began = time.monotonic()
        got = delta([query], versions, vertices, cand=cand, since=since, until=mark)
        made, found = got.levels.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0], got.matches.count()
        spent += time.monotonic() - began
        out.append((mark, spent, made, found))
        since = mark
        if spent > seconds:
            break
    return out


def delta_reduced(queries: list[Query], versions: DataFrame, vertices: DataFrame, *, cand: DataFrame, skips: DataFrame | None = None, sign: int = 1) -> Run:
    """Engine B: candidates are first narrowed towards and away from a root over all query edges, on every edge that ever lives; levels then grow along one edge, and bindings count before their other edges are verified, so its counters are compared within this engine only."""
    adj = both_ways(versions.select("src", "dst"))
    from .filters import propagate

    return delta(queries, versions, vertices, cand=propagate(cand, queries, adj, "dag"), skips=skips, sign=sign, late=True)


def match_counts(run: Run) -> DataFrame:
    """(query_id, seq, sign, matches)."""
    return run.matches.groupBy("query_id", "seq", "sign").agg(F.count("*").alias("matches"))


def label_candidates(queries: list[Query], vertices: DataFrame) -> DataFrame:
    """(query_id, u, v) by label alone, which any kind of match respects."""
    asked = vertices.sparkSession.createDataFrame([(q.name, u, label) for q in queries for u, label in enumerate(q.labels)], "query_id string, u int, l int")
    return F.broadcast(asked).join(vertices, F.col("l").isNull() | (F.col("l") == F.col("label"))).select("query_id", "u", F.col("id").alias("v"))


def subgraphs(matches: DataFrame, queries: list[Query]) -> DataFrame:
    """One match for each data subgraph: of those that an automorphism turns into each other, the one that meets the query's order conditions. A filter, without a shuffle."""
    fine = F.lit(False)
    for q in queries:
        ordered = F.col("query_id") == q.name
        for u, w in q.symmetry_breaks():
            ordered = ordered & (F.get("bind", F.lit(u)) < F.get("bind", F.lit(w)))
        fine = fine | ordered
    return matches.where(fine)


def periodic(lives: DataFrame, every: int, last: int) -> DataFrame:
    """(at, matches, found) at every `every`-th update up to `last`: what a check then and not after each update sees; found is the answer where only existence is asked.

    Matches (born, dies) count once when they enter and once when they leave the checks, so
    long lives cost no more than short ones. The checks themselves are rows of a range.
    """
    first, past = F.ceil(F.col("born") / every).cast("bigint"), F.ceil(F.col("dies") / every).cast("bigint")
    steps = lives.select(first.alias("a"), F.least(past, F.lit(last // every + 1).cast("bigint")).alias("b")).where("a < b")
    change = steps.select("a", F.lit(1).alias("d")).union(steps.select("b", F.lit(-1))).groupBy(F.col("a").alias("k")).agg(F.sum("d").alias("d"))
    checks = lives.sparkSession.range(last // every + 1).select(F.col("id").alias("k"))
    run = F.sum(F.coalesce("d", F.lit(0))).over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, 0))  # a row a check
    return checks.join(change, "k", "left").select((F.col("k") * every).alias("at"), run.alias("matches")).withColumn("found", F.col("matches") > 0)


def intermediates(run: Run, queries: list[Query]) -> DataFrame:
    """(query_id, inner, all_levels): bindings beyond the anchor, without and with the last level."""
    last = F.broadcast(run.levels.sparkSession.createDataFrame([(q.name, q.size) for q in queries], "query_id string, size int"))
    total = run.levels.join(last, "query_id", "right").groupBy("query_id")
    return total.agg(F.coalesce(F.sum(F.when(F.col("level") < F.col("size"), F.col("n"))), F.lit(0)).alias("inner"), F.coalesce(F.sum("n"), F.lit(0)).alias("all_levels"))


def lifetimes(query: Query, versions: DataFrame, vertices: DataFrame) -> DataFrame:
    """(m0.., born, dies) of every match of a small query that ever lives, by one join over versions."""
    out, bound = None, []
    for u, w in query.edges:
        a, b = f"m{u}", f"m{w}"
        rows = both_ways(versions).select(F.col("v").alias(a), F.col("w").alias(b), F.col("valid_from").alias("f2"), F.col("valid_to").alias("t2"))
        if out is None:
            out = rows.withColumnsRenamed({"f2": "born", "t2": "dies"})
        else:
            on = [c for c in (a, b) if c in bound]
            fresh = [c for c in (a, b) if c not in bound]
            out = out.join(rows, on).withColumn("born", F.greatest("born", "f2")).withColumn("dies", F.least("dies", "t2")).drop("f2", "t2").where("born < dies")
            for c in fresh:
                for seen in bound:
                    out = out.where(F.col(c) != F.col(seen))
        bound += [c for c in (a, b) if c not in bound]
    for u, label in enumerate(query.labels):
        if label is not None:
            out = out.join(vertices.where(F.col("label") == label).select(F.col("id").alias(f"m{u}")), f"m{u}", "left_semi")
    return out.select(*[f"m{u}" for u in range(query.size)], "born", "dies")


def brute(query: Query, edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Every injective match of a small query."""
    fixed = edges.select("src", "dst", F.lit(0).cast("bigint").alias("valid_from"), F.lit(OPEN_END).alias("valid_to"))
    return lifetimes(query, fixed, vertices).drop("born", "dies")


def candidate_space(queries: list[Query], cand: DataFrame, adj: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(query_id, u, w, a, b) of the candidate edges, and (query_id, scans): neighbours looked at to build them."""
    spark = cand.sparkSession
    asked = F.broadcast(spark.createDataFrame([(q.name, u, w) for q in queries for u, w in q.edges], "query_id string, u int, w int"))
    hops = adj.select(F.col("v"), F.col("w").alias("b")).distinct()
    seen = cand.join(asked, ["query_id", "u"]).join(hops, "v").select("query_id", "u", "w", F.col("v").alias("a"), "b")
    space = seen.join(cand.select("query_id", F.col("u").alias("w"), F.col("v").alias("b")), ["query_id", "w", "b"], "left_semi").select("query_id", "u", "w", "a", "b")
    return space, seen.groupBy("query_id").agg(F.count("*").alias("scans"))


def static(queries: list[Query], edges: DataFrame, vertices: DataFrame, cand: DataFrame, *, injective: bool = True) -> Run:
    """Static matching from vertex 0 over candidates: the delta plan with the candidates of an anchor edge as seeds, one direction of one edge only. Without `injective` query vertices may share a data vertex (homomorphisms); degree and count tests don't hold for those, so cand must come from labels alone."""
    spark = edges.sparkSession
    labels = vertices.select("id", F.coalesce("label", F.lit(-1)).alias("w_label"))
    adj = cut(both_ways(edges.select("src", "dst")).join(labels.withColumnRenamed("id", "w"), "w", "left").select("v", "w", F.coalesce("w_label", F.lit(-1)).alias("w_label"), F.lit(-1).cast("bigint").alias("valid_from"), F.lit(OPEN_END).alias("valid_to")))
    done = spark.createDataFrame([], "query_id string, seq bigint, sign int, bind array<bigint>")
    counted = spark.createDataFrame([], "query_id string, seq bigint, n bigint, level int")
    began = time.monotonic()
    for q in queries:
        u, w = q.edges[0]
        order = q.order(u, w)
        own = cand.where(F.col("query_id") == q.name)
        bind = F.transform(F.sequence(F.lit(0), F.lit(q.size - 1)), lambda i: F.when(i == u, F.col("v")).when(i == w, F.col("w")))
        partials = adj.join(own.where(F.col("u") == u).select("v"), "v", "left_semi").join(own.where(F.col("u") == w).select(F.col("v").alias("w")), "w", "left_semi").select(F.lit(q.name).alias("query_id"), F.lit(0).alias("anchor"), F.lit(0).cast("bigint").alias("seq"), bind.alias("bind"))
        for depth in range(2, q.size):
            x = order[depth]
            steps = F.broadcast(spark.createDataFrame([(q.name, 0, x, q.labels[x], [y for y in order[:depth] if y in q.near(x)])], "query_id string, anchor int, x int, x_label int, back array<int>"))
            partials = cut(_level(partials, steps, adj, own, injective=injective))
            counted = counted.unionByName(partials.groupBy("query_id", "seq").agg(F.count("*").alias("n")).withColumn("level", F.lit(depth + 1)))
        done = done.union(partials.select("query_id", "seq", F.lit(1), "bind"))
    return Run(done, counted, True, time.monotonic() - began)


def list_scan_cost(run: Run, queries: list[Query], cand: DataFrame) -> DataFrame:
    """(query_id, level, scans) of a list-driven engine in the same order: at each level every partial match scans the next vertex's whole list."""
    spark = cand.sparkSession
    order = {q.name: q.order(*q.edges[0]) for q in queries}
    lists = cand.groupBy("query_id", "u").agg(F.count("*").alias("size"))
    nexts = F.broadcast(spark.createDataFrame([(n, depth + 1, o[depth]) for n, o in order.items() for depth in range(2, len(o))], "query_id string, level int, u int"))
    # Partial matches entering a level are those the level below made; the first enter as candidate edges of the anchor.
    entering = run.levels.groupBy("query_id", (F.col("level") + 1).alias("level")).agg(F.sum("n").alias("partials"))
    return nexts.join(lists, ["query_id", "u"]).join(entering, ["query_id", "level"]).select("query_id", "level", (F.col("partials") * F.col("size")).alias("scans"))


def list_driven(queries: list[Query], cand: DataFrame, adj: DataFrame, *, longest: int = 4096) -> tuple[Run, DataFrame]:
    """Static matching over materialised candidate lists, and (query_id, level, scans): the list entries read.

    The list of (query edge u-w, a) holds the candidates of w next to a. A level meets the
    lists of all bound neighbours and intersects them; no adjacency is looked at. Lists are
    dealt into parts by a hash of their entries so that the longest has about `longest`
    entries a row, and parts are intersected one by one: a hub's list never is one row.
    """
    spark, began = cand.sparkSession, time.monotonic()
    one_way, _ = candidate_space(queries, cand, adj)
    space = cut(one_way.union(one_way.select("query_id", F.col("w").alias("u"), F.col("u").alias("w"), F.col("b").alias("a"), F.col("a").alias("b"))))
    most = space.groupBy("query_id", "u", "w", "a").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 1
    part = F.pmod(F.xxhash64("b"), F.lit(-(-most // longest))).alias("part")
    lists = cut(space.groupBy("query_id", "u", "w", "a", part).agg(F.collect_list("b").alias("found")))
    done = spark.createDataFrame([], "query_id string, seq bigint, sign int, bind array<bigint>")
    counted = spark.createDataFrame([], "query_id string, seq bigint, n bigint, level int")
    scans = spark.createDataFrame([], "query_id string, level int, scans bigint")
    for q in queries:
        u, w = q.edges[0]
        order = q.order(u, w)
        own = lists.where(F.col("query_id") == q.name)
        bind = F.transform(F.sequence(F.lit(0), F.lit(q.size - 1)), lambda i: F.when(i == u, F.col("a")).when(i == w, F.col("b")))
        partials = space.where((F.col("query_id") == q.name) & (F.col("u") == u) & (F.col("w") == w)).select(bind.alias("bind"))
        for depth in range(2, q.size):
            x = order[depth]
            met, keys = partials, []
            for y in (y for y in order[:depth] if y in q.near(x)):
                side = own.where((F.col("u") == y) & (F.col("w") == x)).select(F.col("a").alias("__a"), "part", F.col("found").alias("more"))
                met = met.withColumn("__a", F.get("bind", F.lit(y))).join(side, ["__a", *keys]).drop("__a")
                read = F.size("more").cast("bigint")
                if keys:
                    met = met.withColumn("read", F.col("read") + read).withColumn("found", F.array_intersect("found", "more")).drop("more")
                else:
                    met = met.withColumn("read", read).withColumnRenamed("more", "found")
                keys = ["part"]
            met = cut(met)
            scans = scans.union(met.agg(F.sum("read").alias("scans")).where("scans IS NOT NULL").select(F.lit(q.name), F.lit(depth + 1), "scans"))
            grown = met.select("bind", F.explode("found").alias("v")).where(~F.array_contains(F.filter("bind", lambda y: y.isNotNull()), F.col("v")))
            partials = cut(grown.select(F.transform("bind", lambda y, i: F.when(i == x, F.col("v")).otherwise(y)).alias("bind")))
            counted = counted.union(partials.agg(F.count("*").alias("n")).where("n > 0").select(F.lit(q.name), F.lit(0).cast("bigint"), "n", F.lit(depth + 1)))
        done = done.union(partials.select(F.lit(q.name), F.lit(0).cast("bigint"), F.lit(1), "bind"))
    return Run(done, counted, True, time.monotonic() - began), scans


def admit(queries: list[Query], cand: DataFrame, most: float = 1e9) -> DataFrame:
    """(query_id, log10_bound, admitted): the product of candidate counts bounds the matches; empty lists admit nothing to do."""
    spark = cand.sparkSession
    every = spark.createDataFrame([(q.name, u) for q in queries for u in range(q.size)], "query_id string, u int")
    sizes = F.broadcast(every).join(cand.groupBy("query_id", "u").agg(F.count("*").alias("n")), ["query_id", "u"], "left").groupBy("query_id")
    bound = sizes.agg(F.sum(F.log10(F.greatest(F.coalesce("n", F.lit(0)), F.lit(1)))).alias("log10_bound"), F.min(F.coalesce("n", F.lit(0))).alias("least"))
    return bound.select("query_id", "log10_bound", ((F.col("least") > 0) & (F.pow(F.lit(10.0), "log10_bound") <= most)).alias("admitted"))
