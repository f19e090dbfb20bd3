"""DuckDB twins of the registered queries."""

from __future__ import annotations

from deltamatch.plans.query import Query, pattern
from deltamatch.workloads import CAP, LABELLED, PATTERNS, QUERY_SIDE

_END = 2**63 - 1
_DECOYS = "d AS (SELECT count(*) AS n FROM (SELECT l_orderkey FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY l_orderkey HAVING count(*) >= 8 ORDER BY l_orderkey LIMIT 51))"
_BASE = f"""
l AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem WHERE l_returnflag = 'R' AND l_linestatus = 'F'),
e AS (SELECT DISTINCT a.p AS src, b.p AS dst FROM l a JOIN l b ON a.o = b.o AND a.p < b.p),
vx AS (SELECT p_partkey AS id, CAST(p_size % 4 AS INT) AS label FROM part),
adj AS (SELECT src AS v, dst AS w FROM e UNION ALL SELECT dst, src FROM e),
deg AS (SELECT v, count(*) AS degree FROM adj GROUP BY v),
prof AS (SELECT v, coalesce(label, -1) AS w_label, count(*) AS n FROM adj LEFT JOIN vx ON id = w GROUP BY ALL),
num AS (SELECT src, dst, row_number() OVER (ORDER BY md5(concat(src, '-', dst)), src, dst) AS n, (SELECT (count(*) * 9 + 9) // 10 FROM e) AS first, (SELECT count(*) FROM e) AS m FROM e),
s1 AS (SELECT CAST(greatest(n - first, 0) AS BIGINT) AS seq, '+' AS op, src, dst FROM num),
s2 AS (SELECT CAST(CASE WHEN n <= first THEN 0 ELSE ((n - first - 1) // 7) * 10 + (n - first - 1) % 7 + 1 END AS BIGINT) AS seq, '+' AS op, src, dst FROM num
       UNION ALL SELECT CAST(((n - 1) // 3) * 10 + 7 + (n - 1) % 3 + 1 AS BIGINT), '-', src, dst FROM num WHERE n <= least(first, 3 * ((m - first) // 7))),
v1 AS (SELECT src, dst, seq AS valid_from, {_END} AS valid_to FROM s1),
v2 AS (SELECT a.src, a.dst, a.seq AS valid_from, coalesce(b.seq, {_END}) AS valid_to FROM s2 a LEFT JOIN s2 b ON a.src = b.src AND a.dst = b.dst AND b.op = '-' WHERE a.op = '+'),
b1 AS (SELECT v AS center, v AS member FROM adj UNION SELECT v, w FROM adj),
b2all AS (SELECT center, member FROM b1 UNION SELECT b1.center, adj.w FROM b1 JOIN adj ON adj.v = b1.member),
small AS (SELECT center, count(*) AS nv FROM b2all GROUP BY center HAVING count(*) <= {CAP}),
b2 AS (SELECT center, member FROM b2all SEMI JOIN small USING (center)),
ind AS (SELECT x.center, e.src AS a, e.dst AS b FROM b2 x JOIN e ON e.src = x.member JOIN b2 y ON y.center = x.center AND y.member = e.dst),
bd AS (SELECT center, member, count(*) AS d FROM (SELECT center, a AS member FROM ind UNION ALL SELECT center, b FROM ind) GROUP BY ALL),
tri AS (SELECT p.center, count(*) AS tri FROM ind p JOIN ind q ON q.center = p.center AND q.a = p.b JOIN ind r ON r.center = p.center AND r.a = p.a AND r.b = q.b GROUP BY p.center)
"""


def _with(body: str, more: str = "") -> str:
    return f"WITH {_BASE}{', ' + more if more else ''} {body}"


def _versioned(name: str) -> str:
    return f"ax AS (SELECT src AS v, dst AS w, valid_from AS f, valid_to AS t FROM {name} UNION ALL SELECT dst, src, valid_from, valid_to FROM {name})"


def _label(query: Query, u: int, column: str) -> str:
    return "" if query.labels[u] is None else f" AND {column} IN (SELECT id FROM vx WHERE label = {query.labels[u]})"


def _lives(query: Query, injective: bool = True) -> str:
    """All matches that ever live, with born and dies; one adjacency alias for each edge."""
    at: dict[int, str] = {}
    sources, conditions = [], []
    for i, (u, w) in enumerate(query.edges):
        sources.append(f"ax x{i}")
        for vertex, side in ((u, "v"), (w, "w")):
            if vertex in at:
                conditions.append(f"{at[vertex]} = x{i}.{side}")
            else:
                conditions += [f"{other} <> x{i}.{side}" for other in at.values() if injective]
                at[vertex] = f"x{i}.{side}"
    text = " AND ".join(conditions) or "true"
    text += "".join(_label(query, u, at[u]) for u in at)
    froms, tos = (", ".join(f"x{i}.{c}" for i in range(len(query.edges))) for c in "ft")
    names = ", ".join(f"{at[u]} AS m{u}" for u in sorted(at))
    return f"(SELECT * FROM (SELECT {names}, greatest({froms}) AS born, least({tos}) AS dies FROM {', '.join(sources)} WHERE {text}) WHERE born < dies)"


def _born(query: Query) -> str:
    return _with(f"SELECT CAST(born AS BIGINT) AS seq, 1 AS sign, count(*) AS matches FROM {_lives(query)} WHERE born > 0 GROUP BY born", _versioned("v1"))


def _steps(query: Query, cand: bool):
    """(level, u, its vertex, FROM, WHERE) of every binding, level 2 being both ends of an anchor, over all anchors in their matching orders."""
    keep = lambda u, c: f" AND {c} IN (SELECT v FROM nlf WHERE query_id = '{query.name}' AND u = {u})" if cand else ""
    for a, b in query.edges:
        for u, w in ((a, b), (b, a)):
            order = query.order(u, w)
            sources, text = ["v1 s"], "s.valid_from > 0" + _label(query, u, "s.src") + _label(query, w, "s.dst") + keep(u, "s.src") + keep(w, "s.dst")
            at = {u: "s.src", w: "s.dst"}
            for x, here in at.items():
                yield 2, x, here, ", ".join(sources), text
            for depth in range(2, query.size):
                x = order[depth]
                for j, y in enumerate(v for v in order[:depth] if v in query.near(x)):
                    name = f"y{depth}_{j}"
                    sources.append(f"ax {name}")
                    text += f" AND {name}.v = {at[y]} AND {name}.f < s.valid_from" + (f" AND {name}.w = y{depth}_0.w" if j else "")
                here = f"y{depth}_0.w"
                text += "".join(f" AND {here} <> {other}" for other in at.values()) + _label(query, x, here) + keep(x, here)
                at[x] = here
                yield depth + 1, x, here, ", ".join(sources), text


def _levels(query: Query, cand: bool, key: str = "level") -> str:
    """Bindings beyond the anchor, per level or per update (seq)."""
    parts = [f"SELECT {level} AS level, s.valid_from AS seq, count(*) AS n FROM {sources} WHERE {text} GROUP BY s.valid_from" for level, _, _, sources, text in _steps(query, cand) if level > 2]
    return f"SELECT '{query.name}' AS query_id, {key}, CAST(sum(n) AS BIGINT) AS n FROM ({' UNION ALL '.join(parts)}) GROUP BY {key}"


def _visited(queries: tuple[Query, ...]) -> str:
    """Every binding the engine performs without candidates, as a named table."""
    return "seen AS (" + " UNION ".join(f"SELECT '{q.name}' AS query_id, {u} AS u, {here} AS v, {level == 2} AS anchored FROM {sources} WHERE {text}" for q in queries for level, u, here, sources, text in _steps(q, False)) + ")"


_LDF = "ldf AS (" + " UNION ALL ".join(f"SELECT '{q.name}' AS query_id, {u} AS u, v FROM deg JOIN vx ON id = v WHERE label = {q.labels[u]} AND degree >= {len(q.near(u))}" for q in LABELLED for u in range(q.size)) + ")"
_NEEDS = "needs(query_id, u, w_label, need) AS (VALUES " + ", ".join(f"('{q.name}', {u}, {label}, {n})" for q in LABELLED for u in range(q.size) for label, n in q.needs(u).items()) + ")"
_NLF = f"{_LDF}, {_NEEDS}, nlf AS (SELECT query_id, u, v FROM ldf WHERE NOT EXISTS (SELECT 1 FROM needs k WHERE k.query_id = ldf.query_id AND k.u = ldf.u AND coalesce((SELECT n FROM prof p WHERE p.v = ldf.v AND p.w_label = k.w_label), 0) < k.need))"
_QE = "qe(query_id, u, w) AS (VALUES " + ", ".join(f"('{q.name}', {u}, {w})" for q in LABELLED for u, w in q.edges) + ")"
_QB = "qb AS (SELECT query_id, u, w FROM qe UNION ALL SELECT query_id, w, u FROM qe)"
_round = lambda new, old: f"{new} AS (SELECT query_id, u, v FROM {old} c WHERE NOT EXISTS (SELECT 1 FROM qb WHERE qb.query_id = c.query_id AND qb.u = c.u AND NOT EXISTS (SELECT 1 FROM adj JOIN {old} d ON d.v = adj.w AND d.query_id = c.query_id AND d.u = qb.w WHERE adj.v = c.v)))"
_DEGREES = "ranked AS (SELECT center, d, row_number() OVER (PARTITION BY center ORDER BY d DESC, member) AS t FROM bd), dv AS (SELECT center, " + ", ".join(f"coalesce(max(CASE WHEN t = {t} THEN d END), 0) AS d{t}" for t in range(1, 5)) + " FROM ranked WHERE t <= 4 GROUP BY center)"
_COST = " + ".join(f"greatest(0, {int(q)} - d{t})" for t, q in enumerate(QUERY_SIDE, 1))


def _ceiling(i: int, k: str, most: int) -> str:
    """c_i for k given as SQL; j runs over what both k and i allow."""
    return "least(" + ", ".join(f"CASE WHEN {j} <= {k} THEN d{i - j} + 2 * ({k} - {j}) ELSE 1000000 END" for j in range(min(most, i - 1) + 1)) + ")"


def _any(parts: list[str]) -> str:
    return "(" + " OR ".join(parts) + ")"


_SHIFT = [f"CASE WHEN {t} > k THEN CASE " + " ".join(f"WHEN {t} - k = {s} THEN {int(q)} > d{s}" for s in range(1, t + 1)) + f" END ELSE {int(q)} > d{t} + 2 * k END" for t, q in enumerate(QUERY_SIDE, 1)]
_ABOVE = [f"{int(q)} > {_ceiling(t, 'k', 3)}" for t, q in enumerate(QUERY_SIDE, 1)]
_RULES = {
    "flat": _any([f"{int(q)} > d{t} + 2 * k" for t, q in enumerate(QUERY_SIDE, 1)]), "rank_shift": _any(_SHIFT), "ceilings": _any(_ABOVE),
    "mass": f"({_COST} > 2 * k)", "tightest": f"({_COST} > 2 * k OR {_any(_ABOVE)})",
}
_BUCKET = "CASE WHEN nv <= 8 THEN '01-08' WHEN nv <= 16 THEN '09-16' WHEN nv <= 32 THEN '17-32' WHEN nv <= 64 THEN '33-64' ELSE '65-' END"
_ALLSIZES = "al AS (SELECT center, count(*) AS nv FROM b2all GROUP BY center)"
def _gate(name: str, at: str, changed: str, alive: str, inside: str) -> str:
    """Balls within one hop of either end of each changed edge, with their counts, in the graph of that moment."""
    return f"""{_versioned(name)}, up AS (SELECT {at} AS seq, src, dst FROM {name} WHERE {changed}),
gb AS (SELECT seq, src AS member FROM up UNION SELECT seq, dst FROM up UNION SELECT seq, w FROM up JOIN ax ON ax.v IN (src, dst) AND {alive}),
gn AS (SELECT seq, count(*) AS nv FROM gb GROUP BY seq),
gi AS (SELECT x.seq, {name}.src AS a, {name}.dst AS b FROM gb x JOIN {name} ON {name}.src = x.member AND {inside} JOIN gb y ON y.seq = x.seq AND y.member = {name}.dst),
ge AS (SELECT seq, count(*) AS ne FROM gi GROUP BY seq),
gt AS (SELECT p.seq, count(*) AS tri FROM gi p JOIN gi q ON q.seq = p.seq AND q.a = p.b JOIN gi r ON r.seq = p.seq AND r.a = p.a AND r.b = q.b GROUP BY p.seq),
gs AS (SELECT up.seq, src, dst, nv, coalesce(ne, 0) AS ne, coalesce(tri, 0) AS tri FROM up LEFT JOIN gn USING (seq) LEFT JOIN ge USING (seq) LEFT JOIN gt USING (seq))"""


_GATE = _gate("v1", "valid_from", "valid_from > 0", "ax.f <= seq", "v1.valid_from <= x.seq")
def _reach(name: str, alive: str) -> str:
    """Vertices within two hops of either end of each change, in the graph of that moment."""
    hop = lambda old: f"SELECT seq, e, c FROM {old} UNION SELECT seq, e, w FROM {old} JOIN ax ON ax.v = c AND {alive}"
    return f"{name}1 AS ({hop('ends')}), {name} AS ({hop(name + '1')})"


#: Symmetries of the patterns.
_SYMMETRIES = {"triangle": 6, "diamond": 4, "clique4": 24, "cycle4": 8, "tailed_triangle": 2}
_ZERO = "SELECT CAST(0 AS BIGINT) AS violations"
_G4 = """WITH l AS (SELECT l_orderkey AS o, l_partkey AS p FROM lineitem WHERE l_returnflag = 'R' AND l_linestatus = 'F' GROUP BY ALL),
x AS (SELECT o_custkey AS c, o, p FROM l JOIN orders ON o_orderkey = o GROUP BY ALL)"""
_deltas = {f"delta_{p}": _born(pattern(p)) for p in PATTERNS}

ORACLES: dict[str, str] = _deltas | {
    "copurchase_edges": _with("SELECT src, dst FROM e"),
    "copurchase_stream_90_10": _with("SELECT seq, op, src, dst FROM s1"),
    "mixed_stream_70_30": _with("SELECT seq, op, src, dst FROM s2"),
    "edge_versions": _with("SELECT src, dst, valid_from, CAST(valid_to AS BIGINT) AS valid_to FROM v2"),
    "degree_table": _with("SELECT v, degree FROM deg"),
    "label_profile": _with("SELECT v, w_label, n FROM prof"),
    "shared_line_edges": """WITH l AS (SELECT DISTINCT doc_id, trim(unnest(string_split(text, chr(10)))) AS line FROM documents),
        f AS (SELECT line FROM l WHERE length(line) >= 40 GROUP BY line HAVING count(DISTINCT doc_id) BETWEEN 2 AND 20)
        SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM l a JOIN f USING (line) JOIN l b ON b.line = a.line AND a.doc_id < b.doc_id""",
    "page_link_fanout": """SELECT page_id AS page, count(DISTINCT href) AS links FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) GROUP BY page_id""",
    "trade_degrees": """WITH l AS (SELECT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'R' AND l_linestatus = 'F'),
        e AS (SELECT DISTINCT 0 AS k1, o_custkey AS a, 1 AS k2, o_orderkey AS b FROM orders UNION SELECT 1, o, 2, p FROM l UNION SELECT 2, p, 3, s FROM l),
        d AS (SELECT k, v, count(*) AS n FROM (SELECT k1 AS k, a AS v FROM e UNION ALL SELECT k2, b FROM e) GROUP BY ALL)
        SELECT k AS kind, count(*) AS vertices, max(n) AS most FROM d GROUP BY k""",
    "zipf_label_counts": """WITH u AS (SELECT CAST(concat('0x', left(md5(CAST(p_partkey AS VARCHAR)), 8)) AS BIGINT) / 4294967296.0 AS x FROM part),
        w AS (SELECT 1.0::DOUBLE AS a, pow(2, -1.5) AS b, pow(3, -1.5) AS c, pow(4, -1.5) AS d)
        SELECT CASE WHEN x < a / (a + b + c + d) THEN 1 WHEN x < (a + b) / (a + b + c + d) THEN 2 WHEN x < (a + b + c) / (a + b + c + d) THEN 3 ELSE 4 END AS label, count(*) AS n FROM u, w GROUP BY 1""",
    "renewed_stream_births": _with(
        f"SELECT CAST(born AS BIGINT) AS seq, count(*) AS matches FROM {_lives(pattern('triangle'))} WHERE born > 0 GROUP BY born",
        f"v5 AS (SELECT src, dst, seq * 6 AS valid_from, CASE WHEN seq > 0 AND seq % 5 = 0 THEN seq * 6 + 2 ELSE {_END} END AS valid_to FROM s1 UNION ALL SELECT src, dst, seq * 6 + 4, {_END} FROM s1 WHERE seq > 0 AND seq % 5 = 0), {_versioned('v5')}"),
    "deletion_gate": _with(
        f"SELECT CASE WHEN nv <= {CAP} AND (nv < 4 OR ne < 6 OR tri < 4) THEN 'skip' ELSE 'pass' END AS decision, count(*) AS n FROM gs GROUP BY 1",
        _gate("v2", "valid_to", f"valid_to < {_END}", "ax.f < seq AND ax.t >= seq", "v2.valid_from < x.seq AND v2.valid_to >= x.seq")),
    "temporal_user_edges": """SELECT least(a.user_id, b.user_id) AS src, greatest(a.user_id, b.user_id) AS dst, epoch_us(min(b.ts)) AS us FROM events a JOIN events b
        ON a.event_type = b.event_type AND a.props = b.props AND a.user_id <> b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1, 2""",
    "sliding_window_edges": """SELECT CAST(s AS BIGINT) AS start_us, count(*) AS n FROM (SELECT unnest([h, h - 3600000000]) AS s FROM (SELECT (epoch_us(ts) // 3600000000) * 3600000000 AS h FROM events WHERE ts IS NOT NULL)) GROUP BY s""",
    "event_sessions": """WITH m AS (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) <= 1800000000 THEN 0 ELSE 1 END AS opens FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL),
        g AS (SELECT user_id, us, sum(opens) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS s FROM m)
        SELECT user_id, min(us) AS start_us, count(*) AS n FROM g GROUP BY user_id, s""",
    "asof_version_lookup": _with("SELECT a.seq, a.src, a.dst, max(b.seq) AS valid_from FROM s2 a JOIN s2 b ON b.op = '+' AND b.src = a.src AND b.dst = a.dst AND b.seq < a.seq WHERE a.op = '-' GROUP BY ALL"),
    "ldf_candidates": _with("SELECT query_id, u, v FROM ldf", _LDF),
    "nlf_candidates": _with("SELECT query_id, u, v FROM nlf", _NLF),
    "propagation_two_rounds": _with("SELECT query_id, u, count(*) AS n FROM r2 GROUP BY ALL", f"{_NLF}, {_QE}, {_QB}, {_round('r1', 'nlf')}, {_round('r2', 'r1')}"),
    "candidate_space_scans": _with("SELECT query_id, CAST(sum(degree) AS BIGINT) AS scans FROM qe JOIN nlf USING (query_id, u) JOIN deg USING (v) GROUP BY query_id", f"{_NLF}, {_QE}"),
    "list_scan_cost": _with(
        "SELECT 'labelled_diamond' AS query_id, 4 AS level, (SELECT count(*) FROM adj x JOIN adj y ON y.v = x.v JOIN adj z ON z.v = x.w AND z.w = y.w WHERE " + " AND ".join(f"{c} IN (SELECT v FROM nlf WHERE query_id = 'labelled_diamond' AND u = {u})" for u, c in ((0, "x.v"), (1, "x.w"), (2, "y.w"))) + " AND x.w <> y.w) * (SELECT count(*) FROM nlf WHERE query_id = 'labelled_diamond' AND u = 3) AS scans", _NLF),
    "dominance_candidates": _with(
        "SELECT query_id, u, v FROM ldf JOIN (VALUES " + ", ".join(f"('{q.name}', {u}, {len(q.near(u))}, {sum(len(q.near(w)) for w in q.near(u))})" for q in LABELLED for u in range(q.size))
        + ") q(query_id, u, q1, q2) USING (query_id, u) JOIN (SELECT a.v, count(*) AS d1, sum(d.degree) AS d2 FROM adj a JOIN deg d ON d.v = a.w GROUP BY a.v) USING (v) WHERE d1 >= q1 AND d2 >= q2", _LDF),
    "list_driven_scans": _with(
        "SELECT 'labelled_triangle' AS query_id, 3 AS level, CAST(sum(x.n + y.n) AS BIGINT) AS scans FROM adj JOIN pairs x ON x.u = 0 AND x.v = adj.v JOIN pairs y ON y.u = 1 AND y.v = adj.w WHERE adj.w IN (SELECT v FROM nt WHERE u = 1) HAVING count(*) > 0",
        f"{_NLF}, nt AS (SELECT u, v FROM nlf WHERE query_id = 'labelled_triangle'), pairs AS (SELECT nt.u, nt.v, count(*) AS n FROM nt JOIN adj USING (v) WHERE nt.u < 2 AND adj.w IN (SELECT v FROM nt WHERE u = 2) GROUP BY nt.u, nt.v)"),
    "ball_sizes_h1": _with("SELECT center, count(*) AS nv FROM b1 GROUP BY center"),
    "ball_sizes_h2": _with("SELECT center, nv FROM small"),
    "ball_edge_counts": _with("SELECT center, nv, coalesce(ne, 0) AS ne FROM small LEFT JOIN (SELECT center, count(*) AS ne FROM ind GROUP BY center) USING (center)"),
    "ball_triangles": _with("SELECT center, coalesce(tri, 0) AS tri FROM small LEFT JOIN tri USING (center)"),
    "degree_overflow_screen": _with("SELECT v, degree >= 8 OR EXISTS (SELECT 1 FROM adj JOIN deg d ON d.v = adj.w WHERE adj.v = deg.v AND d.degree >= 8) AS over FROM deg"),
    "hub_excluded_components": _with("SELECT center, CAST(t AS INT) AS component FROM (SELECT center, d, row_number() OVER (PARTITION BY center ORDER BY d DESC, member) AS t FROM bd) WHERE t <= 4 AND d >= 5 + t"),
    "conjugate_degree_ceiling": _with("SELECT center, " + ", ".join(f"count(*) FILTER (d >= {i}) AS d{i}" for i in range(1, 5)) + " FROM bd GROUP BY center"),
    "spectral_moments": _with("SELECT center, CAST(sum(d) AS BIGINT) AS m1, CAST(sum(d * d + d) AS BIGINT) AS m2, CAST(sum(d * d * d + 3 * d * d) - 6 * coalesce(max(tri), 0) AS BIGINT) AS m3 FROM bd LEFT JOIN tri USING (center) GROUP BY center"),
    "closed_walks_are_triangles": _with("SELECT center, 6 * coalesce(tri, 0) AS walks FROM small LEFT JOIN tri USING (center)"),
    "reverse_index_fanout": _with("SELECT member, count(*) AS centers FROM b2 GROUP BY member"),
    "reverse_compaction": _with("SELECT (SELECT count(*) FROM b2all) AS rows, (SELECT count(*) FROM b2) AS live_rows"),
    "coverage_by_cap": _with("SELECT cap, count(*) FILTER (nv <= cap) AS deployed, count(*) AS vertices FROM al, (VALUES (8), (16), (32), (64), (128)) c(cap) GROUP BY cap", _ALLSIZES),
    "utility_bucket_sizes": _with(f"SELECT {_BUCKET} AS bucket, count(*) AS n FROM al GROUP BY 1", _ALLSIZES),
    "report_rollup": _with("SELECT label, CAST(bucket AS BIGINT) AS bucket, count(*) AS n FROM (SELECT label, least(degree, 5) AS bucket FROM deg JOIN vx ON id = v) GROUP BY ROLLUP (label, bucket)"),
    "mass_cost": _with(f"SELECT center, CAST({_COST} AS BIGINT) AS cost FROM dv", _DEGREES),
    "ceilings_vs_lattice": _with("SELECT center, " + ", ".join(f"CAST({_ceiling(i, '2', 2)} AS BIGINT) AS c{i}" for i in range(1, 5)) + " FROM dv", _DEGREES),
    "bound_rules": _with(" UNION ALL ".join(f"SELECT k, '{n}' AS rule, CAST(count(*) FILTER ({rule}) AS BIGINT) AS rejected FROM dv, (VALUES (0), (1), (2), (3)) ks(k) GROUP BY k" for n, rule in _RULES.items()), _DEGREES),
    "delta_mixed_signs": _with(f"SELECT CAST(born AS BIGINT) AS seq, 1 AS sign, count(*) AS matches FROM {_lives(pattern('triangle'))} WHERE born > 0 GROUP BY born UNION ALL SELECT CAST(dies AS BIGINT), -1, count(*) FROM {_lives(pattern('triangle'))} WHERE dies < {_END} GROUP BY dies", _versioned("v2")),
    "delta_labelled": _with(" UNION ALL ".join(f"SELECT '{q.name}' AS query_id, CAST(born AS BIGINT) AS seq, count(*) AS matches FROM {_lives(q)} WHERE born > 0 GROUP BY born" for q in LABELLED), _versioned("v1")),
    "match_lifetimes": _with(f"SELECT m0, m1, m2, CAST(born AS BIGINT) AS born, CAST(dies AS BIGINT) AS dies FROM {_lives(pattern('triangle'))}", _versioned("v2")),
    "static_matches": _with("SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{q.name}' AS query_id, count(*) AS matches FROM {_lives(q)}" for q in LABELLED) + ") WHERE matches > 0", _versioned("v1")),
    "list_driven_matches": _with("SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{q.name}' AS query_id, count(*) AS matches FROM {_lives(q)}" for q in LABELLED) + ") WHERE matches > 0", _versioned("v1")),
    "level_intermediates_control": _with(_levels(LABELLED[2], False) + " HAVING sum(n) > 0", _versioned("v1")),
    "level_intermediates_nlf": _with(_levels(LABELLED[2], True) + " HAVING sum(n) > 0", f"{_versioned('v1')}, {_NLF}"),
    "trade_rings": _G4 + " SELECT a.c AS customer, count(*) AS rings FROM x a JOIN x b ON a.c = b.c AND a.p = b.p AND a.o <> b.o GROUP BY a.c",
    "gate_counts_fire": _with(f"SELECT seq, CASE WHEN nv <= {CAP} AND (nv < 4 OR ne < 6 OR tri < 4) THEN 'skip' ELSE 'pass' END AS decision FROM gs", _GATE),
    "gate_fire_by_label": _with(
        f"SELECT CASE WHEN a.label = b.label OR a.label > 2 OR b.label > 2 THEN 'label_skip' WHEN nv <= {CAP} AND (nv < 3 OR ne < 3 OR tri < 1) THEN 'skip' ELSE 'pass' END AS decision, count(*) AS n FROM gs JOIN vx a ON a.id = src JOIN vx b ON b.id = dst GROUP BY 1", _GATE),
    "exact_vs_naive_triggers": _with(
        "SELECT seq, (SELECT count(*) FROM b2 x JOIN b2 y ON y.center = x.center AND y.member = s.dst WHERE x.member = s.src) AS exact, (SELECT count(DISTINCT center) FROM b2 x WHERE x.member IN (s.src, s.dst)) AS either FROM s1 s WHERE seq > 0"),
    "decoy_workload": f"WITH {_DECOYS} SELECT n AS updates, n - 1 AS skipped, CAST(720 AS BIGINT) AS matches FROM d",
    # A decoy is a clique of eight, in which each of 58 anchors binds 6, 6 * 5, ... vertices; the true region's bindings are counted by a test.
    "decoy_control": f"WITH {_DECOYS} SELECT 'off' AS test, CAST((n - 1) * 58 * (6 + 30 + 120 + 360 + 720 + 720) + 36870 AS BIGINT) AS intermediates, CAST(720 AS BIGINT) AS matches FROM d UNION ALL SELECT 'on', 36870, 720",
    "update_triggers": _with(
        "SELECT seq, (SELECT count(*) FROM post a JOIN post b ON a.seq = b.seq AND a.c = b.c AND a.e = 0 AND b.e = 1 WHERE a.seq = up.seq) AS exact, (SELECT count(DISTINCT c) FROM pre WHERE pre.seq = up.seq) AS either FROM up",
        f"{_versioned('v2')}, up AS (SELECT valid_from AS seq, src, dst FROM v2 WHERE valid_from > 0 UNION ALL SELECT valid_to, src, dst FROM v2 WHERE valid_to < {_END}), ends AS (SELECT seq, 0 AS e, src AS c FROM up UNION ALL SELECT seq, 1, dst FROM up), {_reach('post', 'f <= seq AND t >= seq')}, {_reach('pre', 'f < seq AND t >= seq')}"),
    "intermediates_per_update": _with(_levels(LABELLED[2], False, "seq"), _versioned("v1")),
    "homomorphic_matches": _with("SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{q.name}' AS query_id, count(*) AS matches FROM {_lives(q, False)}" for q in (pattern("cycle4"), LABELLED[0])) + ") WHERE matches > 0", _versioned("v1")),
    "distinct_subgraphs": _with(" UNION ALL ".join(f"SELECT '{p}' AS query_id, CAST(born AS BIGINT) AS seq, count(*) // {n} AS n FROM {_lives(pattern(p))} WHERE born > 0 GROUP BY born" for p, n in _SYMMETRIES.items()), _versioned("v1")),
    "periodic_checks": _with(
        "SELECT k * 10 AS at, (SELECT count(*) FROM lives WHERE born <= k * 10 AND dies > k * 10) AS matches, (SELECT count(*) FROM lives WHERE born <= k * 10 AND dies > k * 10) > 0 AS found FROM (SELECT unnest(generate_series(0, (SELECT max(valid_from) FROM v2) // 10)) AS k)",
        f"{_versioned('v2')}, lives AS (SELECT * FROM {_lives(pattern('triangle'))})"),
    "pruned_visited_overlap": _with(
        "SELECT query_id, u, count(*) AS rejected, count(*) FILTER ((query_id, u, v) IN (SELECT (query_id, u, v) FROM seen WHERE anchored)) AS anchored, count(*) FILTER ((query_id, u, v) IN (SELECT (query_id, u, v) FROM seen WHERE NOT anchored)) AS visited FROM (SELECT * FROM ldf EXCEPT SELECT * FROM nlf) GROUP BY ALL",
        f"{_versioned('v1')}, {_NLF}, {_visited(LABELLED)}"),
} | {k: _ZERO for k in ("interlacing_violations", "majorisation_violations", "ceiling_violations", "gate_wrong_skips", "envelope_violations", "versioned_match_changes")}
