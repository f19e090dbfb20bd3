"""Query graphs: patterns, samplers, matching orders, anchored sub-queries and their invariants."""

from __future__ import annotations

from collections import deque
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from deltamatch.operators.invariants import query_triangles


@dataclass(frozen=True)
class Query:
    """Vertices 0..n-1 with labels (None: any), and edges (u, w)."""

    name: str
    labels: tuple[int | None, ...]
    edges: tuple[tuple[int, int], ...]
    _near: dict = field(default_factory=dict, compare=False, repr=False)

    @property
    def size(self) -> int:
        return len(self.labels)

    def near(self, u: int) -> set[int]:
        if not self._near:
            self._near.update({v: {b if a == v else a for a, b in self.edges if v in (a, b)} for v in range(self.size)})
        return self._near[u]

    def distances(self, *sources: int) -> dict[int, int]:
        out, ready = dict.fromkeys(sources, 0), deque(sources)
        while ready:
            u = ready.popleft()
            for w in self.near(u) - out.keys():
                out[w] = out[u] + 1
                ready.append(w)
        return out

    def part(self, members: set[int]) -> tuple[int, list[tuple[int, int]]]:
        """Size and renumbered edges of the sub-query on members."""
        at = {u: i for i, u in enumerate(sorted(members))}
        return len(at), [(at[a], at[b]) for a, b in self.edges if a in at and b in at]

    def ball(self, u: int, h: int) -> tuple[int, list[tuple[int, int]]]:
        return self.part({w for w, d in self.distances(u).items() if d <= h})

    def anchored(self, u: int, w: int, rho: int) -> tuple[int, list[tuple[int, int]]]:
        """The sub-query within rho of either end of the edge (u, w)."""
        return self.part({x for x, d in self.distances(u, w).items() if d <= rho})

    def order(self, u: int, w: int, sizes: dict[int, int] | None = None) -> list[int]:
        """Matching order from the anchor: most bound neighbours, then degree, then number; with sizes, the smallest candidate set first."""
        bound = [u, w]
        while len(bound) < self.size:
            front = [x for x in range(self.size) if x not in bound and self.near(x) & set(bound)]
            if not front:
                raise ValueError("a query must be connected")
            key = (lambda x: (sizes[x], x)) if sizes else (lambda x: (-len(self.near(x) & set(bound)), -len(self.near(x)), x))
            bound.append(min(front, key=key))
        return bound

    def automorphisms(self) -> list[tuple[int, ...]]:
        """All label-preserving maps of the query onto itself."""
        out: list[tuple[int, ...]] = []

        def grow(held: tuple[int, ...]) -> None:
            u = len(held)
            if u == self.size:
                out.append(held)
                return
            for v in range(self.size):
                alike = v not in held and self.labels[u] == self.labels[v] and len(self.near(u)) == len(self.near(v))
                if alike and all((w in self.near(u)) == (held[w] in self.near(v)) for w in range(u)):
                    grow((*held, v))

        grow(())
        return out

    def symmetry_breaks(self) -> list[tuple[int, int]]:
        """Pairs (u, w) such that exactly one of a match's images under automorphisms has a smaller data vertex at u than at w for all of them."""
        group, out = self.automorphisms(), []
        for u in range(self.size):
            out += [(u, w) for w in sorted({a[u] for a in group} - {u})]
            group = [a for a in group if a[u] == u]
        return out

    def needs(self, u: int) -> dict[int, int]:
        """Neighbours of u by label."""
        out: dict[int, int] = {}
        for w in self.near(u):
            if self.labels[w] is not None:
                out[self.labels[w]] = out.get(self.labels[w], 0) + 1
        return out


def padded_spectrum(n: int, edges: list[tuple[int, int]], r: int) -> list[float]:
    m = np.zeros((n, n))
    for a, b in edges:
        m[a, b] = m[b, a] = -1
    m[np.diag_indices(n)] = -m.sum(1)
    values = np.linalg.eigvalsh(m)[::-1] if n else np.zeros(0)
    return [float(max(x, 0.0)) for x in values[:r]] + [0.0] * max(0, r - n)


def invariant_values(n: int, edges: list[tuple[int, int]], r: int) -> dict:
    return {"nv": n, "ne": len(edges), "tri": query_triangles(n, edges), "spec": padded_spectrum(n, edges, r)}


def pattern(name: str, labels: tuple[int | None, ...] | None = None) -> Query:
    """A fixed pattern by name, unlabelled unless labels are given."""
    edges = {
        "edge": ((0, 1),),
        "triangle": ((0, 1), (0, 2), (1, 2)),
        "diamond": ((0, 1), (0, 2), (1, 2), (1, 3), (2, 3)),
        "clique4": ((0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)),
        "cycle4": ((0, 1), (1, 2), (2, 3), (0, 3)),
        "tailed_triangle": ((0, 1), (0, 2), (1, 2), (2, 3)),
        "star3": ((0, 1), (0, 2), (0, 3)),
        "path4": ((0, 1), (1, 2), (2, 3)),
        "trade_ring": ((0, 1), (1, 2), (2, 3), (0, 3)),
        "tailed_clique4": ((0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (3, 4)),
    }
    if name == "near_clique8_tail":
        chosen = tuple((i, j) for i in range(8) for j in range(i + 1, 8) if (i, j) != (0, 1)) + ((0, 8), (8, 9))
    else:
        chosen = edges[name]
    return Query(name, labels or (None,) * (1 + max(max(e) for e in chosen)), chosen)


def sample(edges: DataFrame, vertices: DataFrame, kind: str, size: int, count: int) -> list[Query]:
    """`count` connected queries of a kind ("dense": the frontier vertex with most links next; "walk": a tree-like walk).

    Seeds come in the order of their ids' md5. Only the surroundings of the seeds reach the
    driver: at most `size` hops are needed, taken hop by hop and bounded to the first 50,000 edges.
    """
    from pyspark.sql import functions as F

    from deltamatch.operators.graph import both_ways

    adj = both_ways(edges.select("src", "dst"))
    seeds = [r.v for r in adj.select("v").distinct().orderBy(F.md5(F.col("v").cast("string")), "v").limit(8 * count).collect()]
    near: dict[int, set[int]] = {}
    front = set(seeds)
    for _ in range(4 if kind == "dense" else min(size, 8)):
        rows = adj.where(F.col("v").isin(sorted(front))).orderBy("v", "w").limit(50_000).collect() if front else []
        for r in rows:
            near.setdefault(r.v, set()).add(r.w)
        front = {r.w for r in rows} - near.keys()
        if len(near) > 20_000:
            break
    labels = {r.id: r.label for r in vertices.where(F.col("id").isin(sorted(near.keys() | front))).collect()}
    out: list[Query] = []
    for seed in seeds:
        if len(out) == count:
            break
        chosen, walked = [seed], []
        while len(chosen) < size:
            if kind == "dense":
                ready = {w for v in chosen for w in near.get(v, ()) if w in near} - set(chosen)
                if not ready:
                    break
                chosen.append(min(ready, key=lambda w: (-len(near[w] & set(chosen)), w)))
            else:
                ready = [(v, w) for v in reversed(chosen) for w in sorted(near.get(v, set()) & near.keys() - set(chosen))]
                if not ready:
                    break
                v, w = ready[(seed + len(chosen)) % len(ready)]
                chosen.append(w)
                walked.append((v, w))
        if len(chosen) < size:
            continue
        at = {v: i for i, v in enumerate(chosen)}
        pairs = {(min(at[v], at[w]), max(at[v], at[w])) for v in chosen for w in near.get(v, ()) if w in at} if kind == "dense" else {(min(at[v], at[w]), max(at[v], at[w])) for v, w in walked}
        out.append(Query(f"{kind}{size}_{len(out)}", tuple(labels.get(v, -1) for v in chosen), tuple(sorted(pairs))))
    return out


def query_vertices(spark: SparkSession, queries: list[Query]) -> DataFrame:
    """(query_id, u, q_label, q_degree); a vertex without a label asks for ANY."""
    from deltamatch.operators.graph import ANY

    return spark.createDataFrame([(q.name, u, ANY if q.labels[u] is None else q.labels[u], len(q.near(u))) for q in queries for u in range(q.size)], "query_id string, u int, q_label int, q_degree int")
