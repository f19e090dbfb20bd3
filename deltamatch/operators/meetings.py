"""Triangles of users who meet, counted in windows of time, without a row for an edge.

Events (u, g, t, n, f) are the rows: n users stand behind u, whose first event is at f, and
users meet where events of one g are within a span. Only a pair's first meeting is its edge.
Events are cheap to deal out, edges are not, so tasks make the edges from events again:
pairs of blocks of users find the pairs that meet more than once, and windows of two
lifetimes count the triangles of their edges, less the pairs that met before the window.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

COLUMNS = ("u", "g", "t", "n", "f")


def _packed(a: np.ndarray) -> bytes:
    return zlib.compress(np.diff(a, prepend=0).astype(np.int64).view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def _unpacked(held: list[bytes]) -> np.ndarray:
    parts = [np.frombuffer(zlib.decompress(x), np.uint8).reshape(8, -1).T.copy().view(np.int64).ravel().cumsum() for x in held]
    return np.concatenate(parts) if parts else np.zeros(0, np.int64)


def _fresh(*cols: np.ndarray) -> np.ndarray:
    """Rows of sorted columns that differ from the row before."""
    out = np.zeros(len(cols[0]), bool)
    out[:1] = True
    for x in cols:
        out[1:] |= x[1:] != x[:-1]
    return out


def _dealt(events: DataFrame, places, rows: int = 2**18) -> DataFrame:
    """(k, u, g, t, n, f): events as packed columns, sorted by g and t, for each key and some batches. places: the columns to (positions, their keys)."""
    import pyarrow as pa

    def packs(held):
        cols = [np.concatenate(x) for x in zip(*held)]
        at, k = places(dict(zip(COLUMNS, cols)))
        order = np.lexsort((cols[0][at], cols[2][at], cols[1][at], k))
        at, k = at[order], k[order]
        fine = _fresh(k, *(cols[c][at] for c in range(3)))
        at, k = at[fine], k[fine]
        edges = [0, *(np.flatnonzero(np.diff(k)) + 1).tolist(), len(k)]
        for a, b in zip(edges, edges[1:]):
            if b > a:
                packed = {c: pa.array([_packed(x[at[a:b]])], pa.binary()) for c, x in zip(COLUMNS, cols)}
                yield pa.RecordBatch.from_pydict({"k": pa.array([k[a]], pa.int64())} | packed)

    def run(batches):
        held, size = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(c).to_numpy(zero_copy_only=False) for c in COLUMNS])
                size += batch.num_rows
            if size >= rows:
                yield from packs(held)
                held, size = [], 0
        if held:
            yield from packs(held)

    return events.select(*COLUMNS).mapInArrow(run, "k bigint, u binary, g binary, t binary, n binary, f binary")


def _blocks(u: np.ndarray, blocks: int) -> np.ndarray:
    return ((u.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)).astype(np.int64) % blocks


def _meets(g: np.ndarray, t: np.ndarray, span: int, most: int = 2**21):
    """Positions (i, j) of events of one g within the span, each pair once, t[j] >= t[i], in chunks; g and t are sorted."""
    end = np.empty(len(t), np.int64)
    edges = [0, *(np.flatnonzero(np.diff(g)) + 1).tolist(), len(t)]
    for a, b in zip(edges, edges[1:]):
        end[a:b] = a + np.searchsorted(t[a:b], t[a:b] + span, "right")
    many = end - np.arange(len(t)) - 1
    total = np.concatenate([[0], many.cumsum()])
    lo = 0
    while lo < len(t):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + most, "right")) - 1)
        i = np.repeat(np.arange(lo, hi), many[lo:hi])
        yield i, np.arange(len(i)) - (total[i] - total[lo]) + i + 1
        lo = hi


def _opened(held) -> dict[str, np.ndarray]:
    cols = {c: _unpacked(list(held[c])) for c in COLUMNS}
    order = np.lexsort((cols["u"], cols["t"], cols["g"]))
    order = order[_fresh(*(cols[c][order] for c in ("u", "t", "g")))]
    return {c: x[order] for c, x in cols.items()}


def _found(keys: np.ndarray, sorted_keys: np.ndarray) -> np.ndarray:
    if not len(sorted_keys):
        return np.zeros(len(keys), bool)
    return sorted_keys[np.minimum(np.searchsorted(sorted_keys, keys), len(sorted_keys) - 1)] == keys


def known_before(events: DataFrame, span: int, life: int, blocks: int) -> DataFrame:
    """(k, u, v): pairs that meet in window k, of two lifetimes from k on, and met before it."""
    import pandas as pd

    def places(cols):
        own, n = _blocks(cols["u"], blocks), len(cols["u"])
        other = np.arange(blocks - 1)[None, :] + (np.arange(blocks - 1)[None, :] >= own[:, None])
        k = np.minimum(own[:, None], other) * blocks + np.maximum(own[:, None], other)
        return np.repeat(np.arange(n), blocks - 1), k.ravel()

    def run(held: pd.DataFrame) -> pd.DataFrame:
        x, (i, j) = _opened(held), divmod(int(held["k"].iloc[0]), blocks)
        users, u = np.unique(x["u"], return_inverse=True)
        own = _blocks(users, blocks)[u]
        # Pairs within a block belong to it and the block after it.
        inner = [b for b, c in ((i, j), (j, i)) if (b + 1) % blocks == c]

        def pairs():
            for a, b in _meets(x["g"], x["t"], span):
                fine = (u[a] != u[b]) & ((own[a] != own[b]) | np.isin(own[a], inner))
                a, b = a[fine], b[fine]
                yield np.minimum(u[a], u[b]) * len(users) + np.maximum(u[a], u[b]), x["t"][b]

        keys = np.concatenate([np.zeros(0, np.int64), *(k for k, _ in pairs())])
        keys.sort()
        again = np.unique(keys[1:][keys[1:] == keys[:-1]])
        del keys
        more = [(k[fine], t[fine]) for k, t in pairs() for fine in [_found(k, again)]]
        k, t = (np.concatenate([np.zeros(0, np.int64), *p]) for p in ([m[0] for m in more], [m[1] for m in more]))
        at, day = np.searchsorted(again, k), t // life
        first = np.full(len(again), np.iinfo(np.int64).max)
        np.minimum.at(first, at, day)
        out = [(at[fine], day[fine] - back) for back in (0, 1) for fine in [first[at] < day - back]]
        out = pd.DataFrame({"at": np.concatenate([o[0] for o in out]), "k": np.concatenate([o[1] for o in out])}).drop_duplicates()
        pair = again[out["at"].to_numpy()]
        return pd.DataFrame({"k": out["k"].to_numpy(), "u": users[pair // len(users)], "v": users[pair % len(users)]})

    return _dealt(events, places).groupBy("k").applyInPandas(run, "k bigint, u bigint, v bigint")


def _triangles(a: np.ndarray, b: np.ndarray, t: np.ndarray, n: np.ndarray, since: int, life: int, most: int = 2**20) -> int:
    """The sum of n of the corners' product over triangles whose first edge is before since + life and whose last less than a lifetime later."""
    size = len(n)
    degree = np.bincount(a, minlength=size) + np.bincount(b, minlength=size)
    rank = np.empty(size, np.int32)
    rank[np.lexsort((np.arange(size), degree))] = np.arange(size)
    low, high = np.minimum(rank[a], rank[b]), np.maximum(rank[a], rank[b])
    weight = np.empty(size, np.int64)
    weight[rank] = n
    order = np.argsort(low, kind="stable")
    to, at = high[order], t[order] - since
    start = np.concatenate([[0], np.bincount(low, minlength=size).cumsum()])
    del low, high, order
    out = np.diff(start)
    mark = np.full(size, -1, np.int64)
    total = 0
    for x in np.flatnonzero(out > 1).tolist():
        s, e = start[x], start[x + 1]
        near = to[s:e]
        mark[near] = at[s:e]
        lens = out[near]
        sums = lens.cumsum()
        p = 0
        while p < len(near):
            done = int(sums[p - 1]) if p else 0
            q = max(p + 1, int(np.searchsorted(sums, done + most, "right")))
            shift = start[near[p:q]] - (sums[p:q] - lens[p:q] - done)
            spread = np.arange(int(sums[q - 1]) - done) + np.repeat(shift, lens[p:q])
            m = mark[to[spread]]
            hit = np.flatnonzero(m >= 0)
            if len(hit):
                far, t1, t2 = spread[hit], m[hit], at[spread[hit]]
                y = p + np.searchsorted(sums[p:q] - done, hit, "right")
                t3 = at[s + y]
                begin = np.minimum(np.minimum(t1, t2), t3)
                fine = (begin < life) & (np.maximum(np.maximum(t1, t2), t3) - begin < life)
                total += int((weight[near[y[fine]]] * weight[to[far[fine]]]).sum()) * int(weight[x])
            p = q
        mark[near] = -1
    return total


def triangle_matches(events: DataFrame, span: int, life: int, block: int = 10**6) -> DataFrame:
    """(matches): triangle matches that ever live between the users of events, whose edges live from a pair's first meeting for a lifetime.

    An edge's times order the stream as its numbers do, expiry first, so a triangle lives if
    its first and last edge are less than a lifetime apart. Users behind one u have equal
    events: they meet each other at f and all others when u does. A block of users has about
    `block` events.
    """
    import pandas as pd

    blocks = max(2, -(-events.count() // block))
    before = known_before(events, span, life, blocks)

    def places(cols):
        day, soon, n = cols["t"] // life, (cols["t"] + span) // life, np.arange(len(cols["t"]))
        later = soon > day
        return np.concatenate([n, n, n[later]]), np.concatenate([day - 1, day, soon[later]])

    def run(key, held: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        if not len(held):
            return pd.DataFrame({"x": np.zeros(0, np.int64)})
        x, since = _opened(held), int(key[0]) * life
        users, one, u = np.unique(x["u"], return_index=True, return_inverse=True)
        n, f = x["n"][one], x["f"][one]
        keys, times = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for a, b in _meets(x["g"], x["t"], span):
            t = x["t"][b]
            fine = (u[a] != u[b]) & (t >= since) & (t < since + 2 * life)
            a, b = a[fine], b[fine]
            keys.append(np.minimum(u[a], u[b]) * len(users) + np.maximum(u[a], u[b]))
            times.append(t[fine])
        keys, times = np.concatenate(keys), np.concatenate(times)
        order = np.argsort(keys)
        keys, times = keys[order], times[order]
        del order
        first = np.flatnonzero(np.diff(keys, prepend=-1))
        times = np.minimum.reduceat(times, first) if len(first) else times
        keys = keys[first]
        gone = np.sort(np.searchsorted(users, known["u"].to_numpy(np.int64)) * len(users) + np.searchsorted(users, known["v"].to_numpy(np.int64)))
        fine = ~_found(keys, gone)
        keys, times = keys[fine], times[fine]
        a, b = (keys // len(users)).astype(np.int32), (keys % len(users)).astype(np.int32)
        del keys, first, gone, fine
        total = 6 * _triangles(a, b, times, n, since, life)
        # Two of one u stand at three pairs of places, in n (n - 1) ways.
        now = times < since + life
        for one, other in ((a, b), (b, a)):
            fine = now & (n[one] > 1) & (np.abs(times - f[one]) < life)
            one, other = one[fine], other[fine]
            total += 3 * int((n[one] * (n[one] - 1) * n[other]).sum())
        alone = (f >= since) & (f < since + life)
        total += int((n[alone] * (n[alone] - 1) * (n[alone] - 2)).sum())
        return pd.DataFrame({"x": np.array([total], np.int64)})

    each = _dealt(events, places).groupBy("k").cogroup(before.groupBy("k")).applyInPandas(run, "x bigint")
    return each.agg(F.coalesce(F.sum("x"), F.lit(0)).cast("bigint").alias("matches"))
