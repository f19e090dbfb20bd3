"""Upper bounds on spectra after insertions, and the rules that reject with them, as column expressions.

q and d are descending ARRAY<DOUBLE>s of the same length (query side, stale data side), k
counts the edges inserted inside the ball since d was exact. Deletions only lower true
values, so they need no rule. `register` offers all of it to SQL.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

EPSILON = 1e-7


def _positions(d: Column) -> Column:
    return F.when(F.size(d) > 0, F.sequence(F.lit(1), F.size(d))).otherwise(F.array().cast("array<int>"))


def flat(d: Column, k: Column) -> Column:
    """Each value rises by at most 2 per edge. Counting updates instead of edges in k makes this unsafe."""
    return F.transform(d, lambda x: x + 2 * k)


def rank_shift(d: Column, k: Column) -> Column:
    """The i-th value stays below the old (i - k)-th; the first k have no such bound and take the flat one."""
    return F.transform(_positions(d), lambda i: F.when(i > k, F.get(d, (i - k - 1).cast("int"))).otherwise(F.get(d, i - 1) + 2 * k))


def ceilings(d: Column, k: Column) -> Column:
    """The least upper bound from mixing both steps: over j positions given up, old value i - j plus 2 for each other edge."""

    def at(i: Column) -> Column:
        most = F.least(k.cast("int"), i - 1)
        return F.array_min(F.transform(F.sequence(F.lit(0), most), lambda j: F.get(d, i - j - 1) + 2 * (k - j)))

    return F.transform(_positions(d), at)


def ceilings_stepwise(d: Column, k: Column) -> Column:
    """The same by k single steps, each the smaller of the two alternatives; the reference for the closed form."""
    step = lambda b: F.transform(b, lambda x, i: F.when(i == 0, x + 2).otherwise(F.least(F.get(b, i - 1), x + 2)))
    turns = F.when(k > 0, F.sequence(F.lit(1), k.cast("int"))).otherwise(F.array().cast("array<int>"))
    return F.aggregate(turns, d.cast("array<double>"), lambda b, _: step(b))


def mass_cost(q: Column, d: Column) -> Column:
    """The least total increase with which d comes to dominate q."""
    return F.aggregate(F.zip_with(q, d, lambda x, y: F.greatest(F.lit(0.0), x - y)), F.lit(0.0), lambda s, x: s + x)


def exceeds(q: Column, bound: Column) -> Column:
    """Some query value lies above the bound, by more than solves can err."""
    return F.exists(F.zip_with(q, bound, lambda x, y: x > y + EPSILON * F.greatest(F.lit(1.0), x)), lambda b: b)


def mass_rule(q: Column, d: Column, k: Column) -> Column:
    """k edges add 2 k in all; q needs more."""
    return mass_cost(q, d) > 2 * k + EPSILON


def tightest(q: Column, d: Column, k: Column) -> Column:
    """Reject if the mass or a ceiling says so: no safe rule that knows only d and k rejects more."""
    return mass_rule(q, d, k) | exceeds(q, ceilings(d, k))


RULES = {
    "flat": lambda q, d, k: exceeds(q, flat(d, k)),
    "rank_shift": lambda q, d, k: exceeds(q, rank_shift(d, k)),
    "ceilings": lambda q, d, k: exceeds(q, ceilings(d, k)),
    "mass": mass_rule,
    "tightest": tightest,
}


def feasible(q: list[float], d: list[float], k: int) -> bool:
    """Whether some sequence that k insertions may reach, as far as the three constraints tell, dominates q. For tests."""
    least = [max(x, y) for x, y in zip(q, d)]
    top = [min(d[i - j] + 2 * (k - j) for j in range(min(k, i) + 1)) for i in range(len(d))]
    return all(x <= c + 1e-9 for x, c in zip(least, top)) and sum(x - y for x, y in zip(least, d)) <= 2 * k + 1e-9


def lazy_refreshes(touch: Column, tau: int) -> Column:
    """Number of the refresh that covers a touch, if a center is solved anew after tau touches; saves no more than the factor tau + 1."""
    return F.floor((touch - 1) / (tau + 1))


def register(spark: SparkSession) -> None:
    """SQL functions spectrum_flat, spectrum_ceilings, spectrum_mass_cost and spectrum_interlaces over arrays."""
    for name, returns, body in (
        ("spectrum_flat(d ARRAY<DOUBLE>, k INT)", "ARRAY<DOUBLE>", "transform(d, x -> x + 2 * k)"),
        ("spectrum_ceilings(d ARRAY<DOUBLE>, k INT)", "ARRAY<DOUBLE>", "transform(if(size(d) > 0, sequence(1, size(d)), CAST(array() AS ARRAY<INT>)), i -> array_min(transform(sequence(0, least(k, i - 1)), j -> get(d, i - j - 1) + 2 * (k - j))))"),
        ("spectrum_mass_cost(q ARRAY<DOUBLE>, d ARRAY<DOUBLE>)", "DOUBLE", "aggregate(zip_with(q, d, (x, y) -> greatest(0.0D, x - y)), 0.0D, (s, x) -> s + x)"),
        ("spectrum_interlaces(q ARRAY<DOUBLE>, d ARRAY<DOUBLE>)", "BOOLEAN", "NOT exists(zip_with(q, d, (x, y) -> x > y + 1e-7 * greatest(1.0D, x)), b -> b)"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} RETURNS {returns} RETURN {body}")
