"""Temperature mixing of sources to target weights, in DataFrame functions only.

Weights are the sources' token shares raised to an exponent a in [0, 1] and normalised: 1
keeps the corpus as it is, 0 makes all sources equal. Bisection finds the largest a whose
mix reaches the target entropy, one aggregation over the sources a round, then raises it as
far as the repetition limit asks, for which the largest and smallest share suffice. Weights become
rows by permutations: a source with a budget of e and a fraction epochs gets all its
documents e times, each time in another hash order, and then the head of one more
permutation up to the remaining tokens. A position in [0, 1) spreads every source evenly,
so each block of the output holds all sources at their weights.

The head ends where a histogram over 4096 hash ranges says; only documents in the range
that holds the end are sorted, so no task sees a whole source. Without a budget the
smallest one that places every document once is taken: nothing is dropped.

Null sources form a source. Documents without words cost nothing and are placed like any
other. Repeated rows are placed one by one. An empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut
from .quality_rules import word_array

_RANGES_LOG2 = 12


def sources(sizes: DataFrame) -> DataFrame:
    """(m_source, m_tokens, m_docs, m_share) per source of sizes (source, n_tokens). Shares of sources without tokens are null."""
    each = cut(sizes.groupBy(F.col("source").alias("m_source")).agg(F.sum("n_tokens").alias("m_tokens"), F.count("*").alias("m_docs")))
    total = each.agg(F.sum("m_tokens")).first()[0] or 0
    return each.withColumn("m_share", F.when(F.col("m_tokens") > 0, F.col("m_tokens") / F.lit(float(max(total, 1)))))


def _bisect(holds, rounds: int = 48) -> float:
    """The largest exponent in [0, 1] up to which `holds`, which must be monotone, is true; 0 if it never is."""
    if holds(1.0):
        return 1.0
    if not holds(0.0):
        return 0.0
    low, high = 0.0, 1.0
    for _ in range(rounds):
        middle = (low + high) / 2
        low, high = (middle, high) if holds(middle) else (low, middle)
    return low


def mix_entropy(shares: DataFrame, a: float) -> float:
    """Entropy of the normalised weights m_share ** a, over the sources that hold tokens."""
    power = F.pow("m_share", F.lit(float(a)))
    z, s = shares.where("m_share > 0").agg(F.sum(power), F.sum(power * F.ln("m_share"))).first()
    return math.log(z) - a * s / z if z else 0.0


def exponent(shares: DataFrame, *, entropy: float | None = None, max_repeats: float | None = None) -> float:
    """The exponent whose mix has an entropy of at least `entropy` (a share of the highest possible), raised until no source recurs over max_repeats times as often as the least repeated."""
    n, least, most = shares.where("m_share > 0").agg(F.count("*"), F.min("m_share"), F.max("m_share")).first()
    a = 1.0
    if entropy is not None and n > 1:
        wanted = min(entropy, 1.0) * math.log(n)
        a = _bisect(lambda x: mix_entropy(shares, x) >= wanted - 1e-12, rounds=24)
    if max_repeats is not None and n > 1:
        a = max(a if entropy is not None else 0.0, _bisect(lambda x: (most / least) ** (1 - x) > max_repeats))
    return a


def plan(shares: DataFrame, a: float, budget: float | None = None) -> DataFrame:
    """shares with m_weight, m_epochs (whole permutations), m_rest (tokens of one more) and m_rounds (both together)."""
    z, least = shares.where("m_share > 0").agg(F.sum(F.pow("m_share", F.lit(a))), F.max(F.col("m_tokens") / F.pow("m_share", F.lit(a)))).first()
    weight = F.when(F.col("m_share") > 0, F.pow("m_share", F.lit(a)) / F.lit(z or 1.0))
    total = budget if budget is not None else (least or 0.0) * (z or 1.0)
    out = shares.withColumn("m_weight", weight)
    rounds = F.coalesce(F.col("m_weight") * F.lit(float(total)) / F.col("m_tokens"), F.lit(1.0))
    rounds = F.when(F.abs(rounds - F.round(rounds)) < 1e-9, F.round(rounds)).otherwise(rounds)
    out = out.withColumn("m_rounds", rounds).withColumn("m_epochs", F.floor("m_rounds").cast("bigint"))
    return out.withColumn("m_rest", F.floor((F.col("m_rounds") - F.col("m_epochs")) * F.col("m_tokens")).cast("bigint"))


def _order(epoch: Column, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), epoch.cast("bigint"), F.col("__id"), F.col("__print"))


def mixed(docs: DataFrame, *, entropy: float | None = None, max_repeats: float | None = 2.0, budget: float | None = None, block_tokens: int = 1 << 20, seed: int = 17) -> DataFrame:
    """Every placed copy of a row: its own columns under `row`, and epoch, block, position, weight, n_tokens."""
    tokens = F.size(word_array(F.coalesce(F.col("text"), F.lit("")))).cast("bigint")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("__id"), "source", F.xxhash64("text").alias("__print"), tokens.alias("n_tokens"))
    slim = cut(rows.drop("row"))
    shares = sources(slim)
    planned = cut(plan(shares, exponent(shares, entropy=entropy, max_repeats=max_repeats), budget))
    # Where the last, partial permutation ends: bounded histogram rows per source.
    known = _met(slim, planned)
    place = F.shiftrightunsigned(_order(F.col("m_epochs"), seed), 64 - _RANGES_LOG2)
    ranges = known.where("m_rest > 0").groupBy("m_source", place.alias("r")).agg(F.sum("n_tokens").alias("t"))
    before = F.sum("t").over(Window.partitionBy("m_source").orderBy("r").rowsBetween(Window.unboundedPreceding, -1))
    ends = ranges.select("m_source", "r", "t", F.coalesce(before, F.lit(0)).alias("b")).join(_sized(planned.select(F.col("m_source").alias("s2"), F.col("m_rest").alias("rest2"))), F.col("m_source").eqNullSafe(F.col("s2")))
    ends = ends.where("b <= rest2 and b + t > rest2").select(F.col("m_source").alias("c_source"), F.col("r").alias("c_range"), (F.col("rest2") - F.col("b")).alias("c_room"))
    planned = cut(planned.join(ends, F.col("m_source").eqNullSafe(F.col("c_source")), "left").drop("c_source"))
    total = planned.agg(F.sum(F.col("m_rounds") * F.col("m_tokens"))).first()[0] or 0.0
    blocks = max(1, math.ceil(total / block_tokens))

    dealt = _met(rows, planned).withColumn("__place", place)
    at_end = (F.col("m_rest") > 0) & (F.col("__place") == F.col("c_range"))
    inside = (F.col("m_rest") > 0) & (F.col("c_range").isNull() | (F.col("__place") < F.col("c_range")))
    sure = dealt.withColumn("copies", F.col("m_epochs") + inside.cast("bigint")).where("copies > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int"))))
    order = Window.partitionBy("m_source").orderBy(_order(F.col("m_epochs"), seed), "__id", "__print").rowsBetween(Window.unboundedPreceding, 0)
    tail = dealt.where(at_end).withColumn("__upto", F.sum("n_tokens").over(order)).where(F.col("__upto") <= F.col("c_room")).withColumn("copies", F.lit(1).cast("bigint")).withColumn("epoch", F.col("m_epochs").cast("int"))
    out = sure.unionByName(tail.drop("__upto").select(*sure.columns))
    unit = F.shiftrightunsigned(_order(F.col("epoch"), seed), 11) / F.lit(float(1 << 53))
    position = (F.col("epoch") + unit) / F.greatest("m_rounds", F.col("copies").cast("double"))
    return out.select("row", "source", "n_tokens", "epoch", F.least(F.floor(position * blocks), F.lit(blocks - 1)).cast("bigint").alias("block"), position.alias("position"), F.coalesce("m_weight", F.lit(0.0)).alias("weight"))


def _sized(small: DataFrame, most: int = 20_000) -> DataFrame:
    """Broadcast a table of sources only if it has at most `most` rows."""
    return F.broadcast(small) if small.limit(most + 1).count() <= most else small


def _met(rows: DataFrame, planned: DataFrame) -> DataFrame:
    return rows.join(_sized(planned), F.col("source").eqNullSafe(F.col("m_source")))


def mix_report(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, source, n_tokens, epoch, block, position, weight) of every placed copy."""
    return mixed(docs.select("doc_id", "source", "text"), **options).select("row.doc_id", "source", "n_tokens", "epoch", "block", "position", "weight")


def mix_documents(docs: DataFrame, **options) -> DataFrame:
    """Documents repeated as the mix asks, with their own columns, block after block within each task."""
    return mixed(docs, **options).sortWithinPartitions("block", "position").select("row.*")
