"""Update streams (seq, op, src, dst) and edge versions (src, dst, valid_from, valid_to).

seq 0 marks initial edges. A version is alive at s if valid_from <= s < valid_to.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltamatch.session import OPEN_END, numbered


def first_part(total: int, share: float) -> int:
    """The share of total, rounded up, in whole per mille so that no float error tips it."""
    return -(-total * round(1000 * share) // 1000)


def shuffled(edges: DataFrame) -> DataFrame:
    """Edges with n = 1, 2, ... in the order of the digest of their ends."""
    return numbered(edges.select("src", "dst"), F.md5(F.concat("src", F.lit("-"), "dst")), "src", "dst")


def insert_stream(edges: DataFrame, initial: float = 0.9) -> DataFrame:
    """The first share of the shuffled edges stands at the start, the rest arrives one by one."""
    first = first_part(edges.count(), initial)
    return shuffled(edges).select(F.greatest(F.col("n") - first, F.lit(0)).alias("seq"), F.lit("+").alias("op"), "src", "dst")


def mixed_stream(edges: DataFrame, initial: float = 0.9) -> DataFrame:
    """Blocks of seven insertions and three deletions of initial edges, both in shuffled order."""
    total = edges.count()
    first = first_part(total, initial)
    gone = min(first, 3 * ((total - first) // 7))
    rows = shuffled(edges)
    i, j = F.col("n") - first - 1, F.col("n") - 1
    added = rows.select(F.when(F.col("n") <= first, F.lit(0)).otherwise(F.floor(i / 7) * 10 + i % 7 + 1).cast("bigint").alias("seq"), F.lit("+").alias("op"), "src", "dst")
    removed = rows.where(F.col("n") <= gone).select((F.floor(j / 3) * 10 + 7 + j % 3 + 1).cast("bigint").alias("seq"), F.lit("-").alias("op"), "src", "dst")
    return added.union(removed)


def renewed_stream(edges: DataFrame, initial: float = 0.9) -> DataFrame:
    """The insert stream, six times slower; every fifth insertion is taken back two steps later and renewed four steps later."""
    base = insert_stream(edges, initial)
    slow = base.select((F.col("seq") * 6).alias("seq"), "op", "src", "dst")
    fifth = base.where("seq > 0 AND seq % 5 = 0")
    return slow.union(fifth.select(F.col("seq") * 6 + 2, F.lit("-"), "src", "dst")).union(fifth.select(F.col("seq") * 6 + 4, F.lit("+"), "src", "dst"))


def expiring_stream(timed: DataFrame, hours: int = 24) -> DataFrame:
    """Edges (src, dst, ts) inserted at their time and deleted some hours later; seq follows (time, deletions first)."""
    adds = timed.select("src", "dst", "ts", F.lit("+").alias("op"))
    ends = timed.select("src", "dst", (F.col("ts") + F.expr(f"INTERVAL {hours} HOURS")).alias("ts"), F.lit("-").alias("op"))
    late = F.when(F.col("op") == "-", 0).otherwise(1)
    # Days deal the rows out; counts of days give offsets.
    rows = adds.union(ends).withColumn("late", late).withColumn("d", F.date_trunc("day", F.col("ts")))
    sizes = rows.groupBy("d").agg(F.count("*").alias("c"))
    before = F.coalesce(F.sum("c").over(Window.orderBy("d").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = rows.join(F.broadcast(sizes.select(F.col("d").alias("d2"), before.alias("b"))), F.col("d") == F.col("d2"))
    own = F.row_number().over(Window.partitionBy("d").orderBy("ts", "late", "src", "dst"))
    return rows.select((F.col("b") + own).cast("bigint").alias("seq"), "op", "src", "dst", "ts")


def edge_versions(updates: DataFrame) -> DataFrame:
    """Lifetimes of edges; an insertion of a live edge and a deletion of a missing one change nothing."""
    by = Window.partitionBy("src", "dst").orderBy("seq", "op")
    rows = updates.withColumn("before", F.lag("op").over(by))
    rows = rows.where("(op = '+' AND coalesce(before, '-') = '-') OR (op = '-' AND before = '+')")
    rows = rows.withColumn("end", F.lead("seq").over(by))
    return rows.where("op = '+'").select("src", "dst", F.col("seq").alias("valid_from"), F.coalesce("end", F.lit(OPEN_END)).alias("valid_to"))


def noop_updates(updates: DataFrame) -> DataFrame:
    """(op, n): updates without effect."""
    by = Window.partitionBy("src", "dst").orderBy("seq", "op")
    rows = updates.withColumn("before", F.lag("op").over(by))
    return rows.where("(op = '+' AND before = '+') OR (op = '-' AND coalesce(before, '-') = '-')").groupBy("op").agg(F.count("*").alias("n"))


def alive_at(versions: DataFrame, seq: int) -> DataFrame:
    return versions.where((F.col("valid_from") <= seq) & (F.col("valid_to") > seq)).select("src", "dst")
