"""Live matching: micro-batches of edge updates against versioned state.

State lives in generation folders named after batch ids, in the cluster's shared storage. A
batch reads the newest generation that was committed before it, writes its matches and the
next generation, and commits last by a marker; a replayed batch overwrites its own folders
and so changes nothing twice. Sequence numbers continue from the committed generation.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamatch.operators import engines, gate
from deltamatch.plans.query import Query
from deltamatch.session import OPEN_END, cut

UPDATES = "op STRING, src BIGINT, dst BIGINT, ts TIMESTAMP, event_id BIGINT"
VERSIONS = "src BIGINT, dst BIGINT, valid_from BIGINT, valid_to BIGINT"


@dataclass
class LiveMatcher:
    """Keeps edge versions and emits signed matches batch by batch; `gated` puts the anchored gate before enumeration."""

    spark: SparkSession
    queries: list[Query]
    vertices: DataFrame
    folder: str
    gated: bool = False

    def _path(self, kind: str, batch: int) -> str:
        return f"{self.folder}/{kind}/batch={batch}"

    def _committed(self) -> list[tuple[int, int]]:
        """(batch, last seq) of all commits, one small row each."""
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/commit")
        if not hadoop.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(hadoop):
            return []
        return sorted((r.batch, r.last) for r in self.spark.read.schema("last BIGINT, batch BIGINT").parquet(f"{self.folder}/commit").collect())

    def state(self, before: int | None = None) -> tuple[DataFrame, int]:
        """Versions and the last sequence number of the newest generation, or of the newest one before a batch."""
        done = [x for x in self._committed() if before is None or x[0] < before]
        if not done:
            return self.spark.createDataFrame([], VERSIONS), 0
        batch, last = done[-1]
        return self.spark.read.schema(VERSIONS).parquet(self._path("versions", batch)), last

    def load(self, edges: DataFrame) -> None:
        """Initial edges, as generation -1."""
        edges.select("src", "dst", F.lit(0).cast("bigint").alias("valid_from"), F.lit(OPEN_END).alias("valid_to")).write.mode("overwrite").parquet(self._path("versions", -1))
        self._commit(-1, 0)

    def _commit(self, batch: int, last: int) -> None:
        self.spark.createDataFrame([(last,)], "last BIGINT").coalesce(1).write.mode("overwrite").parquet(self._path("commit", batch))

    def process(self, updates: DataFrame, batch: int) -> None:
        """One micro-batch: number, open and close versions, gate, enumerate, write, commit."""
        versions, last = self.state(before=batch)
        rows = updates.where("src IS NOT NULL AND dst IS NOT NULL AND src <> dst")
        rows = rows.select("op", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "ts", "event_id")
        # One order for the batch alone; batches are bounded by the source's trigger options.
        seq = F.row_number().over(Window.orderBy("ts", "event_id", "src", "dst")) + F.lit(last)
        rows = cut(rows.withColumn("seq", seq.cast("bigint")))
        newest = rows.agg(F.max("seq")).first()[0]
        if newest is None:
            versions.write.mode("overwrite").parquet(self._path("versions", batch))
            self._commit(batch, last)
            return
        # A live edge acts as an insertion before the batch; alternating operations open and close versions.
        alive = versions.where(F.col("valid_to") == OPEN_END)
        ops = rows.select("src", "dst", "seq", "op").union(alive.select("src", "dst", "valid_from", F.lit("+")))
        by = Window.partitionBy("src", "dst").orderBy("seq", "op")
        kept = ops.withColumn("before", F.lag("op").over(by)).where("(op = '+' AND coalesce(before, '-') = '-') OR (op = '-' AND before = '+')")
        opened = kept.withColumn("end", F.lead("seq").over(by)).where("op = '+'").select("src", "dst", F.col("seq").alias("valid_from"), F.coalesce("end", F.lit(OPEN_END)).alias("valid_to"))
        now = cut(opened.union(versions.where(F.col("valid_to") < OPEN_END)))
        out = None
        for sign in (1, -1):
            skips = gate.skips(gate.decide(self.queries, now, self.vertices, sign=sign, since=last)) if self.gated else None
            found = engines.match_counts(engines.delta(self.queries, now, self.vertices, sign=sign, skips=skips, since=last))
            out = found if out is None else out.union(found)
        out.write.mode("overwrite").parquet(self._path("matches", batch))
        # Versions closed before this batch can't meet any later anchor.
        now.where(F.col("valid_to") > last).write.mode("overwrite").parquet(self._path("versions", batch))
        self._commit(batch, newest)

    def matches(self) -> DataFrame:
        return self.spark.read.schema("query_id STRING, seq BIGINT, sign INT, matches BIGINT").parquet(f"{self.folder}/matches")

    def start(self, stream: DataFrame, checkpoint: str):
        """A running query over a streaming DataFrame of UPDATES."""
        return stream.writeStream.foreachBatch(self.process).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_updates(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Streaming updates from Parquet files."""
    return spark.readStream.schema(UPDATES).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def event_edges(events: DataFrame, minutes: int = 60, late: str = "10 minutes") -> DataFrame:
    """Streaming edges between users of like events: duplicates dropped within the watermark, then an interval join of the stream with itself."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    first = rows.select(F.col("user_id").alias("u1"), F.col("event_type").alias("k1"), F.col("props").alias("p1"), F.col("ts").alias("t1"))
    later = rows.select(F.col("user_id").alias("u2"), F.col("event_type").alias("k2"), F.col("props").alias("p2"), F.col("ts").alias("t2"), F.col("event_id").alias("event_id"))
    met = first.join(later, F.expr(f"k1 = k2 AND p1 = p2 AND u1 <> u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {minutes} MINUTES"))
    return met.select(F.lit("+").alias("op"), F.least("u1", "u2").alias("src"), F.greatest("u1", "u2").alias("dst"), F.col("t2").alias("ts"), "event_id")


def update_rates(updates: DataFrame, width: str = "10 minutes", slide: str = "5 minutes", late: str = "10 minutes") -> DataFrame:
    """Updates per sliding window; late rows beyond the watermark are dropped."""
    return updates.withWatermark("ts", late).groupBy(F.window("ts", width, slide), "op").agg(F.count("*").alias("n"))


def touch_counters(touches: DataFrame, tau: int = 4) -> DataFrame:
    """Stateful per-center counters of a stream (center, seq): touches so far, and whether a lazy schedule solves anew now."""

    def count(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = state.get[0] if state.exists else 0
        for part in parts:
            part = part.sort_values("seq")
            number = range(n + 1, n + 1 + len(part))
            n += len(part)
            yield pd.DataFrame({"center": part["center"], "seq": part["seq"], "touch": list(number), "refresh": [i % (tau + 1) == 0 for i in number]})
        state.update((n,))

    return touches.groupBy("center").applyInPandasWithState(count, "center BIGINT, seq BIGINT, touch BIGINT, refresh BOOLEAN", "n BIGINT", "append", "NoTimeout")
