"""Helpers that several operators share: table access, Arrow maps, checkpoints, components."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A whole table. One that comes in fewer splits than half the cores, as a file of a single row group does, is dealt out to all of them first."""
    rows = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    cores = spark.sparkContext.defaultParallelism
    return rows.repartition(cores) if 2 * rows.rdd.getNumPartitions() < cores else rows


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares, from spark.checkpoint.dir.

    Only where that is unset and all runs on one machine, as in tests, a temporary folder is
    used; a cluster without a shared folder is an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
    if not found:
        found = tempfile.mkdtemp(prefix="deltamatch-")
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(found)
    return found


def cut(df: DataFrame) -> DataFrame:
    """Materialise df in the shared folder, so that a lost executor loses nothing and lineage ends."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """At most `rows` texts travel to a Python worker at once, so its memory and the JVM's Arrow buffers follow a few megabytes, not the default's 10,000 texts. A session setting that may change at any time."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key, "10000")) <= rows:
        spark.conf.set(key, rows)


def map_rows(df: DataFrame, columns: list[str | Column], schema: str, fn: Callable[[Iterator[dict]], Iterable[dict]]) -> DataFrame:
    """mapInArrow over the given columns; fn gets a dict of Python lists per batch and yields such dicts."""
    small_batches(df.sparkSession)
    out = df.sparkSession.createDataFrame([], schema).schema
    arrow = pa.schema([(f.name, _ARROW[f.dataType.simpleString()]) for f in out])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for got in fn(dict(zip(b.schema.names, (c.to_pylist() for c in b.columns))) for b in batches):
            yield pa.RecordBatch.from_arrays([pa.array(got[f.name], f.type) for f in arrow], schema=arrow)

    return df.select(*columns).mapInArrow(run, out)


_ARROW = {
    "bigint": pa.int64(), "int": pa.int32(), "string": pa.string(), "double": pa.float64(), "boolean": pa.bool_(), "binary": pa.binary(),
    "array<bigint>": pa.list_(pa.int64()), "array<float>": pa.list_(pa.float32()), "array<int>": pa.list_(pa.int32()), "array<double>": pa.list_(pa.float64()),
}


def rekeyed(column: str) -> Column:
    """The same bigint, but opaque to the planner: a later join deals it out anew and can split a hot key."""
    return F.col(column).bitwiseXOR(F.lit(0)).cast("bigint").alias(column)


def components(edges: DataFrame) -> DataFrame:
    """Connected components of edges (a bigint, b bigint) as (node, root), root being the smallest node.

    Alternates two star contractions: every node hands its larger neighbours, then its
    smaller ones, to the smallest one it knows. Minima are combined before the shuffle and
    hot hubs only meet them in joins that adaptive execution may split; each round is
    written to the shared folder. Nodes without an edge don't occur in the result.
    """
    edges = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = None
    while True:
        both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select(rekeyed("a"), F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m")).select(rekeyed("a"), "m")
        met = large.join(low, "a")
        small = met.select("a", F.col("m").alias("b")).union(met.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct()
        edges = cut(small)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before or now[0] == 0:
            break
        before = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).union(edges.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
