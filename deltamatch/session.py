"""What operators need of a session: the shared folder and cut lineage."""

from __future__ import annotations

import sys
import tempfile

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


# Workers then need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__.split(".")[0]])

OPEN_END = 2**63 - 1


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a temporary one where spark.checkpoint.dir is unset and all runs on one machine."""
    context = spark.sparkContext._jsc.sc()
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found and context.getCheckpointDir().isDefined():
        found = context.getCheckpointDir().get()
    if not found and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
    if not found:
        found = tempfile.mkdtemp(prefix="deltamatch-")
    if not context.getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(found)
    return found


def cut(df: DataFrame) -> DataFrame:
    """Materialise df in the shared folder and end its lineage there."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def small(df: DataFrame, most: int = 50_000) -> DataFrame:
    """Broadcast df only if it has at most `most` rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def numbered(df: DataFrame, digest: Column, *ties: str, name: str = "n") -> DataFrame:
    """Global row number from 1 in the order of a hexadecimal digest, then ties, without one task seeing all rows.

    The first three digits deal rows into 4096 ranges; counts of the ranges give offsets.
    """
    from pyspark.sql import Window

    rows = df.withColumn("__d", digest).withColumn("__r", F.substring("__d", 1, 3))
    sizes = rows.groupBy("__r").agg(F.count("*").alias("__c"))
    before = F.sum("__c").over(Window.orderBy("__r").rowsBetween(Window.unboundedPreceding, -1))  # at most 4096 rows
    offsets = F.broadcast(sizes.select(F.col("__r").alias("__o"), F.coalesce(before, F.lit(0)).alias("__b")))
    own = F.row_number().over(Window.partitionBy("__r").orderBy("__d", *ties))
    return rows.join(offsets, F.col("__r") == F.col("__o")).withColumn(name, (F.col("__b") + own).cast("bigint")).drop("__d", "__r", "__o", "__b")
