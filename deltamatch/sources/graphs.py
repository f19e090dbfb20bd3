"""Graphs of the given tables: `vertices(id, label)` and `edges(src, dst)` with src < dst."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamatch.operators.graph import canonical_edges
from deltamatch.session import cut, numbered, small

#: Vertex kinds of the trade graph are kept apart by this offset.
KIND = 10**10


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(df: DataFrame, column: str) -> Column:
    """Microseconds since 1970 of a timestamp; one without a zone counts as UTC whatever the session's zone is."""
    if dict(df.select(F.col(column).alias("c")).dtypes)["c"] == "timestamp_ntz":
        return F.unix_micros(F.from_utc_timestamp(F.col(column).cast("timestamp"), F.current_timezone()))
    return F.unix_micros(column)


def copurchase_edges(spark: SparkSession, sf_dir: str, *, dense: bool = False, most_quantity: float | None = None) -> DataFrame:
    """Parts that share an order among returned lines; the sparse form also asks for finished lines."""
    lines = table(spark, sf_dir, "lineitem").where(F.col("l_returnflag") == "R")
    if not dense:
        lines = lines.where(F.col("l_linestatus") == "F")
    if most_quantity is not None:
        lines = lines.where(F.col("l_quantity") <= most_quantity)
    lines = lines.select(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).distinct()
    other = lines.select("o", F.col("p").alias("q"))
    return lines.join(other, "o").where("p < q").select(F.col("p").alias("src"), F.col("q").alias("dst")).distinct()


def part_vertices(spark: SparkSession, sf_dir: str, labels: int = 8) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), (F.col("p_size") % labels).cast("int").alias("label"))


def trade_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order-customer, order-part and part-supplier edges of returned, finished lines; ids are offset by kind."""
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R' AND l_linestatus = 'F'").select("l_orderkey", "l_partkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer, order, part, supplier = (lambda c, k=k: F.col(c) + F.lit(k * KIND) for k in range(4))
    edges = orders.select(customer("o_custkey").alias("src"), order("o_orderkey").alias("dst"))
    edges = edges.union(lines.select(order("l_orderkey"), part("l_partkey"))).union(lines.select(part("l_partkey"), supplier("l_suppkey")))
    return edges.distinct()


def trade_vertices(edges: DataFrame) -> DataFrame:
    ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
    return ids.select("id", F.floor(F.col("id") / KIND).cast("int").alias("label"))


def temporal_edges(spark: SparkSession, sf_dir: str, minutes: int = 60) -> DataFrame:
    """(src, dst, ts): users whose events agree in type and properties within some minutes; ts is that of the later event, the first time.

    The band join is an equi-join on type, properties and a time bucket, each event also looking into the bucket before.
    """
    events = table(spark, sf_dir, "events")
    return _meetings(events.withColumn("t", micros(events, "ts") / 1_000_000), "user_id", minutes)


def _meetings(events: DataFrame, who: str, minutes: int) -> DataFrame:
    """(src, dst, ts) of `temporal_edges` between the values of a column; events also carry t, their ts in seconds."""
    span = minutes * 60
    base = events.select(F.col(who).alias("u1"), "event_type", "props", "t", F.floor(F.col("t") / span).alias("bucket"))
    bucket = F.floor(F.col("t") / span)
    later = events.select(F.col(who).alias("u2"), "event_type", "props", F.col("ts").alias("ts2"), F.col("t").alias("t2"), F.explode(F.array(bucket, bucket - 1)).alias("bucket"))
    met = base.join(later, ["event_type", "props", "bucket"]).where(f"t2 >= t AND t2 - t <= {span} AND u1 <> u2")
    pairs = met.select(F.least("u1", "u2").alias("src"), F.greatest("u1", "u2").alias("dst"), "ts2")
    return pairs.groupBy("src", "dst").agg(F.min("ts2").alias("ts"))


def _twins(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Classes (id, n) of users with the same set of (type, properties, time), and the events (user_id, event_type, props, ts, us) of their smallest users.

    Sets are compared by their sizes and the XOR of their members' 128-bit digests, so no row
    holds a set; only users who share the smallest and largest hash of their events with
    another user have their events dealt out for that, as digests.
    """
    events = table(spark, sf_dir, "events")
    events = events.select("user_id", "event_type", "props", "ts", micros(events, "ts").alias("us")).where("user_id IS NOT NULL AND event_type IS NOT NULL AND props IS NOT NULL AND us IS NOT NULL")
    h = F.xxhash64("event_type", "props", "us")
    ends = cut(events.groupBy("user_id").agg(F.min(h).alias("lo"), F.max(h).alias("hi")))
    shared = ends.groupBy("lo", "hi").agg(F.count("*").alias("n")).where("n > 1")
    suspects = cut(ends.join(shared, ["lo", "hi"], "left_semi").select("user_id"))
    d = F.md5(F.concat(F.md5("event_type"), F.md5("props"), F.col("us").cast("string")))
    half = lambda at: F.conv(F.substring("d", at, 16), 16, -10).cast("bigint")
    digests = events.select("user_id", d.alias("d")).select("user_id", half(1).alias("x"), half(17).alias("y")).join(small(suspects), "user_id", "left_semi").distinct()
    sets = digests.groupBy("user_id").agg(F.count("*").alias("c"), F.bit_xor("x").alias("x"), F.bit_xor("y").alias("y"))
    alike = sets.groupBy("c", "x", "y").agg(F.min("user_id").alias("id"), F.count("*").alias("n"))
    alone = ends.join(suspects, "user_id", "left_anti").select(F.col("user_id").alias("id"), F.lit(1).cast("bigint").alias("n"))
    classes = cut(alike.select("id", "n").union(alone))
    ids = classes.select(F.col("id").alias("user_id"))
    dropped = suspects.join(ids, "user_id", "left_anti")
    # Broadcast whichever is small: the users that stand for classes or the others.
    kept = events.join(small(dropped), "user_id", "left_anti") if dropped.count() < ids.count() else events.join(small(ids), "user_id", "left_semi")
    return classes, kept


def temporal_twins(spark: SparkSession, sf_dir: str, minutes: int = 60) -> tuple[DataFrame, DataFrame]:
    """The temporal edges in classes of users: (id, n) and (src, dst, ts).

    Users with the same set of (type, properties, time) are twins: they meet every other user,
    and each other, at the same times. A class has the id of its smallest user and n users; an
    edge stands for those between all users of two classes, and a loop, which classes of several
    users have, for those within one.
    """
    classes, kept = _twins(spark, sf_dir)
    kept = cut(kept.select("user_id", "event_type", "props", "ts", (F.col("us") / 1_000_000).alias("t")).distinct())
    several = classes.where("n > 1").select(F.col("id").alias("user_id"))
    loops = kept.join(several, "user_id", "left_semi").groupBy(F.col("user_id").alias("src"), F.col("user_id").alias("dst")).agg(F.min("ts").alias("ts"))
    return classes, _meetings(kept, "user_id", minutes).union(loops)


def twin_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, g, t, n, f): the events of the smallest user of each class of n twins at microsecond t; g stands for type and properties by a 64-bit hash, f is the class's first t where n > 1."""
    classes, kept = _twins(spark, sf_dir)
    several = cut(classes.where("n > 1").select(F.col("id").alias("user_id"), "n"))
    weights = cut(kept.join(small(several), "user_id").groupBy("user_id", "n").agg(F.min("us").alias("f")))
    g = F.xxhash64("event_type", "props").alias("g")
    held = kept.join(small(weights), "user_id", "left")
    return held.select(F.col("user_id").alias("u"), g, F.col("us").alias("t"), F.coalesce("n", F.lit(1)).cast("bigint").alias("n"), F.coalesce("f", F.lit(0)).cast("bigint").alias("f"))


def neighbour_edges(spark: SparkSession, sf_dir: str, k: int = 3, block: int = 2000) -> DataFrame:
    """Each vector with its k nearest by cosine, symmetrised, ties by id. All pairs are compared, blocks of about `block` vectors against blocks. Vectors without a direction (null, zero, not finite) have no neighbours."""
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    rows = rows.where(norm.isNotNull() & (norm > 0) & (norm < float("inf"))).select("vec_id", F.transform("v", lambda x: x / norm).alias("v"))
    blocks = max(1, -(-rows.count() // block))
    own, every = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asked = rows.select(own.alias("i"), every.alias("j"), "vec_id", "v")
    held = rows.select(every.alias("i"), own.alias("j"), "vec_id", "v")

    def nearest(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"a": np.zeros(0, np.int64), "b": np.zeros(0, np.int64), "near": np.zeros(0)})
        ids, names = left["vec_id"].to_numpy(), right["vec_id"].to_numpy()
        near = (np.stack(left["v"].to_list()) @ np.stack(right["v"].to_list()).T).round(9)
        near[ids[:, None] == names] = -2
        order = np.lexsort((np.broadcast_to(names, near.shape), -near), axis=1)[:, :k]
        found = pd.DataFrame({"a": np.repeat(ids, order.shape[1]), "b": names[order].ravel(), "near": np.take_along_axis(near, order, 1).ravel()})
        return found[found["near"] > -2]

    found = asked.groupBy("i", "j").cogroup(held.groupBy("i", "j")).applyInPandas(nearest, "a bigint, b bigint, near double")
    rank = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("near"), "b"))
    return canonical_edges(found.withColumn("rank", rank).where(F.col("rank") <= k).select(F.col("a").alias("src"), F.col("b").alias("dst")))


def link_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src page, dst link): pages and the targets of their links, targets hashed past the pages' ids."""
    pages = table(spark, sf_dir, "pages").where("html is not null")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return links.select(F.col("page_id").alias("src"), (F.lit(KIND) + F.pmod(F.xxhash64("href"), F.lit(10**15))).alias("dst")).distinct()


def shared_line_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share a trimmed line of at least 40 characters which occurs in 2 to 20 documents."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= 40)
    lines = lines.select("doc_id", F.md5("line").alias("line")).distinct()
    fine = lines.groupBy("line").count().where("count BETWEEN 2 AND 20").select("line")
    held = lines.join(fine, "line")
    other = held.select("line", F.col("doc_id").alias("d2"))
    return held.join(other, "line").where("doc_id < d2").select(F.col("doc_id").alias("src"), F.col("d2").alias("dst")).distinct()


def random_edges(spark: SparkSession, n: int, degree: float = 3.0, seed: int = 1) -> DataFrame:
    """Erdős–Rényi style graph: round(n * degree / 2) hashed pairs, equal ones merged."""
    draw = lambda k: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(n))
    return canonical_edges(spark.range(round(n * degree / 2)).select(draw(1).alias("src"), draw(2).alias("dst")))


def small_world_edges(spark: SparkSession, n: int, k: int = 4, rewire: float = 0.1, seed: int = 1) -> DataFrame:
    """Ring of n vertices joined to k / 2 on each side; an edge's far end is redrawn with the given probability."""
    unit = F.pmod(F.xxhash64("id", F.lit(seed), "step"), F.lit(1_000_000)) / 1_000_000
    rows = spark.range(n).withColumn("step", F.explode(F.array(*map(F.lit, range(1, k // 2 + 1)))))
    far = F.when(unit < rewire, F.pmod(F.xxhash64("id", F.lit(seed + 1), "step"), F.lit(n))).otherwise((F.col("id") + F.col("step")) % n)
    return canonical_edges(rows.select(F.col("id").alias("src"), far.alias("dst")))


def uniform_labels(ids: DataFrame, labels: int) -> DataFrame:
    return ids.select("id", (F.col("id") % labels).cast("int").alias("label"))


def zipf_labels(ids: DataFrame, labels: int, s: float = 1.5) -> DataFrame:
    """Label j of 1..labels with weight j ** -s, drawn by the first eight digits of the id's md5."""
    weights = [j**-s for j in range(1, labels + 1)]
    unit = F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("double") / float(2**32)
    label: Column = F.lit(labels)
    for j in range(labels - 1, 0, -1):
        label = F.when(unit < math.fsum(weights[:j]) / math.fsum(weights), F.lit(j)).otherwise(label)
    return ids.select("id", label.cast("int").alias("label"))


def decoys(spark: SparkSession, regions: int = 50) -> tuple[DataFrame, DataFrame]:
    """(vertices, updates) of the constructed exception: eight-vertex cliques whose last edge arrives as an update, and one true region with the tail.

    Region r holds ids 100 r to 100 r + 7; the missing edge joins the first two. The true
    region is the last: it never gets that edge, carries its tail on the first vertex, and
    waits for the edge between the third and the fourth.
    """
    core = spark.range(regions + 1).withColumnRenamed("id", "r").select("r", F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in range(8) for j in range(i + 1, 8)])).alias("e"))
    i, j, last = F.col("e.i"), F.col("e.j"), F.col("r") == regions
    arrives = F.when(last, (i == 2) & (j == 3)).otherwise((i == 0) & (j == 1))
    core = core.where(~(last & (i == 0) & (j == 1))).select((F.col("r") * 100 + i).alias("src"), (F.col("r") * 100 + j).alias("dst"), F.when(arrives, F.col("r") + 1).otherwise(F.lit(0)).cast("bigint").alias("seq"))
    top = regions * 100
    tail = spark.createDataFrame([(top, top + 8, 0), (top + 8, top + 9, 0)], "src bigint, dst bigint, seq bigint")
    edges = core.union(tail)
    vertices = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct().select("id", F.lit(0).alias("label"))
    return vertices, edges.select("seq", F.lit("+").alias("op"), "src", "dst")


def order_decoys(spark: SparkSession, sf_dir: str, regions: int = 50) -> tuple[DataFrame, DataFrame]:
    """`decoys` over the lines of orders: the first eight lines of an order are a region's clique, named 100 times the order's key and on.

    All orders of at least eight lines are looked up; those of the smallest keys are the
    regions, in the order of their keys, and the last of them is the true one.
    """
    large = table(spark, sf_dir, "lineitem").where("l_orderkey IS NOT NULL").groupBy(F.col("l_orderkey").alias("o")).agg(F.count("*").alias("n")).where("n >= 8")
    chosen = large.select("o").orderBy("o").limit(regions + 1)
    held = cut(chosen.withColumn("r", F.row_number().over(Window.orderBy("o"))).withColumn("last", F.col("o") == F.max("o").over(Window.partitionBy())))  # a row a region
    pairs = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in range(8) for j in range(i + 1, 8)])).alias("e")
    i, j, last, base = F.col("e.i"), F.col("e.j"), F.col("last"), F.col("o") * 100
    arrives = F.when(last, (i == 2) & (j == 3)).otherwise((i == 0) & (j == 1))
    core = held.select("o", "r", "last", pairs).where(~(last & (i == 0) & (j == 1)))
    core = core.select((base + i).alias("src"), (base + j).alias("dst"), F.when(arrives, F.col("r")).otherwise(F.lit(0)).cast("bigint").alias("seq"))
    tail = held.where("last").select(F.explode(F.array(F.struct(base.alias("src"), (base + 8).alias("dst")), F.struct((base + 8).alias("src"), (base + 9).alias("dst")))).alias("e"))
    edges = cut(core.union(tail.select("e.src", "e.dst", F.lit(0).cast("bigint"))))
    vertices = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct().select("id", F.lit(0).alias("label"))
    return vertices, edges.select("seq", F.lit("+").alias("op"), "src", "dst")


def placed(made: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges between numbers 0, 1, ... as edges between ids, which are numbered in the order of their md5."""
    names = cut(numbered(ids.select("id"), F.md5(F.col("id").cast("string")), "id").select((F.col("n") - 1).alias("n"), "id"))
    ends = names.select(F.col("n").alias("src"), F.col("id").alias("a")), names.select(F.col("n").alias("dst"), F.col("id").alias("b"))
    return canonical_edges(made.join(ends[0], "src").join(ends[1], "dst").select(F.col("a").alias("src"), F.col("b").alias("dst")))


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Edges of a text file with two ids a line and # comments."""
    rows = spark.read.schema("src BIGINT, dst BIGINT").option("sep", sep).option("comment", "#").csv(path)
    return canonical_edges(rows)


def read_updates(spark: SparkSession, path: str) -> DataFrame:
    """Updates as JSON lines."""
    return spark.read.schema("seq BIGINT, op STRING, src BIGINT, dst BIGINT, ts TIMESTAMP").json(path)
