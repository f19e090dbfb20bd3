"""Graph primitives: canonical edges, labelled adjacency, degrees and label profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: Stands for "any label" on the query side; data rows are offered under their own label and under this one.
ANY = -2


def offered(label: str) -> Column:
    """A row for each label value under which a query may ask for a vertex, so that label tests stay equi-joins."""
    return F.explode(F.array(F.coalesce(F.col(label), F.lit(-1)), F.lit(ANY)))


def canonical_edges(edges: DataFrame) -> DataFrame:
    """Undirected edges once each, smaller end first; loops and null ends go."""
    return edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """(v, w) in both directions, with the other columns of edges."""
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select(F.col("src").alias("v"), F.col("dst").alias("w"), *rest).union(edges.select(F.col("dst"), F.col("src"), *rest))


def adjacency(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """both_ways with v_label and w_label; a vertex without a label has -1."""
    ends = vertices.select("id", F.coalesce("label", F.lit(-1)).alias("label"))
    out = both_ways(edges).join(ends.withColumnsRenamed({"id": "v", "label": "v_label"}), "v", "left").join(ends.withColumnsRenamed({"id": "w", "label": "w_label"}), "w", "left")
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return out.select("v", "w", F.coalesce("v_label", F.lit(-1)).alias("v_label"), F.coalesce("w_label", F.lit(-1)).alias("w_label"), *rest)


def degrees(adj: DataFrame) -> DataFrame:
    return adj.groupBy("v").agg(F.count("*").alias("degree"))


def label_profile(adj: DataFrame) -> DataFrame:
    """(v, w_label, n): neighbours by label."""
    return adj.groupBy("v", "w_label").agg(F.count("*").alias("n"))
