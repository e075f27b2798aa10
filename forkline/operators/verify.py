"""Checks of results by anti-joins and aggregates: violations as rows, none if all is well."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.graph import Graph


def verify_components(g: Graph, labels: DataFrame) -> DataFrame:
    """Labels cover the vertices, agree over each edge, and are the smallest id of their component."""
    a = labels.select(F.col("id").alias("src"), F.col("component").alias("a"))
    b = labels.select(F.col("id").alias("dst"), F.col("component").alias("b"))
    torn = g.edges.join(a, "src").join(b, "dst").where("a <> b").select(F.lit("edge").alias("rule"), F.col("src").alias("id"))
    missing = g.vertices.join(labels, "id", "left_anti").select(F.lit("missing").alias("rule"), "id")
    low = labels.groupBy("component").agg(F.min("id").alias("least")).where("component <> least").select(F.lit("least").alias("rule"), F.col("component").alias("id"))
    return torn.unionByName(missing).unionByName(low)


def verify_distances(g: Graph, root: int, dist: DataFrame) -> DataFrame:
    """Each reached edge spans one level at most, each vertex but the root has one a level above, and nothing reachable is missing."""
    a = dist.select(F.col("id").alias("src"), F.col("dist").alias("a"))
    b = dist.select(F.col("id").alias("dst"), F.col("dist").alias("b"))
    met = g.edges.join(a, "src").join(b, "dst", "left")
    wide = met.where("b IS NULL OR b > a + 1").select(F.lit("span").alias("rule"), F.col("src").alias("id"))
    above = met.where("b = a + 1").select(F.col("dst").alias("id")).distinct()
    orphan = dist.where("dist > 0").join(above, "id", "left_anti").select(F.lit("orphan").alias("rule"), "id")
    start = dist.where((F.col("dist") == 0) != (F.col("id") == root)).select(F.lit("root").alias("rule"), "id")
    return wide.unionByName(orphan).unionByName(start)


def label_diff(x: DataFrame, y: DataFrame) -> DataFrame:
    """Rows of either that the other lacks."""
    return x.exceptAll(y).unionByName(y.exceptAll(x))
