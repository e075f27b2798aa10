"""SQL surface: views of a graph, functions, and declarative recursion as a baseline."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.graph import Graph
from forkline.operators.verify import verify_components
from forkline.sources.tables import stored


_ROW_LIMIT = "spark.sql.cteRecursionRowLimit"


def register_views(g: Graph, prefix: str = "") -> None:
    """Temporary views ``<prefix>edges`` and ``<prefix>vertices``."""
    g.edges.createOrReplaceTempView(f"{prefix}edges")
    g.vertices.createOrReplaceTempView(f"{prefix}vertices")


def register_functions(spark: SparkSession) -> None:
    """SQL functions ``miss_rate_two_bit(p)`` and ``miss_rate_one_bit(p)``; they stay in the JVM."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION miss_rate_two_bit(p DOUBLE) RETURNS DOUBLE RETURN p * (1 - p) / (p * p + (1 - p) * (1 - p))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION miss_rate_one_bit(p DOUBLE) RETURNS DOUBLE RETURN 2 * p * (1 - p)")


def components_recursive(g: Graph, depth: int) -> DataFrame:
    """Components by a recursive query: labels walk ``depth`` edges along vertices above them.

    Recursion may neither aggregate nor drop repeats, so walks are enumerated: a baseline for
    small, shallow graphs. Only ids below all their neighbours send labels, as the least id of
    a component is one of them, and no walk turns back at once, as no shortest path does; on a
    tree a label then comes to a vertex once. ``depth`` has to reach the eccentricity of each
    component's least id; labels that still differ over an edge raise an error.
    """
    register_views(g, "__recursive_")
    spark = g.edges.sparkSession
    limit = spark.conf.get(_ROW_LIMIT)
    spark.conf.set(_ROW_LIMIT, "-1")  # rows grow with the graph; Spark's default ends the query at a million
    try:
        walks = spark.sql(
            f"""WITH RECURSIVE walk(id, label, last, steps) AS (
                SELECT id, id, id, 0 FROM __recursive_vertices LEFT ANTI JOIN __recursive_edges ON src = id AND dst < id
                UNION ALL
                SELECT e.dst, w.label, w.id, w.steps + 1 FROM walk w JOIN __recursive_edges e ON e.src = w.id
                WHERE w.steps < {int(depth)} AND e.dst > w.label AND e.dst <> w.last)
                SELECT id, label FROM walk UNION ALL SELECT id, id FROM __recursive_vertices"""
        )
        labels = stored(walks.groupBy("id").agg(F.min("label").alias("component")), "recursive")
    finally:
        spark.conf.set(_ROW_LIMIT, limit)
    if verify_components(g, labels).limit(1).count():
        raise ValueError(f"depth {depth} does not reach every vertex")
    return labels


def sample_trace(trace: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    """Outcomes of a share of the vertices, each with all of its own: an estimate, for sites too large to fold."""
    share = F.pmod(F.xxhash64("seq_hi", F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000)
    return trace.where(share)


def knn_edges(pairs: DataFrame, k: int) -> DataFrame:
    """The ``k`` strongest partners of each ``a`` in ``(a, b, weight)``; ties to the smaller b."""
    from pyspark.sql import Window as W

    own = W.partitionBy("a").orderBy(F.desc("weight"), "b")
    return pairs.withColumn("place", F.row_number().over(own)).where(F.col("place") <= k).drop("place")
