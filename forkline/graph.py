"""Graphs as two DataFrames, and what is done to them as a whole."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from forkline.sources.tables import shuffles_dropped, stored


@dataclass(frozen=True)
class Graph:
    """``edges(src, dst)`` without loops and repeats, both orientations if undirected; ``vertices(id)`` holds all endpoints."""

    edges: DataFrame
    vertices: DataFrame
    directed: bool = False
    name: str = "graph"
    alone: DataFrame | None = None  # vertices given beside the edges, if any
    pairs: DataFrame | None = None  # ``(src, dst)`` the edges come from, with nulls, loops and repeats; of graphs that are plans


def _ends_named(pairs: DataFrame) -> DataFrame:
    a, b = pairs.columns[:2]
    return pairs.select(F.col(a).cast("bigint").alias("src"), F.col(b).cast("bigint").alias("dst"))


def normalize_edges(pairs: DataFrame, directed: bool = False) -> DataFrame:
    """Bigint pairs without nulls, loops and repeats; symmetric unless ``directed``. Takes the first two columns."""
    one = _ends_named(pairs)
    if directed:
        return one.where("src <> dst").distinct()
    once = one.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()  # half as many rows to compare as in both orientations
    return once.select(F.explode(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e")).select("e.src", "e.dst")


def _ends(edges: DataFrame, directed: bool, alone: DataFrame | None) -> DataFrame:
    ends = edges.select(F.col("src").alias("id"))
    if directed:
        ends = ends.union(edges.select(F.col("dst").alias("id")))
    if alone is not None:
        ends = ends.union(alone.select(F.col(alone.columns[0]).cast("bigint").alias("id")))
    return ends.distinct()


def written(g: Graph) -> Graph:
    """The graph of a builder in the shared folder; vertices come from the written edges, which are made once."""
    with shuffles_dropped(g.edges.sparkSession):
        edges = stored(g.edges, "edges")
        return replace(g, edges=edges, vertices=stored(_ends(edges, g.directed, g.alone), "vertices"), pairs=None)


def graph_of(pairs: DataFrame, name: str, directed: bool = False, vertices: DataFrame | None = None) -> Graph:
    edges = normalize_edges(pairs, directed)
    return Graph(edges, _ends(edges, directed, vertices), directed, name, vertices, _ends_named(pairs))


def prepare(g: Graph, partitions: int | None = None) -> Graph:
    """Lay the graph out once in the shared folder: edges dealt by the vertex that receives messages, sorted inside.

    The running minimum of a vertex is then taken where its edges lie, before any exchange.
    """
    edges = g.edges.repartition(partitions, "src") if partitions else g.edges.repartition("src")
    return replace(g, edges=stored(edges.sortWithinPartitions("src", "dst"), "edges"), vertices=stored(g.vertices, "vertices"), pairs=None)


def check(g: Graph) -> DataFrame:
    """Violations ``(rule, n)`` of the graph's contract; no rows if it holds."""
    ends = g.edges.select(F.col("src").alias("id")).union(g.edges.select(F.col("dst").alias("id"))).distinct()
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    rules = [
        ("null", g.edges.where("src IS NULL OR dst IS NULL")),
        ("loop", g.edges.where("src = dst")),
        ("repeat", g.edges.groupBy("src", "dst").count().where("count > 1").select("src", "dst")),
        ("endpoint", ends.join(g.vertices, "id", "left_anti").select(F.col("id").alias("src"), F.col("id").alias("dst"))),
    ]
    if not g.directed:
        rules.append(("one way", g.edges.join(back, ["src", "dst"], "left_anti")))
    out = None
    for rule, bad in rules:
        n = bad.select(F.lit(rule).alias("rule"))
        out = n if out is None else out.unionByName(n)
    return out.groupBy("rule").agg(F.count("*").alias("n"))


def adjacency(g: Graph, hub_chunk: int = 65_536) -> DataFrame:
    """``(src, chunk, degree, nbrs)``: neighbours by ascending id, a hub's in chunks of bounded length."""
    place = W.partitionBy("src").orderBy("dst")
    placed = g.edges.withColumn("position", F.row_number().over(place) - 1).withColumn("chunk", F.floor(F.col("position") / hub_chunk).cast("int"))
    lists = placed.groupBy("src", "chunk").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
    degree = g.edges.groupBy("src").agg(F.count("*").alias("degree"))
    return lists.join(degree, "src").select("src", "chunk", "degree", "nbrs")


def degrees(g: Graph) -> DataFrame:
    """``(id, degree)`` of every vertex, isolated ones too."""
    seen = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    return g.vertices.join(seen, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("bigint").alias("degree"))


def degree_histogram(g: Graph) -> DataFrame:
    return degrees(g).groupBy("degree").agg(F.count("*").alias("vertices"))


def degree_quantiles(g: Graph, at: tuple[float, ...] = (0.5, 0.9, 0.99), accuracy: int = 10_000) -> DataFrame:
    found = degrees(g).agg(F.percentile_approx("degree", list(at), accuracy).alias("q"))
    return found.select(F.posexplode("q").alias("i", "degree")).select(F.element_at(F.array(*map(F.lit, at)), F.col("i") + 1).alias("quantile"), "degree")


def top_degree(g: Graph, k: int) -> DataFrame:
    return degrees(g).orderBy(F.desc("degree"), "id").limit(k)


def subgraph(g: Graph, vertex_pred: Column | None = None, edge_pred: Column | None = None) -> Graph:
    """Induced by the vertices that satisfy ``vertex_pred`` (over ``id``) and the edges that satisfy ``edge_pred``."""
    vertices = g.vertices.where(vertex_pred) if vertex_pred is not None else g.vertices
    edges = g.edges.where(edge_pred) if edge_pred is not None else g.edges
    if vertex_pred is not None:
        for end in ("src", "dst"):
            edges = edges.join(vertices.select(F.col("id").alias(end)), end, "left_semi")
    return replace(g, edges=edges.select("src", "dst"), vertices=vertices, pairs=None)


def graph_union(a: Graph, b: Graph) -> Graph:
    return replace(a, edges=a.edges.unionByName(b.edges).distinct(), vertices=a.vertices.unionByName(b.vertices).distinct(), name=f"{a.name}+{b.name}", pairs=None)


def graph_intersect(a: Graph, b: Graph) -> Graph:
    return replace(a, edges=a.edges.intersect(b.edges), vertices=a.vertices.intersect(b.vertices), name=f"{a.name}&{b.name}", pairs=None)


def graph_difference(a: Graph, b: Graph) -> Graph:
    """Edges of ``a`` that ``b`` lacks, over the vertices of ``a``."""
    return replace(a, edges=a.edges.subtract(b.edges), name=f"{a.name}-{b.name}", pairs=None)


def dense_ids(df: DataFrame, column: str) -> DataFrame:
    """``(column, id)``: distinct values of a column numbered from 0 in their order, without a single-partition window."""
    return ranked(df.select(column).where(F.col(column).isNotNull()).distinct(), [column], "id")


def ranked(df: DataFrame, order: list[str], name: str, start: int = 0) -> DataFrame:
    """Number rows from ``start`` in the order of ``order``: range partitions, local numbers, and offsets of the partitions."""
    laid = stored(df.repartitionByRange(*(F.col(c) for c in order)).withColumn("__part", F.spark_partition_id()), "ranked")
    sizes = laid.groupBy("__part").agg(F.count("*").alias("n"))  # one row a partition
    before = sizes.alias("a").join(sizes.alias("b"), F.col("b.__part") < F.col("a.__part"), "left").groupBy("a.__part").agg(F.coalesce(F.sum("b.n"), F.lit(0)).alias("__before"))
    own = F.row_number().over(W.partitionBy("__part").orderBy(*order))
    return laid.join(F.broadcast(before), "__part").withColumn(name, (F.col("__before") + own - 1 + start).cast("bigint")).drop("__part", "__before")


def inventory(graphs: Iterable[Graph]) -> DataFrame:
    """``(graph, directed, vertices, edges)``; an undirected edge counts once.

    Each graph is counted by an action of its own, whose shuffle files go with it, so that disk
    holds one graph's at a time. Graphs may be plans; an orientation is counted without the other.
    """
    rows, spark = [], None
    for g in graphs:
        spark = g.edges.sparkSession
        once = (g.edges if g.directed else g.edges.where("src < dst")).agg(F.count("*").alias("edges"))
        with shuffles_dropped(spark):
            n = once.crossJoin(g.vertices.agg(F.count("*").alias("vertices"))).first()  # one row each
        rows.append((g.name, g.directed, n["vertices"], n["edges"]))
    return (spark or SparkSession.active()).createDataFrame(rows, "graph string, directed boolean, vertices bigint, edges bigint")
