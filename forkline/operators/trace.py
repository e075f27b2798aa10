"""Branch sites of the sequential kernels and their exact outcomes, as relations.

Orders of the component kernel: ``sync`` reads the labels of the sweep before; ``inplace``
sees those of smaller neighbours as this sweep left them. Vertices and neighbours go by
ascending id. Searches: vertices by place in the queue, neighbours by ascending id.

Traces are derived from labels or places and folded at once, never stored: dealt by ranges,
sorted there, and folded as they stream by. Where a vertex has more than ``HUB_CHUNK``
neighbours, the tests of the component kernel are folded by pieces instead: hubs are cut at
ids that split their edges evenly, so that no group of rows, and no window, holds more than a
piece; the running minimum crosses cuts as the minimum of the pieces before, one row each.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from forkline.operators.folding import fold_improvements, fold_in_order
from forkline.operators.predictor import PredictorSpec, start_codes, step_codes

HUB_CHUNK = 65_536
#: Cuts at most; more would only make the pieces of the largest hubs smaller.
MOST_CUTS = 10_000


def hub_cuts(edges: DataFrame, chunk: int = HUB_CHUNK) -> list[int]:
    """Ids that part the neighbours of hubs into pieces of about ``chunk``; none if no vertex has so many."""
    hubs = edges.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > chunk)
    most = hubs.agg(F.max("n").alias("n")).first()["n"]
    if not most:
        return []
    pieces = min(MOST_CUTS, -(-most // chunk))
    at = [i / pieces for i in range(1, pieces)]
    found = edges.join(hubs.select("src"), "src", "left_semi").agg(F.percentile_approx("dst", at, 100 * pieces).alias("q")).first()["q"]
    return sorted(set(found))


def piece_of(dst: Column, cuts: list[int]) -> Column:
    """Number of the piece that a neighbour falls into."""
    if not cuts:
        return F.lit(0)
    return F.aggregate(F.array(*(F.lit(c).cast("bigint") for c in cuts)), F.lit(0), lambda n, c: n + (dst > c).cast("int"))


def _heard(edges: DataFrame, history: DataFrame, order: str) -> DataFrame:
    """``(iteration, src, dst, heard)``: the label that the kernel reads at each neighbour; ``history(iteration, id, before, after)``."""
    far = history.select("iteration", F.col("id").alias("dst"), "before", "after")
    met = edges.select("src", "dst").join(far, "dst")
    label = F.col("before") if order == "sync" else F.when(F.col("dst") < F.col("src"), F.col("after")).otherwise(F.col("before"))
    return met.select("iteration", "src", "dst", label.alias("heard"))


def cc_test_trace(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """``(seq_hi, seq_lo, taken)`` of one synchronous sweep over ``labels``, row by row: is the neighbour's label below the least so far?"""
    far = labels.select(F.col("id").alias("dst"), F.col("component").alias("heard"))
    own = labels.select(F.col("id").alias("src"), F.col("component").alias("own"))
    before = W.partitionBy("src").orderBy("dst").rowsBetween(W.unboundedPreceding, -1)
    met = edges.join(far, "dst").join(own, "src")
    low = F.least("own", F.coalesce(F.min("heard").over(before), F.col("own")))
    return met.select(F.col("src").alias("seq_hi"), F.col("dst").alias("seq_lo"), (F.col("heard") < low).alias("taken"))


def _columns(edges: DataFrame, history: DataFrame, order: str, iterations: list[int]) -> DataFrame:
    """``(src, dst, h0, h1, ..)``: what the kernel reads at each neighbour, a column an iteration; rows without ``dst`` bring own labels."""
    at = lambda i, c: F.max(F.when(F.col("iteration") == i, F.col(c)))
    wide = history.groupBy("id").agg(*(at(i, c).alias(f"{c}{k}") for k, i in enumerate(iterations) for c in ("before", "after") if order != "sync" or c == "before"))
    read = lambda k: F.col(f"before{k}") if order == "sync" else F.when(F.col("dst") < F.col("src"), F.col(f"after{k}")).otherwise(F.col(f"before{k}"))
    names = range(len(iterations))
    far = edges.select("src", "dst").join(wide.withColumnRenamed("id", "dst"), "dst").select("src", "dst", *(read(k).alias(f"h{k}") for k in names))
    return far.unionByName(wide.select(F.col("id").alias("src"), F.lit(None).cast("bigint").alias("dst"), *(F.col(f"before{k}").alias(f"h{k}") for k in names)))


def cc_test_fold(edges: DataFrame, history: DataFrame, specs: tuple[PredictorSpec, ...], order: str = "sync", iterations: list[int] | None = None, bounds: list[int] | None = None, chunk: int = HUB_CHUNK) -> DataFrame:
    """Functions of the improvement tests. Without hubs, by range of vertices, see ``fold_improvements``; else by piece.

    One exchange of messages for all iterations of ``history``.
    """
    cuts = hub_cuts(edges, chunk)
    if not cuts:
        iterations = iterations or sorted(r["iteration"] for r in history.select("iteration").distinct().collect())
        return fold_improvements(_columns(edges, history, order, iterations), iterations, bounds or [], specs)
    return by_predictor(specs, lambda spec: _hub_fold(edges, history, spec, order, cuts))


def by_predictor(specs: tuple[PredictorSpec, ...], fold: Callable[[PredictorSpec], DataFrame]) -> DataFrame:
    out = None
    for spec in specs:
        one = fold(spec).withColumn("predictor", F.lit(spec.name))
        out = one if out is None else out.unionByName(one)
    return out


def _hub_fold(edges: DataFrame, history: DataFrame, spec: PredictorSpec, order: str, cuts: list[int]) -> DataFrame:
    """``(iteration, seq_hi, chunk, f, evaluations, taken)``: the function of the improvement tests of each vertex, or piece of a hub.

    The least before a piece is the minimum of those of the pieces before, one row each.
    """
    heard = _heard(edges, history, order).withColumn("chunk", piece_of(F.col("dst"), cuts))
    keys = ["iteration", "src", "chunk"]
    own = history.select("iteration", F.col("id").alias("src"), F.lit(-1).alias("chunk"), F.col("before").alias("least"))
    least = heard.groupBy(*keys).agg(F.min("heard").alias("least")).unionByName(own)
    before = W.partitionBy("iteration", "src").orderBy("chunk").rowsBetween(W.unboundedPreceding, -1)
    low = least.withColumn("low", F.min("least").over(before)).where("chunk >= 0").drop("least")  # a row a piece
    lists = heard.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("dst", "heard"))).alias("o")).join(low, keys)
    start = F.struct(F.col("low").alias("low"), start_codes(spec).alias("f"), F.lit(0).cast("bigint").alias("taken"))

    def test(acc: Column, x: Column) -> Column:
        taken = x["heard"] < acc["low"]
        return F.struct(F.least(acc["low"], x["heard"]).alias("low"), step_codes(acc["f"], taken, spec).alias("f"), (acc["taken"] + taken.cast("bigint")).alias("taken"))

    folded = lists.withColumn("done", F.aggregate("o", start, test))
    return folded.select("iteration", F.col("src").alias("seq_hi"), "chunk", F.col("done.f").alias("f"), F.size("o").cast("bigint").alias("evaluations"), F.col("done.taken").alias("taken"))


def bfs_test_trace(queue: DataFrame, edges: DataFrame) -> DataFrame:
    """``(seq_hi, seq_lo, taken, dist)``: does this adjacency, in queue order, discover its far end?"""
    near = queue.select(F.col("id").alias("src"), F.col("rank").alias("seq_hi"), "dist")
    far = queue.select(F.col("id").alias("dst"), F.col("parent").alias("by"))
    met = edges.join(near, "src").join(far, "dst", "left")
    return met.select("seq_hi", F.col("dst").alias("seq_lo"), (F.coalesce(F.col("by") == F.col("src"), F.lit(False))).alias("taken"), "dist")


def bfs_test_fold(queue: DataFrame, edges: DataFrame, specs: tuple[PredictorSpec, ...], bounds: list[int] | None = None, chunk: int = HUB_CHUNK) -> DataFrame:
    """Functions of the discovery tests, by range of places in the queue; hubs' tests are dealt no finer, as they stream by."""
    trace = bfs_test_trace(queue, edges).select(F.col("dist").alias("iteration"), "seq_hi", "seq_lo", F.col("taken").alias("x"))
    return fold_in_order(trace, ["seq_hi", "seq_lo"], bounds or [], specs)

