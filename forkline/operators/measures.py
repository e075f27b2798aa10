"""Comparisons of the two disciplines: ratios, bounds, crossover, correlation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from forkline.functions.selection import ratio

VARIANTS = ["conditional", "unconditional"]
METRICS = ["time", "instructions", "branches", "mispredictions", "loads", "stores"]


def _sides(samples: DataFrame, metric: str, keys: list[str]) -> DataFrame:
    return samples.groupBy(*keys).pivot("variant", VARIANTS).agg(F.sum(metric))


def variant_ratio(samples: DataFrame, metric: str, by_iteration: bool = True) -> DataFrame:
    """``(graph, method[, iteration], conditional, unconditional, ratio)`` of a metric."""
    keys = ["graph", "method", *(["iteration"] if by_iteration else [])]
    return _sides(samples, metric, keys).withColumn("ratio", ratio(F.col("conditional"), F.col("unconditional")))


def branch_ratio(samples: DataFrame) -> DataFrame:
    return variant_ratio(samples, "branches")


def miss_ratio(samples: DataFrame) -> DataFrame:
    return variant_ratio(samples, "mispredictions")


def miss_ratio_spread(samples: DataFrame) -> DataFrame:
    """Spread of the total miss ratio of a graph over predictors."""
    total = _sides(samples, "mispredictions", ["graph", "method", "predictor"]).withColumn("r", F.try_divide(F.col("conditional").cast("double"), F.col("unconditional").cast("double")))
    return total.groupBy("graph", "method").agg(F.round(F.min("r"), 6).alias("least"), F.round(F.max("r"), 6).alias("most"), F.round(F.max("r") - F.min("r"), 6).alias("spread"), F.round(F.stddev_samp("r"), 6).alias("deviation"))


def time_ratio(samples: DataFrame, metric: str = "elapsed_ns") -> DataFrame:
    """Each iteration against the fastest conditional one of its graph and method."""
    fastest = F.min(F.when(F.col("variant") == "conditional", F.col(metric))).over(W.partitionBy("graph", "method"))
    return samples.withColumn("ratio", ratio(F.col(metric), fastest)).select("graph", "method", "variant", "iteration", metric, "ratio")


def total_speedup(samples: DataFrame, metric: str = "elapsed_ns") -> DataFrame:
    """Conditional over unconditional time: above 1 the unconditional run is faster."""
    return _sides(samples, metric, ["graph", "method"]).withColumn("speedup", ratio(F.col("conditional"), F.col("unconditional")))


def slowdown(samples: DataFrame, metric: str = "elapsed_ns") -> DataFrame:
    return _sides(samples, metric, ["graph", "method"]).withColumn("slowdown", ratio(F.col("unconditional"), F.col("conditional")))


def store_growth(samples: DataFrame) -> DataFrame:
    return _sides(samples, "stores", ["graph", "method"]).withColumn("growth", ratio(F.col("unconditional"), F.col("conditional")))


def per_edge(samples: DataFrame, metrics: list[str]) -> DataFrame:
    """Metrics divided by traversed edges, as ``<metric>_per_edge``; null where none was traversed."""
    return samples.select("graph", "method", "variant", "iteration", "edges_traversed", *(ratio(F.col(m), F.col("edges_traversed")).alias(f"{m}_per_edge") for m in metrics))


def cc_bounds(samples: DataFrame) -> DataFrame:
    """Total misses against one for each vertex and sweep."""
    total = samples.where("method = 'cc'").groupBy("graph", "method", "variant").agg(F.sum("mispredictions").alias("mispredictions"), F.sum("vertices_active").alias("lower"))
    return total.withColumn("ratio_lower", ratio(F.col("mispredictions"), F.col("lower")))


def bfs_bounds(samples: DataFrame, constant: int = 0) -> DataFrame:
    """Total misses against one and three (plus ``constant``) for each reached vertex."""
    total = samples.where("method = 'bfs'").groupBy("graph", "method", "variant").agg(F.sum("mispredictions").alias("mispredictions"), F.sum("vertices_active").alias("lower"))
    total = total.withColumn("upper", 3 * F.col("lower") + constant)
    return total.withColumn("ratio_lower", ratio(F.col("mispredictions"), F.col("lower"))).withColumn("ratio_upper", ratio(F.col("mispredictions"), F.col("upper")))


def crossover(samples: DataFrame, metric: str, extra: list[str] | None = None) -> DataFrame:
    """First iteration from which conditional is never worse again, and how often the better side changes."""
    keys = ["graph", "method", *(extra or [])]
    own = W.partitionBy(*keys).orderBy("iteration")
    sides = _sides(samples, metric, [*keys, "iteration"]).withColumn("gain", F.col("unconditional") - F.col("conditional"))
    rest = sides.withColumn("least_rest", F.min("gain").over(own.rowsBetween(0, W.unboundedFollowing))).withColumn("sign", F.signum("gain"))
    turned = rest.withColumn("turn", (F.coalesce(F.lag("sign").over(own), F.col("sign")) != F.col("sign")).cast("bigint"))
    return turned.groupBy(*keys).agg(F.min(F.when(F.col("least_rest") >= 0, F.col("iteration"))).alias("crossover"), F.sum("turn").alias("turns"), F.count("*").alias("iterations"))


def iteration_variation(samples: DataFrame, metric: str) -> DataFrame:
    """Standard deviation over mean of a metric over the iterations of a run."""
    m = F.col(metric).cast("double")
    return samples.groupBy("graph", "method", "variant").agg(F.count("*").alias("iterations"), F.round(F.try_divide(F.stddev_samp(m), F.avg(m)), 6).alias("variation"))


def correlation_matrix(samples: DataFrame, method: str, variant: str = "conditional", time: str = "modelled_time", metrics: list[str] | None = None) -> DataFrame:
    """``(method, row_metric, col_metric, n, r)``: Pearson's r of per-edge metrics over iterations of graphs, 15 pairs.

    Two passes, so that moments are taken around the mean; r is null if a side is constant.
    """
    metrics = metrics or METRICS
    edges = F.col("edges_traversed").cast("double")
    own = samples.where((F.col("method") == method) & (F.col("variant") == variant) & (F.col("edges_traversed") > 0))
    x = own.select(*((F.col(time if m == "time" else m).cast("double") / edges).alias(m) for m in metrics))
    mean = x.agg(*(F.avg(m).alias(f"mean_{m}") for m in metrics))
    pairs = [(a, b) for i, a in enumerate(metrics) for b in metrics[i + 1 :]]
    centred = x.crossJoin(F.broadcast(mean)).select(*((F.col(m) - F.col(f"mean_{m}")).alias(m) for m in metrics))  # one row of means
    sums = centred.agg(F.count("*").alias("n"), *(F.sum(F.col(m) * F.col(m)).alias(f"v_{m}") for m in metrics), *(F.sum(F.col(a) * F.col(b)).alias(f"c_{a}_{b}") for a, b in pairs))
    some = lambda m: F.when(F.col(f"v_{m}") > 1e-18, F.col(f"v_{m}"))
    rows = F.array(*(F.struct(F.lit(a).alias("row_metric"), F.lit(b).alias("col_metric"), F.round(F.try_divide(F.col(f"c_{a}_{b}"), F.sqrt(some(a) * some(b))), 6).alias("r")) for a, b in pairs))
    return sums.select(F.lit(method).alias("method"), "n", F.explode(rows).alias("x")).select("method", "x.row_metric", "x.col_metric", "n", "x.r")


def rank_time_predictors(correlations: DataFrame) -> DataFrame:
    """Which counter goes with time: rank by the size of r."""
    own = W.partitionBy("method").orderBy(F.desc_nulls_last(F.abs("r")))
    return correlations.where("row_metric = 'time'").select("method", F.col("col_metric").alias("metric"), "r", F.rank().over(own).alias("rank"))


def scatter_points(samples: DataFrame, x: str, y: str) -> DataFrame:
    edges = F.col("edges_traversed").cast("double")
    return samples.where("edges_traversed > 0").select("graph", "method", "variant", "iteration", F.round(F.col(x) / edges, 6).alias("x"), F.round(F.col(y) / edges, 6).alias("y"))


def counter_cube(samples: DataFrame) -> DataFrame:
    """Totals over every combination of graph, method and variant; ``level`` tells which are summed over."""
    return samples.cube("graph", "method", "variant").agg(F.grouping_id().cast("bigint").alias("level"), F.sum("branches").alias("branches"), F.sum("mispredictions").alias("mispredictions"), F.sum("stores").alias("stores"))


def counter_rollup(samples: DataFrame) -> DataFrame:
    return samples.rollup("graph", "method", "variant").agg(F.grouping_id().cast("bigint").alias("level"), F.sum("branches").alias("branches"), F.sum("mispredictions").alias("mispredictions"))


def counter_grouping_sets(samples: DataFrame) -> DataFrame:
    """Totals by graph and by method and variant, in one pass."""
    sets = [[F.col("graph")], [F.col("method"), F.col("variant")]]
    return samples.groupingSets(sets, "graph", "method", "variant").agg(F.sum("branches").alias("branches"), F.sum("mispredictions").alias("mispredictions"))
