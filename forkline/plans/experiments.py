"""Experiments: each measure of the study over workloads, as a DataFrame. X1 to X15."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.functions.selection import ratio
from forkline.graph import Graph, degrees, inventory
from forkline.operators import measures as m
from forkline.operators.bfs import bfs_conditional, diameter_lower_bound, eccentricity, pick_root
from forkline.operators.blocks import Laid
from forkline.operators.components import CCRun, SwitchPolicy, components_hybrid, components_in_place, components_unconditional, init_labels
from forkline.operators.counters import Profile, Weights, bfs_site_stats, cc_site_stats, elapsed_frame, modelled_time, samples_of, unconditional_sites
from forkline.operators.predictor import PredictorSpec, miss_rates, nested_loop_misses, one_bit, saturating, static, two_bit
from forkline.plans.workloads import WORKLOADS, build
from forkline.sources.tables import load, stored

#: A graph of each kind of the study: sparse matrix, partitioning mesh, collaboration, clustering, and a tree; whole workloads.
TRACED = ("part_supplier_matrix", "order_mesh", "supplier_co_order", "bulk_supplier_part", "supplier_geo_tree")
PROFILES = (Profile("balanced"), Profile("deep-pipeline", per_miss=24.0, wrong_path=3.0), Profile("narrow", per_instruction=2.0, per_miss=8.0, per_store=4.0))
POLICIES = (SwitchPolicy.at_iteration(2), SwitchPolicy.changed_fraction(0.1), SwitchPolicy.test_miss_rate(0.1), SwitchPolicy.modelled_cost(2.0, 14.0))

#: Graphs, runs and site statistics (some dozens of rows each) that this application has made: many measures look at one study.
_KEPT: dict[tuple, object] = {}


def _kept(spark: SparkSession, key: tuple, make: Callable[[], object]) -> object:
    key = (spark.sparkContext.applicationId, *key)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return _kept(spark, (sf_dir, name, "graph"), lambda: build(name, spark, sf_dir))


def laid(spark: SparkSession, sf_dir: str, name: str) -> Laid:
    """A graph in blocks, straight from its pairs: its edges are not written for it."""
    return _kept(spark, (sf_dir, name, "laid"), lambda: Laid(WORKLOADS[name](spark, sf_dir)))


def run_of(spark: SparkSession, sf_dir: str, name: str, order: str = "sync") -> CCRun:
    """A component run with the labels of every sweep."""
    g = graph(spark, sf_dir, name)
    return _kept(spark, (sf_dir, name, order), lambda: components_in_place(g) if order == "inplace" else components_unconditional(g, keep_history=True))


def sites(spark: SparkSession, sf_dir: str, name: str, method: str, spec: PredictorSpec | None = None, order: str = "sync", among: Sequence[PredictorSpec] = ()) -> DataFrame:
    """Site statistics of the conditional kernel. Those of the predictors ``among`` which ``spec`` will be asked for are made in the same pass."""
    spec, own = spec or two_bit(), laid(spark, sf_dir, name)
    key = lambda s: (sf_dir, name, method, s, order)

    def make() -> DataFrame:
        new = [s for s in dict.fromkeys((spec, *among)) if (spark.sparkContext.applicationId, *key(s)) not in _KEPT]
        g = graph(spark, sf_dir, name) if own.has_hub else WORKLOADS[name](spark, sf_dir)
        found = stored(cc_site_stats(g, "conditional", new, order, laid=own) if method == "cc" else bfs_site_stats(g, "conditional", new, laid=own), "sites")
        for s in new[1:]:
            _kept(spark, key(s), lambda s=s: found.where(F.col("predictor") == s.name))
        return found.where(F.col("predictor") == spec.name)

    return _kept(spark, key(spec), make)


def samples(spark: SparkSession, sf_dir: str, names: Sequence[str] = TRACED, methods: Sequence[str] = ("cc", "bfs"), bits: int = 2, order: str = "sync", among: Sequence[PredictorSpec] = ()) -> DataFrame:
    out = None
    for name in names:
        for method in methods:
            one = sites(spark, sf_dir, name, method, saturating(bits), order, among)
            both = one.unionByName(unconditional_sites(one))
            out = both if out is None else out.unionByName(both)
    return samples_of(out)


def timed(spark: SparkSession, sf_dir: str, method: str, names: Sequence[str] = TRACED) -> DataFrame:
    """Samples with the elapsed time of this engine's own iterations."""
    out = None
    for name in names:
        one = elapsed_frame(spark, graph(spark, sf_dir, name), method)
        out = one if out is None else out.unionByName(one)
    return stored(out, "elapsed")


def x1_cc_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.time_ratio(timed(spark, sf_dir, "cc"))


def x2_cc_branches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.branch_ratio(samples(spark, sf_dir, methods=("cc",)))


def x3_cc_mispredictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.miss_ratio(samples(spark, sf_dir, methods=("cc",)))


def x4_bfs_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.time_ratio(timed(spark, sf_dir, "bfs"))


def x5_bfs_branches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.branch_ratio(samples(spark, sf_dir, methods=("bfs",)))


def x6_bfs_mispredictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.miss_ratio(samples(spark, sf_dir, methods=("bfs",)))


def x7_cc_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.cc_bounds(samples(spark, sf_dir, methods=("cc",)))


def x8_bfs_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.bfs_bounds(samples(spark, sf_dir, methods=("bfs",)))


def _correlation(spark: SparkSession, sf_dir: str, method: str) -> DataFrame:
    return m.correlation_matrix(modelled_time(samples(spark, sf_dir, methods=(method,)), PROFILES[:1]), method)


def x9_cc_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _correlation(spark, sf_dir, "cc")


def x10_bfs_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _correlation(spark, sf_dir, "bfs")


def x11_stores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.store_growth(samples(spark, sf_dir))


def x12_crossover(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.crossover(modelled_time(samples(spark, sf_dir), PROFILES), "modelled_time", ["profile"])


def x12_hybrid(spark: SparkSession, sf_dir: str, name: str = "bulk_supplier_part") -> DataFrame:
    """Sweeps of the hybrid under each policy that counts decide: discipline, changes, and rows written."""
    out = None
    for policy in POLICIES:
        one = components_hybrid(graph(spark, sf_dir, name), policy).sweep_frame(spark).drop("elapsed_ns").withColumn("policy", F.lit(policy.name))
        out = one if out is None else out.unionByName(one)
    return out


def x12_hybrid_by_time(spark: SparkSession, sf_dir: str, name: str = "bulk_supplier_part") -> DataFrame:
    """Sweeps of the hybrid that switches by its own elapsed times."""
    return components_hybrid(graph(spark, sf_dir, name), SwitchPolicy.measured_time()).sweep_frame(spark)


def x13_inventory(spark: SparkSession, sf_dir: str, names: Sequence[str] = tuple(WORKLOADS)) -> DataFrame:
    return inventory(WORKLOADS[n](spark, sf_dir) for n in names)  # counted as plans, none is written


def x13_profiles(spark: SparkSession, sf_dir: str, name: str = "bulk_order_part") -> DataFrame:
    """The stand-ins for machines: weights of modelled time, the predictor, and what one walk through all adjacencies of a graph costs on each."""
    g, weights = graph(spark, sf_dir, name), Weights()
    degree = degrees(g)
    n, adjacent = g.vertices.count(), g.edges.count()
    missed = {p: nested_loop_misses(degree, "id", p) for p in {p.predictor for p in PROFILES}}
    work = weights.branch * (n + adjacent) + weights.load * adjacent
    rows = [(p.name, p.predictor.name, p.per_instruction, p.per_miss, p.per_load, p.per_store, p.wrong_path, n + adjacent, missed[p.predictor], p.per_instruction * work + p.per_miss * missed[p.predictor] + p.per_load * adjacent) for p in PROFILES]
    return spark.createDataFrame(rows, "profile string, predictor string, per_instruction double, per_miss double, per_load double, per_store double, wrong_path double, branches bigint, mispredictions bigint, modelled_time double")


def loop_trips(spark: SparkSession, sf_dir: str, name: str = "with_isolated") -> DataFrame:
    """``(trips)``: how often the neighbour loops of a graph's vertices run, each count once."""
    return degrees(graph(spark, sf_dir, name)).select(F.col("degree").alias("trips")).distinct()


def supplier_rates(spark: SparkSession, sf_dir: str, min_quantity: float = 45) -> DataFrame:
    """``(supplier, p, one_bit, two_bit)``: the share of a supplier's lines that pass the test on quantity, and the stationary miss rates of that test."""
    lines = load(spark, sf_dir, "lineitem", ["l_suppkey", "l_quantity"])
    bulk = F.sum((F.col("l_quantity") >= min_quantity).cast("bigint")).cast("double") / F.count("*").cast("double")
    return miss_rates(lines.groupBy(F.col("l_suppkey").alias("supplier")).agg(bulk.alias("p")))


def x14_predictors(spark: SparkSession, sf_dir: str, names: Sequence[str] = ("bulk_supplier_part", "supplier_co_order")) -> DataFrame:
    """Misses of each site of both kernels under several predictors."""
    out, specs = None, (one_bit(), two_bit(), saturating(3), static(True), static(False))
    for name in names:
        for method in ("cc", "bfs"):
            for spec in specs:
                one = sites(spark, sf_dir, name, method, spec, among=specs).groupBy("graph", "method", "predictor", "site").agg(F.sum("evaluations").alias("evaluations"), F.sum("mispredictions").alias("mispredictions"))
                out = one if out is None else out.unionByName(one)
    return out


def x15_propagation(spark: SparkSession, sf_dir: str, name: str = "bulk_supplier_part") -> DataFrame:
    """``(sweep, id, component)``: labels before the first and after each sweep."""
    rows = run_of(spark, sf_dir, name).before_and_after(spark).select(F.col("iteration").alias("sweep"), "id", F.col("after").alias("component"))
    return init_labels(graph(spark, sf_dir, name)).select(F.lit(0).alias("sweep"), "id", "component").unionByName(rows)


def totals_in_place(spark: SparkSession, sf_dir: str, names: Sequence[str] = ("bulk_order_part", "part_supplier_matrix", "supplier_co_order")) -> DataFrame:
    """Sums over the sweeps of the kernel in its own, sequential order, against the bound of one miss a vertex and sweep."""
    found = samples(spark, sf_dir, names, ("cc",), order="inplace")
    total = found.groupBy("graph", "variant").agg(F.max("iteration").alias("sweeps"), *(F.sum(c).alias(c) for c in ("branches", "mispredictions", "stores")), F.sum("vertices_active").alias("lower"))
    return total.withColumn("ratio_lower", ratio(F.col("mispredictions"), F.col("lower")))


def select_styles(spark: SparkSession, sf_dir: str, names: Sequence[str] = TRACED) -> DataFrame:
    """Modelled instructions of the unconditional kernels by the form of their selection."""
    out = None
    for name in names:
        for method in ("cc", "bfs"):
            for style in ("least", "mask", "case"):
                one = samples_of(unconditional_sites(sites(spark, sf_dir, name, method)), weights=Weights(), select_style=style)
                total = one.groupBy("graph", "method").agg(F.lit(style).alias("style"), F.sum("instructions").alias("instructions"))
                out = total if out is None else out.unionByName(total)
    return out


def search_levels(spark: SparkSession, sf_dir: str, name: str = "bulk_supplier_part") -> DataFrame:
    return bfs_conditional(graph(spark, sf_dir, name)).levels()


def predictor_band(spark: SparkSession, sf_dir: str, names: Sequence[str] = TRACED) -> DataFrame:
    """Spread of the miss ratio of each graph over one-, two- and three-bit counters, the axis that differs between machines here."""
    out = None
    for bits in (1, 2, 3):
        one = samples(spark, sf_dir, names, ("cc",), bits, among=[saturating(b) for b in (1, 2, 3)])
        out = one if out is None else out.unionByName(one)
    return m.miss_ratio_spread(out)


def modelled_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    timed_ = modelled_time(samples(spark, sf_dir), PROFILES)
    total = timed_.groupBy("graph", "method", "profile").pivot("variant", m.VARIANTS).agg(F.sum("modelled_time"))
    return total.withColumn("speedup", ratio(F.col("conditional"), F.col("unconditional")))


def slowdown_and_growth(spark: SparkSession, sf_dir: str, cap: float = 2.0) -> DataFrame:
    """Searches: how much slower the unconditional one is in modelled time, how much more it stores, and whether the slowdown stays below ``cap``."""
    own = modelled_time(samples(spark, sf_dir, methods=("bfs",)), PROFILES)
    total = own.groupBy("graph", "profile").agg(*(F.sum(F.when(F.col("variant") == v, F.col(c))).alias(f"{c}_{v[0]}") for v in m.VARIANTS for c in ("modelled_time", "stores")))
    found = total.select("graph", "profile", ratio(F.col("modelled_time_u"), F.col("modelled_time_c")).alias("slowdown"), ratio(F.col("stores_u"), F.col("stores_c")).alias("growth"))
    return found.withColumn("within_cap", F.col("slowdown") <= cap)


def work_constancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adjacencies that the sweeps of each component run traverse: least, most, and whether all sweeps do equal work."""
    found = samples(spark, sf_dir, methods=("cc",)).groupBy("graph", "variant").agg(F.count("*").alias("sweeps"), F.min("edges_traversed").alias("least"), F.max("edges_traversed").alias("most"))
    return found.withColumn("constant", F.col("least") == F.col("most"))


def depth_bounds(spark: SparkSession, sf_dir: str, names: Sequence[str] = ("bulk_supplier_part", "order_mesh")) -> DataFrame:
    """``(graph, root, eccentricity, diameter_least)``: depth from the least id, and from a vertex farthest from it."""
    rows = []
    for name in names:
        g = graph(spark, sf_dir, name)
        root = pick_root(g)
        rows.append((name, root, eccentricity(g, root), diameter_lower_bound(g, root)))
    return spark.createDataFrame(rows, "graph string, root bigint, eccentricity int, diameter_least int")


def root_choice(spark: SparkSession, sf_dir: str, names: Sequence[str] = TRACED) -> DataFrame:
    rows = [(n, how, pick_root(graph(spark, sf_dir, n), how)) for n in names for how in ("min_id", "max_degree")]
    return spark.createDataFrame(rows, "graph string, how string, root bigint")


EXPERIMENTS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (x1_cc_time, x2_cc_branches, x3_cc_mispredictions, x4_bfs_time, x5_bfs_branches, x6_bfs_mispredictions, x7_cc_bounds, x8_bfs_bounds, x9_cc_correlation, x10_bfs_correlation, x11_stores, x12_crossover, x12_hybrid, x12_hybrid_by_time, x13_inventory, x14_predictors, x15_propagation)
}


def experiment(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return EXPERIMENTS[name](spark, sf_dir)
