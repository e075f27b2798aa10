"""Modelled counters of the sequential kernels: evaluations, misses, loads, stores, and linear costs.

``site_stats`` has a row for each branch site and iteration; ``samples`` one for each
iteration. Both are exact for the named predictor; each site starts in the predictor's start
state and keeps its state over the whole run. Elapsed times are the engine's own.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.graph import Graph, degrees
from forkline.operators.bfs import bfs_conditional, bfs_unconditional, pick_root, queue_order
from forkline.operators.blocks import Laid, component_run, search_run
from forkline.operators.components import CCRun, components_conditional, components_in_place, components_unconditional
from forkline.operators.folding import composed, even_bounds, fold_in_order, ranges_for
from forkline.operators.predictor import PredictorSpec, compose_ordered, identity, run_function, then, two_bit, walk
from forkline.operators.trace import bfs_test_fold, cc_test_fold
from forkline.sources.tables import stored

SITE_SCHEMA = "graph string, method string, variant string, order string, predictor string, iteration int, site string, evaluations bigint, taken bigint, mispredictions bigint"


@dataclass(frozen=True)
class Profile:
    """Stand-in for a machine: a predictor and the weights of a linear time. Weights are ours, not measured hardware."""

    name: str
    per_instruction: float = 1.0
    per_miss: float = 14.0
    per_load: float = 2.0
    per_store: float = 2.0
    wrong_path: float = 0.0
    predictor: PredictorSpec = two_bit()


#: Instructions charged to a branch, a load, a store, and to a selection without a branch.
@dataclass(frozen=True)
class Weights:
    branch: int = 2
    load: int = 1
    store: int = 1
    select: int = 1


SELECT_INSTRUCTIONS = {"least": 1, "case": 1, "mask": 9}


class _Site:
    """A site's state along the run."""

    def __init__(self, spec: PredictorSpec):
        self.spec, self.state = spec, spec.start

    def pass_(self, f: list[int]) -> int:
        code = f[self.state]
        self.state = code % self.spec.states
        return code // self.spec.states


#: Messages that one job folds at least, if so many sweeps are left, and sweeps of one job at most.
JOB_MESSAGES, JOB_SWEEPS = 200_000_000, 64


def _specs(spec: PredictorSpec | Iterable[PredictorSpec] | None) -> tuple[PredictorSpec, ...]:
    return (spec or two_bit(),) if spec is None or isinstance(spec, PredictorSpec) else tuple(spec)


def _composed(folded: DataFrame, specs: tuple[PredictorSpec, ...]) -> dict[tuple[int, str], tuple[list[int], int]]:
    """``(iteration, predictor)`` to function and number of taken tests, of ranges or of pieces of hubs."""
    if "part" in folded.columns:
        return {k: (f, taken) for k, (f, _, taken) in composed(folded, specs).items()}
    out, pieces = {}, stored(folded, "trace")
    taken = {(r["iteration"], r["predictor"]): r["taken"] for r in pieces.groupBy("iteration", "predictor").agg(F.sum("taken").alias("taken")).collect()}
    for spec in specs:
        own = compose_ordered(pieces.where(F.col("predictor") == spec.name), ["iteration"], ["seq_hi", "chunk"], spec)
        out |= {(i, spec.name): (f, taken[i, spec.name]) for (i,), f in own.items()}
    return out


def cc_site_stats(g: Graph, variant: str = "conditional", spec: PredictorSpec | Iterable[PredictorSpec] | None = None, order: str = "sync", run: CCRun | None = None, laid: Laid | None = None) -> DataFrame:
    """Sites ``cc.sweep``, ``cc.vertex``, ``cc.neighbor`` and, if conditional, ``cc.test``; an iteration is a sweep.

    ``order`` is ``sync`` or ``inplace``. Several predictors share one pass over the traces.
    Sweeps are made and folded by blocks, see ``blocks``. If a run with history is given, or a
    vertex is larger than a block, they are folded from the run's epochs, as many in a job as
    make ``JOB_MESSAGES``, so what a job shuffles does not grow with the number of sweeps.
    """
    if order not in ("sync", "inplace"):
        raise ValueError("order must be sync or inplace")
    specs = _specs(spec)
    spark = g.edges.sparkSession
    found = component_run(g, specs, order, laid) if run is None else None
    if found is not None:
        rows = []
        for s in specs:
            own = {i: (f[s.name], taken) for i, (f, taken) in enumerate(found.tests, 1)} if variant == "conditional" else {}
            rows += _cc_rows(g.name, variant, order, s, len(found.changed), found.n, found.adjacent, found.loops[s.name], own)
        return spark.createDataFrame(rows, SITE_SCHEMA)
    run = run or (components_unconditional(g, keep_history=True) if order == "sync" else components_in_place(g))
    sweeps = len(run.sweeps)
    n, adjacent = g.vertices.count(), g.edges.count()
    step = max(1, min(JOB_SWEEPS, JOB_MESSAGES // max(1, adjacent)))
    bounds = even_bounds(g.edges, "src", ranges_for((adjacent + n) * min(step, sweeps)))
    trips = degrees(g).select(F.lit(0).alias("iteration"), "id", F.col("degree").alias("x"))
    loops = composed(fold_in_order(trips, ["id"], bounds, specs, loops=True), specs)
    tests: dict[tuple[int, str], tuple[list[int], int]] = {}
    if variant == "conditional":
        history = run.before_and_after(spark)
        for first in range(1, sweeps + 1, step):
            iterations = list(range(first, min(sweeps, first + step - 1) + 1))
            some = history.where(F.col("iteration").between(first, iterations[-1]))
            found = _composed(cc_test_fold(g.edges, some, specs, order, iterations, bounds), specs)
            tests |= {(i, s.name): found.get((i, s.name), (identity(s), 0)) for i in iterations for s in specs}
    rows = []
    for s in specs:
        own = {i: test for (i, name), test in tests.items() if name == s.name}
        rows += _cc_rows(g.name, variant, order, s, sweeps, n, adjacent, loops[0, s.name][0] if n else identity(s), own)
    return spark.createDataFrame(rows, SITE_SCHEMA)


def _cc_rows(graph: str, variant: str, order: str, spec: PredictorSpec, sweeps: int, n: int, adjacent: int, loops: list[int], tests: dict[int, tuple[list[int], int]]) -> list[tuple]:
    site = {s: _Site(spec) for s in ("cc.sweep", "cc.vertex", "cc.neighbor", "cc.test")}
    again, leave = walk([True], spec), walk([False], spec)
    vertices = then(run_function(n, True, spec), leave, spec)
    head = (graph, "cc", variant, order, spec.name)
    rows = []
    for i in range(1, sweeps + 1):
        last = i == sweeps
        missed = site["cc.sweep"].pass_(again) + (site["cc.sweep"].pass_(leave) if last else 0)
        rows.append((*head, i, "cc.sweep", 1 + last, 1, missed))
        rows.append((*head, i, "cc.vertex", n + 1, n, site["cc.vertex"].pass_(vertices)))
        rows.append((*head, i, "cc.neighbor", n + adjacent, adjacent, site["cc.neighbor"].pass_(loops)))
        if i in tests:
            rows.append((*head, i, "cc.test", adjacent, tests[i][1], site["cc.test"].pass_(tests[i][0])))
    return rows


def bfs_site_stats(g: Graph, variant: str = "conditional", spec: PredictorSpec | Iterable[PredictorSpec] | None = None, root: int | None = None, queue: DataFrame | None = None, laid: Laid | None = None) -> DataFrame:
    """Sites ``bfs.queue``, ``bfs.neighbor`` and, if conditional, ``bfs.test``; an iteration is a level, from 0."""
    specs = _specs(spec)
    spark = g.edges.sparkSession
    if queue is None and root is None and laid is not None and laid.least is not None:
        root, levels = laid.least, search_run(g, specs, laid.least, laid)
    else:
        levels = search_run(g, specs, pick_root(g) if root is None else pick_root(g, root), laid) if queue is None else None
    if levels is not None:
        loops = {(i, s.name): (x.loops[s.name], x.n + x.traversed, x.traversed) for i, x in enumerate(levels) for s in specs}
        tests = {(i, s.name): (x.tests[s.name], x.taken) for i, x in enumerate(levels) for s in specs}
        return spark.createDataFrame(_bfs_rows(g.name, variant, specs, loops, tests), SITE_SCHEMA)
    queue = stored(queue if queue is not None else queue_order(g, root), "queue")
    reached, ranges = queue.count(), ranges_for(g.edges.count())
    bounds = sorted({reached * i // ranges for i in range(1, ranges)})
    trips = degrees(g).join(queue, "id").select(F.col("dist").alias("iteration"), "rank", F.col("degree").alias("x"))
    loops = composed(fold_in_order(trips, ["rank"], bounds, specs, loops=True), specs)
    tests = _composed(bfs_test_fold(queue, g.edges, specs, bounds), specs) if variant == "conditional" else {}
    return spark.createDataFrame(_bfs_rows(g.name, variant, specs, loops, tests), SITE_SCHEMA)


def _bfs_rows(graph: str, variant: str, specs: tuple[PredictorSpec, ...], loops: dict[tuple[int, str], tuple[list[int], int, int]], tests: dict[tuple[int, str], tuple[list[int], int]]) -> list[tuple]:
    leave, rows = {s: walk([False], s) for s in specs}, []
    last = max(level for level, _ in loops)
    for s in specs:
        site = {x: _Site(s) for x in ("bfs.queue", "bfs.neighbor", "bfs.test")}
        head = (graph, "bfs", variant, "queue", s.name)
        for level in sorted({level for level, _ in loops}):
            loop, evaluations, traversed = loops[level, s.name]
            n = evaluations - traversed
            missed = site["bfs.queue"].pass_(run_function(n, True, s)) + (site["bfs.queue"].pass_(leave[s]) if level == last else 0)
            rows.append((*head, level, "bfs.queue", n + (level == last), n, missed))
            rows.append((*head, level, "bfs.neighbor", evaluations, traversed, site["bfs.neighbor"].pass_(loop)))
            if variant == "conditional":
                test, taken = tests.get((level, s.name), (identity(s), 0))
                rows.append((*head, level, "bfs.test", traversed, taken, site["bfs.test"].pass_(test)))
    return rows


def samples_of(sites: DataFrame, elapsed: DataFrame | None = None, weights: Weights = Weights(), select_style: str = "least") -> DataFrame:
    """One row for each run and iteration: active vertices, edges, changes, instructions, branches, misses, loads, stores.

    Stores: conditional components write each improvement of a running minimum, unconditional
    ones every vertex; a conditional search writes distance and queue slot of a discovery, an
    unconditional one both for every adjacency. Loads: a label for each vertex and adjacency;
    a queue slot for each vertex and a distance for each adjacency.
    """
    keys = ["graph", "method", "variant", "order", "predictor", "iteration"]
    of = lambda site, what: F.sum(F.when(F.col("site").endswith(site), F.col(what)).otherwise(0))
    m = sites.groupBy(*keys).agg(
        F.sum("evaluations").alias("branches"), F.sum("mispredictions").alias("mispredictions"), of(".neighbor", "taken").alias("edges_traversed"), of(".vertex", "taken").alias("v"), of(".queue", "taken").alias("q"), of(".test", "taken").alias("changed")
    )
    active = F.col("v") + F.col("q")
    stores = (
        F.when((F.col("method") == "cc") & (F.col("variant") == "conditional"), F.col("changed"))
        .when(F.col("method") == "cc", F.col("v"))
        .when(F.col("variant") == "conditional", 2 * F.col("changed"))
        .otherwise(2 * F.col("edges_traversed"))
    )
    loads = active + F.col("edges_traversed")
    selections = F.when(F.col("variant") == "conditional", 0).otherwise(F.col("edges_traversed")) * (weights.select * SELECT_INSTRUCTIONS[select_style])
    out = m.select(*keys, active.alias("vertices_active"), "edges_traversed", "changed", "branches", "mispredictions", loads.alias("loads"), stores.alias("stores"), selections.alias("selections"))
    out = out.withColumn("instructions", (weights.branch * F.col("branches") + weights.load * F.col("loads") + weights.store * F.col("stores") + F.col("selections")).cast("bigint")).drop("selections")
    if elapsed is None:
        return out.withColumn("elapsed_ns", F.lit(None).cast("bigint"))
    return out.join(elapsed, ["graph", "method", "variant", "iteration"], "left")


def modelled_time(samples: DataFrame, profiles: Iterable[Profile]) -> DataFrame:
    """Samples by profile with ``modelled_time`` and ``dispatched``, the branches with those of wrong paths."""
    spark = samples.sparkSession
    rows = [(p.name, float(p.per_instruction), float(p.per_miss), float(p.per_load), float(p.per_store), float(p.wrong_path), p.predictor.name) for p in profiles]
    frame = F.broadcast(spark.createDataFrame(rows, "profile string, a double, b double, c double, d double, w double, predictor string"))  # a row a profile
    met = samples.join(frame, "predictor")
    time = F.col("a") * F.col("instructions") + F.col("b") * F.col("mispredictions") + F.col("c") * F.col("loads") + F.col("d") * F.col("stores")
    return met.select(*samples.columns, "profile", F.round(time, 6).alias("modelled_time"), F.round(F.col("branches") + F.col("w") * F.col("mispredictions"), 6).alias("dispatched"))


def elapsed_frame(spark: SparkSession, g: Graph, method: str, repeats: int = 1) -> DataFrame:
    """Wall time of each iteration of both variants on this engine, the least of ``repeats`` runs."""
    best: dict[tuple[str, int], int] = {}
    for _ in range(repeats):
        for variant in ("conditional", "unconditional"):
            if method == "cc":
                run = components_conditional(g) if variant == "conditional" else components_unconditional(g)
                steps = [(s.iteration, s.elapsed_ns) for s in run.sweeps]
            else:
                search = bfs_conditional(g) if variant == "conditional" else bfs_unconditional(g)
                steps = [(s.level, s.elapsed_ns) for s in search.steps]
            for i, ns in steps:
                best[variant, i] = min(ns, best.get((variant, i), ns))
    return spark.createDataFrame([(g.name, method, v, i, ns) for (v, i), ns in best.items()], "graph string, method string, variant string, iteration int, elapsed_ns bigint")


def unconditional_sites(conditional: DataFrame) -> DataFrame:
    """The sites of the unconditional kernel: those of the conditional one without its test."""
    return conditional.where(~F.col("site").endswith(".test")).withColumn("variant", F.lit("unconditional"))


def collect_sites(graphs: Iterable[Graph], methods: Iterable[str] = ("cc", "bfs"), spec: PredictorSpec | None = None) -> DataFrame:
    """Site statistics of all graphs and methods, both variants, under one predictor."""
    out = None
    for g in graphs:
        for method in methods:
            one = stored(cc_site_stats(g, "conditional", spec) if method == "cc" else bfs_site_stats(g, "conditional", spec), "sites")
            both = one.unionByName(unconditional_sites(one))
            out = both if out is None else out.unionByName(both)
    return out


def collect_samples(graphs: Iterable[Graph], methods: Iterable[str] = ("cc", "bfs"), spec: PredictorSpec | None = None) -> DataFrame:
    """Samples of all graphs, methods and variants under one predictor."""
    return samples_of(collect_sites(graphs, methods, spec))


def verify_counters(g: Graph, sites: DataFrame) -> DataFrame:
    """Violations of the closed forms of evaluations; no rows if all hold."""
    n, adjacent = g.vertices.count(), degrees(g).agg(F.sum("degree").alias("d")).first()["d"] or 0
    cc = sites.where("method = 'cc'")
    rules = (
        F.when((F.col("site") == "cc.vertex") & (F.col("evaluations") != n + 1), "vertex loop").when((F.col("site") == "cc.neighbor") & (F.col("evaluations") != n + adjacent), "neighbour loop").when((F.col("site") == "cc.test") & (F.col("evaluations") != adjacent), "test")
    )
    return cc.withColumn("rule", rules).where("rule IS NOT NULL").select("graph", "iteration", "site", "rule")
