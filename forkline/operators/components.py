"""Connected components by minimum-label propagation, in synchronous sweeps.

Two disciplines compute the same labels after every sweep:

* conditional: test first, write the improvements only (a sparse delta each sweep);
* unconditional: take the minimum of every vertex and write every label; no filter and no
  anti-join is in the plan, and a change shows in the OR of the XORs of new and old labels.

A conditional sweep is one action: it writes an epoch to the shared folder and observes its
own metrics on the way. Unconditional sweeps read the labels once each, by way of a loop at
every vertex, so ``unroll`` of them are one action that shuffles the edges once; each has
metrics of its own. Plans stay short and a lost executor costs one action.

``components_in_place`` follows the sequential order, in which a sweep sees its own changes:
a vertex takes the new labels of its neighbours of smaller id and the old ones of the others.
That is a fixed point over edges that lead upwards.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from forkline.functions.selection import change_mask, smaller
from forkline.graph import Graph
from forkline.sources.tables import Epochs

#: Deltas that are merged into a new full label table at once, unconditional sweeps of one action, and edges of a block.
COMPACT_EVERY, UNROLL, BLOCK_EDGES = 8, 3, 1_000_000


@dataclass(frozen=True)
class Sweep:
    iteration: int
    discipline: str
    changed: int
    written: int
    elapsed_ns: int


@dataclass(frozen=True)
class CCRun:
    labels: DataFrame
    sweeps: list[Sweep]
    history: list[DataFrame] = field(default_factory=list)
    epochs: str | None = None  # folder of the epochs ``sweep=N(id, component, old)``, if a history is kept

    def before_and_after(self, spark: SparkSession) -> DataFrame:
        """``(iteration, id, before, after)``: the labels that each sweep found and left."""
        if self.epochs is None:
            raise ValueError("the run kept no history of full labels")
        rows = spark.read.schema("id bigint, component bigint, old bigint, sweep int").parquet(self.epochs)
        return rows.select(F.col("sweep").alias("iteration"), "id", F.col("old").alias("before"), F.col("component").alias("after"))

    def sweep_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(s.iteration, s.discipline, s.changed, s.written, s.elapsed_ns) for s in self.sweeps], "iteration int, discipline string, changed bigint, written bigint, elapsed_ns bigint")


@dataclass(frozen=True)
class SwitchPolicy:
    """Says after a sweep whether the hybrid goes on conditionally. Gets the sweeps so far and the number of vertices."""

    name: str
    switch: Callable[[list[Sweep], int], bool]

    @classmethod
    def at_iteration(cls, k: int) -> SwitchPolicy:
        return cls(f"at_iteration({k})", lambda done, _: len(done) >= k)

    @classmethod
    def changed_fraction(cls, x: float) -> SwitchPolicy:
        return cls(f"changed_fraction({x})", lambda done, n: done[-1].changed <= x * n)

    @classmethod
    def test_miss_rate(cls, x: float, steady: Callable[[float], float] | None = None) -> SwitchPolicy:
        """Switch once a two-bit predictor is expected to miss at most ``x`` of the improvement tests."""
        from forkline.operators.predictor import miss_rate_two_bit

        rate = steady or miss_rate_two_bit
        return cls(f"test_miss_rate({x})", lambda done, n: rate(min(1.0, done[-1].changed / max(1, n))) <= x)

    @classmethod
    def modelled_cost(cls, store: float, miss: float) -> SwitchPolicy:
        """Switch once the expected misses of the tests cost less than the stores that they save."""
        from forkline.operators.predictor import miss_rate_two_bit

        return cls(f"modelled_cost({store},{miss})", lambda done, n: miss * n * miss_rate_two_bit(min(1.0, done[-1].changed / max(1, n))) <= store * (n - done[-1].changed))

    @classmethod
    def measured_time(cls, drop: float = 0.9) -> SwitchPolicy:
        """Switch once a sweep no longer takes less than ``drop`` of the one before."""
        return cls(f"measured_time({drop})", lambda done, _: len(done) > 1 and done[-1].elapsed_ns > drop * done[-2].elapsed_ns)


def init_labels(g: Graph) -> DataFrame:
    return g.vertices.select("id", F.col("id").alias("component"))


def _messages(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """What each vertex hears: the label of the far end of each of its edges."""
    return edges.join(labels, edges["dst"] == labels["id"]).select(F.col("src").alias("id"), F.col("component").alias("heard"))


def closed(g: Graph) -> DataFrame:
    """Edges and a loop at every vertex, by which a vertex hears its own label too."""
    return g.edges.select("src", "dst").unionByName(g.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst")))


def sweep_unconditional(edges: DataFrame, labels: DataFrame, select_style: str = "least") -> DataFrame:
    """``(id, component, old)`` of every vertex after a sweep; ``edges`` are closed."""
    heard = edges.join(labels.select(F.col("id").alias("dst"), "component"), "dst")
    own = F.col("src") == F.col("dst")
    met = heard.groupBy(F.col("src").alias("id")).agg(F.min("component").alias("heard"), F.max(F.when(own, F.col("component"))).alias("old"))
    return met.select("id", smaller(F.col("old"), F.col("heard"), select_style).alias("component"), "old")


def sweep_conditional(edges: DataFrame, labels: DataFrame, speaking: DataFrame | None = None) -> DataFrame:
    """``(id, component)`` of the vertices that improve; ``speaking`` are the labels that are sent (all by default)."""
    heard = _messages(edges, labels if speaking is None else speaking).groupBy("id").agg(F.min("heard").alias("heard"))
    return heard.join(labels, "id").where(F.col("heard") < F.col("component")).select("id", F.col("heard").alias("component"))


def _jump(labels: DataFrame, style: str = "least") -> DataFrame:
    """Labels replaced by the label of the label, with ``old`` kept if there is one."""
    beyond = labels.select(F.col("id").alias("component"), F.col("component").alias("beyond"))
    jumped = labels.join(beyond, "component", "left")
    extra = ["old"] if "old" in labels.columns else []
    return jumped.select("id", smaller(F.col("component"), F.coalesce("beyond", "component"), style).alias("component"), *extra)


class _Loop:
    """State of a run: full labels, deltas on top of them, and what the last sweep changed."""

    def __init__(self, g: Graph, keep: bool):
        self.g, self.keep = g, keep
        self.epochs = Epochs(g.edges.sparkSession, "components")
        self.base = init_labels(g)
        self.deltas: list[DataFrame] = []
        self.changed: DataFrame | None = None  # None: all
        self.sweeps: list[Sweep] = []
        self.history: list[DataFrame] = []
        self.stale: list[str] = []  # epochs that the next full label table replaces

    def _put(self, name: str, df: DataFrame, full: bool) -> DataFrame:
        """Write an epoch; a full table of labels makes those before it stale, which then go."""
        written = self.epochs.put(name, df)
        if full:
            if not self.keep:
                self.epochs.drop(*self.stale)
            self.stale = []
        self.stale.append(name)
        return written

    def labels(self) -> DataFrame:
        """Labels only fall, so the minimum over a table and its deltas is the current one."""
        if not self.deltas:
            return self.base
        out = self.base
        for d in self.deltas:
            out = out.unionByName(d)
        return out.groupBy("id").agg(F.min("component").alias("component"))

    def _note(self, discipline: str, changed: int, written: int, elapsed_ns: int) -> bool:
        self.sweeps.append(Sweep(len(self.sweeps) + 1, discipline, changed, written, elapsed_ns))
        if self.keep:
            self.history.append(self.labels())
        return changed > 0

    def unconditional(self, shortcut: bool, style: str, most: int | None = None) -> bool:
        """Some sweeps in one action; ``most`` are allowed. Sweeps after the one that changes nothing don't count."""
        began, edges, new, seen = time.perf_counter_ns(), closed(self.g), self.labels(), []
        # a jump reads the labels twice, a history needs each sweep's, and plans of no rows lose inner metrics
        alone = shortcut or self.keep or not (self.sweeps or self.g.vertices.limit(1).count())
        unroll = 1 if alone else min(UNROLL, most or UNROLL)
        for _ in range(unroll):
            new = sweep_unconditional(edges, new, style)
            if shortcut:
                new = _jump(new, style)
            seen.append(Observation())
            new = new.observe(seen[-1], change_mask(F.col("component"), F.col("old")).alias("mask"), F.sum((F.col("component") != F.col("old")).cast("bigint")).alias("changed"), F.count("*").alias("written"))
        written = self._put(f"sweep={len(self.sweeps) + unroll}", new, True)
        self.base, self.deltas = written.select("id", "component"), []
        self.changed = written.where("component <> old").select("id", "component")
        told, each = [x.get for x in seen], (time.perf_counter_ns() - began) // unroll
        for one in told:
            if not self._note("unconditional", int(one["changed"] or 0), int(one["written"]), each) or not one["mask"]:
                return False
        return True

    def conditional(self, delta_scan: bool, shortcut: bool) -> bool:
        began, seen = time.perf_counter_ns(), Observation()
        labels = self.labels()
        delta = sweep_conditional(self.g.edges, labels, self.changed if delta_scan else None)
        if shortcut:
            merged = labels.select("id", "component", F.col("component").alias("old")).unionByName(delta.withColumn("old", F.lit(None).cast("bigint"))).groupBy("id").agg(F.min("component").alias("component"), F.max("old").alias("old"))
            delta = _jump(merged).where("component < old").select("id", "component")
        written = self._put(f"sweep={len(self.sweeps) + 1}", delta.observe(seen, F.count("*").alias("n")), False)
        n = int(seen.get["n"])
        self.changed = written
        self.deltas.append(written)
        if len(self.deltas) >= COMPACT_EVERY:
            last = self.stale.pop()  # the next sweep reads what this one changed
            self.base, self.deltas = self._put(f"labels-{len(self.sweeps) + 1}", self.labels(), True), []
            self.stale.append(last)
        return self._note("conditional", n, n, time.perf_counter_ns() - began)

    def result(self) -> CCRun:
        return CCRun(self.labels(), self.sweeps, self.history, self.epochs.root if self.keep and not self.deltas else None)


def _bounded(max_sweeps: int | None) -> Callable[[int], bool]:
    if max_sweeps is not None and max_sweeps < 0:
        raise ValueError("max_sweeps must not be negative")
    return lambda done: max_sweeps is None or done < max_sweeps


def components_unconditional(g: Graph, max_sweeps: int | None = None, shortcut: bool = False, select_style: str = "least", keep_history: bool = False) -> CCRun:
    loop, more = _Loop(g, keep_history), _bounded(max_sweeps)
    while more(len(loop.sweeps)) and loop.unconditional(shortcut, select_style, None if max_sweeps is None else max_sweeps - len(loop.sweeps)):
        pass
    return loop.result()


def components_conditional(g: Graph, scan: str = "full", max_sweeps: int | None = None, shortcut: bool = False, keep_history: bool = False) -> CCRun:
    """``scan="delta"`` sends only what the last sweep changed; the labels after each sweep are the same."""
    if scan not in ("full", "delta"):
        raise ValueError("scan must be full or delta")
    loop, more = _Loop(g, keep_history), _bounded(max_sweeps)
    while more(len(loop.sweeps)) and loop.conditional(scan == "delta", shortcut):
        pass
    return loop.result()


def components_hybrid(g: Graph, policy: SwitchPolicy | None = None, max_sweeps: int | None = None, shortcut: bool = False) -> CCRun:
    """Unconditional sweeps until ``policy`` says so, conditional ones over the changed labels from then on."""
    policy = policy or SwitchPolicy.changed_fraction(0.1)
    loop, more = _Loop(g, False), _bounded(max_sweeps)
    n = g.vertices.count()
    switched, going = False, True
    while going and more(len(loop.sweeps)):
        going = loop.conditional(True, shortcut) if switched else loop.unconditional(shortcut, "least", 1)  # the policy is asked after each
        switched = switched or policy.switch(loop.sweeps, n)
    return loop.result()


def labels_after(g: Graph, sweeps: int) -> DataFrame:
    return components_unconditional(g, max_sweeps=sweeps).labels


def distinct_labels(run: CCRun, spark: SparkSession) -> DataFrame:
    """``(iteration, labels)``: how many different labels each sweep of a run with history leaves."""
    return run.before_and_after(spark).groupBy("iteration").agg(F.countDistinct("after").alias("labels"))


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count("*").alias("size"))


def component_summary(labels: DataFrame) -> DataFrame:
    """One row: vertices, components, the largest, whether connected."""
    return component_sizes(labels).agg(F.coalesce(F.sum("size"), F.lit(0)).alias("vertices"), F.count("*").alias("components"), F.max("size").alias("largest"), (F.count("*") == 1).alias("connected"))


def top_components(labels: DataFrame, k: int) -> DataFrame:
    return component_sizes(labels).orderBy(F.desc("size"), "component").limit(k)


def count_components(labels: DataFrame) -> DataFrame:
    return labels.agg(F.countDistinct("component").alias("components"))


def approx_components(labels: DataFrame, rsd: float = 0.02) -> DataFrame:
    return labels.agg(F.approx_count_distinct("component", rsd).alias("components"))


def _climb(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """``(id, component, old, origin)`` after every vertex took the least label over ``edges``, which have a loop at each."""
    heard = edges.join(labels.select(F.col("id").alias("dst"), "component", "origin"), "dst")
    own = F.col("src") == F.col("dst")
    return heard.groupBy(F.col("src").alias("id")).agg(F.min("component").alias("component"), F.max(F.when(own, F.col("component"))).alias("old"), F.max(F.when(own, F.col("origin"))).alias("origin"))


def _in_order(edges: DataFrame, epochs: Epochs, sweep: int, labels: DataFrame) -> tuple[DataFrame, int]:
    """``(id, component, old)`` after one sweep in sequential order over ``labels``, and how many labels changed.

    First every vertex hears its larger neighbours, then labels climb from smaller to larger
    ones, ``UNROLL`` steps an action, until a step changes nothing.
    """
    now, up, part = labels.select("id", "component", F.col("component").alias("origin")), edges.where("dst <= src"), 0
    now = _climb(edges.where("dst >= src"), now)
    while True:
        for _ in range(UNROLL):
            now = _climb(up, now.select("id", "component", "origin"))
        seen, part = Observation(), part + 1
        told = now.observe(seen, F.sum((F.col("component") != F.col("old")).cast("bigint")).alias("last"), F.sum((F.col("component") != F.col("origin")).cast("bigint")).alias("changed"))
        now = epochs.put(f"part-{sweep}-{part}", told)
        if not int(seen.get["last"] or 0):
            break
    done = epochs.put(f"labels/sweep={sweep}", now.select("id", "component", F.col("origin").alias("old")))
    epochs.drop(*(f"part-{sweep}-{i}" for i in range(1, part + 1)))
    return done, int(seen.get["changed"] or 0)


def components_in_place(g: Graph, max_sweeps: int | None = None) -> CCRun:
    """Sweeps in the sequential order, vertices by ascending id, that see their own changes; any size.

    Labels after each sweep, and the number of sweeps, are those of a sequential kernel.
    """
    epochs, more, sweeps = Epochs(g.edges.sparkSession, "in-place"), _bounded(max_sweeps), []
    edges, labels, changed = closed(g), init_labels(g), 1
    while changed and more(len(sweeps)):
        began = time.perf_counter_ns()
        written, changed = _in_order(edges, epochs, len(sweeps) + 1, labels)
        labels = written.select("id", "component")
        sweeps.append(Sweep(len(sweeps) + 1, "in-place", changed, changed, time.perf_counter_ns() - began))
    return CCRun(labels, sweeps, [], f"{epochs.root}/labels")


def sequential_reference(g: Graph, conditional: bool = True) -> DataFrame:
    """The same walked by one task, for tests on small graphs: ``(id, component, sweeps, stores)``."""

    def run(t: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, list[int]] = {int(v): [] for v in t.loc[t["dst"].isna(), "src"]}
        for a, b in t.dropna().sort_values(["src", "dst"]).itertuples(index=False):
            near[int(a)].append(int(b))
        label, sweeps, stores, moved = {v: v for v in near}, 0, 0, True
        while moved:
            moved, sweeps = False, sweeps + 1
            for v in sorted(near):
                now = label[v]
                for u in near[v]:
                    if label[u] < now:
                        now = label[u]
                        stores += conditional
                stores += not conditional
                moved |= now != label[v]
                label[v] = now
        return pd.DataFrame({"id": list(label), "component": list(label.values()), "sweeps": sweeps, "stores": stores})

    rows = g.edges.select("src", "dst").unionByName(g.vertices.select(F.col("id").alias("src"), F.lit(None).cast("bigint").alias("dst")))
    return rows.groupBy(F.lit(0).alias("all")).applyInPandas(lambda t: run(t[["src", "dst"]]), "id bigint, component bigint, sweeps int, stores bigint")


def _settled(t: pa.Table) -> pa.Table:
    """Lowest labels within a block whose outside neighbours keep theirs: ``(id, heard)``."""
    src, dst, own, far = (t.column(c).to_numpy() for c in ("src", "dst", "own", "far"))
    ids, at = np.unique(src, return_inverse=True)
    label = np.full(len(ids), np.iinfo(np.int64).max)
    np.minimum.at(label, at, np.minimum(own, far))
    to = np.searchsorted(ids, dst)
    to[to == len(ids)] = 0
    inside = ids[to] == dst
    a, b = at[inside], to[inside]
    while True:
        before = label.copy()
        np.minimum.at(label, a, label[b])
        if (label == before).all():
            return pa.table({"id": ids, "heard": label})


def components_blocked(g: Graph, blocks: int | None = None, max_sweeps: int | None = None) -> CCRun:
    """Sweeps that are in place inside a block of vertices and synchronous between blocks.

    A block is a hash of ids, of about ``BLOCK_EDGES`` edges unless ``blocks`` says how many
    there are. Each task settles its own edges before labels are exchanged.
    """
    blocks = blocks or max(8, -(-g.edges.count() // BLOCK_EDGES))
    dealt = g.edges.withColumn("block", F.pmod(F.xxhash64("src"), F.lit(blocks)).cast("int"))
    loop, more = _Loop(g, False), _bounded(max_sweeps)
    while more(len(loop.sweeps)):
        began, seen = time.perf_counter_ns(), Observation()
        labels = loop.labels()
        both = dealt.join(labels.select(F.col("id").alias("dst"), F.col("component").alias("far")), "dst").join(labels.select(F.col("id").alias("src"), F.col("component").alias("own")), "src")
        heard = both.groupBy("block").applyInArrow(_settled, "id bigint, heard bigint")
        new = labels.join(heard, "id", "left").select("id", F.least("component", F.coalesce("heard", "component")).alias("component"), F.col("component").alias("old"))
        written = loop._put(f"sweep={len(loop.sweeps) + 1}", new.observe(seen, F.sum((F.col("component") != F.col("old")).cast("bigint")).alias("changed"), F.count("*").alias("written")), True)
        loop.base = written.select("id", "component")
        if not loop._note("blocked", int(seen.get["changed"] or 0), int(seen.get["written"]), time.perf_counter_ns() - began):
            break
    return loop.result()
