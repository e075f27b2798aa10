"""Top-down breadth-first search, level by level.

* conditional: neighbours that were seen are dropped by an anti-join; discoveries are written;
* unconditional: every traversed adjacency proposes a distance, minima are taken over the
  whole table and it is written anew; a vertex is new if its distance was infinite.

Each level is one action that writes an epoch and observes the number of discoveries.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from forkline.functions.selection import smaller
from forkline.graph import Graph, ranked
from forkline.sources.tables import Epochs

INFINITE = 2_147_483_647


@dataclass(frozen=True)
class Level:
    level: int
    discovered: int
    written: int
    elapsed_ns: int


@dataclass(frozen=True)
class BFSRun:
    distances: DataFrame
    steps: list[Level]

    def levels(self) -> DataFrame:
        return self.distances.groupBy("dist").agg(F.count("*").alias("vertices"))


def pick_root(g: Graph, how: str | int = "min_id") -> int:
    """``min_id``, ``max_degree`` (ties to the smaller id) or an id that has to be a vertex."""
    if how == "min_id":
        found = g.vertices.agg(F.min("id").alias("id")).first()["id"]
    elif how == "max_degree":
        top = g.edges.groupBy(F.col("src").alias("id")).count().orderBy(F.desc("count"), "id").first()
        found = top["id"] if top else g.vertices.agg(F.min("id").alias("id")).first()["id"]
    else:
        found = how if g.vertices.where(F.col("id") == int(how)).limit(1).count() else None
    if found is None:
        raise ValueError(f"no vertex for root {how!r}")
    return int(found)


def init_bfs(g: Graph, root: int) -> DataFrame:
    return g.vertices.select("id", F.when(F.col("id") == root, 0).otherwise(INFINITE).alias("dist"))


def level_conditional(edges: DataFrame, frontier: DataFrame, visited: DataFrame) -> DataFrame:
    """Ids that the frontier sees for the first time."""
    near = edges.join(frontier.select(F.col("id").alias("src")), "src").select(F.col("dst").alias("id"))
    return near.join(visited.select("id"), "id", "left_anti").distinct()


def level_unconditional(edges: DataFrame, dist: DataFrame, level: int, select_style: str = "least") -> DataFrame:
    """``(id, dist, old)`` of every vertex after ``level`` has been expanded."""
    proposed = edges.join(dist.where(F.col("dist") == level).select(F.col("id").alias("src")), "src").select(F.col("dst").alias("id"), F.lit(level + 1).alias("heard"), F.lit(None).cast("int").alias("old"))
    own = dist.select("id", F.lit(None).cast("int").alias("heard"), F.col("dist").alias("old"))
    met = own.unionByName(proposed).groupBy("id").agg(F.min("heard").alias("heard"), F.max("old").alias("old"))
    return met.select("id", smaller(F.col("old"), F.coalesce("heard", "old"), select_style).cast("int").alias("dist"), "old")


def bfs_conditional(g: Graph, root: int | None = None, max_level: int | None = None) -> BFSRun:
    spark = g.edges.sparkSession
    root = pick_root(g) if root is None else pick_root(g, root)
    epochs, steps = Epochs(spark, "bfs"), []
    schema = "id bigint, dist int"
    frontier = epochs.put("dist=0", spark.createDataFrame([(root,)], "id bigint")).withColumn("dist", F.lit(0))
    # all levels so far are the sub-folders of one Parquet folder
    visited = lambda: spark.read.schema(schema).parquet(epochs.root)
    level = 0
    while max_level is None or level < max_level:
        began, seen = time.perf_counter_ns(), Observation()
        new = level_conditional(g.edges, frontier, visited())
        frontier = epochs.put(f"dist={level + 1}", new.observe(seen, F.count("*").alias("n")))
        n = int(seen.get["n"])
        steps.append(Level(level, n, n, time.perf_counter_ns() - began))
        if not n:
            break
        level += 1
    return BFSRun(visited().select("id", "dist"), steps)


def bfs_unconditional(g: Graph, root: int | None = None, max_level: int | None = None, select_style: str = "least", include_unreached: bool = False) -> BFSRun:
    root = pick_root(g) if root is None else pick_root(g, root)
    epochs, steps = Epochs(g.edges.sparkSession, "bfs"), []
    dist, level = init_bfs(g, root), 0
    while max_level is None or level < max_level:
        began, seen = time.perf_counter_ns(), Observation()
        new = level_unconditional(g.edges, dist, level, select_style).observe(seen, F.sum((F.col("old") > F.col("dist")).cast("bigint")).alias("new"), F.count("*").alias("written"))
        dist = epochs.put(f"level-{level + 1}", new).select("id", "dist")
        found = int(seen.get["new"] or 0)
        steps.append(Level(level, found, int(seen.get["written"]), time.perf_counter_ns() - began))
        if not found:
            break
        level += 1
    public = dist.select("id", F.nullif("dist", F.lit(INFINITE)).alias("dist"))
    return BFSRun(public if include_unreached else public.where("dist IS NOT NULL"), steps)


def bfs_hybrid(g: Graph, root: int | None = None, unconditional_levels: int = 0) -> BFSRun:
    """Unconditional for the first levels, conditional from then on; by default conditional throughout."""
    root = pick_root(g) if root is None else pick_root(g, root)
    if unconditional_levels <= 0:
        return bfs_conditional(g, root)
    first = bfs_unconditional(g, root, max_level=unconditional_levels)
    spark, epochs, steps = g.edges.sparkSession, Epochs(g.edges.sparkSession, "bfs"), list(first.steps)
    seen_so_far = epochs.put("start", first.distances.select("id", F.col("dist").cast("int").alias("dist")))
    frontier = seen_so_far.where(F.col("dist") == unconditional_levels)
    level = unconditional_levels
    while True:
        began, seen = time.perf_counter_ns(), Observation()
        new = level_conditional(g.edges, frontier, seen_so_far).withColumn("dist", F.lit(level + 1))
        frontier = epochs.put(f"level-{level + 1}", new.observe(seen, F.count("*").alias("n")))
        n = int(seen.get["n"])
        steps.append(Level(level, n, n, time.perf_counter_ns() - began))
        if not n:
            return BFSRun(seen_so_far, steps)
        seen_so_far = spark.read.schema("id bigint, dist int").parquet(f"{epochs.root}/start", *(f"{epochs.root}/level-{k}" for k in range(unconditional_levels + 1, level + 2)))
        level += 1


def queue_order(g: Graph, root: int | None = None) -> DataFrame:
    """``(id, parent, dist, rank)``: the exact place of each reached vertex in the sequential queue, and who put it there.

    A vertex is put by the first of its neighbours in the queue; those put by one vertex
    follow each other by id. Places come from range partitions and their offsets.
    """
    spark = g.edges.sparkSession
    root = pick_root(g) if root is None else pick_root(g, root)
    epochs = Epochs(spark, "queue")
    schema = "id bigint, parent bigint, rank bigint, dist int"
    frontier = epochs.put("dist=0", spark.createDataFrame([(root, None, 0)], "id bigint, parent bigint, rank bigint"))
    visited = lambda: spark.read.schema(schema).parquet(epochs.root)
    done, level = 1, 0
    while True:
        near = g.edges.join(frontier.select(F.col("id").alias("src"), F.col("rank").alias("from_rank")), "src")
        fresh = near.join(visited().select(F.col("id").alias("dst")), "dst", "left_anti")
        first = fresh.groupBy("dst").agg(F.min_by("src", "from_rank").alias("parent"), F.min("from_rank").alias("from_rank"))
        new = ranked(first.withColumnRenamed("dst", "id"), ["from_rank", "id"], "rank", done).select("id", "parent", "rank")
        seen = Observation()
        frontier = epochs.put(f"dist={level + 1}", new.observe(seen, F.count("*").alias("n")))
        if not int(seen.get["n"]):
            return visited().select("id", "parent", "dist", "rank")
        done, level = done + int(seen.get["n"]), level + 1


def reach_stats(g: Graph, distances: DataFrame) -> DataFrame:
    """One row: vertices reached, adjacencies traversed, levels."""
    traversed = g.edges.join(distances.select(F.col("id").alias("src")), "src", "left_semi").agg(F.count("*").alias("adjacencies"))
    return distances.agg(F.count("*").alias("reached"), (F.max("dist") + 1).cast("bigint").alias("levels")).crossJoin(traversed).select("reached", "adjacencies", "levels")  # one row each


def reach_curve(distances: DataFrame) -> DataFrame:
    """Vertices reached up to each level; a window over one row a level."""
    own = W.orderBy("dist").rowsBetween(W.unboundedPreceding, 0)
    return distances.groupBy("dist").agg(F.count("*").alias("vertices")).withColumn("reached", F.sum("vertices").over(own))


def bfs_multi(g: Graph, roots: list[int], max_level: int | None = None) -> DataFrame:
    """``(root, id, dist)``: searches from several roots side by side."""
    spark = g.edges.sparkSession
    epochs, level = Epochs(spark, "bfs-multi"), 0
    schema = "root bigint, id bigint, dist int"
    frontier = epochs.put("dist=0", spark.createDataFrame([(r, r) for r in sorted(set(roots))], "root bigint, id bigint"))
    visited = lambda: spark.read.schema(schema).parquet(epochs.root)
    while max_level is None or level < max_level:
        near = frontier.withColumnRenamed("id", "src").join(g.edges, "src").select("root", F.col("dst").alias("id"))
        seen = Observation()
        frontier = epochs.put(f"dist={level + 1}", near.join(visited().select("root", "id"), ["root", "id"], "left_anti").distinct().observe(seen, F.count("*").alias("n")))
        if not int(seen.get["n"]):
            break
        level += 1
    return visited().select("root", "id", "dist")


def betweenness_sampled(g: Graph, roots: list[int]) -> DataFrame:
    """``(id, betweenness)``: dependencies of shortest paths from ``roots``, summed; each pair's ends don't count."""
    spark = g.edges.sparkSession
    reached = bfs_multi(g, roots)
    epochs = Epochs(spark, "betweenness")
    dist = epochs.put("dist", reached)
    deepest = int(dist.agg(F.max("dist").alias("d")).first()["d"] or 0)
    down = epochs.put(
        "down",
        g.edges.join(dist.select("root", F.col("id").alias("src"), F.col("dist").alias("a")), "src").join(dist.select("root", F.col("id").alias("dst"), F.col("dist").alias("b")), ["root", "dst"]).where("b = a + 1").select("root", "src", "dst", "a"),
    )
    paths = epochs.put("paths-0", dist.where("dist = 0").select("root", "id", F.lit(1.0).alias("paths")))
    layers = [paths]
    for d in range(deepest):
        step = down.where(F.col("a") == d).join(layers[-1].withColumnRenamed("id", "src"), ["root", "src"]).groupBy("root", F.col("dst").alias("id")).agg(F.sum("paths").alias("paths"))
        layers.append(epochs.put(f"paths-{d + 1}", step))
    owed = layers[-1].select("root", "id", "paths", F.lit(0.0).alias("owed"))
    total = [owed]
    for d in range(deepest - 1, -1, -1):
        share = down.where(F.col("a") == d).join(owed.select("root", F.col("id").alias("dst"), ((F.col("owed") + 1) / F.col("paths")).alias("unit")), ["root", "dst"]).groupBy("root", F.col("src").alias("id")).agg(F.sum("unit").alias("unit"))
        owed = epochs.put(f"owed-{d}", layers[d].join(share, ["root", "id"], "left").select("root", "id", "paths", (F.coalesce("unit", F.lit(0.0)) * F.col("paths")).alias("owed")))
        total.append(owed)
    every = total[0]
    for t in total[1:]:
        every = every.unionByName(t)
    return every.where("id <> root").groupBy("id").agg(F.sum("owed").alias("betweenness"))


def eccentricity(g: Graph, root: int) -> int:
    return int(bfs_conditional(g, root).distances.agg(F.max("dist").alias("d")).first()["d"])


def diameter_lower_bound(g: Graph, root: int | None = None) -> int:
    """The eccentricity of a vertex that is farthest from ``root``."""
    run = bfs_conditional(g, root)
    far = run.distances.orderBy(F.desc("dist"), "id").first()["id"]
    return eccentricity(g, far)


def steps_frame(spark: SparkSession, run: BFSRun) -> DataFrame:
    return spark.createDataFrame([(s.level, s.discovered, s.written, s.elapsed_ns) for s in run.steps], "level int, discovered bigint, written bigint, elapsed_ns bigint")
