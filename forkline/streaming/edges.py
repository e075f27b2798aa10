"""Edges that arrive over time: windows, time joins, and components kept up to date by micro-batches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from forkline.graph import Graph, graph_of
from forkline.operators.components import components_conditional
from forkline.sources.tables import stored

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def edge_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """Streamed ``(src, dst, ts)``: a user and the hour of each event; Parquet files of ``folder`` as they come."""
    events = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    hour = F.expr("timestampdiff(HOUR, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")
    return events.select((F.col("user_id") * 2).alias("src"), (hour * 2 + 1).alias("dst"), F.col("ts").cast("timestamp").alias("ts"))


def deduplicated(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each edge once within the watermark; rows later than ``late`` are dropped."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def window_counts(edges: DataFrame, width: str = "1 hour", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """``(start, edges)``: edges of each tumbling or sliding window, appended once it has passed the watermark."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return edges.withWatermark("ts", late).groupBy(window).agg(F.count("*").alias("edges")).select(F.col("window.start").alias("start"), "edges")


def session_counts(edges: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """``(src, start, edges)``: bursts of a vertex's edges, parted by ``gap``."""
    return edges.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "src").agg(F.count("*").alias("edges")).select("src", F.col("session_window.start").alias("start"), "edges")


class ComponentState:
    """Labels kept over micro-batches: ``labels/batch=N`` below ``folder`` holds the state after batch N.

    The folder alone is the state: a batch starts from the last complete batch before it, also
    after a restart, and writes a folder that only later batches read. So a batch that runs
    again after a failure replaces what it wrote and gives the same state.
    """

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def last(self, below: int | None = None) -> int | None:
        """The greatest batch that was written to its end, of those below ``below``."""
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        path = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/labels")
        files = path.getFileSystem(conf)
        if not files.exists(path):
            return None
        folders = [s.getPath() for s in files.listStatus(path) if s.getPath().getName().startswith("batch=")]
        done = [int(f.getName().removeprefix("batch=")) for f in folders if files.exists(jvm.org.apache.hadoop.fs.Path(f, "_SUCCESS"))]
        return max((n for n in done if below is None or n < below), default=None)

    def labels(self, below: int | None = None) -> DataFrame:
        last = self.last(below)
        if last is None:
            return self.spark.createDataFrame([], "id bigint, component bigint")
        return self.spark.read.schema("id bigint, component bigint").parquet(f"{self.folder}/labels/batch={last}")

    def update(self, batch: DataFrame, batch_id: int) -> None:
        """New edges join the old components: their graph is that of labels, which is small, and its labels are relabelled."""
        edges = stored(graph_of(batch.select("src", "dst"), "batch").edges, "batch")
        old = self.labels(batch_id)
        ends = edges.select(F.col("src").alias("id")).distinct()
        known = ends.join(old, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
        a = known.select(F.col("id").alias("src"), F.col("component").alias("a"))
        b = known.select(F.col("id").alias("dst"), F.col("component").alias("b"))
        among = edges.join(a, "src").join(b, "dst").select("a", "b")
        g = graph_of(among, "labels", vertices=known.select("component").distinct())
        merged = components_conditional(Graph(stored(g.edges, "edges"), stored(g.vertices, "vertices"), False, "labels"), scan="delta").labels
        moved = merged.select(F.col("id").alias("component"), F.col("component").alias("lower"))
        every = old.unionByName(known).groupBy("id").agg(F.min("component").alias("component"))
        new = every.join(moved, "component", "left").select("id", F.least("component", F.coalesce("lower", "component")).alias("component"))
        new.write.mode("overwrite").parquet(f"{self.folder}/labels/batch={batch_id}")


def stream_components(edges: DataFrame, folder: str, checkpoint: str) -> tuple[StreamingQuery, ComponentState]:
    state = ComponentState(edges.sparkSession, folder)
    query = edges.writeStream.foreachBatch(state.update).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    return query, state


def event_pairs(events: DataFrame, minutes: int) -> DataFrame:
    """``(a, b)``: users with events at most ``minutes`` apart. A range join by time buckets: an event meets its own and the next."""
    width = minutes * 60_000_000
    at = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")
    x = events.select(F.col("user_id").alias("u"), at.alias("at")).withColumn("bucket", F.floor(F.col("at") / width).cast("bigint"))
    left = x.select("u", "at", F.explode(F.array(F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    right = x.select(F.col("u").alias("w"), F.col("at").alias("then"), "bucket")
    near = left.join(right, "bucket").where((F.col("then") >= F.col("at")) & (F.col("then") - F.col("at") <= width) & (F.col("u") != F.col("w")))
    return near.select(F.least("u", "w").alias("a"), F.greatest("u", "w").alias("b")).distinct()


def previous_event(events: DataFrame) -> DataFrame:
    """As-of: each event with the last earlier one of its user."""
    from pyspark.sql import Window as W

    own = W.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("event_id", "user_id", "ts", F.lag("event_id").over(own).alias("previous_id"))


def windowed_components(events: DataFrame, width: str = "1 day") -> DataFrame:
    """``(day, vertices, components)`` of the user-hour graph of each window; all windows propagate side by side."""
    hour = F.expr("timestampdiff(HOUR, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")
    start = F.window(F.col("ts").cast("timestamp"), width)["start"]
    kept = events.select(F.unix_timestamp(start).alias("w"), (F.col("user_id") * 2).alias("u"), (hour * 2 + 1).alias("h"))
    # one id space: window and vertex are numbered together
    keys = stored(kept.select(F.struct("w", F.col("u").alias("k")).alias("key")).unionByName(kept.select(F.struct("w", F.col("h").alias("k")).alias("key"))).distinct(), "keys")
    from forkline.graph import dense_ids

    ids = stored(dense_ids(keys, "key"), "ids")
    a = ids.select(F.col("key").alias("ka"), F.col("id").alias("a"))
    b = ids.select(F.col("key").alias("kb"), F.col("id").alias("b"))
    pairs = kept.select(F.struct("w", F.col("u").alias("k")).alias("ka"), F.struct("w", F.col("h").alias("k")).alias("kb")).distinct().join(a, "ka").join(b, "kb").select("a", "b")
    g = graph_of(pairs, "windows")
    labels = components_conditional(Graph(stored(g.edges, "edges"), stored(g.vertices, "vertices"), False, "windows"), scan="delta").labels
    return labels.join(ids, "id").groupBy(F.date_format(F.timestamp_seconds("key.w"), "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("vertices"), F.countDistinct("component").alias("components"))
