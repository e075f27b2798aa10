"""Reading and writing: tables, edge files, epochs of iterations in the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src bigint, dst bigint"


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A table of the given folder; named columns only reach the scan."""
    table = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return table.select(*columns) if columns else table


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", header: bool = False) -> DataFrame:
    """Text lines ``src<sep>dst``; lines that begin with # or % are comments."""
    lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%].*)?$"))
    if header:
        lines = lines.where(F.col("value").rlike(r"^\s*-?\d"))
    parts = F.split(F.trim("value"), r"\s+" if sep.isspace() else f"[{sep}]")
    return lines.select(parts[0].cast("bigint").alias("src"), parts[1].cast("bigint").alias("dst"))


def read_adjacency_text(spark: SparkSession, path: str, one_based: bool = True) -> DataFrame:
    """Line i lists the neighbours of vertex i; the first line, the header with both counts, and % lines are no vertex.

    The line number comes from the order of the lines in one file, so the file is read as a
    whole by one task; wide inputs should come as edge lists.
    """
    whole = spark.read.text(path, wholetext=True)
    lines = whole.select(F.posexplode(F.filter(F.split("value", "\n"), lambda x: ~x.startswith("%"))).alias("line", "text")).where("line > 0")
    shift = 0 if one_based else 1
    return lines.select((F.col("line") - shift).cast("bigint").alias("src"), F.explode(F.filter(F.split(F.trim("text"), r"\s+"), lambda x: x != "").cast("array<bigint>")).alias("dst"))


def read_edges(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """Edges ``(src, dst)`` of a JSON, ORC, CSV or Parquet source."""
    return spark.read.schema(EDGE_SCHEMA).format(fmt).load(path).select("src", "dst")


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(edges: DataFrame, table: str, buckets: int, mode: str = "overwrite") -> DataFrame:
    """Edges as a bucketed table: joins on ``dst`` with labels bucketed alike need no exchange of edges."""
    edges.write.bucketBy(buckets, "dst").sortBy("dst", "src").mode(mode).saveAsTable(table)
    return edges.sparkSession.table(table)


#: Folders that this process has made, by application.
_made: dict[str, list[str]] = {}


def shared_folder(spark: SparkSession, kind: str) -> str:
    """A new folder that driver and executors share, below ``spark.checkpoint.dir``.

    Only a session on one machine may leave that setting empty; on a cluster that is an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = f"file://{tempfile.gettempdir()}/forkline-shared"
    folder = f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"
    _made.setdefault(spark.sparkContext.applicationId, []).append(folder)
    return folder


def drop(spark: SparkSession, *folders: str) -> None:
    """Delete folders through Hadoop's file system, wherever they lie."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for folder in folders:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)


def clean(spark: SparkSession) -> None:
    """Delete all that runs have written on the way; DataFrames that they returned can't be read after it."""
    drop(spark, *_made.pop(spark.sparkContext.applicationId, []))


class Epochs:
    """Successive states of an iteration, each a Parquet folder; reading one needs no earlier plan."""

    def __init__(self, spark: SparkSession, kind: str):
        self.spark, self.root = spark, shared_folder(spark, kind)

    def put(self, name: str | int, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str | int) -> None:
        """Delete states that no plan reads any more."""
        drop(self.spark, *(f"{self.root}/{name}" for name in names))


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Actions within leave no shuffle files behind; by default Spark keeps them until the driver collects garbage."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def stored(df: DataFrame, kind: str) -> DataFrame:
    return Epochs(df.sparkSession, kind).put("all", df)
