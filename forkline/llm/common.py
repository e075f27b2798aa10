"""Shared plumbing of the text operators: columns, shared folders, chunking of documents.

The operators take any DataFrame that has an id and a text column; other columns, whatever
their names, are dropped at the door, so they can't clash. A null text counts as an empty one.
"""

from __future__ import annotations

import inspect
import math
import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.sources.tables import clean, drop, shared_folder  # noqa: F401  (the operators' own name for it)


def give_back() -> None:
    """Return this process's free memory to the system."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


#: Rows in an Arrow batch at most: whole texts may be long, and a batch is held several times over.
BATCH_ROWS = 2000


def small_batches(spark: SparkSession) -> None:
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def lean(work):
    """Wrap a task or group function: when it ends, its free memory leaves the idle worker.

    Workers are kept for later stages, whose executors need the room.
    """

    if inspect.isgeneratorfunction(work):

        def task(batches):
            try:
                yield from work(batches)
            finally:
                give_back()

        return task
    if len(inspect.signature(work).parameters) == 1:

        def group(t):
            try:
                return work(t)
            finally:
                give_back()

        return group

    def groups(t, u):
        try:
            return work(t, u)
        finally:
            give_back()

    return groups


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def through_disk(df: DataFrame, kind: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it again: cuts lineage, survives executors."""
    spark = df.sparkSession
    path = shared_folder(spark, kind)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", extra: list[str] | None = None) -> DataFrame:
    small_batches(docs.sparkSession)
    return docs.select(
        *(extra or []),
        F.col(id_col).cast("bigint").alias("doc_id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )


def volume(docs: DataFrame) -> tuple[int, int]:
    """Rows and UTF-8 bytes of ``docs(text)``; one aggregate row reaches the driver."""
    row = docs.agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("b")).first()
    return int(row["n"] or 0), int(row["b"] or 0)


class Grid:
    """How many chunks of documents and buckets of hashes an exchange between the two uses.

    Every chunk sends one row to every bucket, so the number of those rows is the product
    of both counts. It stays below ``units / MIN_ENTRIES`` because chunks and buckets both
    grow with the square root of the input beyond a fixed least size: 4 MB of text and a
    million hashes at this scale, about a gigabyte each at 100 TB.
    """

    LEAST_CHUNK_UNITS, LEAST_BUCKET_UNITS, MIN_ENTRIES = 600_000, 1_000_000, 400

    def __init__(self, rows: int, size: int, bytes_per_unit: float, unit_share: float = 1.0):
        units = max(1.0, size / bytes_per_unit)
        sent = max(1.0, units * unit_share)
        root = math.sqrt(self.MIN_ENTRIES * sent)
        per_chunk = max(self.LEAST_CHUNK_UNITS, root / unit_share)
        per_bucket = max(self.LEAST_BUCKET_UNITS, root)
        self.chunks = int(max(1, math.ceil(units / per_chunk), min(12, rows // 50)))
        self.buckets = int(max(1, math.ceil(sent / per_bucket), min(12, rows // 50)))


def into_chunks(docs: DataFrame, chunks: int) -> DataFrame:
    """Deal documents to chunks by a hash of id and text: the same on every attempt, even for equal ids."""
    return docs.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunks)).cast("int"))


def tokenizer_file(name: str) -> str:
    """Place of a public vocabulary file; looked up where it is read, on each machine."""
    if os.path.isabs(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


#: Rows of fixed width (16 bytes) that are broadcast at most; more are shuffled.
BROADCAST_ROWS = 2_000_000


def without(docs: DataFrame, bad: DataFrame, on: dict[str, str]) -> DataFrame:
    """``docs`` without the rows that ``bad`` names, null-safe; ``on`` maps expressions over ``docs`` to columns of ``bad``."""
    keys = through_disk(bad.select(*(F.col(c).alias(f"__bad_{i}") for i, c in enumerate(on.values()))).distinct(), "bad")
    if keys.count() <= BROADCAST_ROWS:
        keys = F.broadcast(keys)
    same = None
    for i, expression in enumerate(on):
        one = F.expr(expression).eqNullSafe(F.col(f"__bad_{i}"))
        same = one if same is None else same & one
    return docs.join(keys, same, "left_anti")
