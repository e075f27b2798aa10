"""Token ids in flat unsigned-integer files with 64-bit document offsets.

A shard is two files: ``NAME.bin`` holds the ids of its documents in a row, ``NAME.idx``
holds, as 64-bit integers, the count n of documents, their n ids, and n + 1 offsets in
tokens. Shards follow each other in ascending document id; the place of a shard's first
token in the whole is the prefix sum of the counts in the manifest, which has one row a
shard. A task writes under a name of its own and renames at the end, so that repeated or
lost attempts leave whole shards only.

Null texts are empty documents, which hold the end id alone. Documents of one id stand in
the order of their texts' hashes; null ids come first and are marked in the manifest.
"""

from __future__ import annotations

import itertools
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean
from forkline.llm.encoding import encoder

BATCH = 512
NULL_ID = -(1 << 63)


def _filesystem(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder)


def write_token_files(docs: DataFrame, folder: str, vocabulary: str, end_id: int = 1, dtype: str = "uint16", partitions: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode and write all documents; returns the manifest ``(shard, name, documents, tokens, base)``.

    ``folder`` is a URI that driver and executors share. ``dtype`` must hold every id of the vocabulary.
    """
    spark = docs.sparkSession
    limit = np.iinfo(dtype).max

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = encoder(vocabulary, np.dtype(dtype).newbyteorder("<").str)
        if encode.vocabulary_size - 1 > limit:
            raise ValueError(f"{dtype} cannot hold the ids of {vocabulary}")
        shard = TaskContext.get().partitionId()
        files, root = _filesystem(folder)
        files.create_dir(root, recursive=True)
        own, name = uuid.uuid4().hex, f"shard-{shard:06d}"
        end = np.array([end_id], dtype).tobytes()
        ids, ends, total = [], [0], 0
        with files.open_output_stream(f"{root}/.{own}.bin") as out:
            for batch in batches:
                for i in range(0, batch.num_rows, BATCH):
                    some = batch.slice(i, BATCH)
                    ids += [NULL_ID if x is None else x for x in some.column(0).to_pylist()]
                    for coded in encode(some.column(1).to_pylist()):
                        out.write(coded + end)
                        total += len(coded) // encode.step + 1
                        ends.append(total)
        with files.open_output_stream(f"{root}/.{own}.idx") as out:
            out.write(np.array([len(ids), *ids, *ends], "<i8").tobytes())
        for kind in ("bin", "idx"):
            files.move(f"{root}/.{own}.{kind}", f"{root}/{name}.{kind}")
        yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "name": [name], "documents": pa.array([len(ids)], pa.int64()), "tokens": pa.array([total], pa.int64())})

    texts = id_and_text(docs, id_col, text_col).withColumn("tie", F.xxhash64("text"))
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    manifest = (
        texts.repartitionByRange(n, "doc_id", "tie").sortWithinPartitions("doc_id", "tie").select("doc_id", "text").mapInArrow(lean(task), "shard int, name string, documents bigint, tokens bigint")
    )
    manifest.write.parquet(f"{folder}/manifest")
    counts = sorted(spark.read.parquet(f"{folder}/manifest").collect())  # a row for each shard
    bases = [0, *itertools.accumulate(r["tokens"] for r in counts)]
    return spark.createDataFrame([(*r, base) for r, base in zip(counts, bases, strict=False)], "shard int, name string, documents bigint, tokens bigint, base bigint")


def read_token_files(spark: SparkSession, manifest: DataFrame, folder: str, dtype: str = "uint16") -> DataFrame:
    """Documents from the files: ``(doc_id, start, n_tokens, ids)``; ``start`` counts all tokens before, ``ids`` are 32-bit.

    Local files are memory-mapped; other stores are read a document range at a time.
    """

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        files, root = _filesystem(folder)
        step = np.dtype(dtype).itemsize
        for batch in batches:
            for row in batch.to_pylist():
                with files.open_input_file(f"{root}/{row['name']}.idx") as f:
                    index = np.frombuffer(f.read(), "<i8")
                n = int(index[0])
                ids, ends = index[1 : 1 + n], index[1 + n :]
                if not n:
                    continue
                local = isinstance(files, fs.LocalFileSystem)
                tokens = np.memmap(f"{root}/{row['name']}.bin", np.dtype(dtype).newbyteorder("<"), "r") if local else None
                source = None if local else files.open_input_file(f"{root}/{row['name']}.bin")
                for i in range(0, n, BATCH):
                    j = min(n, i + BATCH)
                    a, b = int(ends[i]), int(ends[j])
                    part = tokens[a:b] if local else np.frombuffer(source.read_at((b - a) * step, a * step), np.dtype(dtype).newbyteorder("<"))
                    wide = part.astype("<u4")
                    cut = (ends[i : j + 1] - a).tolist()
                    yield pa.RecordBatch.from_pydict(
                        {
                            "doc_id": pa.array([None if x == NULL_ID else x for x in ids[i:j].tolist()], pa.int64()),
                            "start": pa.array(ends[i:j] + row["base"], pa.int64()),
                            "n_tokens": pa.array(np.diff(ends[i : j + 1]), pa.int64()),
                            "ids": pa.array([wide[x:y].tobytes() for x, y in zip(cut, cut[1:], strict=False)], pa.binary()),
                        }
                    )

    shards = max(1, manifest.count())
    return manifest.select("name", "base").repartition(shards).mapInArrow(lean(task), "doc_id bigint, start bigint, n_tokens bigint, ids binary")


def documents_digest(read: DataFrame) -> DataFrame:
    return read.select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))
