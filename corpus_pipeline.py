"""Corpus pipeline: quality rules, line dedup, near-duplicate removal, benchmark decontamination, packing.

Each stage takes (spark, docs, sf_dir), works on every row it gets and returns a DataFrame,
which is written as Parquet and read again for the next one. All but the last return the
columns of ``documents``; the last returns the pieces of packed sequences with their ids.

In every stage rows of equal or null ids are told apart by their text, other columns are
carried along whatever their names, and an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.llm.common import table, through_disk, without

#: SQL has no conditional random field, SimHash or tokenizer: the stages are tested against brute force.
ORACLE_SQL = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the texts that pass the base rules and are mostly content lines; null and empty texts fail the rules and go."""
    from forkline.llm.line_quality import fit, keep_good

    field = fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return keep_good(docs, field)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Delete runs of lines that occur earlier; a text of which no word is left goes. ``n_chars`` follows the text.

    Null and empty texts stay (as empty ones); a null id is later than all others.
    """
    from forkline.llm.repeats import line_dedup as dedup

    others = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    kept = dedup(docs, run=2, long_line=50, carry=others).where("n_units = 0 OR n_removed < n_units")
    back = {"doc_id": F.col("doc_id"), "text": F.col("text")} | {c: F.col(f"carry_{i}") for i, c in enumerate(others)}
    if "n_chars" in back:
        back["n_chars"] = F.char_length("text").cast(docs.schema["n_chars"].dataType)
    return kept.select(*(back[c].alias(c) for c in docs.columns))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of similar texts (0.8 or more over five-word shingles) one row stays: that of smallest id, null last, then of smallest text hash.

    SimHash finds the first candidates and MinHash the rest; all are compared by their
    shingles. Null and empty texts are one group.
    """
    from forkline.llm.similar import similar_rows

    rows = through_disk(similar_rows(docs, similarity=0.8, shingle=5), "groups")
    rank = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")
    groups = rows.groupBy("group").agg(F.count("*").alias("n"), F.min(rank).alias("first")).where("n > 1")
    members = rows.join(groups, "group").groupBy("doc_id", "text_hash").agg(F.count("*").alias("n"), F.max(rank == F.col("first")).alias("stays"))
    members = through_disk(members, "members")
    hashed = docs.withColumn("__hash", F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    rest = without(hashed, members.where("NOT stays OR n > 1"), {"cast(doc_id AS bigint)": "doc_id", "__hash": "text_hash"})
    # equal rows of one id and text that stay as one
    equal = members.where("stays AND n > 1").select(F.col("doc_id").alias("__id"), F.col("text_hash").alias("__hash"))
    several = hashed.join(equal, F.col("doc_id").cast("bigint").eqNullSafe(F.col("__id")) & (hashed["__hash"] == equal["__hash"]), "left_semi")
    one = several.groupBy("doc_id", "__hash").agg(F.min(F.struct(*docs.columns)).alias("row")).select("row.*")
    return rest.drop("__hash").unionByName(one)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts that hold a window of ten words of a benchmark item go; null and empty texts hold none."""
    from forkline.llm.decontaminate import decontaminate

    found = decontaminate(docs, table(spark, sf_dir, "benchmark"), width=10)
    return without(docs, found.where("contaminated"), {"doc_id": "doc_id", "xxhash64(text)": "text_hash"})


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 1024 tokens or a shorter power of two, with their ids; a null text is an empty one, which is its end token."""
    from forkline.llm.packing import pack

    return pack(docs, "byte_bpe_50k.json", sequence_length=1024, end_id=0).withColumn("ids_crc32", F.crc32("ids"))


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = through_disk(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
