"""Benchmark decontamination as a prefix-filtered set join, in DataFrame operations only.

A window is ``width`` consecutive words of an item (all its words, if it has fewer but some).
Its tokens are shingles of up to three words. A document contains a window only if it holds
every token of it, so of the tokens ordered by rarity in the corpus the prefix that has to be
shared is one: the rarest. The plan:

1. the shingles of all documents meet the distinct shingles of the benchmark, by hash; what
   meets (a small part of the corpus) goes to the shared folder and yields the rarities;
2. each window's rarest shingle joins those places; windows with a shingle that occurs
   nowhere are dropped; the length and the position of a match bound where it may begin;
3. candidates fetch their document's words and are compared word by word;
4. overlapping hits become covered words by one sort within each document.

The windows with their rarest shingles are broadcast if there are at most
``BROADCAST_WINDOWS`` of them. The benchmark's shingles, and the keys of the documents with candidates, are broadcast if
there are at most ``BROADCAST_ROWS`` of them (8 and 16 bytes each), else they are shuffled
like the rest.

Null texts have no words; items without words or without an id match nothing; items of one id
count as one; documents of equal or null ids are judged apart, by their text; an empty table
gives no rows, an empty benchmark no hits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import BROADCAST_ROWS, through_disk

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Windows of at most ``width`` words that are broadcast at most.
BROADCAST_WINDOWS = 200_000
NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """Lower-cased (A-Z only) words of letters, digits and all characters beyond ASCII."""
    return F.array_remove(F.split(F.translate(F.coalesce(text.cast("string"), F.lit("")), UPPER, LOWER), NOT_WORD), "")


def shingles_of(words: Column, size: int) -> Column:
    """Hash of each ``size`` consecutive words, in order; none if there are fewer."""
    at = F.sequence(F.lit(0), F.size(words) - size)
    hashed = F.transform(at, lambda i: F.xxhash64(F.lit(size), *(F.get(words, i + k) for k in range(size))))
    return F.when(F.size(words) >= size, hashed).otherwise(F.array().cast("array<bigint>"))


def item_windows(items: DataFrame, width: int, id_col: str, text_col: str) -> DataFrame:
    """``(item_id, window, len, size)``: each distinct window with the size of its shingles."""
    spelt = items.select(F.col(id_col).alias("item_id"), words_of(F.col(text_col)).alias("words")).where("item_id IS NOT NULL AND size(words) > 0")
    length = F.least(F.size("words"), F.lit(width))
    cut = F.transform(F.sequence(F.lit(1), F.size("words") - length + 1), lambda i: F.slice("words", i, length))
    return spelt.select("item_id", F.explode(cut).alias("window")).distinct().withColumn("len", F.size("window")).withColumn("size", F.least("len", F.lit(3)))


def decontaminate(docs: DataFrame, items: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``(doc_id, n_words, n_hit, item_ids, contaminated, text_hash)`` for each document; ``item_ids`` are strings in order."""
    texts = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    texts = texts.withColumn("rid", F.coalesce("doc_id", F.lit(-1))).withColumn("tid", F.xxhash64("text"))
    spelt = texts.select("doc_id", "rid", "tid", words_of(F.col("text")).alias("words"))

    windows = through_disk(item_windows(items, width, item_id_col, item_text_col), "windows")
    sizes = sorted(r["size"] for r in windows.select("size").distinct().collect())  # of 1, 2 and 3
    base = spelt.select("doc_id", "rid", "tid", F.size("words").alias("n_words"))
    if not sizes:
        return base.select("doc_id", F.col("n_words").cast("bigint").alias("n_words"), F.lit(0).cast("bigint").alias("n_hit"), F.array().cast("array<string>").alias("item_ids"), F.lit(False).alias("contaminated"), F.col("tid").alias("text_hash"))

    tokens = None
    for size in sizes:
        own = windows.where(F.col("size") == size).select("item_id", "window", "len", F.posexplode(shingles_of(F.col("window"), size)).alias("offset", "token"))
        tokens = own if tokens is None else tokens.unionByName(own)
    tokens = through_disk(tokens, "tokens")
    sought = tokens.select("token").distinct()
    if sought.count() <= BROADCAST_ROWS:
        sought = F.broadcast(sought)

    found = None
    for size in sizes:
        own = spelt.select("rid", "tid", F.size("words").alias("n_words"), F.posexplode(shingles_of(F.col("words"), size)).alias("pos", "token")).join(sought, "token")
        found = own if found is None else found.unionByName(own)
    found = through_disk(found, "places")

    seen = found.groupBy("token").agg(F.count("*").alias("often"))
    ranked = tokens.join(seen, "token", "left").groupBy("item_id", "window", "len").agg(
        F.min(F.coalesce("often", F.lit(0))).alias("least"), F.min_by(F.struct("token", "offset"), F.struct(F.coalesce("often", F.lit(0)), "offset")).alias("rarest")
    )
    prefix = through_disk(ranked.where("least > 0").select("item_id", "window", "len", F.col("rarest.token").alias("token"), F.col("rarest.offset").alias("offset")), "prefixes")
    if prefix.count() <= BROADCAST_WINDOWS:  # so places of a common token need not meet in one task
        prefix = F.broadcast(prefix)
    candidates = (
        found.join(prefix, "token")
        .select("rid", "tid", "item_id", "window", "len", (F.col("pos") - F.col("offset")).alias("start"), "n_words")
        .where((F.col("start") >= 0) & (F.col("start") + F.col("len") <= F.col("n_words")))
        .distinct()
    )
    candidates = through_disk(candidates.drop("n_words"), "candidates")
    keys = through_disk(candidates.select("rid", "tid").distinct(), "suspects")
    if keys.count() <= BROADCAST_ROWS:
        keys = F.broadcast(keys)
    suspects = texts.join(keys, ["rid", "tid"], "left_semi").dropDuplicates(["rid", "tid"]).select("rid", "tid", words_of(F.col("text")).alias("words"))
    verified = candidates.join(suspects, ["rid", "tid"]).where(F.slice("words", F.col("start") + 1, F.col("len")) == F.col("window")).select("rid", "tid", "item_id", "start", (F.col("start") + F.col("len")).alias("end"))
    verified = through_disk(verified, "verified")

    spans = verified.select("rid", "tid", "start", "end").distinct()
    before = F.expr("max(end) OVER (PARTITION BY rid, tid ORDER BY start, end ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)")
    covered = spans.select("rid", "tid", F.greatest(F.lit(0), F.col("end") - F.greatest("start", F.coalesce(before, F.lit(0)))).alias("new"))
    hit = covered.groupBy("rid", "tid").agg(F.sum("new").alias("n_hit"))
    named = verified.groupBy("rid", "tid").agg(F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("item_ids"))
    both = hit.join(named, ["rid", "tid"])
    return base.join(both, ["rid", "tid"], "left").select(
        "doc_id",
        F.col("n_words").cast("bigint").alias("n_words"),
        F.coalesce("n_hit", F.lit(0)).cast("bigint").alias("n_hit"),
        F.coalesce("item_ids", F.array().cast("array<string>")).alias("item_ids"),
        F.col("n_hit").isNotNull().alias("contaminated"),
        F.col("tid").alias("text_hash"),
    )
