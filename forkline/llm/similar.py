"""SimHash groups of similar texts, made whole from a stated similarity on: links by the Jaccard similarity of the shingles themselves.

A text is the set of its word shingles (A-Z lower-cased, 64-bit hashes; all its words, if it
has fewer than a shingle). Texts of equal sets become one class. Candidates come from two
sources, and are links only if the similarity of their sets suffices:

* SimHash fingerprints of the sets within ``RADIUS`` bits, by the generalised pigeonhole
  principle (``simhash.links``): found for sure, but only near-equal texts. At a similarity of
  0.8 two 64-bit fingerprints differ by 9.7 bits on average, and a radius that holds nearly
  all such pairs (20) would make a constant share of all pairs candidates;
* so the rest comes from MinHash: the minima of a class under ``ROWS * BANDS`` fixed
  permutations give one key a band; two classes of similarity J share a key with probability
  ``1 - (1 - J ** ROWS) ** BANDS``: all but 3 in a million at 0.8, more above. Seeds are
  constants, so whether two texts are linked depends on them alone, neither on the other rows
  nor on their number.

Every two classes that share a key are compared or already connected:

1. SimHash candidates come as a spanning forest. A key of up to ``RUN`` classes gives all its
   pairs, a fuller one a star around its smallest class; each pair is told once. Of the pairs
   of a class with smaller ones, that with the smallest is compared with the candidates of
   SimHash: both sets are fetched;
2. so are the other pairs whose classes are still in different components, which in a group
   of copies are few;
3. a full key whose classes are still in several components deals its classes to chunks, and
   each pair of chunks compares all of its pairs of different components in a task of its own.

Null text is empty; empty texts are one class; a null id is larger than all others; rows of
equal ids are told apart by their text's hash; an empty table stays empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean, through_disk
from forkline.llm.components import components
from forkline.llm.simhash import links as simhash_links
from forkline.llm.simhash import majority_bits
from forkline.llm.textblock import TextBlock, blocks, mix, windows

#: Minima in a key, keys of a class, classes of a key that are paired at once, and classes of a chunk.
ROWS, BANDS, RUN, CHUNK = 5, 32, 16, 1000
#: Bits in which SimHash candidates differ at most.
RADIUS = 2
_FACTORS = mix(np.arange(1, ROWS * BANDS + 1, dtype=np.uint64), 77) | np.uint64(1)
_SHIFTS = mix(np.arange(1, ROWS * BANDS + 1, dtype=np.uint64), 78)


def shingle_sets(block: TextBlock, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text in order, and the offsets of the texts."""
    low = block.lowered()
    s, e, doc = low.words()
    h = low.hashes(s, e)
    count = np.bincount(doc, minlength=low.n_docs)
    first = np.concatenate([[0], np.cumsum(count)])[:-1]
    value, inside = windows(h, doc, size)
    found, owner = [value[inside]], [doc[: len(value)][inside]]
    for k in range(1, size):
        short = np.flatnonzero(count == k)
        if len(short):
            found.append(windows(h, doc, k)[0][first[short]])
            owner.append(short)
    value, own = np.concatenate(found), np.concatenate(owner)
    order = np.lexsort((value, own))
    value, own = value[order], own[order]
    new = np.ones(len(value), bool)
    new[1:] = (value[1:] != value[:-1]) | (own[1:] != own[:-1])
    value, own = value[new], own[new]
    return value, np.searchsorted(own, np.arange(low.n_docs + 1))


def band_keys(value: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """(sets, BANDS) keys of sets that are not empty."""
    out = np.zeros((len(edges) - 1, BANDS), np.uint64)
    with np.errstate(over="ignore"):
        for b in range(BANDS):
            key = np.full(len(out), b, np.uint64)
            for k in range(b * ROWS, (b + 1) * ROWS):
                key = mix(key ^ np.minimum.reduceat(value * _FACTORS[k] + _SHIFTS[k], edges[:-1]), k)
            out[:, b] = key
    return out


def _named(value: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """One 64-bit name for each set."""
    with np.errstate(over="ignore"):
        sums = np.concatenate([[np.uint64(0)], np.cumsum(mix(value, 5), dtype=np.uint64)])
        return mix(sums[edges[1:]] - sums[edges[:-1]], 6) ^ np.diff(edges).astype(np.uint64)


def _prints(texts: DataFrame, shingle: int) -> DataFrame:
    """``(doc_id, text_hash, class, f0, keys)`` of ``(doc_id, text, text_hash)``; ``f0`` is the SimHash fingerprint."""
    schema = pa.schema([("doc_id", pa.int64()), ("text_hash", pa.int64()), ("class", pa.int64()), ("f0", pa.int64()), ("keys", pa.list_(pa.int64()))])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, block in blocks(batch.column(1)):
                value, edges = shingle_sets(block, shingle)
                some = np.diff(edges) > 0
                bits = majority_bits(mix(value, 7), edges)[:, 0]
                keys = band_keys(value, np.concatenate([edges[:-1][some], edges[-1:]])) if some.any() else np.zeros((0, BANDS), np.uint64)
                offsets = np.concatenate([[0], np.cumsum(some * BANDS)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys.reshape(-1).view(np.int64)))
                own = [batch.column(k).slice(at, block.n_docs) for k in (0, 2)]
                yield pa.RecordBatch.from_arrays([*own, pa.array(_named(value, edges).view(np.int64)), pa.array(bits.view(np.int64)), lists], schema=schema)

    return texts.select("doc_id", "text", "text_hash").mapInArrow(lean(task), "doc_id bigint, text_hash bigint, class bigint, f0 bigint, keys array<bigint>")


def _sets(texts: DataFrame, shingle: int) -> DataFrame:
    """``(class, hashes)`` of ``(class, text)``: the sorted 64-bit hashes of its set."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, block in blocks(batch.column(1)):
                value, edges = shingle_sets(block, shingle)
                blobs = [value[a:b].tobytes() for a, b in zip(edges, edges[1:], strict=False)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, block.n_docs), pa.array(blobs, pa.binary())], names=["class", "hashes"])

    return texts.select("class", "text").mapInArrow(lean(task), "class bigint, hashes binary")


def similar(shared: int | np.ndarray, x: int | np.ndarray, y: int | np.ndarray, similarity: float) -> bool | np.ndarray:
    """Whether sets of ``x`` and ``y`` members that share so many reach the similarity."""
    return shared >= similarity * (x + y - shared) - 1e-9


def _near_fingerprints(classes: DataFrame) -> DataFrame:
    """``(a, b)``: classes whose fingerprints a forest of links within ``RADIUS`` bits connects; equal ones form a star."""
    named = classes.select("f0", "class")
    prints = through_disk(named.groupBy("f0").agg(F.min("class").alias("id")), "fingerprints")
    near = simhash_links(prints, 1, RADIUS, range(1, RADIUS + 2))
    star = named.join(prints, "f0").select(F.col("id").alias("a"), F.col("class").alias("b"))
    return near.union(star).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct()


def _apart(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """The ``pairs(a, b)`` of different components."""
    x, y = (labels.select(F.col("id").alias(c), F.col("component").alias(f"of_{c}")) for c in "ab")
    met = pairs.join(x, "a", "left").join(y, "b", "left")
    return met.where(F.coalesce("of_a", "a") != F.coalesce("of_b", "b")).select("a", "b")


def _verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The links among ``pairs(a, b)``."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                keep.append(bool(similar(len(np.intersect1d(p, q, assume_unique=True)), len(p), len(q), similarity)))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    first = sets.select(F.col("class").alias("a"), F.col("hashes").alias("x"))
    second = sets.select(F.col("class").alias("b"), F.col("hashes").alias("y"))
    return pairs.join(first, "a").join(second, "b").select("a", "b", "x", "y").mapInArrow(lean(task), "a bigint, b bigint")


def cross_links(classes: np.ndarray, component: np.ndarray, half: np.ndarray, blobs: list[bytes], similarity: float) -> list[tuple[int, int]]:
    """Enough links to connect the components of a tile that links connect: of half 0 with half 1, or all if one half is empty."""
    _, at = np.unique(np.frombuffer(b"".join(blobs), np.uint64), return_inverse=True)
    size = np.array([len(b) // 8 for b in blobs])
    edges = np.concatenate([[0], np.cumsum(size)])
    mark = np.zeros(len(at) + 1, np.int32)
    both = len(np.unique(half)) > 1
    out = []
    _, root = np.unique(component, return_inverse=True)  # a component's name in the tile falls together with those it is linked to
    for i in range(len(blobs)):
        if both and half[i]:
            continue
        own = at[edges[i] : edges[i + 1]]
        mark[own] = 1
        shared = np.add.reduceat(mark[at], edges[:-1])
        mark[own] = 0
        hit = similar(shared, size[i], size, similarity) & (root != root[i]) & ((half == 1) if both else True)
        others, at_ = np.unique(root[hit], return_index=True)
        out += [(int(classes[i]), int(classes[j])) for j in np.flatnonzero(hit)[at_]]
        root[np.isin(root, others)] = root[i]
    return out


def _links_of_full_keys(full: DataFrame, labels: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """``(a, b)``: links between components that meet in ``full(key, class, n)``."""
    member = full.join(labels.select(F.col("id").alias("class"), "component"), "class", "left").select("key", "class", "n", F.coalesce("component", "class").alias("component"))
    mixed = member.groupBy("key").agg(F.min("component").alias("least"), F.max("component").alias("most")).where("least <> most").select("key")
    chunks = F.ceil(F.col("n") / CHUNK).cast("int")
    own = member.join(mixed, "key").withColumn("own", F.pmod(F.xxhash64("class"), chunks).cast("int"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), chunks - 1)))
    tiles = dealt.select("key", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), (F.col("own") > F.col("other")).cast("int").alias("half"), "class", "component")

    def tile(t: pa.Table) -> pa.Table:
        links = cross_links(*(t.column(c).to_numpy() for c in ("class", "component", "half")), t.column("hashes").to_pylist(), similarity)
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return tiles.join(sets, "class").groupBy("key", "p", "q").applyInArrow(lean(tile), "a bigint, b bigint")


def similar_rows(docs: DataFrame, similarity: float = 0.8, shingle: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, text_hash, group)`` for each row; ``text_hash`` is the XXH64 of the text, a null one taken as empty."""
    texts = id_and_text(docs, id_col, text_col).withColumn("text_hash", F.xxhash64("text"))
    prints = through_disk(_prints(texts, shingle), "shingle-prints")
    classes = through_disk(prints.dropDuplicates(["class"]).select("class", "text_hash", "f0", "keys"), "shingle-classes")
    alike = through_disk(_near_fingerprints(classes), "near-fingerprints")
    keyed = classes.select("class", F.explode("keys").alias("key"))
    count = keyed.groupBy("key").agg(F.count("*").alias("n"), F.min("class").alias("pivot")).where("n > 1")
    shared = through_disk(keyed.join(count, "key").select("key", "class", "n", "pivot"), "shared-keys")
    full = shared.where(F.col("n") > RUN)
    few = shared.where(F.col("n") <= RUN).groupBy("key").agg(F.collect_list("class").alias("own"))
    pairs = few.select(F.explode("own").alias("a"), "own").select("a", F.explode("own").alias("b")).where("a < b")
    pairs = through_disk(pairs.union(full.select(F.col("pivot").alias("a"), F.col("class").alias("b")).where("a < b")).distinct(), "pairs")
    suspects = shared.select("class").union(alike.select("a")).union(alike.select("b")).distinct().join(classes.select("class", "text_hash"), "class")
    bodies = texts.join(suspects, "text_hash").select("class", "text").dropDuplicates(["class"])
    sets = through_disk(_sets(bodies, shingle), "shingle-sets")
    first = pairs.groupBy("b").agg(F.min("a").alias("a")).select("a", "b").union(alike).distinct()
    links = through_disk(_verified(first, sets, similarity), "similar")
    labels = components(links)
    apart = through_disk(_apart(pairs.join(first, ["a", "b"], "left_anti"), labels), "apart")
    if apart.limit(1).count():
        links = through_disk(links.union(_verified(apart, sets, similarity)), "similar")
        labels = components(links)
    if full.limit(1).count():
        more = through_disk(_links_of_full_keys(full, labels, sets, similarity), "similar")
        if more.limit(1).count():
            labels = components(links.union(more))
    return prints.join(labels.withColumnRenamed("id", "class"), "class", "left").select("doc_id", "text_hash", F.coalesce("component", "class").alias("group"))


def similar_groups(docs: DataFrame, similarity: float = 0.8, shingle: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, component_id)``: the smallest id of the rows reached over links of Jaccard similarity ``similarity`` or more."""
    rows = through_disk(similar_rows(docs, similarity, shingle, id_col, text_col), "groups")
    return rows.join(rows.groupBy("group").agg(F.min("doc_id").alias("component_id")), "group").select("doc_id", "component_id")
