"""SimHash fingerprints and near-duplicate groups by the generalised pigeonhole principle.

Fingerprints of ``64 * words`` bits; two texts are linked if theirs differ in at most
``radius`` bits. Equal fingerprints become one class at once, so only distinct ones are
compared. The bits are dealt to partitions, correlated ones together; partition i gets a
threshold t_i of -1 or more with ``sum(t_i + 1) = radius + 1``, so that any linked pair
agrees up to t_i bits in some partition. A dynamic programme over partitions picks the
thresholds that minimise the candidates estimated on a bounded sample of fingerprints. Since
the thresholds always meet the whole radius, every choice finds every link: sample and row
count steer cost alone.

A fingerprint is indexed by its value in each used partition and probes all values within
t_i. Rows meet by key. A key of up to ``RUN`` fingerprints is compared in one sorted run of
a task and yields a spanning forest of its links, not all pairs. A fuller key is hot: with
``radius`` up to 2 its fingerprints go on to an exact detour, in which each names itself and
its one-bit neighbours; two fingerprints are within 2 bits if and only if they share such a
name, and a name has at most ``bits + 1`` members. With larger radii a run of any length is
clustered around pivots in one task at 8 bytes a word and member.

Results: ``component_id`` is the smallest id reachable over links. Null text is empty; an
empty text has fingerprint zero and is linked like any other; rows of equal ids share one
class; a row of null id links others but is never the smallest: a group of such rows alone has
a null ``component_id``; an empty table stays empty.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean, through_disk
from forkline.llm.components import components
from forkline.llm.textblock import blocks, mix

SEED = 42
#: Fingerprints that steer the choice of thresholds, and members of a key that one run compares.
PLAN_SAMPLE, RUN = 20_000, 512


def majority_bits(base: np.ndarray, owner_edges: np.ndarray, words: int = 1) -> np.ndarray:
    """(texts, words) fingerprints of 64-bit hashes grouped by text: a bit is one if set in over half of them."""
    n = len(owner_edges) - 1
    out = np.zeros((n, words), np.uint64)
    size = np.diff(owner_edges)
    some = np.flatnonzero(size)
    if not len(some):
        return out
    for k in range(words):
        h = mix(base, k) if k else base
        i = 0
        while i < len(some):  # so many texts that their bits take some megabytes
            j = max(i + 1, int(np.searchsorted(owner_edges[some], owner_edges[some[i]] + 40_000, side="left")))
            own = some[i:j]
            first, last = owner_edges[own[0]], owner_edges[own[-1] + 1]
            if j == i + 1:
                ones = sum((np.unpackbits(h[x : min(x + 40_000, last)].view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.int64) for x in range(first, last, 40_000)), np.zeros(64, np.int64))[None]
            else:
                bits = np.unpackbits(h[first:last].view(np.uint8), bitorder="little").reshape(-1, 64)
                ones = np.add.reduceat(bits, owner_edges[own] - first, axis=0, dtype=np.int32)
            set_ = (2 * ones > size[own][:, None]).astype(np.uint8)
            out[own, k] = np.packbits(set_, axis=1, bitorder="little").view(np.uint64)[:, 0]
            i = j
    return out


def _shingle_hashes(buffer: bytes, starts: list[int], ends: list[int]) -> np.ndarray:
    """XXH64 of byte spans."""
    from xxhash import xxh64_intdigest

    return np.fromiter((xxh64_intdigest(buffer[a:b], SEED) for a, b in zip(starts, ends, strict=True)), np.uint64, len(starts))


def fingerprints(docs: DataFrame, shingle: int = 3, words: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, f0, f1, ...)``: SimHash over word shingles with A-Z lower-cased, repeats included, hashed by XXH64."""
    schema = pa.schema([("doc_id", pa.int64()), *((f"f{k}", pa.int64()) for k in range(words))])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, raw in blocks(batch.column(1)):
                block = raw.lowered()
                s, e, doc = block.words()
                # words of a text in a row, parted by one space
                length = e - s
                at = np.concatenate([[0], np.cumsum(length + 1)])
                flat = np.full(at[-1], 32, np.uint8)
                inside = np.ones(at[-1], bool)
                inside[at[1:] - 1] = False
                word = np.zeros(len(block.data) + 1, np.int8)
                word[s] += 1
                np.add.at(word, e, -1)
                flat[inside] = block.data[np.cumsum(word)[:-1] > 0]
                count = np.bincount(doc, minlength=block.n_docs)
                shingles = np.where(count >= shingle, count - shingle + 1, np.minimum(count, 1))
                edges = np.concatenate([[0], np.cumsum(shingles)])
                word0 = np.concatenate([[0], np.cumsum(count)])[:-1]
                w = np.arange(edges[-1]) - np.repeat(edges[:-1] - word0, shingles)
                last = w + np.repeat(np.minimum(count, shingle), shingles) - 1
                f = majority_bits(_shingle_hashes(flat.tobytes(), at[w].tolist(), (at[last + 1] - 1).tolist()), edges, words)
                ids = batch.column(0).slice(first, block.n_docs)
                yield pa.RecordBatch.from_arrays([ids, *(pa.array(f[:, k].view(np.int64)) for k in range(words))], schema=schema)

    return id_and_text(docs, id_col, text_col).mapInArrow(lean(task), "doc_id bigint, " + ", ".join(f"f{k} bigint" for k in range(words)))


def bit_groups(bits: np.ndarray, parts: int) -> list[np.ndarray]:
    """Deal bit positions to ``parts`` groups of nearly equal size, each grown by the bit most correlated with it."""
    rows, n = bits.shape
    x = bits.astype(np.float64)
    ones, both = x.sum(0), x.T @ x  # whole numbers, hence exact in any order of summation
    spread = np.sqrt(rows * ones - ones**2) + 1e-9
    r = np.abs(rows * both - np.outer(ones, ones)) / np.outer(spread, spread)
    left, groups = set(range(n)), []
    for k in range(parts):
        size = n // parts + (k < n % parts)
        own = [min(left)]
        left.discard(own[0])
        while len(own) < size:
            nxt = max(left, key=lambda b, own=own: (r[b, own].sum(), -b))
            own.append(nxt)
            left.discard(nxt)
        groups.append(np.array(sorted(own)))
    return groups


def variants(width: int, t: int) -> list[int]:
    """XOR masks of all values within ``t`` bits."""
    return [sum(1 << b for b in some) for k in range(t + 1) for some in itertools.combinations(range(width), k)]


def thresholds(values: list[np.ndarray], widths: list[int], radius: int, total: int) -> tuple[float, list[int]]:
    """The cheapest t_i >= -1 with ``sum(t_i + 1) == radius + 1``: probes plus estimated candidates, by dynamic programming."""
    scale = total / max(1, len(values[0])) if values else 1
    cost = []
    for v, w in zip(values, widths, strict=True):
        seen, count = np.unique(v, return_counts=True)
        row = [0.0]
        for t in range(min(radius, 2) + 1):
            masks = variants(w, t)
            near = 0.0
            for m in masks if len(masks) <= 64 else masks[:: len(masks) // 64]:
                other = np.searchsorted(seen, seen ^ np.uint64(m))
                other[other == len(seen)] = 0
                near += float((count * count[other])[seen[other] == (seen ^ np.uint64(m))].sum())
            near *= len(masks) / min(64, len(masks))
            chance = len(masks) * total * total / 2.0**w
            row.append(len(masks) * total * 10 + max(near * scale * scale - scale * len(v), chance))
        cost.append(row)
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for row in cost:
        step: dict[int, tuple[float, list[int]]] = {}
        for spent, (c, chosen) in best.items():
            for t, own in enumerate(row, start=-1):
                if spent + t + 1 <= radius + 1:
                    new = (c + own, [*chosen, t])
                    if spent + t + 1 not in step or new[0] < step[spent + t + 1][0]:
                        step[spent + t + 1] = new
        best = step
    return best.get(radius + 1, (math.inf, []))


def choose(sample: np.ndarray, bits: int, radius: int, total: int, parts_tried: range) -> list[tuple[np.ndarray, int]]:
    """Bit groups with their thresholds, of the cheapest number of partitions."""
    as_bits = np.unpackbits(sample.view(np.uint8), axis=1, bitorder="little").reshape(len(sample), bits)
    found = (math.inf, [])
    for parts in parts_tried:
        if bits / parts > 60:
            continue
        groups = bit_groups(as_bits, parts)
        values = [(as_bits[:, g].astype(np.uint64) << np.arange(len(g), dtype=np.uint64)).sum(1, dtype=np.uint64) for g in groups]
        c, t = thresholds(values, [len(g) for g in groups], radius, total)
        if c < found[0]:
            found = (c, [(g, x) for g, x in zip(groups, t, strict=True) if x >= 0])
    if not found[1]:
        raise ValueError("no partition meets the radius; allow more partitions")
    return found[1]


def forest(ids: np.ndarray, f: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links that connect what all links within ``radius`` connect, among distinct fingerprints of one run."""
    n = len(ids)
    root = np.arange(n)
    edges = []
    if n <= 64:
        near = np.bitwise_count(f[:, None, :] ^ f[None, :, :]).sum(2) <= radius
        seen = np.zeros(n, bool)
        for i in range(n):
            if seen[i]:
                continue
            seen[i] = True
            todo = [i]
            while todo:
                x = todo.pop()
                new = np.flatnonzero(near[x] & ~seen)
                seen[new] = True
                edges += [(ids[i], ids[y]) for y in new]
                todo += new.tolist()
        return edges
    # clusters around pivots; two clusters can only touch if their pivots are within 3 radii
    free, pivots, members = np.ones(n, bool), [], []
    while free.any():
        p = int(np.argmax(free))
        own = np.flatnonzero(free & (np.bitwise_count(f ^ f[p]).sum(1) <= radius))
        free[own] = False
        pivots.append(p)
        members.append(own)
        root[own] = p
        edges += [(ids[p], ids[x]) for x in own if x != p]

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = int(root[x])
        return x

    heads = f[pivots]
    for a in range(len(pivots)):
        close = np.flatnonzero(np.bitwise_count(heads[a + 1 :] ^ heads[a]).sum(1) <= 3 * radius) + a + 1
        for b in close.tolist():
            if find(pivots[a]) == find(pivots[b]):
                continue
            x, y = members[a], members[b]
            for i in x if len(x) < len(y) else y:
                other = y if len(x) < len(y) else x
                hit = np.flatnonzero(np.bitwise_count(f[other] ^ f[i]).sum(1) <= radius)
                if len(hit):
                    edges.append((ids[i], ids[other[hit[0]]]))
                    root[find(pivots[a])] = find(pivots[b])
                    break
    return edges


def links(classes: DataFrame, words: int, radius: int, parts: range) -> DataFrame:
    """``(a, b)``: enough links among distinct fingerprints ``(id, f0, ...)`` to connect all that are within ``radius`` bits."""
    names = [f"f{k}" for k in range(words)]
    total = classes.count()
    bits = 64 * words
    rows = classes.select(*names).orderBy(F.xxhash64(*names)).limit(PLAN_SAMPLE).toPandas()
    if len(rows) == 0:
        return classes.select(F.col("id").alias("a"), F.col("id").alias("b")).limit(0)
    plan = choose(np.ascontiguousarray(rows.to_numpy(np.int64)).view(np.uint64), bits, radius, total, parts)

    def key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            f = np.stack([batch.column(1 + k).to_numpy() for k in range(words)], axis=1).view(np.uint64)
            for at in range(0, len(f), 2000):
                part = np.ascontiguousarray(f[at : at + 2000])
                flat = np.unpackbits(part.view(np.uint8), axis=1, bitorder="little").reshape(len(part), bits)
                ids = batch.column(0).slice(at, 2000)
                for p, (group, t) in enumerate(plan):
                    value = (flat[:, group].astype(np.uint64) << np.arange(len(group), dtype=np.uint64)).sum(1, dtype=np.uint64)
                    for mask in variants(len(group), t):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), p, np.int32)), pa.array((value ^ np.uint64(mask)).view(np.int64)), pa.array(np.full(len(part), mask == 0)), ids, *(pa.array(part[:, k].view(np.int64)) for k in range(words))], names=["part", "value", "own", "id", *names])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def runs(table: np.ndarray) -> Iterator[pa.RecordBatch]:
            new = np.flatnonzero((table[1:, :2] != table[:-1, :2]).any(1)) + 1
            edges: list[tuple[int, int]] = []
            cuts = np.concatenate([[0], new, [len(table)]])
            for i in np.flatnonzero(np.diff(cuts) > 1).tolist():
                run = table[cuts[i] : cuts[i + 1]]
                edges += forest(run[:, 2], np.ascontiguousarray(run[:, 3:]).view(np.uint64), radius)
            if edges:
                yield pa.RecordBatch.from_arrays([pa.array([int(a) for a, _ in edges], pa.int64()), pa.array([int(b) for _, b in edges], pa.int64())], names=["a", "b"])

        for batch in batches:
            table = np.stack([batch.column(k).to_numpy().astype(np.int64) for k in range(batch.num_columns)], axis=1)
            if not len(table):
                continue
            if held and (held[-1][-1, :2] == table[-1, :2]).all():
                held.append(table)
                continue
            last = len(table) - int(np.argmax((table[::-1, :2] != table[-1, :2]).any(1))) if (table[:, :2] != table[-1, :2]).any() else 0
            yield from runs(np.concatenate([*held, table[:last]]))
            held = [table[last:]]
        if held:
            yield from runs(np.concatenate(held))

    keyed = classes.select("id", *names).mapInArrow(lean(key), "part int, value bigint, own boolean, id bigint, " + ", ".join(f"{n} bigint" for n in names))
    count = keyed.groupBy("part", "value").agg(F.count("*").alias("n"), F.max("own").alias("indexed")).where("n > 1 AND indexed")
    shared = keyed.drop("own").join(count.drop("indexed"), ["part", "value"])
    usual = shared if radius > 2 else shared.where(F.col("n") <= RUN)
    near = usual.drop("n").repartition("part", "value").sortWithinPartitions("part", "value").mapInArrow(lean(compare), "a bigint, b bigint")
    if radius > 2:
        return near
    hot = shared.where(F.col("n") > RUN).select("id", "f0").distinct()
    flips = F.array(F.lit(0).cast("bigint"), *(F.shiftleft(F.lit(1).cast("bigint"), b) for b in range(bits)))
    named = hot.select("id", F.explode(F.transform(flips, lambda m: F.col("f0").bitwiseXOR(m))).alias("name"))
    stars = named.groupBy("name").agg(F.collect_list("id").alias("ids")).where(F.size("ids") > 1)
    meets = stars.select(F.array_min("ids").alias("a"), F.explode("ids").alias("b")).where("a <> b").distinct()
    return near.unionByName(meets)


def near_duplicate_groups(prints: DataFrame, words: int, radius: int, parts: range | None = None) -> DataFrame:
    """``prints`` with ``component_id``. ``prints(doc_id, f0, ...)`` is read several times: write it first.

    Classes are named by their fingerprints, so a class without an id links others all the same.
    """
    names = [f"f{k}" for k in range(words)]
    name = F.col("f0") if words == 1 else F.xxhash64(*names)
    classes = through_disk(prints.groupBy(*names).agg(F.min("doc_id").alias("least")).withColumn("id", name), "fingerprints")
    reached = components(links(classes, words, radius, parts or range(1, radius + 2)))
    grouped = classes.join(reached, "id", "left").select(*names, "least", F.coalesce("component", "id").alias("group"))
    grouped = through_disk(grouped, "groups")
    named = grouped.join(grouped.groupBy("group").agg(F.min("least").alias("component_id")), "group").drop("group", "least")
    return prints.join(named, names)


def simhash_groups(docs: DataFrame, shingle: int = 3, radius: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` of 64-bit fingerprints linked within ``radius`` bits."""
    prints = through_disk(fingerprints(docs, shingle, 1, id_col, text_col), "simhash")
    found = near_duplicate_groups(prints, 1, radius)
    return found.select("doc_id", F.lpad(F.lower(F.hex("f0")), 16, "0").alias("fingerprint"), "component_id")
