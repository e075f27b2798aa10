"""Language-model scoring: a hashed maximum-entropy model with a class-factored softmax.

The probability of a token is that of its class given the classes before it, times that of
its slot within the class given the words before it, times that of the token within the slot.
Words fall into ``cells`` by their last three bytes and length; cells are clustered into
classes by the cells around them, counted over all training texts; the cells of a class are
dealt to its ``slots`` by rank of their counts.

* Class layer: a softmax over ``classes``. Its features are n-grams and skips of the three
  classes before (first, second, third, first+second, first+third, second+third), hashed to
  ``2 ** bits`` rows.
* Word layer: a softmax over the slots of the class. Its features are the class itself, the
  word before, and, skipping that, the word two before, each together with the class and
  hashed to ``2 ** b`` rows; ``b`` follows the logarithm of the training volume up to
  ``word_bits``.
* Within a slot a word has its relative count, smoothed by one for each word and for one
  unknown word. So all probabilities after a history sum to one.

What is gathered from the corpus covers all training texts and grows with it:

* counts of cells with their neighbours, and of classes in context, summed in Spark; their
  number of distinct rows is bounded by the model's size;
* the word layer's sums of features, over all training tokens;
* counts of words: chunks of documents send each distinct word's count once to a bucket and
  get the corpus count back (packed hashes of 64 bits; two words that share one are counted
  as one). The vocabulary is never broadcast or collected.

Both layers are trained by distributed gradient updates: partitions add up observed and
expected feature counts under the present weights, whose difference is the gradient of the
log likelihood; the step divides it by the expected count, a bound of the curvature's
diagonal, and by the number of features that act at once. The class layer begins with the
relative counts after two classes and sees the table of all contexts in each round. The word
layer begins with the relative counts of the slots; each of its rounds sees another part of
the training texts, which together are all of them, and sums parts by blocks of rows on the
executors. Scoring is vectorised in sparse batches: a token gathers the rows of its features.

A text is its words, A-Z lower-cased, then one end token. Null text is empty and has the end
token alone. A null id is never held out. Rows of equal or null ids are scored apart; an
empty table stays empty; without training texts all layers are uniform.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import Grid, id_and_text, into_chunks, lean, through_disk, volume
from forkline.llm.textblock import blocks, by_bucket, mix

END = np.uint64(0x9D5C_3A77_E1B2_4F01)


@dataclass(frozen=True)
class Settings:
    cells: int = 4096
    around: int = 32  # hashed neighbours on each side that describe a cell
    classes: int = 32
    bits: int = 12
    rounds: int = 12
    ridge: float = 2.0
    slots: int = 32
    word_bits: int = 14  # of the volume's logarithm, ten less
    word_rounds: int = 3


@dataclass(frozen=True)
class Tokens:
    """Tokens of many texts in a row: word hash, cell (-1: end) and text."""

    word: np.ndarray
    cell: np.ndarray
    owner: np.ndarray


def tokens(texts: pa.ChunkedArray | pa.Array, s: Settings) -> Tokens:
    word, cell, owner = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for first, raw in blocks(texts):
        block = raw.lowered()
        starts, ends, doc = block.words()
        tail = np.minimum(ends - starts, 4).astype(np.uint64)
        with np.errstate(over="ignore"):
            for j in (1, 2, 3):
                at = ends - j
                tail = tail * np.uint64(257) + np.where(at >= starts, block.data[np.maximum(at, 0)].astype(np.uint64) + np.uint64(1), np.uint64(0))
        n = len(starts) + block.n_docs
        place = np.arange(len(starts)) + doc
        h, c = np.full(n, END), np.full(n, -1, np.int64)
        h[place] = block.hashes(starts, ends)
        c[place] = (mix(tail) % np.uint64(s.cells)).astype(np.int64)
        word.append(h)
        cell.append(c)
        owner.append(np.repeat(np.arange(block.n_docs), np.bincount(doc, minlength=block.n_docs) + 1) + first)
    return Tokens(np.concatenate(word), np.concatenate(cell), np.concatenate(owner))


def contexts(t: Tokens, classes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Class of each token (0: end) and its context code ``(first * k + second) * k + third``; 0 before the start."""
    y = np.where(t.cell < 0, 0, classes[t.cell])
    code = np.zeros(len(y), np.int64)
    for j in (1, 2, 3):
        before = np.zeros(len(y), np.int64)
        before[j:] = np.where(t.owner[j:] == t.owner[:-j], y[:-j], 0)
        code = code * k + before
    return y, code


def features(code: np.ndarray, k: int, bits: int) -> np.ndarray:
    """Hashed feature rows (contexts, 6)."""
    a, b, c = code // (k * k), code // k % k, code % k
    raw = np.stack([a, b, c, a * k + b, a * k + c, b * k + c], axis=1).astype(np.uint64)
    return (mix(raw + (np.arange(6, dtype=np.uint64) << np.uint64(40))) >> np.uint64(64 - bits)).astype(np.int64)


def log_probabilities(weights: np.ndarray, code: np.ndarray, k: int, bits: int) -> np.ndarray:
    z = weights[features(code, k, bits)].sum(1)
    z -= z.max(1, keepdims=True)
    return z - np.log(np.exp(z).sum(1, keepdims=True))


def cluster(rows: np.ndarray, weight: np.ndarray, k: int, rounds: int = 20) -> np.ndarray:
    """Weighted k-means from the heaviest rows."""
    centre = rows[np.argsort(-weight, kind="stable")[:k]].copy()
    own = np.zeros(len(rows), np.int64)
    for _ in range(rounds):
        own = ((centre**2).sum(1)[None] - 2 * rows @ centre.T).argmin(1)
        for j in range(k):
            held = weight * (own == j)
            if held.sum() > 0:
                centre[j] = held @ rows / held.sum()
    return own


def words_before(t: Tokens, y: np.ndarray, bits: int) -> np.ndarray:
    """Hashed rows (tokens, 2) of the word before and the one before that, each with the token's class."""
    out = np.empty((len(y), 2), np.int64)
    with np.errstate(over="ignore"):
        for j in (1, 2):
            word = np.zeros(len(y), np.uint64)
            word[j:] = np.where(t.owner[j:] == t.owner[:-j], t.word[:-j], np.uint64(0))
            out[:, j - 1] = (mix(word * np.uint64(0x9E3779B97F4A7C15) + y.astype(np.uint64), j) >> np.uint64(64 - bits)).astype(np.int64)
    return out


@dataclass(frozen=True)
class WordLayer:
    """Scores of slots: ``bias`` (classes, slots), very low where a class has none; ``weights`` (2, rows, slots)."""

    slot_of_cell: np.ndarray
    bias: np.ndarray
    weights: np.ndarray
    bits: int

    def slot(self, t: Tokens) -> np.ndarray:
        return np.where(t.cell < 0, 0, self.slot_of_cell[t.cell])

    def log_probabilities(self, y: np.ndarray, rows: np.ndarray) -> np.ndarray:
        z = self.bias[y] + self.weights[0][rows[:, 0]] + self.weights[1][rows[:, 1]]
        z -= z.max(1, keepdims=True)
        return z - np.log(np.exp(z).sum(1, keepdims=True))


#: Tokens whose scores are computed at once, blocks of rows that sums travel in, and sums of a block that one group adds up.
SLICE, BLOCKS, FAN = 20_000, 8, 256


def _short(x: np.ndarray) -> bytes:
    """Floats rounded to eight bits of mantissa, compressed."""
    return zlib.compress(((np.ascontiguousarray(x, np.float32).view(np.uint32) + np.uint32(0x8000)) & np.uint32(0xFFFF0000)).tobytes(), 1)


def _long(blob: bytes) -> np.ndarray:
    return np.frombuffer(zlib.decompress(blob), np.float32)


def train_words(learn: DataFrame, classes: np.ndarray, layer: WordLayer, s: Settings) -> WordLayer:
    """The layer after ``word_rounds`` steps, each on another part of ``learn(part, text)``."""
    sc, size = learn.sparkSession.sparkContext, layer.weights.size
    for k in range(s.word_rounds):
        shared = sc.broadcast((classes, layer))  # of the model's size

        def part(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            classes, own = shared.value
            rows, slots = own.weights.shape[1:]
            seen, expected = np.zeros((2, rows * slots)), np.zeros((2, rows * slots))
            some = False
            for batch in batches:
                for first in range(0, batch.num_rows, 1000):
                    t = tokens(batch.column(0).slice(first, 1000), s)
                    y = np.where(t.cell < 0, 0, classes[t.cell])
                    slot, before = own.slot(t), words_before(t, y, own.bits)
                    for i in range(0, len(y), SLICE):
                        at, some = slice(i, i + SLICE), True
                        model = np.exp(own.log_probabilities(y[at], before[at]))
                        for j in (0, 1):
                            seen[j] += np.bincount(before[at, j] * slots + slot[at], minlength=rows * slots)
                            expected[j] += np.bincount((before[at, j][:, None] * slots + np.arange(slots)).ravel(), weights=model.ravel(), minlength=rows * slots)
            if some:
                pieces = [np.array_split(x.ravel(), BLOCKS) for x in (seen, expected)]
                yield pa.RecordBatch.from_arrays([pa.array(range(BLOCKS), pa.int32()), pa.array([TaskContext.get().partitionId()] * BLOCKS, pa.int32()), *(pa.array([_short(x) for x in p], pa.binary()) for p in pieces)], names=["block", "lane", "seen", "expected"])

        def add_up(t: pa.Table) -> pa.Table:
            sums = [sum(_long(x).astype(np.float64) for x in t.column(c).to_pylist()) for c in ("seen", "expected")]
            return pa.table({**{c: pa.array([t.column(c)[0].as_py()], pa.int32()) for c in ("block", "lane")}, **{c: pa.array([_short(x)], pa.binary()) for c, x in zip(("seen", "expected"), sums, strict=True)}})

        kinds = "block int, lane int, seen binary, expected binary"
        texts = learn.where(F.col("part") == k).select("text")
        sums, lanes = texts.mapInArrow(lean(part), kinds), texts.rdd.getNumPartitions()
        while lanes > FAN:  # a tree, so that a group stays small however many tasks there are
            sums, lanes = sums.withColumn("lane", F.floor(F.col("lane") / FAN).cast("int")).groupBy("block", "lane").applyInArrow(lean(add_up), kinds), -(-lanes // FAN)
        found = sums.groupBy("block").applyInArrow(lean(add_up), kinds).collect()  # BLOCKS rows
        shared.unpersist()
        if not found:
            continue
        found.sort(key=lambda r: r["block"])
        seen, expected = (np.concatenate([_long(r[c]) for r in found]).astype(np.float64) for c in ("seen", "expected"))
        if seen.size != size:
            raise ValueError("sums of another size than the model's")
        step = (seen - expected) / (expected + s.ridge) / 2
        layer = WordLayer(layer.slot_of_cell, layer.bias, (layer.weights.ravel() + np.clip(step, -1, 1)).reshape(layer.weights.shape).astype(np.float32), layer.bits)
    return layer


def _sums(docs: DataFrame, count) -> DataFrame:
    """``(code, n)`` summed over tasks; ``count(texts)`` gives the codes of a batch, which a task adds up before it sends."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for batch in batches:
            for i in range(0, batch.num_rows, 1000):
                codes = count(batch.column(0).slice(i, 1000))
                both = np.concatenate([held[0], codes])
                values, where = np.unique(both, return_inverse=True)
                held = values, np.bincount(where, weights=np.concatenate([held[1], np.ones(len(codes))]), minlength=len(values)).astype(np.int64)
        for i in range(0, len(held[0]), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(held[0][i : i + 100_000]), pa.array(held[1][i : i + 100_000])], names=["code", "n"])

    return docs.select("text").mapInArrow(lean(task), "code bigint, n bigint").groupBy("code").agg(F.sum("n").alias("n"))


def induce_classes(docs: DataFrame, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Class 1 and up of each cell, and how often cells have a neighbour, from counts over all of ``docs(text)``."""
    width = 2 * s.around

    def count(texts: pa.Array) -> np.ndarray:
        t = tokens(texts, s)
        near = (mix(t.cell.astype(np.uint64), 5) % np.uint64(s.around)).astype(np.int64)
        own = np.flatnonzero((t.owner[1:] == t.owner[:-1]) & (t.cell[1:] >= 0))
        return np.concatenate([t.cell[own] * width + s.around + near[own + 1], t.cell[own + 1] * width + near[own]])

    table = np.zeros(s.cells * width)
    rows = _sums(docs, count).toPandas()  # at most cells * width rows
    table[rows["code"].to_numpy(np.int64)] = rows["n"].to_numpy(np.float64)
    table = table.reshape(s.cells, width)
    share = (table.sum(0) + 1) / (table.sum() + width)
    rows = np.log((table + share * 20) / ((table.sum(1, keepdims=True) + 20) * share))
    return cluster(rows, np.sqrt(table.sum(1) + 0.1), s.classes - 1) + 1, table.sum(1)


def first_layer(classes: np.ndarray, often: np.ndarray, s: Settings, bits: int) -> WordLayer:
    """Slots of all cells, and the relative counts of slots as the only scores."""
    slot, bias = np.zeros(s.cells, np.int64), np.full((s.classes, s.slots), -1e9)
    bias[0, 0] = 0  # the end token's
    for c in range(1, s.classes):
        own = np.flatnonzero(classes == c)
        own = own[np.argsort(-often[own], kind="stable")]
        slot[own] = np.arange(len(own)) % s.slots
        used = min(len(own), s.slots)
        bias[c, :used] = np.log(np.bincount(slot[own], weights=often[own], minlength=s.slots)[:used] + 1)
    return WordLayer(slot, bias.astype(np.float32), np.zeros((2, 1 << bits, s.slots), np.float32), bits)


def train(table: DataFrame, s: Settings) -> np.ndarray:
    """Weights (2 ** bits, classes) of the class layer from ``table(context, classes, counts)``."""
    k, rows = s.classes, 1 << s.bits
    weights = np.zeros((rows, k))
    sc = table.sparkSession.sparkContext
    empirical = None
    for _ in range(s.rounds):
        shared = sc.broadcast(weights.astype(np.float32))

        def part(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            seen, expected = np.zeros((rows, k)), np.zeros((rows, k))
            for batch in batches:
                code = batch.column(0).to_numpy()
                own = np.zeros((len(code), k))
                for i, (ys, ns) in enumerate(zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)):
                    own[i, ys] = ns
                model = np.exp(log_probabilities(shared.value, code, k, s.bits)) * own.sum(1, keepdims=True)
                f = features(code, k, s.bits)
                for j in range(f.shape[1]):
                    np.add.at(seen, f[:, j], own)
                    np.add.at(expected, f[:, j], model)
            yield pa.RecordBatch.from_arrays([pa.array([zlib.compress(np.stack([seen, expected]).astype(np.float32).tobytes(), 1)])], names=["sums"])

        parts = [np.frombuffer(zlib.decompress(r["sums"]), np.float32).reshape(2, rows, k).astype(np.float64) for r in table.mapInArrow(lean(part), "sums binary").collect()]
        if not parts:
            return weights
        seen, expected = np.sum(parts, axis=0)
        if empirical is None:
            # begin with the relative counts after the two classes before
            empirical = seen
            share = seen[np.unique(features(np.arange(k**3), k, s.bits)[:, 0])].sum(0) + s.ridge
            share /= share.sum()
            pairs = np.unique(features(np.arange(k**3), k, s.bits)[:, 3])
            weights[pairs] = np.log((seen[pairs] + s.ridge * k * share) / (seen[pairs].sum(1, keepdims=True) + s.ridge * k))
        else:
            # every token has six features that act at once
            weights += np.clip((empirical - expected) / (expected + s.ridge / k), -1, 1) / 6
        shared.unpersist()
    return weights


def _unique_words(t: Tokens, y: np.ndarray, learn: np.ndarray, buckets: int):
    """Distinct words of a chunk with training counts and groups; the index of each token's word; positions by bucket."""
    values, first, where = np.unique(t.word, return_index=True, return_inverse=True)
    counts = np.bincount(where[learn], minlength=len(values)).astype(np.int64)
    return values, counts, y[first], where, by_bucket(values, buckets)


@dataclass(frozen=True)
class Model:
    """The trained layers without the words' counts; of fixed size."""

    classes: np.ndarray
    log_class: np.ndarray  # (contexts, classes), to base ten
    words: WordLayer
    settings: Settings

    def places(self, t: Tokens) -> tuple[np.ndarray, np.ndarray]:
        """Group (class and slot) of each token, and the log10 probability of the group after the tokens before."""
        k, slots = self.settings.classes, self.settings.slots
        y, code = contexts(t, self.classes, k)
        slot, before, out = self.words.slot(t), words_before(t, y, self.words.bits), np.zeros(len(y))
        for i in range(0, len(y), SLICE):
            at = slice(i, i + SLICE)
            p = self.words.log_probabilities(y[at], before[at])
            out[at] = p[np.arange(len(p)), slot[at]] / np.log(10)
        return y * slots + slot, out + self.log_class[code, y]

    def groups(self, t: Tokens) -> np.ndarray:
        return np.where(t.cell < 0, 0, self.classes[t.cell]) * self.settings.slots + self.words.slot(t)


def fit(learn: DataFrame, size: int, s: Settings) -> Model:
    """Both layers from ``learn(text, part)`` of about ``size`` bytes; parts 0 to ``word_rounds - 1``."""
    k, spark = s.classes, learn.sparkSession
    classes, often = induce_classes(learn.select("text"), s)

    def in_context(batch: pa.Array) -> np.ndarray:
        y, code = contexts(tokens(batch, s), classes, k)
        return code * k + y

    by_context = _sums(learn.select("text"), in_context).groupBy((F.col("code") / k).cast("bigint").alias("context")).agg(F.collect_list(F.struct((F.col("code") % k).cast("int").alias("y"), "n")).alias("c"))
    table = through_disk(by_context.select("context", F.col("c.y").alias("classes"), F.col("c.n").alias("counts")).coalesce(6), "contexts")
    weights = train(table, s)
    log_class = (log_probabilities(weights, np.arange(k**3), k, s.bits) / np.log(10)).astype(np.float32)
    bits = max(8, min(s.word_bits, int(math.log2(max(1.0, size / 6.5))) - 10))
    return Model(classes, log_class, train_words(learn, classes, first_layer(classes, often, s, bits), s), s)


def score(docs: DataFrame, held_out: Column, settings: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score)``; learns where ``held_out`` (of ``doc_id``) isn't true."""
    s, groups = settings, settings.classes * settings.slots
    texts = id_and_text(docs, id_col, text_col).withColumn("held_out", F.coalesce(held_out, F.lit(False)))
    learn = texts.where(~F.col("held_out")).select("text", F.pmod(F.xxhash64("doc_id"), F.lit(s.word_rounds)).alias("part"))
    spark = docs.sparkSession
    rows, size = volume(texts)
    model = spark.sparkContext.broadcast(fit(learn, size, s))

    grid = Grid(rows, size, 6.5, 0.3)
    buckets = grid.buckets
    chunked = into_chunks(texts, grid.chunks)

    def send(t: pa.Table) -> pa.Table:
        own = tokens(t.column("text"), s)
        learnt = ~t.column("held_out").to_numpy()[own.owner]
        values, counts, kind, _, places = _unique_words(own, model.value.groups(own), learnt, buckets)
        rows = [(b, p) for b, p in enumerate(places) if len(p)]
        return pa.table(
            {
                "bucket": pa.array([b for b, _ in rows], pa.int32()),
                "chunk": pa.array([t.column("chunk")[0].as_py()] * len(rows), pa.int32()),
                "words": pa.array([values[p].tobytes() for _, p in rows], pa.binary()),
                "counts": pa.array([zlib.compress(counts[p].tobytes(), 1) for _, p in rows], pa.binary()),
                "kinds": pa.array([zlib.compress(kind[p].astype(np.uint16).tobytes(), 1) for _, p in rows], pa.binary()),
            }
        )

    def add_up(t: pa.Table) -> pa.Table:
        words = [np.frombuffer(b, np.uint64) for b in t.column("words").to_pylist()]
        counts = np.concatenate([np.frombuffer(zlib.decompress(b), np.int64) for b in t.column("counts").to_pylist()])
        kinds = np.concatenate([np.frombuffer(zlib.decompress(b), np.uint16) for b in t.column("kinds").to_pylist()])
        values, first, where = np.unique(np.concatenate(words), return_index=True, return_inverse=True)
        total = np.bincount(where, weights=counts, minlength=len(values)).astype(np.int64)
        kind = kinds[first]
        n_k, v_k = np.bincount(kind, weights=total, minlength=groups).astype(np.int64), np.bincount(kind[total > 0], minlength=groups)
        ends = np.cumsum([len(w) for w in words])
        back = [zlib.compress(total[where[e - len(w) : e]].tobytes(), 1) for w, e in zip(words, ends, strict=True)]
        bucket = t.column("bucket")[0].as_py()
        return pa.table(
            {
                "chunk": pa.array([*t.column("chunk").to_pylist(), -1], pa.int32()),
                "bucket": pa.array([bucket] * (len(words) + 1), pa.int32()),
                "totals": pa.array([*back, None], pa.binary()),
                "sums": pa.array([*([None] * len(words)), np.concatenate([n_k, v_k]).tolist()], pa.list_(pa.int64())),
            }
        )

    sent = chunked.groupBy("chunk").applyInArrow(lean(send), "bucket int, chunk int, words binary, counts binary, kinds binary")
    answers = through_disk(sent.groupBy("bucket").applyInArrow(lean(add_up), "chunk int, bucket int, totals binary, sums array<bigint>"), "word-counts")
    sums = np.zeros(2 * groups, np.int64)
    for r in answers.where("chunk = -1").select(F.posexplode("sums").alias("i", "n")).groupBy("i").agg(F.sum("n").alias("n")).collect():
        sums[r["i"]] = r["n"]
    n_k, v_k = sums[:groups], sums[groups:]
    n_all, v_all = int(n_k.sum()), int(v_k.sum())
    within = np.log10(n_k + v_k + 1.0)
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])

    def finish(t: pa.Table, told: pa.Table) -> pa.Table:
        if not t.num_rows:
            return schema.empty_table()
        own = tokens(t.column("text"), s)
        group, log_group = model.value.places(own)
        values, _, _, where, places = _unique_words(own, group, np.zeros(len(group), bool), buckets)
        total = np.zeros(len(values), np.int64)
        for b, blob in zip(told.column("bucket").to_pylist(), told.column("totals").to_pylist(), strict=True):
            total[places[b]] = np.frombuffer(zlib.decompress(blob), np.int64)
        count = total[where]
        each = np.log10(total + 1.0)[where]
        add = lambda x: np.bincount(own.owner, weights=x, minlength=t.num_rows)
        n = np.bincount(own.owner, minlength=t.num_rows)
        smooth = add(each)
        columns = [n, add(count > 0).astype(np.int64), np.full(len(n), n_all), smooth - n * np.log10(n_all + v_all + 1.0), smooth + add(log_group - within[group])]
        return pa.table([t.column("doc_id"), t.column("held_out"), *(pa.array(c) for c in columns)], schema=schema)

    told = answers.where("chunk >= 0").select("chunk", "bucket", "totals")
    return chunked.groupBy("chunk").cogroup(told.groupBy("chunk")).applyInArrow(lean(finish), "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")
