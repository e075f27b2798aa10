"""Supervised subword embeddings: hashed word and character n-gram vectors, averaged, softmax on top.

Training: numpy stochastic gradient descent on a bounded sample of labelled rows, picked by
the smallest hash of the id (``sample``, a documented parameter), whole texts of any length.
Executors count a text's hashed features; of a sampled text only these counts reach the
driver, at most ``2 ** bits`` of them. Scoring: every text whole, on the executors.
With a softmax over the average of vectors, a feature acts through its vector's product with
the output layer alone; scoring sums that one number per hashed feature, vectorised.

Characters are Unicode code points, A-Z lower-cased; n-grams run within a word and may take
in one border on each side, as in ``<word>``. Features are the n-grams of each order in
``orders`` and whole words, hashed to ``2 ** bits`` rows.

Null text is empty; an empty text has no features and gets the score of the output bias.
Labels other than 0 and 1, null ones, and rows without a text are left out of training; ids
with several labels count once for each. An empty table stays empty; without both labels in
the sample the score is the share of label 1 (0.5 if there is none).
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean
from forkline.llm.textblock import mix

SLICE_CHARS = 400_000


@dataclass(frozen=True)
class Settings:
    dim: int = 12
    bits: int = 16
    orders: tuple[int, ...] = (3, 4)
    epochs: int = 5
    least_steps: int = 25_000
    rate: float = 0.5
    sample: int = 4000
    seed: int = 7


@dataclass(frozen=True)
class Model:
    weight: np.ndarray  # of label 1 against 0, for each hashed feature
    bias: float
    settings: Settings


_SPACES = np.array([0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D], np.uint32)


def features(texts: list[str], s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of all texts in a row, and how many each text has."""
    joined = "\n" + "\n".join(texts) + "\n"
    c = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    lengths = np.array([len(t) for t in texts])
    edge = np.concatenate([[0], np.cumsum(lengths + 1)])  # place of the border before each text
    space = (c <= 32) & ((c == 32) | ((c >= 9) & (c <= 13)))
    x = np.where(space, np.uint32(32), np.where((c >= 65) & (c <= 90), c + np.uint32(32), c)).astype(np.uint64)
    n = len(x)
    ids, owner = [], []
    gap = np.concatenate([[0], np.cumsum(space)])
    with np.errstate(over="ignore"):
        for order in s.orders:
            m = n - order + 1
            if m <= 0:
                continue
            h = np.zeros(m, np.uint64)
            for j in range(order):
                h = h * np.uint64(0x100000001B3) + x[j : j + m]
            inner = gap[order - 1 : order - 1 + m] - gap[1 : 1 + m]  # white space strictly inside
            at = np.flatnonzero((inner == 0) & ~(space[:m] & space[order - 1 :]))
            ids.append(mix(h[at], order) >> np.uint64(64 - s.bits))
            owner.append(np.searchsorted(edge, at, side="right") - 1)
        start = np.flatnonzero(~space & np.concatenate([[True], space[:-1]]))
        end = np.flatnonzero(~space & np.concatenate([space[1:], [True]])) + 1
        up = np.full(n + 1, np.uint64(0x9E3779B97F4A7C15))
        up[0] = 1
        up = np.cumprod(up, dtype=np.uint64)
        inverse = np.full(n + 1, np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64)))
        inverse[0] = 1
        inverse = np.cumprod(inverse, dtype=np.uint64)
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum((x + np.uint64(1)) * up[:n], dtype=np.uint64)])
        ids.append(mix((total[end] - total[start]) * inverse[start], 1) >> np.uint64(64 - s.bits))
        owner.append(np.searchsorted(edge, start, side="right") - 1)
    owner_all = np.minimum(np.concatenate(owner), len(texts) - 1)
    order_all = np.argsort(owner_all, kind="stable")
    return np.concatenate(ids)[order_all].astype(np.int64), np.bincount(owner_all, minlength=len(texts))


def bag(text: str, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Distinct features of a text and how often they occur."""
    return np.unique(features([text], s)[0], return_counts=True)


def train(bags: list[tuple[np.ndarray, np.ndarray]], labels: list[int], s: Settings = Settings()) -> Model:
    y = np.array(labels)
    rows = 1 << s.bits
    if len(set(labels)) < 2:
        share = float(y.mean()) if len(y) else 0.5
        share = min(max(share, 1e-3), 1 - 1e-3)
        return Model(np.zeros(rows, np.float32), float(np.log(share / (1 - share))), s)
    rng = np.random.default_rng(s.seed)
    table = ((rng.random((rows, s.dim)) - 0.5) / s.dim).astype(np.float32)
    out, bias = np.zeros((2, s.dim), np.float32), np.zeros(2, np.float32)
    epochs = max(s.epochs, -(-s.least_steps // len(bags)))
    steps, done = epochs * len(bags), 0
    for _ in range(epochs):
        for i in rng.permutation(len(bags)).tolist():
            rate = s.rate * (1 - done / steps)
            done += 1
            ids, count = bags[i]
            total = count.sum()
            hidden = (count @ table[ids]) / total if total else np.zeros(s.dim, np.float32)
            z = out @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            back = p @ out
            out -= rate * np.outer(p, hidden)
            bias -= rate * 0.1 * p
            if total:
                table[ids] -= (rate / total * count)[:, None].astype(np.float32) * back
    return Model((table @ (out[1] - out[0])).astype(np.float32), float(bias[1] - bias[0]), s)


def scores(texts: list[str], model: Model) -> np.ndarray:
    """Probability of label 1 for each text."""
    out = np.zeros(len(texts))
    i = 0
    while i < len(texts):
        j, size = i, 0
        while j < len(texts) and (j == i or size + len(texts[j]) <= SLICE_CHARS):
            size += len(texts[j])
            j += 1
        ids, count = features(texts[i:j], model.settings)
        total = np.concatenate([[0.0], np.cumsum(model.weight[ids], dtype=np.float64)])
        ends = np.cumsum(count)
        mean = (total[ends] - total[ends - count]) / np.maximum(count, 1)
        out[i:j] = 1 / (1 + np.exp(-np.clip(mean + model.bias, -50, 50)))
        i = j
    return out


def fit(docs: DataFrame, labels: DataFrame, settings: Settings = Settings(), label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Train on the bounded sample. ``labels(id, label)`` says which rows may be learnt from."""
    known = labels.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(label_col).cast("int").alias("label")).where("doc_id IS NOT NULL AND label IN (0, 1)")
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(settings.sample)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bags = [bag(t, settings) for t in batch.column(2).to_pylist()]
            blobs = [[zlib.compress(np.diff(x[0], prepend=0).astype(np.uint32).tobytes(), 1) for x in bags], [zlib.compress(x[1].astype(np.uint32).tobytes(), 1) for x in bags]]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in (0, 1, 3)), *(pa.array(x, pa.binary()) for x in blobs)], names=["doc_id", "label", "tie", "features", "counts"])

    texts = id_and_text(docs, id_col, text_col).where("text <> ''").join(F.broadcast(picked), "doc_id").select("doc_id", "label", "text", F.xxhash64("text").alias("tie"))  # at most ``sample`` ids
    counted = texts.mapInArrow(lean(task), "doc_id bigint, label int, tie bigint, features binary, counts binary")
    rows = counted.orderBy(F.xxhash64("doc_id"), "doc_id", "label", "tie").limit(settings.sample).collect()
    read = lambda blob: np.frombuffer(zlib.decompress(blob), np.uint32).astype(np.int64)
    return train([(np.cumsum(read(r["features"])), read(r["counts"])) for r in rows], [r["label"] for r in rows], settings)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, score)`` for every document; the model, of fixed size, is a broadcast variable."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                some = batch.slice(i, 500)
                yield pa.RecordBatch.from_arrays([some.column(0), pa.array(scores(some.column(1).to_pylist(), shared.value))], schema=schema)

    return id_and_text(docs, id_col, text_col).mapInArrow(lean(task), "doc_id bigint, score double")
