import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from forkline.llm import language_model as lm

SCHEMA = "doc_id bigint, text string, score string, token int"
SMALL = lm.Settings(cells=256, classes=8, slots=4, bits=9, word_bits=9, rounds=6)


def held():
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2



def corpus():
    """Word pairs that go together, so that the word before tells the next one."""
    rnd = random.Random(2)
    pairs = [(f"{a}{i}", f"{b}{i}") for i in range(12) for a, b in (("ba", "ku"), ("mo", "ti"), ("re", "za"))]
    docs = {i: " ".join(" ".join(rnd.choice(pairs)) for _ in range(rnd.randrange(5, 60))) for i in range(150)}
    return docs | {500: None, 501: "", 502: "Never seen before", 503: docs[3].upper()}


def test_probabilities_sum_to_one_and_scores_equal_the_naive_ones(spark):
    docs = corpus()
    frame = spark.createDataFrame([(k, v, "x", 0) for k, v in docs.items()], SCHEMA).repartition(3)
    got = {r["doc_id"]: r["score"] for r in lm.score(frame, held(), SMALL).collect()}
    out = {d for d in docs if zlib.crc32(str(d).encode()) % 7 == 2}
    texts = {d: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "") for d, t in docs.items()}
    words = {d: [*re.findall(r"[^\x20\x09-\x0D]+", t), None] for d, t in texts.items()}
    count = Counter(w for d in docs if d not in out for w in words[d])

    learn = frame.where(~F.coalesce(held(), F.lit(False))).select(F.coalesce("text", F.lit("")).alias("text"), F.pmod(F.xxhash64("doc_id"), F.lit(SMALL.word_rounds)).alias("part"))
    size = sum(len(t) for t in texts.values())
    model = lm.fit(learn, size, SMALL)
    vocabulary = sorted(w for w in count if w)

    def group_of(word):
        t = lm.tokens(pa.array([word or ""]), SMALL)
        return int(model.groups(t)[0])

    group = {w: group_of(w) for w in {x for own in words.values() for x in own}}
    n, v = np.zeros(32), np.zeros(32)
    for w, c in count.items():
        n[group[w]] += c
        v[group[w]] += 1

    def naive(own):
        total = 0.0
        for i, w in enumerate(own):
            y = [0 if x is None else group[x] // 4 for x in own]
            before = [0, 0, 0]
            for j in (1, 2, 3):
                before[j - 1] = y[i - j] if i >= j else 0
            code = (before[0] * 8 + before[1]) * 8 + before[2]
            hashes = [int(lm.tokens(pa.array([x or ""]), SMALL).word[0]) for x in own]
            rows = []
            for j in (1, 2):
                h = np.array([hashes[i - j] if i >= j else 0], np.uint64)
                with np.errstate(over="ignore"):
                    rows.append(int(lm.mix(h * np.uint64(0x9E3779B97F4A7C15) + np.uint64(y[i]), j)[0] >> np.uint64(64 - model.words.bits)))
            z = model.words.bias[y[i]].astype(float) + model.words.weights[0, rows[0]] + model.words.weights[1, rows[1]]
            p = np.exp(z - z.max())
            p /= p.sum()
            g = group[w]
            total += model.log_class[code, y[i]] + math.log10(p[g % 4]) + math.log10((count[w] + 1) / (n[g] + v[g] + 1))
        return total

    for d in (0, 9, 500, 501, 502, 503):
        assert got[d] == pytest.approx(naive(words[d]), abs=0.05 + 0.002 * len(words[d]))

    # all words, the end, and one unknown word in each slot: their probabilities after any history
    rnd = np.random.default_rng(1)
    for _ in range(5):
        code, rows = int(rnd.integers(0, 512)), rnd.integers(0, 1 << model.words.bits, 2)
        total = 0.0
        for c in range(8):
            p = np.exp(model.words.log_probabilities(np.array([c]), rows[None]))[0]
            for slot in range(4):
                g = 4 * c + slot
                inside = (sum(count[w] + 1 for w in [*vocabulary, None] if group[w] == g) + 1) / (n[g] + v[g] + 1)
                total += 10 ** model.log_class[code, c] * p[slot] * inside
        assert total == pytest.approx(1, abs=1e-4)


def test_the_word_before_helps_on_held_out_texts(spark):
    docs = corpus()
    frame = spark.createDataFrame([(k, v, "x", 0) for k, v in docs.items()], SCHEMA)
    out = {d for d in docs if zlib.crc32(str(d).encode()) % 7 == 2}
    total = lambda s: sum(r["score"] for r in lm.score(frame, held(), s).collect() if r["doc_id"] in out)
    blind = lm.Settings(cells=256, classes=8, slots=4, bits=9, word_bits=9, rounds=6, word_rounds=1, ridge=1e12)
    assert total(SMALL) > total(blind)


def test_each_step_follows_the_gradient_of_the_likelihood(spark, monkeypatch):
    s = lm.Settings(cells=256, classes=8, slots=4, bits=9, word_bits=8, word_rounds=1)
    texts = [t for t in corpus().values() if t]
    classes = np.arange(256) % 7 + 1
    layer = lm.first_layer(classes, np.ones(256), s, 8)
    learn = spark.createDataFrame([(t, 0) for t in texts], "text string, part int")

    def likelihood(own):
        t = lm.tokens(pa.array(texts), s)
        y = np.where(t.cell < 0, 0, classes[t.cell])
        p = own.log_probabilities(y, lm.words_before(t, y, own.bits))
        return float(p[np.arange(len(p)), own.slot(t)].sum())

    after = lm.train_words(learn, classes, layer, s)
    monkeypatch.setattr(lm, "FAN", 2)  # sums meet in a tree
    tree = lm.train_words(learn.repartition(7), classes, layer, s)
    assert np.abs(tree.weights - after.weights).max() < 0.02
    assert likelihood(after) > likelihood(layer) + 100
    moved = np.abs(after.weights) > 0.2
    small = lm.WordLayer(layer.slot_of_cell, layer.bias, (layer.weights + 1e-3 * after.weights).astype(np.float32), layer.bits)
    assert moved.any() and likelihood(small) > likelihood(layer)  # the step climbs


def test_long_null_and_repeated_rows(spark):
    long = "alpha beta gamma delta " * 30_000
    rows = [(1, long, "x", 0), (1, "alpha beta", "x", 0), (1, "alpha beta", "x", 0), (None, "alpha", "x", 0), (None, None, "x", 0)]
    got = lm.score(spark.createDataFrame(rows, SCHEMA), held(), SMALL).collect()
    assert sorted(r["n_tokens"] for r in got) == [1, 2, 3, 3, 120_001]
    assert all(r["score"] <= 0 and math.isfinite(r["score"]) for r in got) and not any(r["held_out"] for r in got if r["doc_id"] is None)
