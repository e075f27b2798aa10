import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from forkline.llm import line_quality as lq

SCHEMA = "doc_id bigint, text string, lines string, label int"


def test_likelihood_and_gradient_against_all_labellings():
    rnd = np.random.default_rng(5)
    doc = np.array([0, 0, 0, 1, 3, 3, 3, 3])
    x, theta = rnd.normal(size=(len(doc), 3)), rnd.normal(size=9)
    lines = lq.Lines(x, np.ones(len(doc)), doc, 4)
    y = rnd.integers(0, 2, len(doc))

    def log_likelihood(theta):
        total = 0.0
        for d in (0, 1, 3):
            own = np.flatnonzero(doc == d)

            def value(states, own=own):
                pair, start = theta[3:7].reshape(2, 2), theta[7:]
                return start[states[0]] + sum(x[i] @ theta[:3] * s for i, s in zip(own, states, strict=True)) + sum(pair[a, b] for a, b in zip(states, states[1:], strict=False))

            total += value(y[own]) - np.log(sum(np.exp(value(s)) for s in itertools.product((0, 1), repeat=len(own))))
        return total

    value, gradient = lines.likelihood(theta, y)
    assert value == pytest.approx(log_likelihood(theta))
    for i in range(9):
        step = np.zeros(9)
        step[i] = 1e-5
        assert gradient[i] == pytest.approx((log_likelihood(theta + step) - log_likelihood(theta - step)) / 2e-5, abs=1e-6)


def test_stretches_part_long_texts_in_training_alone():
    doc = np.repeat([0, 1], [7, 2])
    lines = lq.Lines(np.zeros((9, 1)), np.ones(9), doc, 2, stretch=3)
    assert lines.heads.tolist() == [0, 3, 6, 7]
    y = lq.completed(lines, np.array([0.9, 0.9, 0.9, 0.8, 0.7, 0.2, 0.1, 0.4, 0.3]), np.array([0, 1]), 0.5)
    assert y.tolist() == [1, 1, 1, 0, 0, 0, 0, 1, 0]


def made(n, seed):
    """Texts whose lines are known: prose with some menu lines (label 1), menus with some prose (label 0)."""
    rnd = random.Random(seed)
    prose = lambda: " ".join(rnd.choice(["the", "river", "runs", "slowly", "under", "old", "stone", "bridges", "at", "night"]) for _ in range(rnd.randrange(8, 16))).capitalize() + "."
    menu = lambda: " | ".join(rnd.choice(["Home", "About", "Login", "Share", "Next"]) for _ in range(rnd.randrange(4, 9)))
    rows, known = [], {}
    for i in range(n):
        good = i % 3 > 0
        kinds = [int(rnd.random() < (0.85 if good else 0.2)) for _ in range(rnd.randrange(5, 12))]
        kinds[0:3] = [int(good)] * 3
        rows.append((i, "\n".join(prose() if k else menu() for k in kinds), "x", int(good)))
        known[i] = kinds
    return rows, known


def test_known_lines_are_told_apart_from_labels_of_texts(spark):
    rows, known = made(240, 1)
    docs = spark.createDataFrame([*rows, (None, "a b", "x", 1), (900, None, None, None), (901, " \n ", "x", 0)], SCHEMA)
    labels = docs.where("doc_id < 160").selectExpr("doc_id", "label AS quality").unionByName(spark.createDataFrame([(3, None), (5, 7), (None, 1), (900, 0)], "doc_id bigint, quality int"))
    field = lq.fit(docs, labels)
    assert field.pair[0, 0] + field.pair[1, 1] > field.pair[0, 1] + field.pair[1, 0]
    got, right, total = {r["doc_id"]: r for r in lq.judge(docs, field).where("doc_id < 240").collect()}, 0, 0
    from forkline.llm.textblock import blocks
    import pyarrow as pa

    for first, block in blocks(pa.array([r[1] for r in rows])):
        c = lq.Counts(block)
        states = lq.viterbi(c.features @ field.unary, c.line_doc, block.n_docs, field)
        for d in range(block.n_docs):
            own = states[c.line_doc == d].tolist()
            right, total = right + sum(a == b for a, b in zip(own, known[first + d], strict=True)), total + len(own)
            assert got[first + d]["n_content_lines"] == sum(own) and got[first + d]["n_lines"] == len(own)
    assert right / total >= 0.9
    assert sum(0 < r["n_content_lines"] < r["n_lines"] for r in got.values()) > 100


def test_texts_of_the_given_table_mix_both_kinds_of_line(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    judged = lq.judge(docs, lq.fit(docs, labels.where("doc_id % 2 = 0"))).cache()
    mixed = judged.where("n_content_lines > 0 AND n_content_lines < n_lines").count()
    assert mixed >= 0.05 * judged.where("n_lines > 1").count()
    held = judged.where("NOT base_failed").join(labels.where("doc_id % 2 = 1"), "doc_id")
    right = held.agg(F.avg((F.col("kept") == (F.col("quality") == 1)).cast("double"))).first()[0]
    assert right >= 0.95


def test_one_very_long_text(spark):
    text = "\n".join(f"Line {i} of a long text that goes on and on." for i in range(30_000))
    docs = spark.createDataFrame([(1, text, "x", 1), (2, "| a | b\n" * 30, "x", 0)], SCHEMA)
    field = lq.fit(docs, docs.selectExpr("doc_id", "label AS quality"))
    row = lq.judge(docs, field).where("doc_id = 1").first()
    assert row["n_lines"] == 30_000 and row["n_words"] == 330_000
