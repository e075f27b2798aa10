import math
import random
import re
from collections import Counter

import numpy as np
import pytest

from forkline.llm import secrets as sec

LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
BASE62 = LETTERS + LETTERS.lower() + "0123456789"
SCHEMA = "doc_id bigint, text string, runs string, base int"
PARTS = "get user account balance final value index create table order list read write open close file name path config default system handler factory manager service request response token stream buffer".split()


@pytest.mark.parametrize(("letters", "n"), [(BASE62 + "+/", 1624), (BASE62 + "-_", 2400), (LETTERS + "234567", 320), (LETTERS.lower() + "234567", 320), (LETTERS.lower(), 200)])
def test_long_random_strings_are_not_rejected(letters, n):
    rnd = np.random.default_rng(8)
    tested = [sec.judged("".join(rnd.choice(list(letters), n)), 0.001) for _ in range(100)]
    assert sum(fair for _, fair in tested) >= 97
    assert np.median([p for p, _ in tested]) < 1e-3


def name(rnd):
    own = [rnd.choice(PARTS) for _ in range(rnd.randrange(3, 7))]
    number = rnd.randrange(2100)
    return rnd.choice([own[0] + "".join(w.capitalize() for w in own[1:]), "_".join(own), f"{'-'.join(own)}{number}", f"{'/'.join(own)}/v{number}", "".join(f"{w.capitalize()}{rnd.randrange(99)}" for w in own)])


def test_p_values_of_names_hold_their_level():
    rnd = random.Random(4)
    names = [n for n in (name(rnd) for _ in range(4000)) if len(n) >= sec.LEAST_RUN or (len(n) >= sec.LEAST_STEPPED and sec.steps_of(n))]
    p = np.array([sec.judged(n, 0.001)[0] for n in names])
    assert all((p <= level).mean() <= level for level in (0.1, 0.05, 0.01, 0.001))


def test_tails():
    assert sec.binomial_tail(3, 5, 0.3) == pytest.approx(sum(math.comb(5, k) * 0.3**k * 0.7 ** (5 - k) for k in (3, 4, 5)))
    assert sec.binomial_tail(0, 5, 0.3) == 1 and sec.fisher([0.2]) == pytest.approx(0.2)
    assert sec.fisher([0.5, 0.1]) == pytest.approx(0.05 * (1 - math.log(0.05)))
    for x, freedom, want in ((3.84, 1, 0.05), (18.31, 10, 0.05), (61.66, 31, 0.00088)):
        assert sec.chi_squared_tail(x, freedom) == pytest.approx(want, rel=0.1)


def test_step_up_over_bins():
    assert sec.least_bin({}, 0.1) == 300 * sec.BINS + 1
    rnd = random.Random(2)
    p = [rnd.random() ** 3 for _ in range(500)] + [10.0 ** -rnd.randrange(5, 40) for _ in range(30)]
    bins = [math.floor(-math.log10(x) * sec.BINS) for x in p]
    limit = sec.least_bin(Counter(bins), 0.01)
    found = sorted(x for x, b in zip(p, bins, strict=True) if b >= limit)
    exact = max(k for k, x in enumerate(sorted(p), 1) if x <= 0.01 * k / len(p))
    assert exact * 0.9 <= len(found) <= exact


def test_planted_secrets_are_found_and_names_are_not(spark):
    rnd = random.Random(9)
    docs, planted = [], {}
    for i in range(600):
        words = [rnd.choice(PARTS) for _ in range(30)] + [name(rnd) for _ in range(4)]
        rnd.shuffle(words)
        if i % 4 == 0:
            kind = (BASE62, BASE62 + "+/", LETTERS + "234567", "0123456789")[i // 4 % 4]
            planted[i] = secret = "".join(rnd.choices(kind, k=(32, 40, 80, 24)[i // 4 % 4]))
            words.insert(17, "\u00fcn\u00efc\u00f6de")
            words.insert(18, secret)
        docs.append((i, " ".join(words), "x", 1))
    rows = {r["doc_id"]: r for r in sec.scan_secrets(spark.createDataFrame(docs, SCHEMA).repartition(5), rate=0.01).collect()}
    hits = Counter()
    for i, text, _, _ in docs:
        for span in filter(None, rows[i]["spans"].split(",")):
            _, a, b = span.split(":")
            hits[i in planted and planted[i] == text[int(a) : int(b)], len(planted.get(i, "")), rows[i]["n_random"]] += 1
        base = [f"hex:{m.start()}:{m.end()}" for m in re.finditer("[0-9a-f]{16,}", text)]
        assert rows[i]["base_spans"] == ",".join(base)
    false = sum(k for (right, _, _), k in hits.items() if not right)
    found = {n: sum(k for (right, m, _), k in hits.items() if right and m == n) for n in (32, 40, 80, 24)}
    assert false <= 0.01 * sum(hits.values())
    assert found[24] == 37 and found[32] >= 20 and found[40] >= 25 and found[80] >= 30


def test_given_documents_hold_no_further_span(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = sec.scan_secrets(docs).select("n_random", "n_confirmed", "n_hex", "base_spans", "spans").collect()
    assert sum(r["n_random"] for r in found) == 0 and all(r["base_spans"] == r["spans"] for r in found)
    assert sum(r["n_confirmed"] for r in found) > 0


def test_rows_of_every_kind(spark):
    rows = [(1, None, "x", 1), (1, "", "x", 1), (None, "deadbeefdeadbeef " * 2, "x", 1), (None, "deadbeefdeadbeef " * 2, "x", 1), (3, "aB3" * 40_000, "x", 1), (4, "x1 " * 50_000 + "cafecafecafecafe", "x", 1)]
    found = sorted(map(tuple, sec.scan_secrets(spark.createDataFrame(rows, SCHEMA)).select("doc_id", "n_hex", "n_random", "spans").collect()), key=str)
    twice = (None, 2, 0, "hex:0:16,hex:17:33")
    assert found == sorted([(1, 0, 0, ""), (1, 0, 0, ""), twice, twice, (3, 0, 0, ""), (4, 1, 0, "hex:150000:150016")], key=str)
    assert sec.scan_secrets(spark.createDataFrame([], SCHEMA)).count() == 0
