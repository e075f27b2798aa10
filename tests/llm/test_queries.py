"""The registered queries, digests included, over a whole small table against brute force."""

import functools
import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from forkline.llm.queries import QUERIES

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def texts(spark):
    return {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


def run(spark, name):
    return QUERIES[name](spark, SF).collect()


def by_id(spark, name, texts):
    rows = run(spark, name)
    assert sorted(r["doc_id"] for r in rows) == sorted(texts)
    return {r["doc_id"]: r for r in rows}


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


@functools.cache
def library_of(name):
    plain = Tokenizer.from_file(public_tokenizers.path(name))
    plain.encode_special_tokens = True
    return lambda t: plain.encode(t, add_special_tokens=False).ids


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_op3(spark, texts):
    prints = {}
    for d, t in texts.items():
        w = WORD.findall(lower(t))
        shingles = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        prints[d] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0
    label, moved = {d: d for d in texts}, True
    while moved:
        moved = False
        for a in texts:
            for b in texts:
                if label[a] < label[b] and (prints[a] ^ prints[b]).bit_count() <= 2:
                    label[b], moved = label[a], True
    got = by_id(spark, "op3_simhash_groups", texts)
    assert {d: (r["fingerprint"], r["component_id"]) for d, r in got.items()} == {d: (f"{prints[d]:016x}", label[d]) for d in texts}


def test_op4(spark, texts):
    out = {d for d in texts if zlib.crc32(str(d).encode()) % 7 == 2}
    words = {d: [*WORD.findall(lower(t)), None] for d, t in texts.items()}
    count = Counter(w for d in texts if d not in out for w in words[d])
    n, v = sum(count.values()), len(count)
    for d, r in by_id(spark, "op4_language_model", texts).items():
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (d in out, len(words[d]), sum(count[w] > 0 for w in words[d]), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((count[w] + 1) / (n + v + 1)) for w in words[d])) and r["score"] < 0


def test_op5(spark, texts):
    for d, r in by_id(spark, "op5_line_quality", texts).items():
        w, lines = WORD.findall(texts[d]), [x for x in texts[d].split("\n") if WORD.search(x)]
        seen = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        twice = {j for i in range(len(w) - 7) if seen[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in texts[d]), len(lines) - len(set(lines)), len(twice))
        assert tuple(r[c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == want
        assert r["base_failed"] == (len(w) < 20 or 100 * len(twice) > 30 * len(w)) and not (r["base_failed"] and r["kept"])


def test_op7(spark, texts):
    encode = library_of("byte_bpe_50k.json")
    ids = {d: [*encode(t), 0] for d, t in texts.items()}
    at, ends = Counter(), {}
    rows = run(spark, "op7_packing")
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["start"])):
        own = ids[r["doc_id"]]
        assert (r["start"], r["doc_tokens"], r["ids_crc32"]) == (at[r["doc_id"]], len(own), crc(own[r["start"] : r["start"] + r["length"]]))
        at[r["doc_id"]] += r["length"]
    assert at == {d: len(x) for d, x in ids.items()}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == ends.get(r["sequence_id"], 0)
        ends[r["sequence_id"]] = r["offset"] + r["length"]
    padding = sum(0 if n & (n - 1) == 0 else 1024 - n for n in ends.values())
    assert max(ends.values()) <= 1024 and padding <= 0.01 * sum(ends.values())
    tiers = Counter(ends.values())
    assert tiers[1024] > 100 and tiers[512] >= 3 and tiers[256] >= 1


def test_op8(spark, texts):
    assign = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
    for d, r in by_id(spark, "op8_secret_scan", texts).items():
        spans = [(m.start(), 0, m.end()) for m in assign.finditer(texts[d]) if len(m[2]) >= 12]
        spans += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", texts[d]) if len(m[0]) >= 18]
        spans += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", texts[d]) if len(m[0]) >= 16]
        told = [f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in sorted(spans)]
        assert r["base_sha256"] == hashlib.sha256(",".join(told).encode()).hexdigest()
        assert [r["n_assign"], r["n_access"], r["n_hex"]] == [sum(k == i for _, k, _ in spans) for i in range(3)]
        assert set(told) <= set(r["spans"].split(",")) | {""}


def test_op9(spark, texts):
    for d, r in by_id(spark, "op9_quality_classifier", texts).items():
        assert r["held_out"] == (zlib.crc32(str(d).encode()) % 3 == 1) and 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5)


def test_op10(spark, texts):
    encode, at = library_of("word_bpe_49k.json"), 0
    got = by_id(spark, "op10_token_files", texts)
    for d in sorted(texts):
        ids = [*encode(texts[d]), 1]
        assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (at, len(ids), crc(ids))
        at += len(ids)
