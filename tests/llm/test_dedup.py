import hashlib
import re

import numpy as np
import pytest
import xxhash

from forkline.llm.repeats import line_dedup, substring_dedup
from forkline.llm.similar import similar_groups
from forkline.llm.simhash import choose, forest, simhash_groups, thresholds

SPACE = r"[^\x20\x09-\x0D]+"


def words(n, seed, size=400):
    rnd = np.random.default_rng(seed)
    return [f"w{x}" for x in rnd.integers(0, size, n)]


@pytest.fixture(scope="module")
def corpus():
    a, b = words(300, 1), words(200, 2)
    docs = {
        5: " ".join(a),
        9: " ".join(words(40, 3) + a[50:90] + words(30, 4)),
        2: " ".join(a[100:112]),  # one word short of a window
        3: " ".join(a[100:113]),
        7: "\n".join([" ".join(b[:60]), " ".join(b[60:70]), " ".join(b[70:80]), "", "tail line"]),
        8: "\n".join(["head", " ".join(b[60:70]), " ".join(b[70:80]), "other tail"]),
        11: "\n".join(["x", " ".join(b[:60]), "y"]),
        12: "one line only",
        13: "one line only",
        14: "p\nq\np\nq\nr",
        15: "", 16: " \t\n ", 17: "  ä ö  ü\x0bz  ",
        18: "la " * 60, 19: "la " * 40,
    }
    return docs


def frame(spark, docs, extra=()):
    rows = [(k, v, "s", 1) for k, v in docs.items()] + list(extra)
    return spark.createDataFrame(rows, "doc_id bigint, text string, chunk string, bucket int")


def brute_words(docs, width):
    first = {}
    parts = {d: re.findall(SPACE, t) for d, t in docs.items()}
    for d in sorted(parts):
        for i in range(len(parts[d]) - width + 1):
            first.setdefault(tuple(parts[d][i : i + width]), d)
    out = {}
    for d, w in parts.items():
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if first[tuple(w[i : i + width])] < d:
                gone[i : i + width] = [True] * width
        out[d] = (len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g))
    return out


def brute_lines(docs, run, long_line):
    windows, first = {}, {}
    for d, t in docs.items():
        lines = [x for x in t.split("\n") if re.search(SPACE, x)]
        own = [(i, tuple(lines[i : i + run])) for i in range(len(lines) - run + 1)] if len(lines) >= run else [(0, tuple(lines))] if lines else []
        own += [(i, (x,)) for i, x in enumerate(lines) if len(lines) > 1 and len(re.findall(SPACE, x)) >= long_line]
        windows[d] = own
        for i, w in own:
            first[w] = min(first.get(w, (d, i)), (d, i))
    out = {}
    for d, t in docs.items():
        gone = {i + k for i, w in windows[d] if first[w] < (d, i) for k in range(len(w))}
        kept, at = [], 0
        for line in t.split("\n"):
            if re.search(SPACE, line):
                if at not in gone:
                    kept.append(line)
                at += 1
            else:
                kept.append(line)
        out[d] = (at, len(gone), "\n".join(kept))
    return out


@pytest.mark.parametrize("width", [13, 5])
def test_substring_dedup_against_brute_force(spark, corpus, width):
    got = {r["doc_id"]: (r["n_units"], r["n_removed"], r["text"]) for r in substring_dedup(frame(spark, corpus), width).collect()}
    assert got == brute_words(corpus, width)


def test_line_dedup_against_brute_force(spark, corpus):
    got = {r["doc_id"]: (r["n_units"], r["n_removed"], r["text"]) for r in line_dedup(frame(spark, corpus)).collect()}
    assert got == brute_lines(corpus, 2, 50)
    assert got[14][1] == 2 and got[13][1] == 1 and got[11][1] == 1


def test_many_chunks_give_the_same(spark, monkeypatch):
    from forkline.llm.common import Grid

    shared = words(30, 50)
    docs = {i: " ".join(words(60, i) + (shared if i % 3 == 0 else []) + words(20, 1000 + i)) for i in range(60)}
    monkeypatch.setattr(Grid, "LEAST_CHUNK_UNITS", 500)
    monkeypatch.setattr(Grid, "LEAST_BUCKET_UNITS", 900)
    monkeypatch.setattr(Grid, "MIN_ENTRIES", 1)
    rows = substring_dedup(frame(spark, docs), 13).collect()
    assert {r["doc_id"]: (r["n_units"], r["n_removed"], r["text"]) for r in rows} == brute_words(docs, 13)
    spans = {r["doc_id"]: r["removed"] for r in rows}
    assert spans[3] == [60, 90] and spans[0] == []


def test_dedup_edge_rows(spark):
    long = " ".join(words(40, 9))
    rows = [(None, long, "s", 1), (4, long, "s", 1), (4, long, "s", 1), (6, None, None, None), (7, "x" * 300_000, "s", 1)]
    got = sorted(((r["doc_id"] or 99, r["n_units"], r["n_removed"]) for r in substring_dedup(frame(spark, {}, rows)).collect()), key=str)
    assert got == sorted([(99, 40, 40), (4, 40, 0), (4, 40, 0), (6, 0, 0), (7, 1, 0)], key=str)
    assert substring_dedup(frame(spark, {})).count() == 0 and line_dedup(frame(spark, {})).count() == 0
    kept = line_dedup(frame(spark, {1: "a\nb"}), carry=("chunk", "bucket")).first()
    assert (kept["carry_0"], kept["carry_1"]) == ("s", 1)


def brute_print(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    w = re.findall(SPACE, low)
    if not w:
        return 0
    shingles = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def groups_of(prints, radius):
    ids = sorted(prints)
    label = {d: d for d in ids}
    moved = True
    while moved:
        moved = False
        for a in ids:
            for b in ids:
                if label[a] < label[b] and (prints[a] ^ prints[b]).bit_count() <= radius:
                    label[b], moved = label[a], True
    return label


def test_simhash_groups_against_brute_force(spark):
    base = words(400, 20, 5000)
    docs = {i: " ".join([*base[:i], "new", *base[i:]]) for i in range(0, 60, 3)}
    docs |= {100 + i: " ".join(words(50, i)) for i in range(30)} | {200: "", 201: " ", 202: "Two Words", 203: "two words", 204: "ÀB c"}
    prints = {d: brute_print(t) for d, t in docs.items()}
    want = groups_of(prints, 2)
    rows = simhash_groups(frame(spark, docs, [(300, None, "s", 1)])).collect()
    got = {r["doc_id"]: r for r in rows}
    assert all(got[d]["fingerprint"] == f"{prints[d]:016x}" for d in docs)
    assert {d: got[d]["component_id"] for d in docs} == want
    assert got[300]["component_id"] == 200


def test_hot_keys_take_the_exact_detour(spark, monkeypatch):
    import forkline.llm.simhash as sh

    rnd = np.random.default_rng(4)
    prints = {}
    for i in range(80):  # a chain of single flips: dense, and linked from end to end
        prints[i] = (prints[i - 1] if i else 0x0123456789ABCDEF) ^ (1 << int(rnd.integers(0, 20)))
    prints |= {100 + i: int(x) for i, x in enumerate(rnd.integers(0, 2**63, 50))}
    df = spark.createDataFrame([(d, p - (1 << 64) if p >> 63 else p) for d, p in prints.items()], "doc_id bigint, f0 bigint")
    monkeypatch.setattr(sh, "RUN", 3)
    got = {r["doc_id"]: r["component_id"] for r in sh.near_duplicate_groups(df, 1, 2).collect()}
    assert got == groups_of(prints, 2)
    assert sh.near_duplicate_groups(df.limit(0), 1, 2).count() == 0


def test_thresholds_meet_the_pigeonhole_sum():
    rnd = np.random.default_rng(1)
    sample = rnd.integers(0, 2**63, (500, 1)).astype(np.uint64)
    for radius in (1, 2, 3):
        plan = choose(sample, 64, radius, 10_000, range(1, radius + 2))
        assert sum(t + 1 for _, t in plan) == radius + 1
    skewed = [np.zeros(500, np.uint64), sample[:, 0] & np.uint64(0xFFFF)]
    assert thresholds(skewed, [16, 16], 1, 10_000)[1] == [-1, 1]  # the constant part costs all pairs


def test_forest_connects_what_links_connect():
    rnd = np.random.default_rng(2)
    f = rnd.integers(0, 2**63, (150, 1)).astype(np.uint64)
    f[1:100] = f[0] ^ (np.uint64(1) << rnd.integers(0, 12, (99, 1)).astype(np.uint64)) ^ (np.uint64(1) << rnd.integers(0, 12, (99, 1)).astype(np.uint64))
    f = np.unique(f, axis=0)
    want = groups_of({i: int(x) for i, x in enumerate(f[:, 0])}, 2)
    label = {i: i for i in range(len(f))}
    edges = forest(np.arange(len(f)), f, 2)
    assert len(edges) < len(f)
    for _ in range(len(f)):
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    assert label == want


def test_similar_groups(spark):
    base = words(300, 30, 5000)
    near = base.copy()
    near[150] = "other"
    docs = {1: " ".join(base), 2: " ".join(near), 3: " ".join(words(300, 31, 5000)), 4: " ".join(base)}
    got = {r["doc_id"]: r["component_id"] for r in similar_groups(frame(spark, docs)).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 1}


def test_digest_is_of_the_kept_text(spark, tmp_path):
    from forkline.llm.queries import op2_substring_dedup

    frame(spark, {1: "a  b"}).write.parquet(str(tmp_path / "documents.parquet"))
    assert op2_substring_dedup(spark, str(tmp_path)).first()["kept_sha256"] == hashlib.sha256(b"a b").hexdigest()


def test_a_row_without_id_links_two_others(spark):
    from forkline.llm.simhash import near_duplicate_groups

    prints = spark.createDataFrame([(1, 0), (None, 3), (2, 15), (None, 255 << 20), (None, 255 << 20), (7, -1), (None, -2)], "doc_id bigint, f0 bigint")
    got = sorted(((str(r["doc_id"]), r["f0"], r["component_id"]) for r in near_duplicate_groups(prints, 1, 2).collect()), key=str)
    lone = ("None", 255 << 20, None)
    assert got == sorted([("1", 0, 1), ("None", 3, 1), ("2", 15, 1), lone, lone, ("7", -1, 7), ("None", -2, 7)], key=str)


def test_window_keys_hold_more_than_sixty_four_bits():
    from forkline.llm.repeats import pack96, unpack96, wide

    a = np.array([5 << 40, 5 << 40, 5 << 40, (5 << 40) + (1 << 16)], np.uint64)
    b = np.array([1 << 63, (1 << 63) + (1 << 16), 1 << 63, 1 << 63], np.uint64)
    key = wide(a, b)
    assert len(pack96(key)) == 48 and (unpack96(pack96(key)) == key).all() and not len(unpack96(b""))
    assert len(np.unique(key)) == 3 and key[0] == key[2]
    assert np.searchsorted(np.sort(key), key[1]) == 2
