import numpy as np
import pytest

from forkline.llm import similar as sim
from forkline.llm.similar import similar_groups
from forkline.llm.simhash import near_duplicate_groups


def words(n, seed):
    return [f"w{x}" for x in np.random.default_rng(seed).integers(0, 5000, n)]


def changed(base, k, mark):
    """``k`` words replaced so far apart that each breaks five shingles."""
    out = list(base)
    for i in range(k):
        out[10 + i * 280 // k] = f"{mark}{i}"
    return " ".join(out)


def frame(spark, texts):
    return spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())


def brute(texts, similarity=0.8):
    sets = {d: shingles(t) for d, t in texts.items()}
    label, moved = {d: d for d in texts}, True
    while moved:
        moved = False
        for a in texts:
            for b in texts:
                x, y = sets[a], sets[b]
                if label[a] < label[b] and (x == y or len(x & y) >= similarity * len(x | y)):
                    label[b], moved = label[a], True
    return label


def test_every_link_from_the_stated_similarity_on(spark):
    texts = {}
    for i in range(60):  # 296 shingles each: 6 changes leave 0.816, 7 leave 0.789
        base = words(300, i)
        texts |= {10 * i: " ".join(base), 10 * i + 1: changed(base, 6, "x"), 10 * i + 2: changed(base[:150] + words(150, 900 + i), 3, "y")}
        if i % 2:
            texts[10 * i + 3] = changed(base, 7, "z")
    got = {r["doc_id"]: r["component_id"] for r in similar_groups(frame(spark, texts)).collect()}
    assert all(got[10 * i + 1] == 10 * i and got[10 * i + 2] == 10 * i + 2 for i in range(60))
    assert all(got[10 * i + 3] == 10 * i + 3 for i in range(1, 60, 2))


def test_links_do_not_depend_on_other_rows(spark):
    pairs = {}
    for i in range(20):
        base = words(300, 70 + i)
        pairs |= {-2 * i - 2: " ".join(base), -2 * i - 1: changed(base, 6, "x")}
    crowd = {i: " ".join(words(40, 100 + i)) for i in range(2000)}
    for texts in (pairs, pairs | crowd):
        got = {r["doc_id"]: r["component_id"] for r in similar_groups(frame(spark, texts)).where("doc_id < 0").collect()}
        assert got == {d: d if d % 2 == 0 else d - 1 for d in pairs}
    with pytest.raises(TypeError):  # no radius beyond the sure one
        near_duplicate_groups(None, 6, 58, sure=23)


def test_full_keys_and_short_texts_against_brute_force(spark, monkeypatch):
    base, texts = words(120, 1), {}
    rnd = np.random.default_rng(3)
    for i in range(60):  # a chain that drifts away from its start, and strays
        base = list(base)
        base[int(rnd.integers(0, 120))] = f"n{i}"
        texts[i] = " ".join(base)
        texts[100 + i] = changed(base + base[:60] + words(120, 50), 4 + 8 * (i % 3 == 0), f"s{i}")
    texts |= {300: "a b c", 301: "A  b c", 302: "a b", 303: "", 304: " ", 305: "a b c d e f", 306: "a b c d e g"}
    want = brute(texts)
    assert len(set(want.values())) > 8
    monkeypatch.setattr(sim, "RUN", 2)
    monkeypatch.setattr(sim, "CHUNK", 5)
    rows = frame(spark, texts).unionByName(spark.createDataFrame([(400, None)], "doc_id bigint, text string"))
    got = {r["doc_id"]: r["component_id"] for r in similar_groups(rows).collect()}
    assert got.pop(400) == 303 and got == want
    assert similar_groups(rows.limit(0)).count() == 0


def components_of(sets, similarity):
    """Smallest id reached over all pairs of distinct sets that reach the similarity, by a prefix filter that loses none."""
    from collections import Counter, defaultdict

    often = Counter(x for s in sets.values() for x in s)
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    held, links = defaultdict(list), 0
    for d, s in sets.items():
        order = sorted(s, key=lambda x: (often[x], x))
        seen = set()
        for x in order[: len(order) - int(np.ceil(similarity * len(order))) + 1]:
            seen.update(held[x])
            held[x].append(d)
        for e in seen:
            t = sets[e]
            if min(len(s), len(t)) >= similarity * max(len(s), len(t)) and len(s & t) >= similarity * len(s | t):
                links += 1
                a, b = sorted((find(d), find(e)))
                root[b] = a
    return {d: find(d) for d in sets}, links


def test_every_link_of_the_given_table(spark):
    rows = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    sets, first = {}, {}
    for r in sorted(rows.collect(), key=lambda r: r["doc_id"]):
        sets[r["doc_id"]] = frozenset(hash(x) for x in shingles("".join(c.lower() if c.isascii() else c for c in r["text"] or "")))
    for d, s in sets.items():
        first.setdefault(s, d)
    label, links = components_of({d: s for s, d in first.items()}, 0.8)
    assert links > 40 and len(sets) - len(first) > 500
    want = {d: label[first[s]] for d, s in sets.items()}
    got = {r["doc_id"]: r["component_id"] for r in similar_groups(rows).collect()}
    missed = [d for d in want if got[d] != want[d]]
    assert not missed


def test_groups_do_not_depend_on_how_rows_are_dealt(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    runs = [{r["doc_id"]: r["component_id"] for r in similar_groups(x).collect()} for x in (rows, rows.repartition(7, "text"), rows.orderBy("text"))]
    assert runs[0] == runs[1] == runs[2]
