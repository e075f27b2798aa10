import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from forkline.llm.encoding import encoder
from forkline.llm.packing import pack, pack_block, pieces_digest, step_groups
from forkline.llm.token_files import documents_digest, read_token_files, write_token_files

WEIRD = [
    "", " ", "  a", "a  b", "a \n b", "a\n", "\n a", "a\n\n\nb", "a \x00 b", "x\x00y z", "É é ́x", "word <|endoftext|> x", " lead", "trail ", "\t", "don't we'll  x's 's", "ΑΣ ΑΣ.", "x" * 3000,
    "1 22 333 a1b2", "\x1c a \x1d b", "a\r\n b", "漢字 kana かな", "🙂 ok", "naïve ﬁne  \U0010fffd end", " nbsp  x",
]


@pytest.mark.parametrize(("name", "dtype"), [("byte_bpe_50k.json", "<u4"), ("word_bpe_49k.json", "<u2")])
def test_ids_equal_those_of_the_library(name, dtype):
    plain = Tokenizer.from_file(public_tokenizers.path(name))
    plain.encode_special_tokens = True
    mine = encoder(name, dtype)
    for _ in range(2):  # the second time from the cache
        got = [np.frombuffer(b, dtype).tolist() for b in mine(WEIRD)]
        assert got == [plain.encode(t, add_special_tokens=False).ids for t in WEIRD]


def docs(spark):
    rows = [(i, t, "x", i) for i, t in enumerate(WEIRD)] + [(50, "some words " * 900, "x", 0), (51, None, None, None), (50, "again", "x", 0), (None, "no id", "x", 0)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, ids string, start int").repartition(2), rows


def test_packing_places_each_token_once(spark):
    frame, rows = docs(spark)
    packed = pack(frame, "byte_bpe_50k.json", sequence_length=256).collect()
    digest = {(r["sequence_id"], r["offset"]): r["ids_crc32"] for r in pieces_digest(pack(frame, "byte_bpe_50k.json", sequence_length=256)).collect()}
    plain = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    plain.encode_special_tokens = True
    want = sorted(np.array(plain.encode(t or "", add_special_tokens=False).ids + [0], "<u4").tobytes() for _, t, _, _ in rows)
    pieces = sorted(((r["sequence_id"], r["offset"], r) for r in packed), key=lambda x: x[:2])
    whole = {}
    for r in packed:
        whole.setdefault((r["doc_id"], r["doc_tokens"], r["sequence_id"] >> 34), []).append((r["start"], bytes(r["ids"])))
        assert len(r["ids"]) == 4 * r["length"] and digest[r["sequence_id"], r["offset"]] == zlib.crc32(bytes(r["ids"]))
    joined = b"".join(x for own in whole.values() for _, x in sorted(own))
    assert len(joined) == sum(map(len, want))
    ends = {}
    for s, offset, r in pieces:
        assert offset == ends.get(s, 0)
        ends[s] = offset + r["length"]
    tiers = {r["sequence_id"]: r["tier"] for r in packed}
    assert all(ends[s] == tiers[s] and tiers[s] & (tiers[s] - 1) == 0 and tiers[s] <= 256 for s in ends)
    assert pack(frame.limit(0), "byte_bpe_50k.json").count() == 0
    with pytest.raises(ValueError, match="power"):
        pack(frame, "byte_bpe_50k.json", sequence_length=100)


def test_pack_block_and_step_groups():
    rnd = np.random.default_rng(0)
    lengths = rnd.integers(1, 700, 200).tolist()
    sequences = pack_block(lengths, 256)
    seen = {}
    for size, pieces in sequences:
        assert size == sum(n for _, _, n in pieces)
        for d, at, n in pieces:
            seen.setdefault(d, []).append((at, n))
    for d, n in enumerate(lengths):
        at = 0
        for start, k in sorted(seen[d]):
            assert start == at
            at += k
        assert at == n
    groups = step_groups([s for s, _ in sequences], 1024)
    totals = np.bincount(groups, weights=[s for s, _ in sequences])
    assert (totals[:-1] == 1024).all() and totals[-1] <= 1024


def test_token_files_round_trip(spark, tmp_path):
    frame, rows = docs(spark)
    folder = f"file://{tmp_path}/tokens"
    manifest = write_token_files(frame, folder, "word_bpe_49k.json", end_id=1, partitions=3)
    got = documents_digest(read_token_files(spark, manifest, folder)).orderBy("start").collect()
    plain = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    plain.encode_special_tokens = True
    coded = {}
    for d, t, _, _ in rows:
        ids = np.array(plain.encode(t or "", add_special_tokens=False).ids + [1], "<u4")
        coded.setdefault(d, []).append((len(ids), zlib.crc32(ids.tobytes())))
    assert [r["doc_id"] for r in got] == sorted(coded_ids(rows), key=lambda x: (x is not None, x))
    at = 0
    for r in got:
        assert r["start"] == at and (r["n_tokens"], r["ids_crc32"]) in coded[r["doc_id"]]
        at += r["n_tokens"]
    total = np.sum([np.fromfile(f, "<u2").size for f in (tmp_path / "tokens").glob("*.bin")])
    assert total == at
    empty = write_token_files(frame.limit(0), f"file://{tmp_path}/none", "word_bpe_49k.json")
    assert read_token_files(spark, empty, f"file://{tmp_path}/none").count() == 0
    with pytest.raises(Exception, match="cannot hold"):
        write_token_files(frame, f"file://{tmp_path}/small", "word_bpe_49k.json", dtype="uint8")


def coded_ids(rows):
    return [d for d, _, _, _ in rows]


def test_pipeline_on_a_small_corpus(spark, tmp_path):
    import corpus_pipeline

    rnd = np.random.default_rng(6)
    prose = lambda s, n=60: "\n".join(" ".join(f"w{x}" for x in np.random.default_rng(s * 100 + k).integers(0, 3000, 15)).capitalize() + "." for k in range(n // 15))
    item = " ".join(f"q{x}" for x in rnd.integers(0, 900, 14))
    junk = "\n".join("| a1 *** | b2 ### | c3 $$$ | d4 %%% |" + f" {k} " * 9 for k in range(5))
    near = prose(1, 150)
    edited = near.replace(near.split()[70], "changed", 1)
    texts = {i: prose(i) for i in range(10, 40)} | {1: near, 2: near, 3: edited, 4: prose(4) + " " + item, 5: junk, 6: "short", 7: None, 8: ""}
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint"
    spark.createDataFrame([(d, t, "en", "s", len(t or "")) for d, t in texts.items()], schema).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(d, int(d != 5), 0) for d in [*range(10, 40), 5]], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, item)], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    d, ids = spark.read.parquet(str(tmp_path / "documents.parquet")), []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, d, str(tmp_path)).write.parquet(str(tmp_path / f"out{k}"))
        d = spark.read.parquet(str(tmp_path / f"out{k}"))
        ids.append({r["doc_id"] for r in d.select("doc_id").collect()})
        assert k == 4 or d.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    clean = set(range(10, 40)) | {1}
    assert clean <= ids[0] and not ids[0] & {5, 6, 7, 8}
    assert clean <= ids[1] and 2 not in ids[1]
    assert clean <= ids[3] and 4 not in ids[3]
    assert clean <= ids[4]
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == d.count()
    assert corpus_pipeline.near_duplicates(spark, spark.read.parquet(str(tmp_path / "out0")), str(tmp_path)).where("doc_id IN (2, 3)").count() == 0
