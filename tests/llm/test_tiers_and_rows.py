from forkline.llm.packing import pack_block


def test_remainders_are_packed_in_their_own_tier():
    short = pack_block([200] * 400, 1024)
    assert sum(size for size, _ in short) == 80_000
    assert max(size for size, _ in short) == 256
    mixed = pack_block([900, 400, 200] * 100 + [5000], 1024)
    opened = {size: {pieces[0][2] for s, pieces in mixed if s == size} for size in (1024, 512, 256)}
    assert 900 in opened[1024] and opened[512] >= {400} and len(opened[256]) > 0
    assert not any(size < 256 for size, _ in mixed[:-8])  # shorter ones come from the block's rest alone


def test_one_row_of_each_group_stays(spark, tmp_path):
    import corpus_pipeline

    a, b, c = (" ".join(f"{p}{i}" for i in range(60)) for p in "abc")
    near = a.replace("a30", "other")
    rows = [(5, a, "en", "s", 1), (5, b, "en", "s", 1), (3, near, "en", "s", 1), (None, c, "en", "s", 1), (None, c, "en", "s", 1), (None, c + " x", "en", "s", 1), (9, "solo text", "en", "s", 1), (9, "solo text", "en", "s", 1), (None, None, "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = sorted(((r["doc_id"], r["text"]) for r in corpus_pipeline.near_duplicates(spark, docs, str(tmp_path)).collect()), key=str)
    gone = [r for r in got if r[0] is None and r[1] is not None]
    assert len(gone) == 1 and gone[0][1] in (c, c + " x")
    assert [r for r in got if r not in gone] == sorted([(3, near), (5, b), (9, "solo text"), (None, None)], key=str)
