import hashlib

import corpus_pipeline


def test_stages_filter_and_keep_the_columns(spark, tmp_path):
    filler = lambda i: " ".join(f"w{i}x{k}" for k in range(40))
    rows = [(i, filler(i), "en", f"src{i % 3}", 0) for i in range(60)]
    rows += [(100, rows[5][1], "en", "src0", 0), (101, rows[6][1] + " tail", "en", "src1", 0), (102, None, None, None, None), (103, "", "en", "src2", 0)]
    rows += [(200 + i, f"{filler(300 + i)} you worthless idiot clown", "en", "src0", 0) for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    labels = [(i, 0, 1) for i in range(60)] + [(200 + i, 1, 1) for i in range(30)]
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, toxic int, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    d = str(tmp_path)
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "SimHash near-dedup", "source mixing", "byte-level BPE"]
    kept = spark.read.parquet(f"{d}/documents.parquet")
    ids = []
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        kept = stage(spark, kept, d)
        if i < 4:
            assert kept.columns == docs.columns
            kept.write.parquet(f"{d}/{i}")
            kept = spark.read.parquet(f"{d}/{i}")
        ids.append({r.doc_id for r in kept.select("doc_id").collect()})
    assert ids[0] == set(range(60)) | {100, 101, 102, 103}
    assert ids[1] == ids[0] - {100, 101}
    assert ids[2] == set(range(60)) | {102}
    assert ids[3] <= set(range(60)) and len(ids[3]) > 30 and ids[4] == ids[3]
    assert {r.doc_id for r in corpus_pipeline.run(spark, d).select("doc_id").collect()} == ids[4]


def test_near_dedup_removes_near_copies_of_many_lines(spark):
    wrap = lambda words, n: "\n".join(" ".join(words[i : i + n]) for i in range(0, len(words), n))
    rows = []
    for i in range(6):
        words = [f"w{i}x{k}" for k in range(96)]
        copy = [w if k not in (20, 60) else f"new{i}y{k}" for k, w in enumerate(words)]  # 82 of 102 shingles are shared
        far = [w if k % 12 != 5 else f"far{i}y{k}" for k, w in enumerate(words)]
        rows += [(i, wrap(words, 12)), (100 + i, wrap(copy, 19)), (200 + i, wrap(far, 23))]
    docs = spark.createDataFrame([(i, text, "en", "src0", len(text)) for i, text in rows], "doc_id long, text string, lang string, source string, n_chars long")
    lines = corpus_pipeline.line_dedup(spark, docs, "").checkpoint()
    assert lines.count() == len(rows)
    assert sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, lines, "").collect()) == [*range(6), *range(200, 206)]


def test_near_dedup_keeps_different_texts_that_share_an_id(spark):
    text = lambda name: " ".join(f"{name}{k}" for k in range(30))
    rows = [(3, text("a"), "s1"), (5, text("a"), "s1"), (5, text("b"), "s2"), (5, text("b"), "s1"), (5, text("c"), "s1")]
    rows += [(None, text("d"), "s1"), (None, text("e"), "s1"), (None, text("a"), "s1"), (None, None, "s1"), (9, text("e"), "s1")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {(r.doc_id, r.text, r.source) for r in corpus_pipeline.near_dedup(spark, docs, "").collect()}
    assert got == {(3, text("a"), "s1"), (5, text("b"), "s1"), (5, text("c"), "s1"), (None, text("d"), "s1"), (9, text("e"), "s1"), (None, None, "s1")}


def test_every_stage_takes_odd_rows_and_empty_tables(spark, tmp_path):
    text = lambda name, n=30: " ".join(f"{name}{k}" for k in range(n))
    rows = [(1, text("a"), None, "s1", None, "x"), (1, text("b"), "en", None, 3, None), (1, text("b"), "en", None, 3, None), (None, text("c"), "en", "s2", 1, "y")]
    rows += [(2, None, None, None, None, None), (3, "", "en", "s1", 0, "z"), (4, "\n".join(text(f"l{k}x", 12) for k in range(9_000)), "de", "s2", 5, "q")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, `__t` string").withColumnsRenamed({"__t": "score"})
    docs = docs.selectExpr("*", "1 as node", "'r' as root", "2 as taken", "3L as position", "4 as __dropped_lines")
    labels = spark.createDataFrame([(1, 0, 1), (4, 1, 1), (None, 1, 1), (2, None, None)], "doc_id long, toxic int, quality int")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    for name, table in (("some", docs), ("none", docs.limit(0))):
        kept = table
        for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
            made = stage(spark, kept, str(tmp_path))
            made.write.parquet(f"{tmp_path}/{name}{i}")
            kept = spark.read.parquet(f"{tmp_path}/{name}{i}")
            assert i == 4 or kept.columns == docs.columns
        if name == "none":
            assert kept.count() == 0
    mixed = spark.read.parquet(f"{tmp_path}/some3").collect()
    final = spark.read.parquet(f"{tmp_path}/some4").collect()
    digest = lambda t: hashlib.sha256((t or "").encode()).hexdigest()
    assert sorted((r.doc_id is None, r.doc_id, r.decoded_sha256) for r in final) == sorted((r.doc_id is None, r.doc_id, digest(r.text)) for r in mixed)
    assert all(r.ids_sha256 == hashlib.sha256(",".join(map(str, r.ids)).encode()).hexdigest() and r.n_tokens == len(r.ids) for r in final)
    deduplicated = spark.read.parquet(f"{tmp_path}/some2").collect()
    assert {(r.doc_id, r.text) for r in deduplicated} >= {(1, text("a")), (1, text("b")), (None, text("c"))}
    assert sum(r.text == text("b") for r in deduplicated) == 1
