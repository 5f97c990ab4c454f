"""The pipeline's stages in order, over a small corpus."""

import corpus_pipeline


def test_stages(spark, tmp_path):
    good = "ordinary words about rivers and mountains in spring number {}. they flow slowly past the village {} and on to the sea {}."
    rows = [(i, good.format(i, i * 7, i * 13), "en", f"s{i % 2}", 1) for i in range(30)]
    rows += [(100, rows[0][1], "en", "s0", 1), (101, "token = abcdefghijklmnop1234 and some more plain words here", "en", "s1", 1), (102, None, None, None, None)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 1, 0) for i in range(30)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    cols, seen = docs.columns, {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen[name] = docs.collect()
        assert docs.columns == cols or k == len(corpus_pipeline.STAGES) - 1
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "minhash_near_dedup", "secret_scan", "mix_sources", "packing"]
    assert len(seen["toxicity"]) == 33 and {r.doc_id for r in seen["minhash_near_dedup"]} == {*range(30), 101, 102}
    assert next(r.text for r in seen["secret_scan"] if r.doc_id == 101).startswith("[SECRET]")
    assert {r.doc_id for r in seen["packing"]} == {r.doc_id for r in seen["mix_sources"]}


def test_near_copies_of_similarity_080_to_085_go(spark):
    words = [f"w{i}" for i in range(600)]
    a, b = words[:200], words[300:500]
    edit = b[:60] + ["other"] + b[61:120] + ["another"] + b[121:180] + ["third"] + b[181:]  # 181 of 211 shingles: 0.858
    edit = edit[:10] + ["fourth"] + edit[11:]  # 176 of 216: 0.815
    apart = words[500:600] + a[:60]  # 56 of 296 shingles
    texts = [a, a[:165], b, edit, apart]  # a's beginning: 161 of 196 shingles, 0.821
    docs = spark.createDataFrame([(i, " ".join(t), "en", "s", 1) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r.doc_id for r in corpus_pipeline._near_dedup(spark, docs, "").collect()} == {0, 2, 4}


def test_an_empty_corpus_and_repeated_rows(spark, tmp_path):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    for name, rows in (("empty", []), ("repeats", [(i % 3, f"some words about number {i % 3} and nothing else at all", None, None, None) for i in range(30)] + [(None, None, None, None, None)])):
        spark.createDataFrame(rows, schema).write.parquet(str(tmp_path / name / "documents.parquet"))
        spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / name / "labels.parquet"))
        out = corpus_pipeline.run(spark, str(tmp_path / name)).collect()
        assert {r.doc_id for r in out} == ({0, 1, 2, None} if rows else set())


def test_stages_keep_columns_of_any_name(spark, tmp_path):
    words = "plain words on hills and rivers, token = abcdefghijklmnop12 and {} more"
    docs = spark.createDataFrame([(i, words.format(i), "en", "s", 1, 2, 3, 4, 5) for i in range(4)], "doc_id long, text string, lang string, source string, n_chars long, assign int, copies int, h int, own_id int")
    labels = spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int")
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns[5:] == ["assign", "copies", "h", "own_id"] and {tuple(r[5:]) for r in docs.collect()} == {(2, 3, 4, 5)}
