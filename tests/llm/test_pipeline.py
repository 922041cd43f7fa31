"""The pipeline's stages on the smallest tables."""

import corpus_pipeline


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == names, name
        rows = out.collect()
        assert len({r.doc_id for r in rows}) == len(rows)
        docs = spark.createDataFrame(rows, docs.schema)
    bench = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert not any(b in (r.text or "") for r in docs.collect() for b in bench)
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == docs.count()


ITEM = "In which year did the small town by the river build its second stone bridge over the old canal"
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, score string"


def awkward(spark):
    long = "many words that nobody says twice in one single line of text number "
    rows = [(1, "the first plain text of some length that has eleven words", "en"), (2, "the first plain text of some length that has eleven words", "en"), (None, "the first plain text of some length that has eleven words", "en")]
    rows += [(None, "another text that stands alone and has no id at all", "en"), (None, "the words " + ITEM + " end", "en"), (3, "the words before " + ITEM + " end", "en"), (4, None, "en"), (5, "", None)]
    rows += [(6, "a row of an id that two rows share but not the text", "en"), (6, "b text that is quite different from what the other row says", "en"), (7, long * 2000, "en")]
    return spark.createDataFrame([(i, t, g, "s", len(t or ""), "x") for i, t, g in rows], COLUMNS)


def test_stages_with_nulls_repeated_rows_and_clashing_names(spark, tmp_path):
    docs = awkward(spark)
    spark.createDataFrame([(1, ITEM)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    stage = dict(corpus_pipeline.STAGES)
    kept = stage["near"](spark, docs.where("text is not null"), str(tmp_path))
    ids = sorted(str(r.doc_id) for r in kept.collect())
    assert ids == sorted(["1", "None", "None", "3", "5", "6", "7"]) and kept.columns == docs.columns
    assert {r.text for r in kept.where("doc_id = 6").collect()} == {"a row of an id that two rows share but not the text"}
    left = stage["benchmark"](spark, docs, str(tmp_path)).collect()
    assert sorted(str(r.doc_id) for r in left) == sorted(["1", "2", "None", "None", "4", "5", "6", "6", "7"]) and not any(ITEM in (r.text or "") for r in left)
    told = stage["language"](spark, docs, str(tmp_path))
    assert told.columns == docs.columns and {r.doc_id for r in told.collect()}.isdisjoint({4, 5})
    cut = {r.doc_id: r.text for r in stage["repeats"](spark, docs.where("doc_id = 7"), str(tmp_path)).collect()}
    assert len(cut[7].split()) == 13  # the line has 13 words, and each window from the second line on starts earlier too
    for name, f in corpus_pipeline.STAGES:
        assert f(spark, docs.limit(0), str(tmp_path)).count() == 0, name
