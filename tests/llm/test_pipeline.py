import corpus_pipeline
from brute import words


def test_stages_keep_columns_and_drop_copies(spark, docs):
    good = [" ".join(["the", "of", "and", "it"] * 5 + words(120, i)) for i in range(30)]
    data = [(i, t) for i, t in enumerate(good)] + [(100 + i, t) for i, t in enumerate(good[:5])] + [(200, None), (201, "#### " * 80)]
    d = docs(data, extra=False)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, d, "")
        if name != "encode":
            assert out.columns == d.columns, name
            d = spark.createDataFrame(out.collect(), d.schema)
            ids = {r.doc_id for r in d.collect()}
            if name == "quality":
                assert ids == {*range(30), *range(100, 105)}
    assert out.count() == d.count() and {"doc_id", "n_tokens", "ids"} <= set(out.columns)


def test_stages_are_stored(spark, docs, tmp_path):
    docs([(i, " ".join(["the", "of", "and", "it"] * 5 + words(120, i))) for i in range(20)], extra=False).write.parquet(f"{tmp_path}/documents.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path))
    files = out.inputFiles()
    assert files and all("/rarecount-source_mix-" in f for f in files)
    assert out.count() > 0


def test_run_on_empty_and_clashing_tables(spark, docs, tmp_path):
    text = " ".join(["the", "of", "and", "it"] * 5 + words(120, 1))
    extra = docs([(1, text), (None, text + " x"), (3, None)]).selectExpr("*", "'a' as lines", "2 as comp", "3 as tokens", "4 as component_id")
    for name, df in (("empty", docs([], extra=False)), ("clash", extra)):
        df.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        out = corpus_pipeline.run(spark, f"{tmp_path}/{name}")
        assert out.count() == (0 if name == "empty" else 2)
