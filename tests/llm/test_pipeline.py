"""The pipeline's stages, each on its own input."""

import corpus_pipeline


def test_stages_take_effect(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, small)
        assert out.columns == columns
        docs = out.cache()
        seen[name] = docs.toPandas()
    tox, dup, sec, mix = (seen[n] for n, _ in corpus_pipeline.STAGES[:-1])
    assert set(dup["doc_id"]) < set(tox["doc_id"]) and len(dup) == dup["doc_id"].nunique()
    assert set(sec["doc_id"]) == set(dup["doc_id"]) and not sec["text"].str.contains("AKIA[A-Z0-9]{16}").any()
    assert set(mix["doc_id"]) <= set(sec["doc_id"]) and mix["doc_id"].value_counts().max() <= 3
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, small).toPandas()
    assert (packed.groupby("sequence_id")["length"].sum() <= 2048).all() and set(packed["doc_id"]) == set(mix["doc_id"])


def test_mixing_keeps_rows_without_ids(spark):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame([(None, "a b c", None, None, None), (1, "a b", "en", "s", 3), (1, "a b c d", "en", "s", 7), (2, None, None, None, None)], schema)
    out = corpus_pipeline.mixing(spark, docs, "").toPandas()
    assert list(out.columns) == docs.columns and out["doc_id"].isna().any() and set(out["text"]) <= {"a b c", "a b", "a b c d"}
    assert corpus_pipeline.mixing(spark, docs.limit(0), "").count() == 0
