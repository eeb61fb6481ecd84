"""The pipeline end to end on the smallest tables."""

import corpus_pipeline

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    n = docs.count()
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, SF)
        if k + 1 < len(corpus_pipeline.STAGES):
            assert out.columns == columns, name
            out = out.cache()
            assert 0 < out.count() <= n
            n = out.count()
        docs = out
    assert docs.count() == n
    assert corpus_pipeline.run(spark, SF).count() == n


def test_all_queries_give_rows(spark):
    import __spark_entry__ as entry

    found = [name for name in entry.queries() if name[:2] == "op" and name[2].isdigit()]
    assert len(found) == 10
    for name in found:
        df = entry.queries()[name](spark, SF)
        assert df.count() > 0, name


def test_stages_on_awkward_rows(spark):
    from test_text_ops import ROWS

    schema = "doc_id long, text string, lang string, source string, n_chars long, score string, ids string, spans string, root string"
    rows = [(i, t, None, None, None, "old", None, "old", "old") for i, t in ROWS]
    docs = spark.createDataFrame(rows, schema)
    null_ids = sum(i is None for i, _ in ROWS)
    out = dict.fromkeys(name for name, _ in corpus_pipeline.STAGES)
    for name, stage in corpus_pipeline.STAGES:
        out[name] = stage(spark, docs, SF).collect()
        assert stage(spark, spark.createDataFrame([], schema), SF).count() == 0, name
        assert name == "tokens" or out[name] == [] or out[name][0].__fields__ == docs.columns, name
    assert len(out["near_duplicates"]) == len({i for i, _ in ROWS if i is not None}) + null_ids
    assert len(out["decontamination"]) == len(out["personal_data"]) == len(out["tokens"]) == len(ROWS)
    masked = next(r for r in out["personal_data"] if r.doc_id == 7)
    assert "[EMAIL]" in masked.text and masked.n_chars == len(masked.text) and masked.score == "old"
