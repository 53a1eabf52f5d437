"""The pipeline's stages: columns, what goes and what stays, untidy input."""

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
SF = "/root/testdata/sf0.01"


def test_stages_and_result(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    seen = {}
    for name, stage in corpus_pipeline.STAGES[:4]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns and [f.dataType for f in out.schema] == [f.dataType for f in docs.schema]
        seen[name] = {r["doc_id"]: r["text"] for r in out.collect()}
        docs = spark.createDataFrame(out.collect(), docs.schema)
    toxic = {r["doc_id"] for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 1").collect()}
    assert len(toxic & set(seen["toxicity"])) <= 0.5 * len(toxic)
    texts = list(seen["minhash_near_dedup"].values())
    assert len({t.lower() for t in texts}) == len(texts)
    assert set(seen["benchmark_decontamination"]) == set(seen["secret_scans"])
    final = corpus_pipeline.run(spark, SF).collect()
    assert {r["doc_id"] for r in final} == set(seen["secret_scans"])
    assert not any("password=" in t for t in seen["secret_scans"].values())


@pytest.mark.parametrize("k", range(5))
def test_stages_take_untidy_and_empty_documents(spark, k):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(None, None, None, None, None), (1, "", "", "", 0), (2, None, "en", "s", 1), (3, "a b c " * 2000, "en", "s", 12000), (3, "a b c " * 2000, "en", "s", 12000)]
    stage = corpus_pipeline.STAGES[k][1]
    assert stage(spark, spark.createDataFrame(rows, schema), SF).count() >= 4 - (k == 1)
    assert stage(spark, spark.createDataFrame([], schema), SF).count() == 0
