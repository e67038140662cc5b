"""Stages of the corpus pipeline, each against what its operator finds on the same input."""

import corpus_pipeline
from hgpart.llm.ngram_join import ngram_components
from hgpart.llm.queries import COMPANIONS, ORACLE_SQL, QUERIES


def test_stages_keep_columns_and_take_effect(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "ngram_join", "decontaminate", "mix_sources", "token_output"]
    for n, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        out.write.parquet(str(tmp_path / name))
        kept = spark.read.parquet(str(tmp_path / name))
        if name != "token_output":
            assert kept.columns == docs.columns
        if name == "ngram_join":
            found = ngram_components(docs).toPandas()
            want = set(found.loc[found["component_id"] == found["doc_id"], "doc_id"])
            assert {r["doc_id"] for r in kept.collect()} == want
        if name in ("toxicity", "decontaminate"):
            assert 0.5 * docs.count() < kept.count() <= docs.count()
        if name == "token_output":
            assert kept.count() == docs.count()
            rows = kept.orderBy("start").toPandas()
            assert (rows["start"].diff().dropna().to_numpy() == rows["n_tokens"].iloc[:-1].to_numpy()).all()
        docs = kept


def test_registered_queries():
    assert len(QUERIES) == 10 and set(ORACLE_SQL) <= set(QUERIES) | set(COMPANIONS)
    assert [int(n[2:].split("_")[0]) for n in QUERIES] == list(range(1, 11))
