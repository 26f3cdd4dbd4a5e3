"""Stages one by one against what their operators report, and the whole on the small table."""

import corpus_pipeline as P
from packgraph.llm.host_rules import host_quality
from packgraph.llm.ngram_join import jaccard_components
from packgraph.llm.substring_dedup import substring_report

SF = "/root/testdata/sf0.01"


def stored(spark, df, path):
    df.write.parquet(str(path))
    return spark.read.parquet(str(path))


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = stored(spark, P.quality_rules(spark, docs, SF), tmp_path / "a")
    assert sorted(r["doc_id"] for r in kept.select("doc_id").collect()) == sorted(r["doc_id"] for r in host_quality(docs).where("kept").collect())
    lines = stored(spark, P.line_dedup(spark, kept, SF), tmp_path / "b")
    assert lines.columns == docs.columns and lines.count() == kept.count()
    near = stored(spark, P.near_duplicates(spark, docs, SF), tmp_path / "c")
    groups = jaccard_components(docs.select("doc_id", "text"), 5, 80)
    assert near.columns == docs.columns
    assert sorted(r["doc_id"] for r in near.select("doc_id").collect()) == sorted(r["doc_id"] for r in groups.where("component_id = doc_id").collect())
    cut = P.substring_dedup(spark, docs, SF)
    assert cut.columns == docs.columns
    report = {r["doc_id"]: r for r in substring_report(docs).collect()}
    for r in cut.select("doc_id", "text").collect():
        assert len(r["text"].split()) == report[r["doc_id"]]["n_words"] - report[r["doc_id"]]["n_removed"]


def test_run(spark):
    rows = P.run(spark, SF).collect()
    assert {n for n, _ in P.STAGES} == {"quality rules", "line dedup", "n-gram Jaccard join", "substring dedup", "packing"}
    assert len({r["sequence_id"] for r in rows}) * 2048 < 1.05 * sum(r["length"] for r in rows) + 4096
