"""The stages of the pipeline, one after the other, against the operators' own decisions."""

import pytest
from pyspark.sql import functions as F

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from salvage.llm import mixing, packing, simhash  # noqa: E402


def test_stages_take_effect(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = spark.createDataFrame([(90001, "", "en", "a", 0), (90002, None, None, None, None), (90003, "12 34", "en", "a", 5)], docs.schema)
    docs = docs.union(odd)
    counts = [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        counts.append(docs.count())
        if name == "language":
            assert sorted(r[0] for r in before.join(docs, "doc_id", "left_anti").select("doc_id").collect()) == [90001, 90002, 90003]
        if name in ("language", "toxicity", "near_duplicates", "mixing"):
            assert docs.columns == before.columns
        if name == "near_duplicates":
            assert docs.count() == simhash.near_duplicates(before).select("component_id").distinct().count()
            assert simhash.near_duplicates(docs).select("component_id").distinct().count() == docs.count()
        if name == "mixing":
            words = docs.agg(F.sum(mixing.word_count(F.col("text")))).first()[0]
            assert abs(words - 1.5 * before.agg(F.sum(mixing.word_count(F.col("text")))).first()[0]) < 0.02 * words
        if name == "packing":
            assert docs.agg(F.sum("length")).first()[0] == packing.cut_pieces(before).agg(F.sum("length")).first()[0]
    assert counts[1] < counts[0] and counts[3] <= counts[2] <= counts[1]
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_stages_on_odd_tables(spark, sf):
    """An empty table, then nulls in every column, repeated rows, ties, a long text and a further column."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    long = " ".join(reversed(docs.orderBy("doc_id").first()["text"].split())) * 300
    extra = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "a", 0), (7, long, "en", "a", len(long)), (7, long, "en", "a", len(long)), (None, "Also this one stays without any id.", "en", None, 3), (8, "   ", None, "b", 3)], docs.schema)
    odd = docs.union(extra).union(docs.limit(30)).withColumn("language", F.lit("kept"))
    for name, stage in corpus_pipeline.STAGES:
        empty = stage(spark, odd.limit(0), sf)
        assert empty.count() == 0
        rows = stage(spark, odd, sf)
        got = rows.collect()
        if name != "packing":
            assert rows.columns == odd.columns and got and all(r["language"] == "kept" for r in got)
        texts = [r["text"] for r in got] if name != "packing" else []
        if name in ("toxicity", "near_duplicates"):
            assert texts.count(long) == (1 if name == "near_duplicates" else 2) and any(not t for t in texts)
        if name == "mixing":
            assert all(t and t.strip() for t in texts)
        if name == "packing":
            assert sum(r["start"] == 0 for r in got) == odd.count()


def test_only_the_last_stage_stays_on_disk(spark, sf):
    import pathlib

    shared = pathlib.Path(spark.conf.get("spark.checkpoint.dir"))
    before = set(shared.glob("pipeline-*"))
    corpus_pipeline.run(spark, sf).count()
    (folder,) = set(shared.glob("pipeline-*")) - before
    assert [f.name for f in folder.iterdir()] == ["mixing"]
