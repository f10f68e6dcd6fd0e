"""Stages of the corpus pipeline on the smallest tables."""

import duckdb
from pyspark.sql import functions as F

import corpus_pipeline
from conftest import DATA
from pairlattice.llm import decontam, omh, sentencepiece, suffix

SF = f"{DATA}/sf0.001"


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, SF).collect(), docs.schema)
        assert docs.columns == columns, name
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[1] < counts[0] and counts[2] < counts[1] and counts[3] == counts[2] and counts[4] < counts[3]
    assert omh.classes(docs).where("doc_id <> class_id").count() <= 1
    assert decontam.contamination(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).where("contaminated").count() == 0
    tokens = sentencepiece.encode(docs)
    assert tokens.where("not round_trip").count() == 0
    run = corpus_pipeline.run(spark, SF)
    assert {(r["doc_id"], r["n_tokens"]) for r in run.collect()} == {(r["doc_id"], r["n_tokens"]) for r in tokens.collect()}
    assert suffix.digests(docs).agg(F.sum("n_removed")).first()[0] <= 200
    assert duckdb.sql(f"select count(*) from '{SF}/documents.parquet'").fetchall()[0][0] == counts[0]
