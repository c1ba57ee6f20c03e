"""The pipeline stage by stage: whole inputs, kept columns, defined results on odd tables."""

import hashlib
import re

from pyspark.sql import functions as F

import corpus_pipeline
from reelspark.llm import quality_rules, simhash, source_mix


def through(spark, docs, folder):
    out = []
    for k, (_name, stage) in enumerate(corpus_pipeline.STAGES):
        df = stage(spark, docs, "")
        df.write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        out.append(docs)
    return out


def test_stages(spark, docs, tmp_path):
    steps = through(spark, docs, tmp_path)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "secret_scan", "source_mix", "byte_bpe"]
    assert all(s.columns == docs.columns for s in steps[:-1])
    kept = {r["doc_id"] for r in steps[0].collect()}
    assert kept == {r["doc_id"] for r in quality_rules.digest(docs).where("kept").collect()}
    assert sorted(r["doc_id"] for r in steps[1].collect()) == sorted(r["doc_id"] for r in simhash.keep_one(steps[0]).collect())
    copies = {r["t"] for r in steps[0].groupBy(F.col("text").alias("t")).agg(F.count("*").alias("n")).where("n > 1").collect()}
    assert copies and steps[1].where(F.col("text").isin(list(copies))).count() <= len(copies)
    assert steps[2].count() == steps[1].count() and steps[2].where(F.col("text").rlike('token = "[0-9a-f]{40}"')).count() == 0
    want = {r["doc_id"]: r["taken"] for r in source_mix.digest(steps[2]).collect() if r["taken"]}
    got: dict = {}
    for r in steps[3].collect():
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + len(re.findall(r"[^\x20\x09-\x0D]+", r["text"]))
    assert abs(sum(got.values()) - sum(want.values())) <= 0.02 * sum(want.values()) + 40
    texts = sorted(hashlib.sha256(r["text"].encode()).hexdigest() for r in steps[3].collect())
    assert sorted(r["decoded_sha256"] for r in steps[4].collect()) == texts


def test_odd_tables(spark, odd_docs, no_docs, tmp_path):
    steps = through(spark, odd_docs, tmp_path / "odd")
    assert steps[0].count() > 5 and steps[1].where("doc_id IN (2, 3)").count() == 0 and steps[1].where("doc_id = 1").count() == 1
    assert "[SECRET]" in steps[2].where("doc_id = 14").first()["text"]
    assert all(s.count() == 0 for s in through(spark, no_docs, tmp_path / "none"))


def test_run_equals_the_stages(spark, sf_dir, docs, tmp_path):
    a = sorted(map(tuple, corpus_pipeline.run(spark, sf_dir).collect()))
    assert a == sorted(map(tuple, through(spark, docs, tmp_path)[-1].collect()))
