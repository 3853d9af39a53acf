"""The pipeline against brute force, stage by stage."""

import hashlib

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline as p
from fieldlift.llm import bpe, mixing, quality

from .test_llm_operators import DOCS, ODD, brute_components


def test_stages_take_effect(spark, data):
    d = spark.read.parquet(f"{data}/documents.parquet")
    good = p.quality_stage(spark, d, data).cache()
    scores = quality.classify(d, spark.read.parquet(f"{data}/labels.parquet"))
    assert {r.doc_id for r in good.collect()} == {r.doc_id for r in scores.filter("predicted = 1").collect()}
    one = p.near_copies_stage(spark, good, data).cache()
    named = brute_components([(r.doc_id, r.text) for r in good.collect()])
    assert sorted(r.doc_id for r in one.collect()) == sorted(i for i, _, c in named if i == c)
    clean = p.secrets_stage(spark, one, data).cache()
    assert clean.count() == one.count() and clean.filter(F.col("text").rlike("AKIA[0-9A-Z]{16}")).count() == 0
    mixed = p.mixing_stage(spark, clean, data).cache()
    plan = {r.doc_id: r.copies for r in mixing.mix_plan(clean).collect()}
    assert {r.doc_id: r.n for r in mixed.groupBy("doc_id").agg(F.count("*").alias("n")).collect()} == {k: v for k, v in plan.items() if v}
    assert all(set(x.columns) == set(d.columns) for x in (good, one, clean, mixed))
    coded = p.encoding_stage(spark, mixed, data).collect()
    t = bpe.WordCoder(bpe.default_vocabulary())
    want = sorted((r.doc_id, hashlib.sha256(t.encode_batch([r.text])[0]).hexdigest()) for r in mixed.collect())
    assert sorted((r.doc_id, r.ids_sha256) for r in coded) == want and np.all([r.n_tokens >= 0 for r in coded])


def test_near_copies_of_repeated_and_null_ids(spark, data):
    a, b, c, d, e = (" ".join(f"{k}{i}" for i in range(30)) for k in "abcde")
    rows = [(5, a, "s"), (5, b, "s"), (5, b, "s"), (2, b + " x", "s"), (None, c, "s"), (None, c, "s"), (None, d, "t"), (7, d, "s"), (8, a, "s"), (9, e, "s"), (9, e + " y", "s"), (11, "", "s"), (11, None, "s"), (12, " ", "s"), (None, "", "s")]
    got = p.near_copies_stage(spark, spark.createDataFrame(rows, "doc_id long, text string, source string"), data).collect()
    texts = sorted((str(r.doc_id), r.text[:2]) for r in got if r.text and r.text.strip())
    assert texts == [("2", "b0"), ("5", "a0"), ("7", "d0"), ("9", "e0"), ("None", "c0")]
    assert sorted(str(r.doc_id) for r in got if not (r.text and r.text.strip())) == ["11", "12", "None"]


def test_stages_on_odd_and_empty_tables(spark, data, tmp_path):
    for rows in (ODD, []):
        docs = spark.createDataFrame(rows, DOCS)
        for k, (_, stage) in enumerate(p.STAGES):
            out = stage(spark, docs, data)
            assert k == len(p.STAGES) - 1 or out.columns == docs.columns
            out.write.parquet(str(tmp_path / f"{len(rows)}-{k}"))
            docs = spark.read.parquet(str(tmp_path / f"{len(rows)}-{k}"))
        assert rows or docs.count() == 0
    # each stage by itself, on all odd rows
    for name, stage in p.STAGES:
        assert stage(spark, spark.createDataFrame(ODD, DOCS), data).count() > 0 or name == "quality classifier"
