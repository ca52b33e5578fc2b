"""The pipeline's stages against brute force."""

import numpy as np
from conftest import DATA

import corpus_pipeline
from orthant.llm import simhash
from orthant.llm.common import written
from pyspark.sql import functions as F

SF = f"{DATA}/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, rows = docs.columns, {r["doc_id"]: r["text"] for r in docs.collect()}
    extra = spark.createDataFrame([(9000, None, "en", "s", 0), (9001, "12 34", None, None, 5), (9002, "", "en", "s", 0)], docs.schema)
    docs = docs.unionByName(extra)
    kept = []
    for _, stage in corpus_pipeline.STAGES[:3]:
        docs = stage(spark, docs, SF)
        assert docs.columns == columns
        kept.append(sorted(r[0] for r in docs.select("doc_id").collect()))
    assert kept[0] == sorted(rows)
    last = {}
    for i, t in rows.items():
        last[t] = max(i, last.get(t, -1))
    assert kept[1] == sorted(last.values())
    ids = np.array(kept[1])
    fp = np.array([simhash.fingerprint(rows[i].encode()) for i in kept[1]], dtype=np.uint64)
    near, label = np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 3, ids.copy()
    while True:
        new = np.array([label[near[i]].min() for i in range(len(ids))])
        if (new == label).all():
            break
        label = new
    assert kept[2] == sorted(set(label.tolist()))
    mixed = corpus_pipeline.mixed(spark, docs, SF)
    times = {r[0]: r[1] for r in mixed.groupBy("doc_id").count().collect()}
    assert mixed.columns == columns and set(times) <= set(kept[2]) and max(times.values()) <= 3
    packed = corpus_pipeline.packed(spark, mixed, SF)
    assert {r[0]: r[1] for r in packed.where("piece = 0").groupBy("doc_id").count().collect()} == times
    assert packed.groupBy("sequence_id").agg({"length": "sum"}).agg({"sum(length)": "max"}).first()[0] <= 2048


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "exact_dedup", "near_dedup", "mix", "pack"]


def chain(spark, docs):
    """What every stage leaves, each written and read again as the driver does."""
    out = []
    for name, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, SF), name)
        out.append(docs)
    return out


def test_chain_on_an_empty_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("false")
    left = chain(spark, docs)
    assert [d.count() for d in left] == [0] * 5 and all(d.columns == docs.columns for d in left[:4])


def test_chain_on_repeated_rows_and_nulls(spark):
    """Every row twice, rows of nulls, and columns named like the stages' own: copies go once, nulls in the first stage."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(60)
    twice = docs.unionByName(docs).unionByName(spark.createDataFrame([(None, None, None, None, None), (None, "some words in English, and more of them", "en", None, 1)], docs.schema))
    for c in ("_all", "_hex", "_fp", "_row", "_id", "_times", "label", "key"):
        twice = twice.withColumn(c, F.lit(c))
    left = chain(spark, twice)
    assert all(d.columns == twice.columns for d in left[:4])
    distinct = docs.select("text").distinct().count()
    assert left[0].count() == 121 and left[1].count() == distinct + 1 and left[1].where("doc_id is null").count() == 1
    assert left[2].count() <= left[1].count() and left[4].where("doc_id is null").count() == left[3].where("doc_id is null").count()
