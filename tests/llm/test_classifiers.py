"""Held-out accuracy of both classifiers on the given labels, and their behaviour on odd rows."""

import zlib

import pytest
from checks import SMALL

from setstream.llm import learning, mil_toxicity, queries, subword_quality

TABLES = SMALL.replace("sf0.001", "sf0.1")


@pytest.mark.parametrize(("name", "label", "least"), [("op1_subword_quality", "quality", 0.95), ("op7_mil_toxicity", "toxic", 0.97)])
def test_held_out_accuracy(spark, name, label, least):
    rows = queries.QUERIES[name](spark, TABLES)
    labels = spark.read.parquet(f"{TABLES}/labels.parquet")
    assert rows.count() == spark.read.parquet(f"{TABLES}/documents.parquet").count()
    held = rows.where("held_out").join(labels, "doc_id").select("predicted", label).collect()
    assert len(held) > 500
    assert sum(r["predicted"] == r[label] for r in held) / len(held) >= least
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in rows.limit(500).collect())


def test_training_sample_is_bounded_and_not_held_out(spark):
    docs = spark.createDataFrame([(i, f"text {i}") for i in range(200)] + [(3, None), (None, "x")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)] + [(None, 1), (5, None)], "doc_id long, quality int")
    texts, own = learning.training_sample(docs, labels, "quality", rows=20)
    assert len(texts) == 40 and sum(own) == 20
    assert all(zlib.crc32(t.split()[1].encode()) % 5 for t in texts)


def test_odd_rows(spark, dirty, empty):
    labels = spark.createDataFrame([(4, 1, 0), (10, 0, 1)], "doc_id long, quality int, toxic int")
    for run in (subword_quality.classify, mil_toxicity.classify):
        rows = run(dirty, labels).collect()
        assert len(rows) == 12 and all(0 <= r["score"] <= 1 for r in rows)
        by = {}
        for r in rows:
            by.setdefault(r["doc_id"], set()).add(r["score"])
        assert len(by[4]) == 1
        assert run(empty, labels.limit(0)).count() == 0


def test_offending_sentences_are_located(spark):
    texts = ["All is well. You awful grumbler! Good day.", "All is well. Good day.", "Nice things here. Good day to all."]
    rows = [(i, texts[i % 3]) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model = mil_toxicity.NoisyOrModel.fit([t for _, t in rows], [int(i % 3 == 0) for i, _ in rows])
    for r in mil_toxicity.score(docs, model).collect():
        found = [rows[r["doc_id"]][1][s["start"] : s["end"]] for s in r["offending"]]
        assert found == (["You awful grumbler"] if r["doc_id"] % 3 == 0 else [])
        assert (r["score"] >= 0.5) == (r["doc_id"] % 3 == 0)
