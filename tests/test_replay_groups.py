"""Replay of many sets in shared batches."""

import numpy as np
from checks import SMALL, walk

from setstream.functions.hashing import HashFamily
from setstream.operators.replay import replay
from setstream.plans import catalog


def test_sets_across_batches_and_a_null_set(spark):
    rows = [(i, i * 7919 % 61, i * 31 % 23, 1 if i % 5 else -1) for i in range(2000)]
    updates = spark.createDataFrame(rows + [(1, None, 5, 1)], "seq bigint, set_id bigint, element bigint, op int")
    family, want = HashFamily.affine(4, seed=2), walk(rows)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
        got = {r["set_id"]: r for r in replay(updates, "reserve", family, 2).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert set(got) == {*want, None} and got[None]["size"] == 1
    for s, e in want.items():
        assert got[s]["size"] == len(e) and got[s]["ops"] == sum(r[1] == s for r in rows)
        assert got[s]["sig"] == (None if not e else [min(int(x) for x in col) for col in zip(*family.pairs_numpy(np.array(sorted(e))).tolist())])


def test_whole_edges_are_not_replayed_a_set_a_call(spark):
    text = catalog.QUERIES["whole_edge_neighbourhood_signatures"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in text and "FlatMapGroups" not in text


def test_the_grid_of_faults_makes_its_stream_once(spark):
    text = catalog.QUERIES["faults_by_reserve"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "l_orderkey" not in text and "Window" not in text


def test_random_subsets_of_lines_are_taken_before_anything_is_shuffled(spark, tmp_path):
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    from setstream.plans.workloads import big_set

    rows = [(i % 400, i % 7) for i in range(3000)]  # lines are there more than once
    spark.createDataFrame(rows, "l_orderkey bigint, l_linenumber int").repartition(5).write.parquet(str(tmp_path / "lineitem.parquet"))
    got = big_set(spark, str(tmp_path), 100, sets=3)
    assert "MapInArrow" in got._jdf.queryExecution().optimizedPlan().toString()
    every = spark.createDataFrame(sorted({(s, a * 8 + b) for a, b in rows for s in (1, 2, 3)}), "set_id bigint, element bigint")
    order = F.row_number().over(Window.partitionBy("set_id").orderBy(F.xxhash64("element", "set_id"), "element"))
    want = every.withColumn("r", order).where("r <= 100").select("set_id", "element")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
