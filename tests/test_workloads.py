"""Workload queries do the whole job: nothing is left out by id, size or share."""

import numpy as np
from checks import SMALL

from setstream.operators import similarity as S
from setstream.plans import workloads as W


def test_topdim_cosine_covers_all_vectors(spark):
    from setstream.plans import catalog

    rows = spark.read.parquet(f"{SMALL}/embeddings.parquet").collect()
    e = np.array([r["embedding"] for r in rows], np.float64)
    top = [set(np.argsort(-x, kind="stable")[:8].tolist()) for x in e]
    a, b = np.triu_indices(len(e), 1)
    exact = [len(top[i] & top[j]) / len(top[i] | top[j]) for i, j in zip(a, b, strict=True)]
    want = np.corrcoef(exact, (e @ e.T)[a, b])[0, 1]
    (got,) = catalog.QUERIES["topdim_cosine"](spark, SMALL).collect()
    assert got["pairs"] == len(a) and abs(got["correlation"] - want) < 1e-5
    small = spark.read.parquet(f"{SMALL}/embeddings.parquet").selectExpr("cast(vec_id as bigint) as vec_id", "cast(embedding as array<double>) as e")
    (blocks,) = W.topdim_correlation(small, block=100).collect()
    assert blocks["pairs"] == len(a) and abs(blocks["correlation"] - want) < 1e-5


def test_whole_graph_has_every_order_line(spark, duck):
    from setstream.plans import catalog

    (edges,) = duck.execute("SELECT count(*) FROM (SELECT DISTINCT o_custkey, l_partkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey)").fetchone()
    updates = catalog.QUERIES["whole_edge_set_updates"](spark, SMALL)
    assert updates.count() == 2 * edges and updates.agg({"seq": "max"}).first()[0] == edges
    near = duck.execute("""WITH e AS (SELECT DISTINCT o_custkey AS u, l_partkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey)
        SELECT count(*) FROM (SELECT DISTINCT x.u, y.u FROM e x JOIN e y ON x.v = y.v WHERE x.u <> y.u)""").fetchone()[0]
    assert catalog.QUERIES["whole_edge_two_hop"](spark, SMALL).count() == near


def test_all_pairs_has_no_limit(spark):
    n = 5200
    got = S.all_pairs(spark.range(n).withColumnRenamed("id", "set_id"), block=1000).selectExpr("count(*) AS n", "sum(a) AS a", "sum(b) AS b").first()
    assert (got["n"], got["a"], got["b"]) == (n * (n - 1) // 2, sum(a * (n - 1 - a) for a in range(n)), sum(b * b for b in range(n)))
