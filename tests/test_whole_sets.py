"""Sketches of whole sets are made where the sets stand, and elements meet only where sizes can reach the threshold."""

import numpy as np
import pyarrow as pa
import pytest
from checks import SMALL
from pyspark.sql import functions as F

from setstream.functions.hashing import HashFamily, xxhash
from setstream.operators import bins as B
from setstream.operators import cells
from setstream.operators import reserve as R
from setstream.sources import collections as col
from setstream.sources.store import written


@pytest.fixture(scope="module")
def sets(spark):
    rng = np.random.default_rng(6)
    rows = [(i, sorted(rng.choice(1 << 32, n, replace=False).tolist())) for i, n in enumerate([1, 1, 2, 3, 5, 9, 40, 300, *rng.integers(1, 60, 20).tolist()])]
    return written(spark.createDataFrame(rows, "set_id bigint, e array<bigint>"), "sets")


def test_sketches_are_those_of_rows_without_an_exchange(spark, sets):
    members, family = sets.select("set_id", F.explode("e").alias("element")), HashFamily.affine(20, 3)
    for reserve in (1, 4):
        (rows, row_faults), (whole, faults) = R.maintained(members, family, reserve), R.maintained(sets, family, reserve)
        assert "Exchange" not in whole._jdf.queryExecution().executedPlan().toString()
        order = lambda df: sorted(map(tuple, df.collect()), key=repr)
        assert order(whole) == order(rows) and order(faults) == order(row_faults.select(*faults.columns))
    assert faults.count() == 0 < R.maintained(sets, family, 1)[1].count()
    for shape in (B.BinShape(bins=16, levels=8), B.BinShape(bins=64, levels=18)):
        counted = B.bins_init(sets, shape)
        assert order(counted.select("set_id", F.inline("bins"))) == order(B.bins_init(members, shape))
        found = B.bins_level_signatures(counted, family, shape)
        assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
        assert order(found) == order(B.bins_level_signatures(B.bins_init(members, shape), family, shape))


def test_hash_is_sparks(spark):
    x = [0, 1, 77, (1 << 32) - 1]
    assert [r[0] for r in spark.createDataFrame([(v,) for v in x], "x bigint").select(F.xxhash64("x", F.lit(5))).collect()] == xxhash(np.array(x), 5).tolist()


def test_elements_meet_where_sizes_allow(spark, sets):
    def names(left, right, same):
        a, b = left.column("set_id").to_numpy(), right.column("set_id").to_numpy()
        i, j = np.nonzero(np.arange(len(a))[:, None] < np.arange(len(b)) if same else np.ones((len(a), len(b)), bool))
        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a[i], b[j])), pa.array(np.maximum(a[i], b[j]))], names=["a", "b"])

    n = {r["set_id"]: len(r["e"]) for r in sets.collect()}
    met = [tuple(r) for r in cells.over_sized_cells(sets, names, "a bigint, b bigint", 0.5, 4).collect()]
    assert len(met) == len(set(met)) < len(n) * (len(n) - 1) // 2
    assert {(a, b) for a in n for b in n if a < b and min(n[a], n[b]) >= 0.5 * max(n[a], n[b])} <= set(met)


def test_meetings_by_lines_and_one_by_one(monkeypatch):
    rng = np.random.default_rng(2)
    p, q = rng.integers(0, 30, 70), np.r_[rng.integers(0, 30, 100), np.full(30, 3)]
    w_a, w_b = rng.integers(1, 4, 70), np.sort(rng.integers(1, 4, 130))[::-1]
    rows, columns = np.flatnonzero(rng.random(70) < 0.8), np.flatnonzero(rng.random(130) < 0.8)
    want = np.zeros((70, 130), bool)
    want[np.ix_(rows, columns)] = p[rows][:, None] == q[columns]
    for rare in (0, 4, 1000):
        m = cells.Meetings(70, 130)
        m.rare = rare
        m.add(rows, p[rows], columns, q[columns])
        assert (np.unpackbits(m.bits.view(np.uint8), axis=1, bitorder="little")[:, :130] == want).all()
        assert m.weigh(w_a, w_b) == w_a @ want @ w_b


def test_documents_sets_are_those_of_their_rows(spark):
    whole, rows = col.doc_shingle_sets(spark, SMALL), cells.arrays(col.doc_shingles(spark, SMALL))
    assert whole.count() == rows.count() and whole.exceptAll(rows).isEmpty()
    assert whole._jdf.queryExecution().optimizedPlan().toString().count("Aggregate [") == 1
