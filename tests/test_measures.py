"""Measures, generators and sinks that no registered query holds against SQL."""

import numpy as np
import pytest
from checks import SMALL

from setstream.functions.hashing import HashFamily
from setstream.operators import bins as B
from setstream.operators import candidates as C
from setstream.operators import costs, streams
from setstream.operators import reserve as R
from setstream.operators import similarity as S
from setstream.plans import catalog
from setstream.plans import workloads as W
from setstream.sources import collections as col
from setstream.sources import store
from setstream.streaming import live

FAMILY = HashFamily.affine(24, 5)


def members(spark, sets):
    return spark.createDataFrame([(s, x) for s, xs in sets.items() for x in xs], "set_id long, element long")


@pytest.fixture(scope="module")
def sets():
    rng = np.random.default_rng(1)
    return {i: set(rng.choice(60, 20 + i, replace=False).tolist()) for i in range(12)}


def test_sensitivity_is_the_collision_rate():
    rng, family = np.random.default_rng(2), HashFamily.affine(4000, 9)
    every = rng.choice(2**31, 80, replace=False)
    a, b = every[:60], every[20:]
    low = [family.pairs_numpy(rng.permutation(x).astype(np.int64)).min(0) for x in (a, b)]
    got = C.sensitivity("signature", 0.5, 0.2)
    assert got == pytest.approx({"p1": 0.5, "p2": 0.2, "probability": 1.0}) and abs((low[0] == low[1]).mean() - 0.5) < 0.04
    banded = C.sensitivity("signature", 0.5, 0.2, bands=10, rows=3)
    assert banded["p1"] == pytest.approx(1 - (1 - 0.125) ** 10) and banded["p2"] == pytest.approx(1 - (1 - 0.008) ** 10)
    assert C.sensitivity("bins", 0.7, 0.5, gamma=0.2, delta=0.1)["p1"] == pytest.approx(0.56)


def test_bottom_similarity_equals_sets(spark, sets):
    pairs = spark.createDataFrame([(a, b) for a in sets for b in sets if a < b], "a long, b long")
    got = S.bottom_similarity(S.bottom_sketch(members(spark, sets), 200, FAMILY), pairs, 200).collect()
    assert len(got) == 66 and all(r["est"] == pytest.approx(len(sets[r["a"]] & sets[r["b"]]) / len(sets[r["a"]] | sets[r["b"]])) for r in got)
    least = lambda xs: sorted(FAMILY.pairs_numpy(np.array(sorted(xs), np.int64))[:, 0].tolist())[:8]
    for r in S.bottom_similarity(S.bottom_sketch(members(spark, sets), 8, FAMILY), pairs, 8).collect():
        union = sorted(set(least(sets[r["a"]])) | set(least(sets[r["b"]])))[:8]
        assert r["est"] == pytest.approx(len(set(union) & set(least(sets[r["a"]])) & set(least(sets[r["b"]]))) / 8)


def test_tuned_bands_and_search(spark, sets):
    rows = members(spark, sets | {100: sets[0] | {61}, 101: sets[1] | {62}})
    sigs, truth = S.signatures(rows, FAMILY), S.exact_pairs(rows, 0.6)
    tuned = C.tune_bands(sigs, truth, 14, W.band_grid(24)).collect()
    f1 = [r["f1"] for r in tuned if r["f1"] is not None]
    assert len(tuned) == 6 and f1 == sorted(f1, reverse=True) and all(r["tp"] + r["fp"] + r["fn"] + r["tn"] == 91 for r in tuned)
    found = C.similar_to(sigs.where("set_id < 100"), sigs.where("set_id >= 100"), 12, 2, 0.5).collect()
    assert {(r["query_id"], r["set_id"]) for r in found} >= {(100, 0), (101, 1)} and all(r["est"] >= 0.5 for r in found)


def test_cost_measures(spark):
    log = spark.createDataFrame([(1, 5, 0, 10), (1, 9, 2, 7)], "set_id long, seq long, slot int, size_after long")
    assert tuple(costs.recovery_volume(log).first()) == (2, 17) and tuple(costs.recovery_volume(log.limit(0)).first()) == (0, 0)
    times = spark.createDataFrame([(8, "rebuild", 6.0), (8, "reserve", 2.0), (16, "rebuild", 9.0)], "n int, sketch string, seconds double")
    assert {r["n"]: r["speedup"] for r in costs.speedup(times).collect()} == {8: 3.0, 16: None}


def test_generators(spark):
    made = streams.uniform_sets(spark, 5, 40, universe=1000).collect()
    assert {r["set_id"] for r in made} == set(range(5)) and all(0 <= r["element"] < 999 for r in made) and 150 < len(made) <= 200
    updates = spark.range(5000).selectExpr("id as seq", "1L as set_id", "id as element", "1 as op")
    assert abs(streams.mixed_ops(updates, 0.3).where("is_query").count() / 5000 - 0.3) < 0.03 and streams.mixed_ops(updates, 0.0).where("is_query").count() == 0
    rows = spark.createDataFrame([(u, v) for u in (3, 3, 900, -5) for v in (1, 2)], "u long, v long").distinct()
    got = sorted((r["u"], r["v"], r["seq"]) for r in streams.numbered(rows, "u", "v", cells=4).collect())
    assert [n for _, _, n in got] == [1, 2, 3, 4, 5, 6]


def test_maintained_sketches_are_right(spark, sets):
    for k in (8, 72):  # columns, then kernels
        family = HashFamily.affine(k, 5)
        sketch, faults = R.maintained(members(spark, sets), family, 3)
        assert R.audit(sketch, members(spark, sets), family, 3).count() == 0 and faults.count() >= 0
        got = {r["set_id"]: list(r["sig"]) for r in R.reserve_signature(sketch).collect()}
        assert got == {r["set_id"]: list(r["sig"]) for r in S.signatures(members(spark, sets), family).collect()}


def test_bins_meet_across_levels(spark, sets):
    shape = B.BinShape(bins=16, levels=6)
    counters = B.bins_init(members(spark, sets), shape)
    sigs = B.bins_level_signatures(counters, FAMILY, shape)
    own = {(r["set_id"]): list(r["sig"]) for r in B.bins_signature(counters, FAMILY, shape).collect()}
    levels = {}
    for r in sigs.collect():
        levels.setdefault(r["set_id"], {})[r["level"]] = list(r["sig"])
    assert all(own[s] in levels[s].values() and len(levels[s]) <= 3 for s in own)
    pairs = C.candidate_pairs(sigs, 12, 2)
    assert pairs.where("a >= b").count() == 0


def test_sinks_and_repeated_events(spark, sets, tmp_path):
    store.write_bucketed(members(spark, sets), "kept_members", buckets=4)
    try:
        rows = spark.table("kept_members")
        assert rows.count() == sum(map(len, sets.values())) and "Exchange" not in rows.groupBy("set_id").count()._jdf.queryExecution().simpleString()
    finally:
        spark.sql("DROP TABLE kept_members")
    spark.sql("SELECT 1L AS event_id, timestamp'2024-01-01 00:00:00' AS ts UNION ALL SELECT 1, timestamp'2024-01-01 00:01:00' UNION ALL SELECT 2, timestamp'2024-01-01 00:02:00'").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("event_id long, ts timestamp").parquet(str(tmp_path / "in"))
    q = live.drop_repeated_events(stream).writeStream.format("memory").queryName("once").start()
    q.processAllAvailable()
    q.stop()
    assert sorted(r["event_id"] for r in spark.table("once").collect()) == [1, 2]


class PlainReserve:
    """One set's reserve in sorted lists, slot by slot."""

    def __init__(self, family, reserve):
        self.family, self.reserve, self.held = family, reserve, set()
        self.rows, self.lim, self.log = [[] for _ in range(family.k)], [float("inf")] * family.k, []

    def update(self, seq, x, op):
        pairs = self.family.pairs_numpy(np.array([x], np.int64))[0].tolist()
        (self.held.add if op > 0 else self.held.discard)(x)
        for i, p in enumerate(pairs):
            row = self.rows[i]
            if op > 0 and p <= self.lim[i] and p not in row:
                row.append(p)
                row.sort()
                del row[self.reserve :]
                if len(row) == self.reserve:
                    self.lim[i] = row[-1]
            elif op < 0 and p in row:
                row.remove(p)
        bare = [i for i in range(self.family.k) if not self.rows[i] and self.lim[i] < float("inf")]
        if op < 0 and bare:
            self.log.append((seq, bare[0], len(self.held)))
            every = self.family.pairs_numpy(np.array(sorted(self.held), np.int64)).reshape(-1, self.family.k)
            self.rows = [sorted(every[:, i].tolist())[: self.reserve] for i in range(self.family.k)]
            self.lim = [r[-1] if len(r) == self.reserve else float("inf") for r in self.rows]


def test_fault_log_equals_plain_lists(spark):
    updates = [(r["set_id"], r["seq"], r["element"], r["op"]) for r in col.event_updates(spark, SMALL).collect()]
    sketches = {}
    for s, seq, x, op in sorted(updates, key=lambda u: (u[0], u[1], u[2], u[3])):
        sketches.setdefault(s, PlainReserve(catalog.DOCS, 1)).update(seq, x, op)
    want = sorted((s, *row) for s, k in sketches.items() for row in k.log)
    assert want and sorted(tuple(r) for r in catalog.QUERIES["reserve_fault_log"](spark, SMALL).collect()) == want


def test_seq_is_exact_above_2_53(spark):
    from setstream.operators.replay import replay

    n = 1 << 60
    updates = spark.createDataFrame([(n + 1, 1, 7, 1), (n + 2, 1, 7, -1), (n, 1, 7, -1), (n + 3, 1, 8, 1)], "seq long, set_id long, element long, op int")
    (row,) = replay(updates, "reserve", FAMILY, 2).collect()
    assert row["size"] == 1 and [tuple(r) for r in streams.members_at(updates).collect()] == [(1, 8)]


def test_experiments_show_the_published_order(spark):
    from setstream.operators.bins import BinShape

    rows = {(r["j"], r["sketch"]): r for r in W.planted_errors(spark, [0.5], 12, 1 << 12, 64, 4, BinShape(bins=64, levels=14)).collect()}
    assert rows[0.5, "reserve"]["rmse"] < 0.15 and rows[0.5, "reserve"]["rmse"] < rows[0.5, "bins_alpha_bins"]["rmse"] and rows[0.5, "rebuild_same_memory"]["rmse"] < rows[0.5, "reserve"]["rmse"] * 1.2
    found = {r["sketch"]: r for r in W.pair_quality(spark, SMALL, "user_keys", 0.3, budget=48).collect()}
    assert set(found) == {"reserve", "bins"} and found["reserve"]["effective"] == found["bins"]["effective"] > 0 and found["reserve"]["recall"] > 0.5
