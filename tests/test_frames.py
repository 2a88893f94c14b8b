"""DataFrame operations against plain Python: three-way hash equality, netting, merging, recovery, candidates, plans."""

import io
import random
from contextlib import redirect_stdout

import numpy as np
import pytest
from checks import walk
from pyspark.sql import functions as F

from setstream.functions import encoders
from setstream.functions.hashing import UNIVERSE, HashFamily, shuffled
from setstream.operators import bins as B
from setstream.operators import candidates as C
from setstream.operators import reserve as R
from setstream.operators import similarity as S
from setstream.operators import streams
from setstream.operators.replay import replay

FAMILY = HashFamily.affine(3, 3)
ELEMENTS = [0, 1, 2, 17, 2**31 - 1, 2**31, UNIVERSE - 1]


def random_updates(n, sets=6, universe=15, seed=1):
    rng = random.Random(seed)
    return [(i, rng.randrange(sets), rng.randrange(universe), rng.choice([1, 1, -1])) for i in range(n)]


def frame(spark, rows):
    return spark.createDataFrame(rows, "seq long, set_id long, element long, op int")


def members(spark, sets):
    return spark.createDataFrame([(s, x) for s, xs in sets.items() for x in xs], "set_id long, element long")


def truth(sets, family=FAMILY):
    return {s: family.pairs_numpy(np.array(sorted(xs), np.int64)).min(0).tolist() for s, xs in sets.items() if xs}


@pytest.mark.parametrize("kind", HashFamily.KINDS)
def test_hash_forms_are_equal(spark, duck, kind):
    family = HashFamily(kind, 3, 11, degree=4)
    df = spark.createDataFrame([(x,) for x in ELEMENTS], "x long")
    rows = df.select(*[family.pair(i, F.col("x")).alias(f"p{i}") for i in range(3)]).collect()
    expected = family.pairs_numpy(np.array(ELEMENTS))
    assert [list(r) for r in rows] == expected.tolist()
    if kind != "native":
        for x, e in zip(ELEMENTS, expected.tolist(), strict=True):
            text = ", ".join(family.pair_sql(i, f"{x}::BIGINT") for i in range(3))
            assert list(duck.execute(f"SELECT {text}").fetchall()[0]) == e


def test_permutation_family_is_a_permutation(spark):
    rows = shuffled(spark, 10, 2).collect()
    assert all(sorted(r["h"] for r in rows if r["slot"] == s) == list(range(10)) for s in (0, 1))


@pytest.mark.parametrize("rebuild", ["all", "slot"])
@pytest.mark.parametrize(("seed", "column_slots"), [(1, 64), (2, 64), (3, 64), (4, 1), (5, 1)])
def test_netted_batches_keep_signatures_and_invariants(spark, monkeypatch, seed, column_slots, rebuild):
    monkeypatch.setattr(R, "COLUMN_SLOTS", column_slots)  # 1: the numpy kernels
    rows = random_updates(300, seed=seed)
    sketch = R.reserve_init(members(spark, walk(rows[:100])), FAMILY, 2)
    for a, b in ((100, 180), (180, 300)):
        after = members(spark, walk(rows[:b]))
        sketch, faults = R.reserve_apply(sketch, frame(spark, rows[a:b]), after, FAMILY, 2, rebuild=rebuild)
        assert {r["set_id"]: r["sig"] for r in R.reserve_signature(sketch).where("sig is not null").collect()} == truth(walk(rows[:b]))
        assert R.audit(sketch, after, FAMILY, 2).count() == 0
        assert all(f["size_after"] >= 0 for f in faults.collect())


def test_replay_equals_netted_and_scratch(spark):
    rows = random_updates(400, seed=9)
    one = replay(frame(spark, rows), "reserve", FAMILY, 2).where("sig is not null").collect()
    assert {r["set_id"]: list(r["sig"]) for r in one} == truth(walk(rows))


def test_replay_starts_from_members(spark):
    start = members(spark, {1: {3, 4, 5}})
    got = replay(frame(spark, [(1, 1, 3, -1)]), "reserve", FAMILY, 2, start=start).first()
    assert got["size"] == 2 and list(got["sig"]) == truth({1: {4, 5}})[1]


def test_merge_of_shards(spark):
    sets = {1: {1, 4, 2, 3, 9}, 2: set(range(20))}
    a, b = ({s: {x for x in xs if x % 2 == i} for s, xs in sets.items()} for i in (0, 1))
    merged = R.reserve_merge(R.reserve_init(members(spark, a), FAMILY, 2), R.reserve_init(members(spark, b), FAMILY, 2), 2)
    assert {r["set_id"]: list(r["sig"]) for r in R.reserve_signature(merged).collect()} == truth(sets)
    assert R.audit(merged, members(spark, sets), FAMILY, 2).count() == 0


def test_compact_and_expand_are_inverse(spark):
    sketch = R.reserve_init(members(spark, {1: {5}, 2: set(range(9))}), FAMILY, 4)
    small = R.compact(sketch)
    assert {r["set_id"] for r in small.where("elements is not null").collect()} == {1}
    assert sorted(map(str, R.expand(small, FAMILY).collect())) == sorted(map(str, sketch.collect()))


def test_sampled_init_is_the_same(spark):
    m = members(spark, {1: set(range(3)), 2: set(range(500))})
    assert sorted(map(str, R.reserve_init(m, FAMILY, 4, sampled=True).collect())) == sorted(map(str, R.reserve_init(m, FAMILY, 4).collect()))


def test_kernel_signatures_equal_columns(spark):
    m = members(spark, {s: {s * 7 + i for i in range(30)} for s in range(5)})
    family = HashFamily.affine(70, 2)
    assert {r["set_id"]: list(r["sig"]) for r in S.signatures(m, family).collect()} == truth({s: {s * 7 + i for i in range(30)} for s in range(5)}, family)


def test_kernels_build_and_update_the_same_sketch(spark, monkeypatch):
    rows = random_updates(300, seed=12)
    made = []
    for slots in (64, 1):
        monkeypatch.setattr(R, "COLUMN_SLOTS", slots)
        sketch = R.reserve_init(members(spark, walk(rows[:150])), FAMILY, 3)
        after, faults = R.reserve_apply(sketch, frame(spark, rows[150:]), members(spark, walk(rows)), FAMILY, 3)
        made.append([sorted(map(str, df.collect())) for df in (sketch, after, faults)])
    assert made[0] == made[1]


def test_legality_and_netting(spark):
    df = frame(spark, [(1, 1, 7, 1), (2, 1, 7, 1), (3, 1, 7, -1), (4, 1, 7, -1), (5, 1, 7, 1), (6, 1, 8, -1), (7, 1, 8, 1)])
    assert [r["legal"] for r in streams.flag_legal(df).orderBy("seq").collect()] == [True, False, True, False, True, False, True]
    assert sorted((r["element"], r["op"]) for r in streams.net(df).collect()) == [(7, 1), (8, 1)]
    assert [r["size"] for r in streams.sizes(df).orderBy("seq").collect()] == [1, 0, 1, 2]


def test_bad_rows_are_set_aside(spark):
    df = frame(spark, [(1, 1, 7, 1), (2, None, 7, 1), (3, 1, None, 1), (4, 1, 7, None), (5, 1, 7, 2)])
    good, bad = streams.split_valid(df)
    assert good.count() == 1 and bad.count() == 4


def test_exact_pairs_with_and_without_prefix(spark):
    rng = random.Random(2)
    m = members(spark, {s: {rng.randrange(30) for _ in range(12)} for s in range(25)})
    for lam in (0.2, 0.35, 0.5):
        a, b = (sorted((r["a"], r["b"], r["exact"]) for r in S.exact_pairs(m, lam, prefix=p).collect()) for p in (True, False))
        assert a == b and (lam > 0.4 or a)


def test_similarity_of_empty_sets(spark):
    m = members(spark, {1: {1, 2, 3}, 2: {2, 3, 4}})
    pairs = spark.createDataFrame([(1, 2), (1, 3), (3, 4)], "a long, b long")
    assert {(r["a"], r["b"]): r["exact"] for r in S.exact_similarity(m, pairs).collect()} == {(1, 2): 0.5, (1, 3): 0.0, (3, 4): None}


def test_hot_buckets(spark):
    sigs = spark.createDataFrame([(i, [1, 2]) for i in range(12)] + [(20, [5, 6]), (21, [5, 6])], "set_id long, sig array<bigint>")
    everything = {(r["a"], r["b"]) for r in C.candidate_pairs(sigs, 1, 2).collect()}
    assert len(everything) == 67
    assert {(r["a"], r["b"]) for r in C.candidate_pairs(sigs, 1, 2, max_bucket=4, hot="salt").collect()} == everything
    assert C.candidate_pairs(sigs, 1, 2, max_bucket=4, hot="star").count() == 12
    assert C.candidate_pairs(sigs, 1, 2, max_bucket=4, hot="drop").count() == 1
    kept, membership = C.collapse_identical(sigs)
    assert kept.count() == 2 and {(r["a"], r["b"]) for r in C.expand_pairs(C.candidate_pairs(kept, 1, 2), membership).collect()} == everything


def test_quality_identities(spark):
    pairs = lambda rows: spark.createDataFrame(rows, "a long, b long")
    q = C.quality(pairs([(1, 2), (1, 3)]), pairs([(1, 2), (2, 3), (3, 4)]), 5).first()
    assert (q["tp"], q["fp"], q["fn"], q["tn"]) == (1, 1, 2, 6)
    assert abs(q["precision"] * q["returned"] - q["recall"] * q["effective"]) < 1e-6


def test_similarity_join_is_exact_on_what_it_returns(spark):
    sets = {s: set(range(s, s + 40)) for s in range(0, 30, 3)}
    found = C.similarity_join(members(spark, sets), 0.7, HashFamily.affine(256, 5)).collect()
    assert found and all(r["exact"] >= 0.7 for r in found)


def test_bins_merge_by_sums(spark):
    shape = B.BinShape(bins=8, levels=5)
    rows = [(i, 1, i, 1) for i in range(30)] + [(30 + i, 1, i, -1) for i in range(30)]
    df = frame(spark, rows)
    assert B.bins_apply(None, df, shape).count() == 0
    half = B.bins_apply(None, df.where("seq < 20"), shape)
    assert sorted(map(tuple, B.bins_apply(half, df.where("seq between 20 and 29"), shape).collect())) == sorted(map(tuple, B.bins_init(df.where("op = 1").select("set_id", "element"), shape).collect()))


def test_estimates_are_near_the_truth(spark):
    sides = streams.planted_pairs(spark, 0.5, 10, 1 << 13)
    m = sides.select((F.col("pair_id") * 2 + F.col("side")).alias("set_id"), "element")
    pairs = spark.range(10).select((F.col("id") * 2).alias("a"), (F.col("id") * 2 + 1).alias("b"))
    both = S.estimate_similarity(S.signatures(m, HashFamily.tabulation(256, 4)), pairs).join(S.exact_similarity(m, pairs), ["a", "b"]).collect()
    assert all(abs(r["est"] - r["exact"]) < 4 * (0.25 / 256) ** 0.5 for r in both) and all(0.4 < r["exact"] < 0.6 for r in both)


def test_encoders(spark):
    df = spark.createDataFrame([(" A b  c D ", '<a href="/x">', '{"k": 7}')], "t string, h string, j string")
    r = df.select(encoders.shingles(F.col("t"), 3), encoders.links(F.col("h")), encoders.json_key(F.col("j")), encoders.shingles(F.col("h"), 9)).first()
    assert list(r) == [["a b c", "b c d"], ["/x"], 7, []]


def explained(df):
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_plans(spark):
    from checks import SMALL

    from setstream.sources import collections as col

    m = col.supplier_parts(spark, SMALL)
    text = explained(R.reserve_long(m, FAMILY, 4))
    assert "WindowGroupLimit" in text and "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint>" in text
    assert "SortAggregate" not in explained(S.signatures(m, FAMILY))
    stored = spark.createDataFrame([], "set_id long, slots array<struct<pairs: array<bigint>, lim: bigint>>")
    assert "Exchange" not in explained(R.reserve_signature(stored))


def test_sql_functions(spark):
    from setstream.functions import sqlfuncs

    sqlfuncs.register(spark, FAMILY, 2)
    r = spark.sql("SELECT sig_similarity(array(1L, 2L), array(1L, 3L)) AS s, round(band_probability(0.1D, 700, 3), 3) AS p, signature_of(array(5L, 6L)) AS sig").first()
    assert r["s"] == 0.5 and r["p"] == 0.504 and list(r["sig"]) == truth({1: {5, 6}})[1]
    assert [tuple(x) for x in spark.sql("SELECT * FROM bands(array(1L, 2L, 3L, 4L), 2, 2)").collect()] == [(0, "1-2"), (1, "3-4")]
    trace = spark.sql("SELECT * FROM fault_trace(array(1L, 2L, 3L, 4L, 5L), array(1L, 2L, 3L, 1L, 2L), array(1, 1, 1, -1, -1))").collect()
    assert all(t["size_after"] >= 1 for t in trace)
    agg = spark.range(5).groupBy().agg(sqlfuncs.reserve_agg_udf(FAMILY, 2)("id").alias("r")).first()["r"]
    assert agg[0::2] == truth({1: set(range(5))})[1]
