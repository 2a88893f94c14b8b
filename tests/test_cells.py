"""Queries over all pairs of users: pairs come from cells of sets and are never joined or shuffled; kernels against plain loops."""

from itertools import combinations

import numpy as np
import pytest
from checks import SMALL

from setstream.functions.hashing import HashFamily
from setstream.operators import bins as B
from setstream.operators import candidates as C
from setstream.operators import cells
from setstream.operators import similarity as S
from setstream.plans import catalog


def plan(df) -> str:
    return df._jdf.queryExecution().optimizedPlan().toString()


#: Joins that may be left: of one row with the number of sets.
QUERIES = {
    "flagship": 0,
    "threshold_choice": 1,
    "rmse_by_band": 0,
    "sampled_pair_errors": 0,
    "counters_by_rule": 0,
    "error_by_slots": 0,
    "top_similar_users": 0,
    "bins_similarity": 0,
    "estimate_pairs": 0,
}


@pytest.mark.parametrize("name", QUERIES)
def test_pairs_are_not_joined(spark, name):
    text = plan(catalog.QUERIES[name](spark, SMALL))
    assert "MapInArrow" in text and text.count("Join") == QUERIES[name]


@pytest.fixture(scope="module")
def sets():
    rng = np.random.default_rng(5)
    made = {i: sorted(rng.choice(60, rng.integers(1, 30), replace=False).tolist()) for i in range(40)}
    return made | {100 + i: made[i] for i in range(6)} | {200: [1000, 2000], 201: [3000]}


@pytest.fixture(scope="module")
def members(spark, sets):
    return spark.createDataFrame([(s, x) for s, e in sets.items() for x in e], "set_id bigint, element bigint").cache()


def exact_of(sets):
    return {(a, b): len(set(sets[a]) & set(sets[b])) / len(set(sets[a]) | set(sets[b])) for a, b in combinations(sorted(sets), 2)}


def signature(e, family):
    return family.pairs_numpy(np.array(e)).min(0)


def test_errors_of_all_pairs(spark, sets, members):
    exact = exact_of(sets)
    families = [HashFamily.affine(8, 3), HashFamily.affine(16, 3)]
    for sharing in (False, True):
        got = {(r["k"], r["tenth"]): r for r in cells.signature_errors(members, families, by_tenth=True, sharing=sharing, block=16).collect()}
        for f in families:
            sigs = {s: signature(e, f) for s, e in sets.items()}
            want = {}
            for (a, b), x in exact.items():
                if x > 0 or not sharing:
                    want.setdefault((f.k, int(x * 10)), []).append((sigs[a] == sigs[b]).mean() - x)
            assert {k for k in got if k[0] == f.k} == set(want)
            for k, e in want.items():
                e = np.array(e)
                assert got[k]["pairs"] == len(e) and got[k]["rmse"] == pytest.approx((e**2).mean() ** 0.5, abs=1e-12)
                assert got[k]["error_sd"] is None if len(e) == 1 else got[k]["error_sd"] == pytest.approx(e.std(ddof=1), abs=1e-12)


def test_half_of_the_pairs_whatever_the_blocks(members):
    runs = [{(r["tenth"], r["pairs"]) for r in cells.signature_errors(members, [HashFamily.affine(8, 3)], by_tenth=True, half=True, block=b).collect()} for b in (7, 4096)]
    assert runs[0] == runs[1] and 0.4 < sum(n for _, n in runs[0]) / (48 * 47 / 2) < 0.6


def test_thresholds_count_copies(spark, sets, members):
    exact = exact_of(sets)
    for block in (9, 4096):
        got = {r["lam"]: r["pairs"] for r in cells.reached(members, [0.2, 0.5, 1.0], block).collect()}
        assert got == {lam: sum(x >= lam for x in exact.values()) for lam in (0.2, 0.5, 1.0)}
    apart = members.where("set_id >= 200")
    assert C.choose_threshold(apart, [0.5], dense=True).collect() == C.choose_threshold(apart, [0.5]).collect() == []


def test_estimates_and_best_partners(spark, sets, members):
    family = HashFamily.affine(8, 3)
    sigs = {s: signature(e, family) for s, e in sets.items()}
    est = {(a, b): (sigs[a] == sigs[b]).mean() for a, b in combinations(sorted(sets), 2)}
    frame = S.signatures(members, family)
    for block in (9, 4096):
        assert {(r["a"], r["b"]): r["est"] for r in cells.estimates(frame, block=block).collect()} == est
        few = {(r["a"], r["b"]) for r in cells.estimates(frame, 0.25, bands=4, rows=2, block=block).collect()}
        banded = {(r["a"], r["b"]) for r in C.verify_pairs(C.candidate_pairs(frame, 4, 2), frame, 0.25).collect()}
        assert few == banded
    both = [(s, o, e) for (a, b), e in est.items() for s, o in ((a, b), (b, a))]
    want = {s: [o for _, o, _ in sorted((r for r in both if r[0] == s), key=lambda r: (-r[2], r[1]))[:3]] for s in sets}
    got = {}
    for r in sorted(C.top_similar_of_all(frame, 3).collect(), key=lambda r: r["rank"]):
        got.setdefault(r["set_id"], []).append(r["other"])
    assert got == want


@pytest.mark.parametrize("bins", [16, 96])
def test_bins_of_all_pairs(spark, sets, members, bins):
    shape = B.BinShape(bins=bins, levels=6, rule="alpha_root")
    kept = B.bins_init(members, shape)
    joined = B.bins_similarity(kept, S.all_pairs(members), shape)
    for block in (9, 4096):
        got = {(r["a"], r["b"]): r["est"] for r in cells.bin_estimates(kept, shape, block).collect()}
        assert got == {(r["a"], r["b"]): r["est"] for r in joined.collect()}
        exact = exact_of(sets)
        e = np.array([x - exact[k] for k, x in got.items() if x is not None])
        row = cells.bin_errors(members, shape, block).first()
        assert row["pairs"] == len(e) and row["rmse"] == pytest.approx((e**2).mean() ** 0.5, abs=1e-12) and row["error_sd"] == pytest.approx(e.std(ddof=1), abs=1e-12)
