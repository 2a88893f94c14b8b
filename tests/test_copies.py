"""Pairs of a collection with copies are sought among its distinct sets."""

from itertools import combinations

import numpy as np
from checks import SMALL

from setstream.functions.hashing import HashFamily
from setstream.operators import candidates as C
from setstream.operators import similarity as S
from setstream.plans import catalog


def test_copies_are_sought_once_and_counted_as_often_as_they_occur(spark):
    rng = np.random.default_rng(3)
    made = {i: frozenset(rng.choice(14, rng.integers(3, 9), replace=False).tolist()) for i in range(25)}
    sets = made | {50 + i: made[i % 4] for i in range(20)}
    members = spark.createDataFrame([(s, x) for s, e in sets.items() for x in e], "set_id bigint, element bigint")
    exact = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a, b in combinations(sorted(sets), 2)}
    got = C.exact_pairs_of_copies(members, 0.5).collect()
    assert {(r["a"], r["b"]): r["exact"] for r in got} == {p: x for p, x in exact.items() if x >= 0.5} and len(got) == sum(x >= 0.5 for x in exact.values())
    copies, family = C.Copies(members), HashFamily.affine(8, 3)
    assert copies.sets.count() == len(set(sets.values()))
    mine = C.quality_of_copies(copies, C.candidate_pairs(S.signatures(copies.leaders, family), 4, 2), 0.5).first()
    assert mine == C.quality(C.candidate_pairs(S.signatures(members, family), 4, 2), S.exact_pairs(members, 0.5), len(sets)).first()


def test_no_row_for_each_element_of_a_pair(spark):
    for name in ("exact_pairs_docs", "verify_exact_docs", "candidate_quality_docs"):
        assert "array_intersect" in catalog.QUERIES[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
