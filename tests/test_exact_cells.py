"""Pairs of small sets are counted where blocks of sets meet; no pair of two sets that merely share an element is joined or shuffled."""

from itertools import combinations

import numpy as np
import pytest
from checks import SMALL

from setstream.operators import candidates as C
from setstream.operators import cells
from setstream.plans import catalog


def exact_of(sets):
    return {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a, b in combinations(sorted(sets), 2)}


@pytest.fixture(scope="module")
def sets():
    rng = np.random.default_rng(11)
    made = {i: frozenset(rng.choice(40, rng.integers(1, 16), replace=False).tolist()) for i in range(60)}
    skewed = {100 + i: frozenset((40 + rng.zipf(1.3, 12) % 200).tolist()) | {1000} for i in range(40)}
    return made | skewed | {200 + i: made[i] for i in range(5)} | {300: frozenset({-7}), 301: frozenset({1 << 40})}


@pytest.mark.parametrize("lam", [0.05, 0.35, 0.5, 1.0])
def test_kernel_finds_every_pair(sets, lam, monkeypatch):
    ids = sorted(sets)
    want = {p: x for p, x in exact_of(sets).items() if x >= lam}

    def side(some):
        return np.array([x for s in some for x in sorted(sets[s])], np.int64), np.r_[0, np.cumsum([len(sets[s]) for s in some])]

    for meetings in (1 << 22, 50, 1):
        monkeypatch.setattr(cells, "MEETINGS", meetings)
        got = [(ids[i], ids[j], x) for p in cells.reaching(side(ids), side(ids), lam, True) for i, j, x in zip(*p, strict=True)]
        assert {(a, b): x for a, b, x in got} == want and len(got) == len(want)
        low, high = ids[::2], ids[1::2]
        got = [(low[i], high[j], x) for p in cells.reaching(side(low), side(high), lam, False) for i, j, x in zip(*p, strict=True)]
        assert {(min(a, b), max(a, b)): x for a, b, x in got} == {(a, b): x for (a, b), x in want.items() if (a in low) != (b in low)}


@pytest.mark.parametrize("n", [10, 30])
def test_heads_alone_give_every_pair(n):
    rng = np.random.default_rng(n)
    base = [rng.choice(3000, n, replace=False) for _ in range(120)]
    sets = [frozenset(np.r_[base[i % 120][: n - i // 120], rng.choice(3000, i // 120 + i % 3, replace=False)].tolist()) for i in range(120 * (n - 4))]
    flat = np.array([x for s in sets for x in sorted(s)], np.int64), np.r_[0, np.cumsum([len(s) for s in sets])]
    got = {(int(i), int(j)) for p in cells.reaching(flat, flat, 0.35, True) for i, j in zip(p[0], p[1], strict=True)}
    assert got == {(i, j) for i in range(len(sets)) for j in range(i + 1, len(sets)) if len(c := sets[i] & sets[j]) / (len(sets[i]) + len(sets[j]) - len(c)) >= 0.35}


def test_pairs_of_copies_whatever_the_blocks(spark, sets):
    members = spark.createDataFrame([(s, x) for s, e in sets.items() for x in e], "set_id bigint, element bigint")
    want = {p: x for p, x in exact_of(sets).items() if x >= 0.35}
    got = C.exact_pairs_in_cells(members, 0.35).collect()
    assert {(r["a"], r["b"]): r["exact"] for r in got} == want and len(got) == len(want)
    distinct = {min(s for s in sets if sets[s] == e): e for e in set(sets.values())}
    few = cells.similar(cells.arrays(members.where(members["set_id"].isin(list(distinct)))), 0.35, block=13).collect()
    assert {(r["a"], r["b"]): r["exact"] for r in few} == {p: x for p, x in exact_of(distinct).items() if x >= 0.35}


def test_parts_meet_in_cells(spark):
    text = catalog.QUERIES["exact_pairs_part_suppliers"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in text and "element" not in text
