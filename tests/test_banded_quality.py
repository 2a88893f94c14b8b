"""Quality of candidate pairs is counted where blocks of sets meet, and no candidate pair becomes a row."""

from itertools import combinations

import numpy as np
import pytest
from checks import SMALL

from setstream.functions.hashing import HashFamily
from setstream.operators import bins as B
from setstream.operators import candidates as C
from setstream.operators import cells
from setstream.operators import similarity as S
from setstream.plans import workloads as W


def test_counts_are_those_of_a_plain_loop(spark, monkeypatch):
    rng = np.random.default_rng(4)
    sets = {i: frozenset(rng.choice(40, rng.integers(1, 25), replace=False).tolist()) for i in range(40)}
    sets |= {100 + i: sets[i % 3] for i in range(9)} | {200: frozenset([5000]), 201: frozenset([5000]), 202: frozenset([9000])}
    members = spark.createDataFrame([(s, x) for s, e in sets.items() for x in e], "set_id bigint, element bigint")
    family, shape, grid = HashFamily.affine(12, 3), B.BinShape(bins=16, levels=8), [(12, 1), (6, 2), (4, 3), (2, 5)]
    copies = C.Copies(members)
    # A set without a signature of a sketch is returned by none of it.
    sigs = {"plain": S.signatures(copies.leaders, family).where("set_id <> 1"), "bins": B.bins_level_signatures(B.bins_init(copies.leaders, shape), family, shape)}
    leader = {s: min(t for t in sets if sets[t] == e) for s, e in sets.items()}
    true = {(a, b) for a, b in combinations(sorted(sets), 2) if len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.3}
    want = {}
    for name, frame in sigs.items():
        held = {}
        for r in frame.collect():
            held.setdefault(r["set_id"], {})[r["level"] if name == "bins" else 0] = r["sig"]
        for bands, rows in grid:
            met = lambda x, y: any(x[i * rows : (i + 1) * rows] == y[i * rows : (i + 1) * rows] for i in range(bands))  # noqa: E731, B023
            one = {(a, b) for a, b in combinations(sorted(sets), 2) for x, y in [(held.get(leader[a], {}), held.get(leader[b], {}))] if any(met(x[v], y[v]) for v in x.keys() & y.keys())}
            want[name, bands, rows] = (len(one & true), len(one), len(true))
    seen = {}
    monkeypatch.setattr(cells, "banded", lambda sets, lam, g, made=cells.banded: seen.setdefault("counts", made(sets, lam, g, 9)))
    best = C.banded_quality(copies, 0.3, {name: (s, 12, grid) for name, s in sigs.items()}).collect()
    assert {(r["sketch"], r["bands"], r["rows"]): (r["tp"], r["returned"], r["effective"]) for r in seen["counts"].collect()} == want
    assert len(best) == 2
    for r in best:
        f1 = {k[1:]: 2 * tp / (got + due) for k, (tp, got, due) in want.items() if k[0] == r["sketch"]}
        assert r["f1"] == pytest.approx(max(f1.values()), abs=1e-9) == pytest.approx(f1[r["bands"], r["rows"]], abs=1e-9)
        assert r["tp"] + r["fp"] + r["fn"] + r["tn"] == len(sets) * (len(sets) - 1) // 2


def test_no_pair_is_joined(spark):
    df = W.pair_quality(spark, SMALL, "page_links", 0.1, budget=24)
    text = df._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in text and "Join" not in text and len(df.collect()) == 2
