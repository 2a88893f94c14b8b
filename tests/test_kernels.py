"""The sequential kernels: worked examples, invariants on random arbitrary streams, and the variants that are meant to fail."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from setstream.functions.hashing import HashFamily
from setstream.operators.bins import BinShape, bins_guarantee, bins_required_c2
from setstream.operators.candidates import band_probability, choose_bands
from setstream.operators.costs import fault_bound, fault_rate
from setstream.operators.replay import INF, Naive, Reserve, kernel
from setstream.operators.reserve import choose_reserve
from setstream.operators.streams import planted_probabilities


class Identity:
    """One slot whose hash is the element itself."""

    k = 1

    def pairs_numpy(self, x):
        return np.asarray(x, np.int64)[:, None]


class Constant(Identity):
    """All hashes tie: the element decides."""

    def pairs_numpy(self, x):
        return np.asarray(x, np.int64)[:, None]


def apply(sketch, *ops):
    for i, x in enumerate(ops):
        sketch.run(np.array([i]), np.array([abs(x)]), np.array([1 if x > 0 else -1]))
    return sketch


def row(sketch):
    return [int(v) for v in sketch.buffer[0] if v < INF], (None if sketch.lim[0] == INF else int(sketch.lim[0]))


def began(kind, ell, *elements, **options):
    sketch = kind(Identity(), ell, **options)
    sketch.start(np.array(elements, np.int64))
    return sketch


def test_refilling_without_a_limit_gives_a_wrong_minimum():
    ops = (-1, 4, -2)
    assert apply(began(Naive, 2, 1, 2, 3), *ops).signature()[0] == 4
    kept = apply(began(Reserve, 2, 1, 2, 3), *ops)
    assert kept.signature()[0] == 3 and row(kept) == ([3, 4], 4) and len(kept.log) == 1


def test_limit_moves():
    s = began(Reserve, 3, 5, 9)
    expected = [(7, ([5, 7, 9], 9)), (6, ([5, 6, 7], 7)), (-5, ([6, 7], 7)), (8, ([6, 7], 7)), (1, ([1, 6, 7], 7)), (2, ([1, 2, 6], 6))]
    assert row(s) == ([5, 9], None)
    for op, state in expected:
        assert row(apply(s, op)) == state


def test_updates_that_change_nothing():
    s = began(Reserve, 2, 1, 2, 3)
    for op in (1, -9, -3, 3):
        assert row(apply(s, op)) == ([1, 2], 2)


@pytest.mark.parametrize(("flag", "recoveries"), [(False, 0), (True, 1)])
def test_emptying_a_small_set(flag, recoveries):
    s = apply(began(Reserve, 3, 4, recover_when_empty=flag), -4)
    assert row(s) == ([], None) and len(s.log) == recoveries


@pytest.mark.parametrize("n", [0, 1, 2, 3, 4])
def test_sizes_around_the_reserve(n):
    pairs, lim = row(began(Reserve, 3, *range(1, n + 1)))
    assert pairs == list(range(1, min(n, 3) + 1)) and lim == (3 if n >= 3 else None)


streams = st.lists(st.tuples(st.integers(0, 12), st.sampled_from([1, -1])), max_size=60)


@settings(max_examples=60, deadline=None)
@given(streams, st.integers(1, 4), st.sampled_from(["affine", "tabulation", "polynomial", "native"]), st.sampled_from(["reserve", "unordered"]))
def test_invariants_and_signature_on_arbitrary_streams(ops, ell, family, kind):
    family = HashFamily(family, 3, 5, degree=3)
    s, held, limits = kernel(kind, family, ell), set(), None
    for i, (x, op) in enumerate(ops):
        faults = len(s.log)
        s.run(np.array([i]), np.array([x]), np.array([op]))
        (held.add if op > 0 else held.discard)(x)
        own = family.pairs_numpy(np.array(sorted(held), np.int64)) if held else np.zeros((0, 3), np.int64)
        for slot in range(3):
            kept = sorted(int(v) for v in s.buffer[slot] if v < INF)
            assert kept == sorted(int(p) for p in own[:, slot] if p <= s.lim[slot])
            assert len(kept) <= ell and (len(kept) == 0) == (not held)
        assert not held or (s.signature() == own.min(0)).all()
        if limits is not None and len(s.log) == faults:
            assert (s.lim <= limits).all()
        limits = s.lim.copy()


@settings(max_examples=40, deadline=None)
@given(streams, st.sampled_from(["rebuild", "strict"]))
def test_baselines_are_exact(ops, kind):
    family = HashFamily.affine(3, 5)
    s = kernel(kind, family, 3)
    s.run(np.arange(len(ops)), np.array([x for x, _ in ops], np.int64), np.array([o for _, o in ops], np.int64))
    if s.held:
        assert (s.signature() == family.pairs_numpy(s.members()).min(0)).all()


def test_naive_fails_somewhere_and_hash_only_needs_legal_streams():
    rng, family = random.Random(4), HashFamily.affine(4, 3)
    wrong = repeats = 0
    for _ in range(60):
        ops = [(rng.randrange(20), rng.choice([1, 1, -1])) for _ in range(80)]
        for kind in ("naive", "hash_only"):
            s = kernel(kind, family, 2)
            s.run(np.arange(len(ops)), np.array([x for x, _ in ops]), np.array([o for _, o in ops]))
            if s.held:
                p = s.pairs(s.members()).min(0)
                wrong += kind == "naive" and bool((s.signature() != p).any())
                repeats += kind == "hash_only" and bool((s.signature() != p).any())
    assert wrong > 0 and repeats > 0


def test_eager_bins_follow_the_lazy_ones():
    rng, family, shape = random.Random(4), HashFamily.affine(4, 3), BinShape(bins=16, levels=6)
    lazy, eager = kernel("bins", family, shape=shape), kernel("eager_bins", family, shape=shape)
    live = set()
    for i in range(300):
        x = rng.randrange(60)
        op = -1 if x in live else 1
        (live.discard if op < 0 else live.add)(x)
        for s in (lazy, eager):
            s.run(np.array([i]), np.array([x]), np.array([op]))
        assert (lazy.signature() == eager.signature()).all()
    for x in sorted(live):
        lazy.run(np.array([0]), np.array([x]), np.array([-1]))
    assert not lazy.count.any()


def test_faults_fall_steeply_then_level_off():
    def faults(ell):
        family, rng = HashFamily.tabulation(64, 2), np.random.default_rng(1)
        x = rng.choice(2**31, 1024, replace=False).astype(np.int64)
        s = kernel("reserve", family, ell)
        s.run(np.arange(1024), x, np.ones(1024, int))
        s.run(np.arange(1024), rng.permutation(x), -np.ones(1024, int))
        return len(s.log)

    one, two, five, sixteen, more = (faults(ell) for ell in (1, 2, 5, 16, 32))
    assert 140 < one < 300 and 20 < two < 70 and 4 <= five <= 16 and sixteen <= 6 and more <= 4


@pytest.mark.parametrize("ell", [1, 2, 4, 8])
def test_observed_fault_rate_is_within_the_bound(ell):
    p = fault_bound(512, 1024, ell)
    assert fault_rate(1024, 512, ell, trials=3000) <= p + 4 * (p * (1 - p) / 3000) ** 0.5 + 1e-3


def test_published_values():
    g = bins_guarantee(0.7, 0.5, 0.2, 0.1)
    assert round(g["p1"], 2) == 0.56 and round(g["p2"], 2) == 31.49
    assert round(bins_required_c2(0.5, 0.1, 0.1)) == 4 * 10**9
    for b, r, s, p in [(700, 3, 0.1, 0.504), (400, 2, 0.05, 0.633), (150, 5, 0.35, 0.546), (150, 6, 0.4, 0.460)]:
        assert abs(band_probability(s, b, r) - p) < 1e-3
    b, r = choose_bands(0.132)
    assert r == 3 and abs(b - 700) <= 5 and b * r <= 2100
    p1, p2 = planted_probabilities(0.5, 0.05)
    assert abs(p1 - 2 / 3) < 1e-12 and abs(p2 - 0.01754) < 1e-4
    assert choose_reserve(32) == 32 and choose_reserve(32, 1 << 16) == 16


@pytest.mark.parametrize("ell", [1, 2, 5])
def test_long_runs_of_inserts_enter_a_reserve_as_single_ones_do(ell, monkeypatch):
    from setstream.operators import replay as P

    rng = np.random.default_rng(ell)
    for trial in range(20):
        op = np.concatenate([np.repeat(rng.choice([1, -1], p=[0.6, 0.4]), rng.integers(1, 40)) for _ in range(12)])
        element, seq = rng.integers(0, 50, len(op)), np.arange(len(op))
        made = []
        for run in (P.LONG_RUN, 1, len(op) + 1):
            monkeypatch.setattr(P, "LONG_RUN", run)
            sketch = P.Reserve(HashFamily.affine(6, seed=trial), ell)
            sketch.run(seq, element, op)
            made.append(sketch)
            monkeypatch.undo()
        for other in made[:-1]:
            assert (other.buffer == made[-1].buffer).all() and (other.lim == made[-1].lim).all() and (other.high == made[-1].high).all()
            assert other.log == made[-1].log and other.held == made[-1].held


def test_a_long_run_makes_no_step_for_each_insert(monkeypatch):
    from setstream.operators import replay as P

    sketch = P.Reserve(HashFamily.affine(6, seed=1), 3)
    monkeypatch.setattr(P.Reserve, "put", lambda *_: pytest.fail("walked"))
    sketch.run(np.arange(500), np.arange(500), np.ones(500, int))
    assert (sketch.signature() == HashFamily.affine(6, seed=1).pairs_numpy(np.arange(500)).min(0)).all()
