"""Laws of the samplers, by exact enumeration and by fixed-seed frequencies."""

import itertools
from collections import Counter
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from wsample import samplers as S
from wsample.operators import inclusion as I

MILD, HEAVY, MORE, MIXED = [1, 1, 1, 2], [1, 1, 1, 4], [1, 1, 1, 4, 3], [5, 1, 2, 8, 3, 3]


def chances(w, m):
    """min(1, w / tau), in rationals."""
    if len(w) <= m:
        return [Fraction(1)] * len(w)
    order, rest, pinned = sorted(w, reverse=True), Fraction(sum(w)), 0
    while (m - pinned) * order[pinned] > rest:
        rest, pinned = rest - order[pinned], pinned + 1
    return [min(Fraction(1), x * (m - pinned) / rest) for x in w]


def paths(w, m):
    """Chance of every sample after every prefix, from the sampler's own pinning and rational acceptance."""
    states = {(): Fraction(1)}
    for k in range(len(w)):
        before, after, new = chances(w[:k], m), chances(w[: k + 1], m), Counter()
        for held, p in states.items():
            if len(held) < m:
                new[(*held, k)] += p
                continue
            new[held] += p * (1 - after[k])
            freed = [b for b in held if before[b] == 1 and after[b] < 1]
            plain = [b for b in held if before[b] < 1]
            spent = sum(((1 - after[b]) / after[k] for b in freed), Fraction(0))
            for b in held:
                share = (1 - after[b]) / after[k] if b in freed else (1 - spent) / len(plain) if b in plain and plain else Fraction(0)
                new[tuple(k if x == b else x for x in held)] += p * after[k] * share
        states = {s: p for s, p in new.items() if p}
        yield states, after


@pytest.mark.parametrize("w,m", [(MILD, 2), (HEAVY, 2), (MORE, 2), (MIXED, 3), ([8, 1, 1, 1, 9, 2], 2), ([1, 2, 4, 8, 16, 32], 3)])
def test_victim_law_gives_the_chances_at_every_prefix(w, m):
    for states, want in paths([Fraction(x) for x in w], m):
        got = Counter()
        for held, p in states.items():
            for x in held:
                got[x] += p
        assert [got[i] for i in range(len(want))] == want


def frequency(make, w, m, reps):
    hits = np.zeros(len(w))
    for r in range(reps):
        s = make(m, S.keyed_rng(5, r))
        s.offer(range(len(w)), np.array(w, float))
        for e in s.snapshot():
            hits[e.item] += 1
    return hits


@pytest.mark.parametrize("kind", [S.ProportionalSampler, S.ProportionalJumpSampler])
@pytest.mark.parametrize("w,m", [(MILD, 2), (HEAVY, 2), (MORE, 2), (MIXED, 3), ([1] * 20, 5)])
def test_inclusion_frequencies(kind, w, m):
    p = np.array([float(x) for x in chances([Fraction(x) for x in w], m)])
    n = 4000
    z = (frequency(kind, w, m, n) - n * p) / np.sqrt(np.maximum(n * p * (1 - p), 1e-9))
    assert np.abs(z[p < 1]).max() < 4.5 and (frequency(kind, w, m, 200)[p == 1] == 200).all()


@pytest.mark.parametrize("kind", [S.RaceSampler, S.RaceJumpSampler])
@pytest.mark.parametrize("w,m", [(MILD, 2), (HEAVY, 2), (MIXED, 3)])
def test_draw_frequencies(kind, w, m):
    p, n = I.enumerate_draws(w, m), 4000
    assert np.abs((frequency(kind, w, m, n) - n * p) / np.sqrt(n * p * (1 - p))).max() < 4.5


def test_worked_examples():
    assert chances([Fraction(x) for x in MILD], 2) == [Fraction(2, 5)] * 3 + [Fraction(4, 5)]
    assert chances([Fraction(x) for x in HEAVY], 2) == [Fraction(1, 3)] * 3 + [1]
    assert chances([Fraction(x) for x in MORE], 2) == [Fraction(1, 5)] * 3 + [Fraction(4, 5), Fraction(3, 5)]
    assert np.allclose(I.enumerate_draws(MILD, 2), [0.4333, 0.4333, 0.4333, 0.7], atol=1e-4)
    assert np.allclose(I.enumerate_draws(HEAVY, 2), [0.381, 0.381, 0.381, 0.857], atol=1e-3)
    for w, m in ((MILD, 2), (HEAVY, 2), (MIXED, 3)):
        assert np.allclose(I.quadrature_draws(w, m), I.enumerate_draws(w, m), atol=1e-6)


@given(st.lists(st.floats(1e-3, 1e3), min_size=1, max_size=40), st.integers(1, 8))
@settings(max_examples=60, deadline=None)
def test_pins_and_threshold_follow_the_weights(w, m):
    s = S.ProportionalSampler(m)
    for k, x in enumerate(w, 1):
        s.feed(k, x)
        want = chances([Fraction(y) for y in w[:k]], m)
        if k > m:
            assert s.threshold == pytest.approx(float(Fraction(w[0]) / want[0]) if want[0] < 1 else s.threshold, rel=1e-6)
        assert len({e.item for e in s.snapshot()}) == min(k, m)
        sure = {i + 1 for i, p in enumerate(want) if p == 1 and k > m and w[i] > s.threshold * (1 + 1e-9)}
        assert sure <= {e.item for e in s.snapshot()}


def test_merge_keeps_the_chances():
    w, m, n = [8.0, 1.0, 1.0, 1.0, 9.0, 2.0, 3.0, 3.0], 3, 4000
    hits = np.zeros(len(w))
    for r in range(n):
        a, b = S.ProportionalSampler(m, S.keyed_rng(1, r)), S.ProportionalSampler(m, S.keyed_rng(2, r))
        a.offer(range(4), np.array(w[:4]))
        b.offer(range(4, 8), np.array(w[4:]))
        a.merge(b)
        for e in a.snapshot():
            hits[e.item] += 1
    p = np.array([float(x) for x in chances([Fraction(x) for x in w], m)])
    assert np.abs((hits - n * p)[p < 1] / np.sqrt(n * p * (1 - p))[p < 1]).max() < 4.5


def test_race_merge_state_and_ageing():
    rng = np.random.default_rng(0)
    w, u = rng.uniform(0.1, 5, 500), rng.uniform(0, 1, 500)
    whole = S.RaceSampler(20)
    whole.offer(range(500), w, u)
    a, b = S.RaceSampler(20), S.RaceSampler(20)
    a.offer(range(200), w[:200], u[:200])
    b.offer(range(200, 500), w[200:], u[200:])
    a = S.RaceSampler.from_state(a.to_state())
    a.merge(b)
    assert [e.item for e in a.snapshot()] == [e.item for e in whole.snapshot()]
    # ageing the old equals raising the new
    old, raised = S.RaceSampler(20), S.RaceSampler(20)
    old.offer(range(200), w[:200], u[:200])
    old.age(0.25)
    old.offer(range(200, 500), w[200:], u[200:])
    raised.offer(range(200), w[:200], u[:200])
    raised.offer(range(200, 500), 4 * w[200:], u[200:])
    assert [e.item for e in old.snapshot()] == [e.item for e in raised.snapshot()]


def test_every_prefix_is_a_sample():
    rng = np.random.default_rng(3)
    w, u = rng.uniform(0.1, 5, 100), rng.uniform(0, 1, 100)
    s = S.RaceSampler(7)
    for k in range(100):
        s.offer([k], w[k : k + 1], u[k : k + 1])
        assert [e.item for e in s.snapshot()] == np.argsort(-np.log(u[: k + 1]) / w[: k + 1])[:7].tolist()


def test_work_is_as_expected():
    w, m, n = np.random.default_rng(1).uniform(0.01, 1, 100_000), 200, 100_000
    jump, plain = S.RaceJumpSampler(m, S.keyed_rng(1)), S.RaceSampler(m, S.keyed_rng(1))
    jump.offer(range(n), w)
    plain.offer(range(n), w)
    expect = m * np.log(n / m)
    assert plain.draws == n and jump.draws < 4 * expect and 0.7 * expect < jump.insertions - m < 1.4 * expect
    prop, pj = S.ProportionalSampler(m, S.keyed_rng(1)), S.ProportionalJumpSampler(m, S.keyed_rng(1))
    prop.offer(range(n), w)
    pj.offer(range(n), w)
    assert prop.draws > n / 2 and pj.draws < 4 * expect and 0.7 * expect < pj.insertions - m < 1.5 * expect


def test_adversary_of_doubling_weights():
    n, m = 200, 4
    s = S.ProportionalSampler(m)
    s.offer(range(n), 2.0 ** np.arange(n) / 2.0**100)
    assert s.insertions == n and s.heap_steps <= 8 * n * m


def test_roles_agree_for_one_slot_and_bounded_ends():
    w, n = [1.0, 2.0, 5.0], 6000
    for make in (lambda m, r: S.BoundedSampler(m, 1, r), lambda m, r: S.ReplacementSampler(m, r, engine="race"), lambda m, r: S.ReplacementSampler(m, r)):
        hits = frequency(make, w, 1, n // 2) / (n // 2)
        assert np.allclose(hits, np.array(w) / 8, atol=0.035)
    p = I.enumerate_draws(w, 2)
    assert np.allclose(frequency(lambda m, r: S.BoundedSampler(m, 1, r), w, 2, n) / n, p, atol=0.03)
    for r in range(50):
        s = S.BoundedSampler(6, 2, S.keyed_rng(r))
        s.offer(range(5), np.array([100.0, 1, 1, 1, 1]))
        assert max(Counter(e.item for e in s.snapshot()).values()) <= 2 and len(s.snapshot()) == 6


def test_pair_law():
    hits = frequency(S.RaceSampler, [1.0, 3.0], 1, 4000)
    assert abs(hits[1] / 4000 - 0.75) < 0.03


def test_bad_input():
    for bad in (0, -1, float("nan"), float("inf")):
        for kind in (S.RaceSampler, S.RaceJumpSampler, S.ProportionalSampler):
            with pytest.raises(ValueError):
                kind(1).offer([0], [bad])
    with pytest.raises(ValueError):
        S.RaceSampler(-1)
    for kind in (S.RaceSampler, S.RaceJumpSampler, S.ProportionalSampler, S.ProportionalJumpSampler):
        s = kind(0)
        s.offer([1, 2], [1.0, 2.0])
        assert s.snapshot() == []
        s = kind(5)
        s.offer([1, 2], [1.0, 2.0])
        assert {e.item for e in s.snapshot()} == {1, 2}


def test_expansion_is_not_replacement():
    w, m = [1, 1, 4], 2
    copies = [x for x in w for _ in range(m)]
    p = np.zeros(3)
    for a, b in itertools.permutations(range(6), 2):
        chance = copies[a] / 12 * copies[b] / (12 - copies[a])
        for i in {a // 2, b // 2}:
            p[i] += chance
    assert abs(p[2] - (1 - (2 / 6) ** 2)) > 0.01


def test_jumps_after_ageing():
    """After ageing by c, an item that comes next is taken as often as the plain sampler takes it."""
    for c, w in ((0.01, 1.0), (0.5, 3.0)):
        taken = {}
        for kind in (S.RaceSampler, S.RaceJumpSampler):
            n = 0
            for seed in range(1500):
                s = kind(1, S.keyed_rng(seed, 5))
                s.offer([0, 1], np.array([1.0, 1.0]))
                s.age(c)
                s.offer([2], np.array([w]))
                n += s.snapshot()[0].item == 2
            taken[kind.__name__] = n / 1500
        p = w / (w + 2 * c)
        assert all(abs(x - p) < 4.5 * (p * (1 - p) / 1500) ** 0.5 for x in taken.values()), (taken, p)


def test_slots_with_jumps_follow_the_weights():
    w, m = np.array([5.0, 1, 2, 8, 3, 3, 1e-3]), 20_000
    slots = S.SlotRaces(m, S.keyed_rng(3))
    slots.offer(w[:2])
    slots.offer(w[2:2])
    slots.offer(w[2:])
    hits, p = np.bincount(slots.item, minlength=7), w / w.sum()
    assert (abs(hits - m * p) < 4.5 * np.sqrt(m * p * (1 - p)) + 1).all() and slots.draws < m * 3 * 7


def test_engines_of_the_bounded_chain_agree():
    w = np.array([5.0, 1, 2, 8, 3])
    counts = {}
    for engine in ("race", "proportional"):
        hits = np.zeros((3, 5))
        for seed in range(3000):
            s = S.BoundedSampler(3, 1, S.keyed_rng(seed, 1), engine=engine)
            s.offer(range(5), w)
            kept = [e.item for e in s.snapshot()]
            assert len(set(kept)) == 3
            for j, i in enumerate(kept):
                hits[j, i] += 1
        counts[engine] = hits / 3000
    assert abs(counts["race"] - counts["proportional"]).max() < 0.06 and abs(counts["proportional"][0] - w / w.sum()).max() < 0.045
