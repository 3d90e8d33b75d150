"""Similarities and bounds against exact fractions on random sets, and the traps of the printed forms."""

import random
from fractions import Fraction
from math import ceil

import pytest

from autotheta.functions import sims

ALL = [sims.jaccard(), sims.overlap(), sims.dice(), sims.cosine(), sims.tversky("0.1"), sims.tversky("0"), sims.tversky("1"), sims.tversky("0.5")]
THETAS = ["0.07", "0.34", "0.5", "0.625", "0.8", "0.9574", "1"]


def sets(rng):
    u = range(rng.choice([4, 8, 20]))
    return [sorted(rng.sample(u, rng.randint(1, len(u)))) for _ in "rs"]


def exact(sim, o, nr, ns):
    num, den = sim.ratio(o, nr, ns)
    return Fraction(num, den)


@pytest.mark.parametrize("sim", ALL, ids=lambda s: f"{s.name}{s.alpha}")
def test_bounds_hold(sim):
    rng = random.Random(3)
    for _ in range(400):
        r, s = sets(rng)
        o, nr, ns = len({*r} & {*s}), len(r), len(s)
        key = exact(sim, o, nr, ns)
        assert sim.key(o, nr, ns) == float(key)
        # Merge frontier: bounds enclose the key and meet at the end.
        i = j = seen = 0
        while i < nr and j < ns:
            assert sim.least(seen, nr, ns) <= float(key) <= sim.most(seen, nr - i, ns - j, nr, ns)
            if r[i] == s[j]:
                i, j, seen = i + 1, j + 1, seen + 1
            elif r[i] < s[j]:
                i += 1
            else:
                j += 1
        assert seen == o
        for theta in THETAS:
            t = Fraction(theta)
            reaches = key >= (t * t if sim.name == "cosine" else t)
            assert reaches == (sim.key(o, nr, ns) >= sim.key_of(theta))
            if not reaches or not o:
                continue
            for b in ("paper", "tight"):
                assert o >= sim.min_overlap(theta, nr, "r", b) and o >= sim.min_overlap(theta, ns, "s", b)
                pr, ps = sim.prefix_len(theta, nr, "r", b), sim.prefix_len(theta, ns, "s", b)
                assert {*r[:pr]} & {*s[:ps]}
                first = next(x for x in r if x in s)
                assert sim.cap(r.index(first) + 1, nr, "r", b) >= float(key) and sim.cap(s.index(first) + 1, ns, "s", b) >= float(key)
            low, high = sim.size_range(theta, nr)
            assert low - 1e-9 <= ns <= high + 1e-9


def test_half_tversky_is_dice():
    for o, nr, ns in ((1, 2, 3), (2, 2, 5), (3, 7, 4)):
        assert sims.tversky("0.5").key(o, nr, ns) == sims.dice().key(o, nr, ns)


def test_prefix_needs_each_sides_own_size():
    r, s, sim = "cd", "abcd", sims.jaccard()
    assert sim.key(2, 2, 4) == 0.5
    pr, ps = sim.prefix_len("0.5", 2), sim.prefix_len("0.5", 4)
    assert {*r[:pr]} & {*s[:ps]} and not {*r[:pr]} & {*s[:pr]}


def test_overlap_threshold_in_integers():
    assert sims.jaccard().min_overlap("0.07", 100) == 7 and ceil(0.07 * 100) == 8


def test_due_band():
    from autotheta.operators.verify import due_band

    assert [due_band(x, [0.8, 0.5, 0.2]) for x in (0.9, 0.8, 0.6, 0.2, 0.1)] == [0, 0, 1, 2, 3]
