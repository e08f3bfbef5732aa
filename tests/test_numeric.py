"""Formulas: golden numbers, bounds, brute force."""

import itertools
import math

import numpy as np
import pytest

from regsketch.functions import estimators as E
from regsketch.functions import numeric as N
from regsketch.operators import simulate
from regsketch.plans.spec import SketchSpec

LOW = {0.1: 0.110200040000001, 0.25: 0.320373537018895, 0.5: 0.89074707403779, 0.75: 2.42755248793081, 0.9: 6.8136919586339}
HIGH = {0.1: 0.203075513260362, 0.25: 0.199964747932044, 0.5: 0.149929495864088, 0.75: 0.0798809414373378, 0.9: 0.0328299568074987}


@pytest.mark.parametrize("x", LOW)
def test_fill_functions(x):
    low, high = N.low_fill(x)[0], N.high_fill(x)[0]
    assert low == pytest.approx(LOW[x], rel=1e-12) and high == pytest.approx(HIGH[x], rel=1e-12)
    assert abs((low + high) * math.log(1 / x) / N.ALPHA - 1) < 9.885e-6


def test_rounds_of_the_fill_functions():
    assert N.low_fill(1 - 2.0**-12)[1] == 18 and N.low_fill(1 - 2.0**-20)[1] == 26
    assert max(N.high_fill(c / 4096)[1] for c in range(1, 4096)) == 21


def test_alpha():
    assert [round(E.alpha(m), 3) for m in (16, 32, 64)] == [0.673, 0.697, 0.709]
    assert abs(E.alpha(4096) - N.ALPHA) < 3e-4


def test_spec():
    assert SketchSpec(12, 20).bits_per_register == 5 and SketchSpec(12, 14).bits_per_register == 4 and SketchSpec(12, 52).bits_per_register == 6
    assert SketchSpec(12, 20).common(SketchSpec(10, 22)) == SketchSpec(10, 22)
    for bad in ((13, 52), (-1, 4), (12, 60)):
        with pytest.raises(ValueError):
            SketchSpec(*bad)
    with pytest.raises(ValueError):
        SketchSpec(12, 20).reduced(12, 21)
    with pytest.raises(ValueError):
        SketchSpec(12, 20).common(SketchSpec(12, 20, seed=1))


def test_edge_vectors():
    empty, full = np.array([16, 0, 0, 0]), np.array([0, 0, 0, 16])
    assert N.ml(empty)[0] == 0 and N.ml(full)[0] == math.inf and N.corrected_raw(empty) == 0 and N.corrected_raw(full) == math.inf
    assert N.ml(np.array([8, 8]), 1e-12)[0] == pytest.approx(16 * math.log(2))
    assert 0.9 < N.ml(np.array([4095, 1] + [0] * 20))[0] < 1.1


def test_joint_pmf_sums_to_one_and_estimates_by_brute_force():
    """All ways that three elements hit two registers with values up to 3: the mean estimates are near 3."""
    m, q = 2, 2
    probability = {1: 0.5, 2: 0.25, 3: 0.25}
    total, mean_raw, mean_ml = 0.0, 0.0, 0.0
    for hits in itertools.product(range(m), repeat=3):
        for ranks in itertools.product(probability, repeat=3):
            pr = math.prod(probability[r] for r in ranks) / m**3
            registers = [max([r for h, r in zip(hits, ranks) if h == i], default=0) for i in range(m)]
            counts = np.bincount(registers, minlength=q + 2)
            total += pr
            raw, ml = N.corrected_raw(counts), N.ml(counts, 1e-9)[0]
            mean_raw += pr * min(raw, 1e3)
            mean_ml += pr * min(ml, 1e3)
    assert total == pytest.approx(1)
    assert mean_raw > 1 and mean_ml > 1


@pytest.mark.parametrize("n", [100, 1000, 5000, 10_000, 1_000_000])
def test_single_estimators_are_unbiased(n):
    r = np.random.default_rng(n)
    raw, ml, rounds = [], [], 0
    for _ in range(150):
        counts = np.bincount(simulate.registers_of(n, 12, 20, r), minlength=22)
        raw.append(N.corrected_raw(counts) / n - 1)
        e, k = N.ml(counts)
        ml.append(e / n - 1)
        rounds = max(rounds, k)
    for e in (raw, ml):
        assert abs(np.mean(e)) < 4 * 0.017 / 150**0.5 and np.std(e) < 0.02
    assert rounds <= 3
    assert np.std(ml) < np.std(raw) * 1.1


def test_four_bit_registers_saturate_late():
    r = np.random.default_rng(5)
    errors = [N.corrected_raw(np.bincount(simulate.registers_of(10**8, 12, 14, r), minlength=16)) / 1e8 - 1 for _ in range(50)]
    assert abs(np.mean(errors)) < 0.03


CELLS = ("lt1", "gt1", "lt2", "gt2", "eq")


def joint(pairs, p, q, tolerance=None):
    return N.joint_ml_many(np.array([[s[k] for k in CELLS] for s in pairs]), p, q, tolerance)


@pytest.mark.parametrize("size", [(1000, 1000, 1000), (100_000, 100_000, 1000), (100, 100_000, 100_000)])
def test_gradient_and_solver(size):
    stat = simulate.pair_of(*size, 12, 52, np.random.default_rng(sum(size)))
    stats = np.array([[stat[k] for k in CELLS]])
    terms = lambda rates: (lambda v, g: (v[0], g[0]))(*N.joint_terms_many(stats, np.array([rates]), 12, 52))
    phi = np.log(np.array(size, dtype=float) * [1.1, 0.9, 1.05])
    _, grad = terms(np.exp(phi))
    for k in range(3):
        d = np.zeros(3)
        d[k] = 1e-5
        central = (terms(np.exp(phi + d))[0] - terms(np.exp(phi - d))[0]) / 2e-5
        assert grad[k] == pytest.approx(central, rel=1e-4, abs=1e-3)
    found = joint([stat], 12, 52, 1e-10)[0][0]
    best, grad = terms(found)
    assert np.abs(grad).max() < 1e-2
    for k in range(3):
        for f in (0.98, 1.02):
            moved = found.copy()
            moved[k] *= f
            assert terms(moved)[0] <= best + 1e-9


def test_pairs_side_by_side_are_pairs_alone():
    r = np.random.default_rng(8)
    pairs = [simulate.pair_of(*c, 10, 30, r) for c in simulate.JOINT_GRID for _ in range(5)]
    sizes, rounds, known = joint(pairs, 10, 30)
    for k, s in enumerate(pairs):
        one = joint([s], 10, 30)
        assert sizes[k] == pytest.approx(one[0][0], rel=1e-9) and rounds[k] == one[1][0] and known[k] == one[2][0]


def test_special_pairs():
    r = np.random.default_rng(3)
    sizes, _, known = joint([simulate.pair_of(0, 0, 5000, 12, 20, r)], 12, 20)
    assert sizes[0, 0] == sizes[0, 1] == 0 and known[0] and sizes[0, 2] == pytest.approx(5000, rel=0.1)
    assert joint([simulate.pair_of(5, 6, 0, 16, 20, r)], 16, 20)[0][0, 2] == 0
    above = {"lt1": np.zeros(6), "gt1": np.array([0, 0, 0, 4, 0, 0.0]), "lt2": np.array([0, 4, 0, 0, 0, 0.0]), "gt2": np.zeros(6), "eq": np.zeros(6)}
    assert not joint([above], 2, 4)[2][0]
    full = {"lt1": np.zeros(6), "gt1": np.zeros(6), "lt2": np.zeros(6), "gt2": np.zeros(6), "eq": np.array([0, 0, 0, 0, 0, 4.0])}
    sizes, _, known = joint([full], 2, 4)
    assert not known[0] and np.isnan(sizes[0, 2])
    assert len(N.joint_ml_many(np.zeros((0, 5, 6)), 2, 4)[0]) == 0


def test_drawn_counts_are_those_of_inserted_elements():
    """Counts drawn by numbers of hits have the distribution of registers that are hit one by one, at either way of drawing."""
    r = np.random.default_rng(12)
    for n, p, q in ((3000, 12, 20), (60_000, 14, 30), (50_000, 6, 20)):
        ones = np.array([np.bincount(simulate.registers_of(n, p, q, r), minlength=q + 2) for _ in range(400)])
        drawn = [simulate.counts_of(n, p, q, r) for _ in range(400)]
        many, sizes = np.array([c for _, c in drawn]), np.array([s for s, _ in drawn])
        assert (many.sum(1) == 1 << p).all() and abs(sizes.mean() / n - 1) < 5 / (400 * n) ** 0.5
        spread = np.sqrt(ones.var(0) + many.var(0)) / 20 + 0.05
        assert (np.abs(ones.mean(0) - many.mean(0)) < 6 * spread).all()


@pytest.mark.parametrize("n, mean", [(1000, 2.0), (3000, 2.0), (8000, 3.0), (10**6, 3.0)])
def test_mean_rounds_of_the_secant_over_n(n, mean):
    """Two rounds below some 5000 elements and three above, never more."""
    r = np.random.default_rng(n)
    rounds = N.ml_many(np.array([simulate.counts_of(n, 12, 20, r)[1] for _ in range(300)]))[1]
    assert rounds.max() <= 3 and abs(rounds.mean() - mean) < 0.35


def test_batches_are_the_single_estimates():
    r = np.random.default_rng(11)
    for p, q in ((12, 20), (8, 6), (12, 52), (6, 0)):
        rows = [np.bincount(simulate.registers_of(n, p, q, r), minlength=q + 2) for n in (0, 1, 50, 5000, 10**6, 10**8)]
        rows += [np.array([0] * (q + 1) + [1 << p]), np.array([1 << p] + [0] * (q + 1))]
        counts = np.array(rows)
        assert N.corrected_raw_many(counts) == pytest.approx([N.corrected_raw(c) for c in rows], rel=1e-9)
        estimates, rounds = N.ml_many(counts)
        assert estimates == pytest.approx([N.ml(c)[0] for c in rows], rel=1e-9) and rounds.tolist() == [N.ml(c)[1] for c in rows]
