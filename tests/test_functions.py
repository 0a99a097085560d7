import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fewbit.functions import rng, theory
from fewbit.functions.codec import pack, unpack
from fewbit.functions.lattice import Lattice
from fewbit.functions.ledger import bits_paper, compression
from fewbit.plans import memory

L, MU, D = 0.967, 0.2, 9


def test_known_draws():
    assert rng.uniform(42, "worker", 1, 1, 0) == 0.0803721733007865 and rng.worker(42, 1, 1, 10) == 0
    assert rng.uniform(42, "pick", 1, 0, 0) == 0.3080435974580791 and rng.pick(42, 1, 8) == 2
    assert rng.uniform(42, "model", 1, 1, 0) == 0.31223589045225797


def test_lattice_worked_values():
    lat = Lattice.of([0.0], 1.0, 2)
    assert np.allclose(lat.points(0), [-1, -1 / 3, 1 / 3, 1])
    assert lat.position([0.5])[0] == pytest.approx(2.25)
    assert lat.round_random([0.5], np.array([0.74]))[0] == pytest.approx(1 / 3) and lat.round_random([0.5], np.array([0.76]))[0] == pytest.approx(1)
    assert lat.saturated([1.7]) == 1 and lat.round_random([1.7], np.array([0.99]))[0] == pytest.approx(1)
    assert Lattice.of([2.0], 0.0, 3).round_random([5.0], np.array([0.3]))[0] == 2.0


@settings(deadline=None, max_examples=60)
@given(st.floats(-1, 1), st.integers(1, 12))
def test_rounding_keeps_the_mean_and_the_cell(v, p):
    lat = Lattice.of([0.0], 1.0, p)
    u = (np.arange(4096) + 0.5) / 4096
    q = np.array([lat.round_random([v], np.array([x]))[0] for x in u[::16]])
    assert abs(q.mean() - v) <= lat.spacing[0] / 100 + 1e-9
    assert np.abs(q - v).max() <= lat.spacing[0] + 1e-12
    assert ((q - v) ** 2).mean() <= theory.rounding_variance_cap(1.0, p, 1) + 1e-9


def test_rounding_is_idempotent_and_exact_bits_pass():
    lat = Lattice.of([0.3, -1.0], [0.5, 2.0], [4, 7])
    for j in range(16):
        v = np.array([lat.points(0)[j], lat.points(1)[3 * j]])
        assert np.allclose(lat.round_nearest(v), v)
    assert (Lattice.of([0.0], 1.0, 64).round_random([7.123], np.array([0.5])) == [7.123]).all()


@settings(deadline=None)
@given(st.data())
def test_codec_round_trip(data):
    bits = data.draw(st.lists(st.integers(1, 52), min_size=1, max_size=20))
    index = [data.draw(st.integers(0, 2**b - 1)) for b in bits]
    message = pack(index, bits)
    assert len(message) == math.ceil(sum(bits) / 8) and unpack(message, bits).tolist() == index


def test_codec_refuses_what_does_not_fit():
    with pytest.raises(ValueError):
        pack([8], [3])


LEDGER = [
    ((9, 10, 8, 3), 1152, 6336, 19584, 54, 297, 10800, 6192),
    ((9, 10, 8, 9), 1152, 6336, 19584, 162, 891, 11664, 7056),
    ((64, 10, 15, 7), 8192, 45056, 225280, 896, 4928, 115840, 54400),
    ((784, 10, 15, 7), 100352, 551936, 2759680, 10976, 60368, 1419040, 666400),
    ((784, 10, 15, 10), 100352, 551936, 2759680, 15680, 86240, 1489600, 736960),
]


@pytest.mark.parametrize("row", LEDGER)
def test_ledger(row):
    d, n, t, p = row[0]
    made = [bits_paper(m, d, n, t, p * d, p * d) for m in ("sgd", "gd", "avr_memory", "q_sag", "q_gd", "qavrm_adaptive", "qavrm_adaptive_plus")]
    assert made == list(row[1:])


def test_compression_of_messages_and_of_iterations():
    c = compression("qavrm_adaptive_plus", "avr_memory", 9, 10, 8, 3)
    assert c["message"] == pytest.approx(0.953125) and c["iteration"] == pytest.approx(1 - 6192 / 19584)


def test_bounds_identities():
    for a in (0.01, 0.05, 0.1):
        for T in (100, 1000):
            denominator = 2 * T * a - 12 * L * T * a * a - 2 / MU
            assert 2 * T * (a - 3 * L * a * a) * (1 - theory.fixed_rate(L, MU, a, T)) == pytest.approx(denominator)
        t = theory.fixed_epoch_min(L, MU, a)
        assert theory.fixed_rate(L, MU, a, t) == pytest.approx(1)
        p = theory.adaptive_bits_min(L, MU, a, D) + 2
        t = theory.adaptive_epoch_min(L, MU, a, D, p)
        assert theory.adaptive_rate(L, MU, a, D, p, t) == pytest.approx(1)
    a = theory.best_step(0.5, L, MU, D, 12)
    assert theory.adaptive_rate(L, MU, a, D, 12, theory.epoch_for_target(0.5, L, MU, a, D, 12)) == pytest.approx(0.5)
    lo, hi = theory.step_window(0.5, L, MU, D, 12)
    assert lo < a < hi and theory.epoch_for_target(0.5, L, MU, hi * 1.001, D, 12) == math.inf
    assert theory.epoch_best(0.2, L, MU, D, math.inf) == pytest.approx(12 * L * 1.2 / (MU * 0.04))


PLOT = {
    0.2: ({10: 1871, 11: 1772, 12: 1749, 13: 1743, 14: 1742}, 1741, 10),
    0.5: ({8: 449, 9: 369, 10: 354, 11: 350}, 349, 8),
    0.9: ({8: 150, 9: 140}, 137, 8),
    0.99: ({8: 128, 9: 121, 10: 119}, 118, 8),
}


def test_the_98_plotted_epoch_lengths():
    n = 0
    for target, (some, rest, first) in PLOT.items():
        for p in range(first, 33):
            assert math.ceil(theory.epoch_best(target, L, MU, D, p, 0.954)) == some.get(p, rest)
            n += 1
    assert n == 98
    assert theory.epoch_best(0.2, L, MU, D, 10) == pytest.approx(2452.1, abs=0.1)


def test_bits_by_dimension():
    made = [theory.adaptive_bits_min(L, MU, 0.05, d) for d in (10, 32, 100, 316, 1000)]
    assert made == [8, 9, 10, 10, 11] and made[-1] - made[0] in (3, 4)


def test_memory_rejects_only_larger_norms():
    a = memory.Anchor(np.zeros(1), np.zeros((1, 1)), np.zeros(1), 1.0, 0.0)
    b = memory.Anchor(np.ones(1), np.zeros((1, 1)), np.zeros(1), 1.1, 0.0)
    assert memory.step(None, b) == (b, True) and memory.step(a, b) == (a, False) and memory.step(b, a) == (a, True)
    assert memory.step(a, a)[1]
