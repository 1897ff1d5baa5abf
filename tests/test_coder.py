"""Worked examples, and round trips of the coder on random and extreme masses."""

from fractions import Fraction as Q

import numpy as np
import pytest

from relcodec.coder import Decoder, Encoder, Masses, masses_of, put_uniform, take_uniform
from relcodec.interval import HALF, WHOLE, code_with_early_bits, narrow, product_exact, smallest_dyadic, trace_decode

THREE = [(Q(1, 3), Q(1, 2)), (Q(1, 4), Q(1, 2)), (Q(1, 2), Q(2, 3))]


def test_three_letters():
    assert smallest_dyadic(Q(12, 100), Q(204, 1000)) == "0010"
    assert smallest_dyadic(Q(0), Q(1)) == ""


def test_three_intervals():
    assert product_exact(THREE) == (Q(19, 48), Q(29, 72))
    assert smallest_dyadic(*product_exact(THREE)) == "01100110" == code_with_early_bits(THREE)


def test_reference_decoder_finds_the_branches():
    options = [[(Q(0), a), (a, b), (b, Q(1))] for a, b in THREE]
    log = trace_decode(options, "01100110")
    assert [e["branch"] for e in log if e["event"] == "branch"] == [1, 1, 1]
    assert sum(e["event"] == "bit" for e in log) <= 8


def test_narrow_is_inside_and_never_empty():
    rng = np.random.default_rng(0)
    n = 20_000
    low = rng.integers(0, HALF, n)
    high = low + np.maximum(1 << 32, rng.integers(0, WHOLE - HALF, n))
    low[:5000] = HALF - rng.integers(1, 1 << 31, 5000)
    high[:5000] = HALF + (1 << 32)
    c = rng.integers(0, 65536, n)
    d = c + 1 + rng.integers(0, 65536, n) % (65536 - c)
    a, b = narrow(low, high, c, d)
    assert (a < b).all() and (a >= low).all() and (b <= high).all()
    for i in range(0, n, 997):
        w = int(high[i] - low[i])
        assert Q(int(a[i])) >= int(low[i]) + Q(w * int(c[i]), 65536) and Q(int(b[i])) <= int(low[i]) + Q(w * int(d[i]), 65536)


@pytest.mark.parametrize("seed", range(4))
def test_round_trip_and_own_ends(seed):
    rng = np.random.default_rng(seed)
    n, groups = 300, 4
    sizes = np.array([1, 2, 40, 300])
    counts = [(rng.pareto(0.5, k) * 10).astype(np.int64).clip(0, 10**9) for k in sizes]
    mass = np.concatenate([masses_of(c) for c in counts])
    first = np.concatenate([[0], np.cumsum(sizes)])
    low = np.concatenate([np.cumsum(m) - m for m in np.split(mass, first[1:-1])])
    table = Masses(first, np.concatenate([np.arange(k) for k in sizes]), low, mass)
    enc, steps = Encoder(n), []
    for _ in range(25):
        g = rng.integers(0, groups, n)
        at = first[g] + rng.integers(0, 10**9, n) % sizes[g]
        bits = rng.integers(0, 48, n)
        value = rng.integers(0, 1 << 48, n) & ((np.int64(1) << bits) - 1)
        table.encode(enc, at)
        put_uniform(enc, value, bits)
        steps.append((g, at, value, bits))
    code, size = enc.codes()
    starts = np.cumsum(size) - size
    dec, rows = Decoder(np.packbits(code).tobytes(), starts), np.arange(n)
    for g, at, value, bits in steps:
        assert (table.decode(dec, g, rows) == at).all()
        assert (take_uniform(dec, bits, rows) == value).all()
    assert (dec.ends() == starts + size).all()


def test_code_length_bound():
    rng = np.random.default_rng(3)
    mass = masses_of(np.array([50, 30, 15, 5]))
    low = np.cumsum(mass) - mass
    table = Masses(np.array([0, 4]), np.arange(4), low, mass)
    enc, information = Encoder(500), np.zeros(500)
    for _ in range(20):
        s = rng.integers(0, 4, 500)
        table.encode(enc, s)
        information -= np.log2(mass[s] / 65536)
    _, size = enc.codes()
    # The bound of exact arithmetic, and a hair for states cut at the middle.
    assert (size <= np.floor(information) + 2 + 1).all()


def test_masses_recipe():
    m = masses_of(np.array([20029, 19928, 20043]))
    assert m.sum() == 65536 and (m >= 1).all()
    assert (masses_of(np.array([0, 0])) > 0).all()
