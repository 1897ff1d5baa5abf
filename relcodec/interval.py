"""Probability intervals: exact arithmetic for proofs and tests, and the integer arithmetic that codes with."""

from __future__ import annotations

from fractions import Fraction

import numpy as np

STATE_BITS = 48
MASS_BITS = 16
WHOLE = 1 << STATE_BITS
HALF = WHOLE >> 1
MASS = 1 << MASS_BITS
#: A state narrower than this that straddles one half is cut to its larger part, so it never gets too narrow to split.
NARROWEST = 1 << 32

Interval = tuple[Fraction, Fraction]


def product_exact(intervals: list[Interval]) -> Interval:
    """The part of [0, 1] that a sequence of nested choices selects."""
    low, width = Fraction(0), Fraction(1)
    for a, b in intervals:
        low, width = low + width * a, width * (b - a)
    return low, low + width


def smallest_dyadic(low: Fraction, high: Fraction) -> str:
    """Bits of the largest cell [M / 2^k, (M + 1) / 2^k] inside [low, high]; of equal ones the first. '' for [0, 1]."""
    k = 0
    while True:
        m = -((-low.numerator << k) // low.denominator)
        if Fraction(m + 1, 1 << k) <= high:
            return format(m, "b").zfill(k) if k else ""
        k += 1


def code_with_early_bits(intervals: list[Interval]) -> str:
    """The same code made bit by bit: what is decided is emitted after every step and the state doubled."""
    out, low, high = "", Fraction(0), Fraction(1)
    for a, b in intervals:
        low, high = low + (high - low) * a, low + (high - low) * b
        while high <= Fraction(1, 2) or low >= Fraction(1, 2):
            bit = int(low >= Fraction(1, 2))
            out += str(bit)
            low, high = 2 * low - bit, 2 * high - bit
    return out + smallest_dyadic(low, high)


def trace_decode(branches: list[list[Interval]], bits: str) -> list[dict]:
    """Reference decoder with a log: one entry per bit read or branch found.

    Two intervals are kept in one frame: that of the choices made and that of the bits read. When the latter lies in a
    branch the branch is taken; shared halves are then doubled away from both.
    """
    log, at = [], 0
    low, high, b_low, b_high = Fraction(0), Fraction(1), Fraction(0), Fraction(1)
    for step, options in enumerate(branches):
        while True:
            found = next((i for i, (a, b) in enumerate(options) if low + (high - low) * a <= b_low and b_high <= low + (high - low) * b), None)
            if found is not None:
                break
            bit = int(bits[at])
            at += 1
            mid = (b_low + b_high) / 2
            b_low, b_high = (mid, b_high) if bit else (b_low, mid)
            log.append({"event": "bit", "bit": bit, "choices": (low, high), "read": (b_low, b_high)})
        a, b = options[found]
        low, high = low + (high - low) * a, low + (high - low) * b
        log.append({"event": "branch", "step": step, "branch": found, "choices": (low, high), "read": (b_low, b_high)})
        while high <= Fraction(1, 2) or low >= Fraction(1, 2):
            k = int(low >= Fraction(1, 2))
            low, high, b_low, b_high = 2 * low - k, 2 * high - k, 2 * b_low - k, 2 * b_high - k
            log.append({"event": "rescale", "choices": (low, high), "read": (b_low, b_high)})
    return log


def narrow(low: np.ndarray, high: np.ndarray, c: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The part of states [low, high) for masses [c, d) of 2^16: never more than the exact part, never empty."""
    # A width is at most 2^48 and c and 2^16 - d are below 2^16, so products stay below 2^64.
    width, up = (high - low).astype(np.uint64), np.uint64(MASS - 1)
    a = low + ((width * np.asarray(c).astype(np.uint64) + up) >> np.uint64(MASS_BITS)).astype(np.int64)
    b = high - ((width * (MASS - np.asarray(d)).astype(np.uint64) + up) >> np.uint64(MASS_BITS)).astype(np.int64)
    thin = b - a < NARROWEST
    if thin.any():
        cut = thin & (a < HALF) & (b > HALF)
        upper = cut & (b - HALF > HALF - a)
        a, b = np.where(upper, HALF, a), np.where(cut & ~upper, HALF, b)
    return a, b


def shared_bits(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """How many leading bits all numbers of [low, high) share."""
    return STATE_BITS - bit_lengths(low ^ (high - 1))


def bit_lengths(x: np.ndarray) -> np.ndarray:
    """Bits of numbers from 0 to 2^53: the exponents of their doubles."""
    return np.maximum((x.astype(np.float64).view(np.int64) >> 52) - 1022, 0)


def finish(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bits, value): the largest dyadic cell inside each state, of equal ones the first."""
    # The first cells that are no wider than the state; where none of them lies inside, one of half their width does.
    k = STATE_BITS + 1 - bit_lengths(high - low)
    value = -(-low >> (STATE_BITS - k))
    half = np.flatnonzero((value + 1) << (STATE_BITS - k) > high)
    k[half] += 1
    value[half] = -(-low[half] >> (STATE_BITS - k[half]))
    return k, value
