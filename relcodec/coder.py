"""Arithmetic coding of many rows in step: every row has its own state and bit string, every numpy call moves all rows.

Rows are independent, so codes can be decoded one by one; a code ends where its decoder knows it ends, so codes can be
laid end to end without lengths.
"""

from __future__ import annotations

import numpy as np

from relcodec.interval import HALF, MASS, MASS_BITS, NARROWEST, STATE_BITS, WHOLE, finish, narrow, shared_bits

#: A table of entries by number is made of at most so many.
DENSE = 1 << 19


class Encoder:
    """States of n rows; `put` narrows some of them, `codes` ends all."""

    def __init__(self, n: int):
        self.low, self.high = np.zeros(n, np.int64), np.full(n, WHOLE, np.int64)
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def put(self, c: np.ndarray, d: np.ndarray, rows: np.ndarray | None = None) -> None:
        """Take masses [c, d) in the given rows (all rows if None)."""
        at = slice(None) if rows is None else rows
        low, high = narrow(self.low[at], self.high[at], c, d)
        t = shared_bits(low, high)
        some = np.flatnonzero(t)
        if len(some):
            names = some if rows is None else rows[some]
            self.parts.append((names, low[some] >> (STATE_BITS - t[some]), t[some]))
            base = (low[some] >> (STATE_BITS - t[some])) << (STATE_BITS - t[some])
            low[some], high[some] = (low[some] - base) << t[some], (high[some] - base) << t[some]
        self.low[at], self.high[at] = low, high

    def codes(self) -> tuple[np.ndarray, np.ndarray]:
        """(bits of all rows end to end as 0/1 bytes, bits per row)."""
        n = len(self.low)
        k, value = finish(self.low, self.high)
        parts = [*self.parts, (np.arange(n), value, k)]
        rows = np.concatenate([p[0] for p in parts])
        value, t = np.concatenate([p[1] for p in parts]), np.concatenate([p[2] for p in parts])
        order = np.argsort(rows, kind="stable")
        rows, value, t = rows[order], value[order], t[order]
        ends = np.cumsum(t)
        place = np.arange(int(t.sum())) - np.repeat(ends - t, t)
        bits = (np.repeat(value, t) >> (np.repeat(t, t) - 1 - place)) & 1
        return bits.astype(np.uint8), np.bincount(rows, t, n).astype(np.int64)


    def packed(self) -> tuple[bytes, np.ndarray]:
        """(what `codes` gives packed into bytes, bits per row), without an array of single bits."""
        n = len(self.low)
        k, value = finish(self.low, self.high)
        parts = [*self.parts, (np.arange(n), value, k)]
        rows = np.concatenate([p[0] for p in parts])
        # Short numbers are sorted by their digits.
        order = np.argsort(rows.astype(np.uint16) if n <= 1 << 16 else rows, kind="stable")
        value, t = np.concatenate([p[1] for p in parts])[order], np.concatenate([p[2] for p in parts])[order]
        ends = np.cumsum(t)
        place = ends - t
        byte, inner = place >> 3, place & 7
        # A part has at most 48 bits, so with those before it in its first byte it lies in seven; parts share bytes, but no bits.
        word = value << (56 - inner - t)
        out = np.zeros((int(ends[-1]) + 7) // 8 if len(ends) else 0, np.uint8)
        for b in range(7):
            some = np.flatnonzero(inner + t > 8 * b)
            if not len(some):
                break
            out |= np.bincount(byte[some] + b, (word[some] >> (48 - 8 * b)) & 255, len(out)).astype(np.uint8)
        return out.tobytes(), np.bincount(rows, np.concatenate([p[2] for p in parts]), n).astype(np.int64)


class Sizes(Encoder):
    """An Encoder that keeps how many bits the rows' codes have, not the bits."""

    def __init__(self, n: int):
        super().__init__(n)
        self.done = np.zeros(n, np.int64)

    def copy(self) -> Sizes:
        out = Sizes(0)
        out.low, out.high, out.done, out.parts = self.low.copy(), self.high.copy(), self.done.copy(), list(self.parts)
        return out

    def put(self, c: np.ndarray, d: np.ndarray, rows: np.ndarray | None = None) -> None:
        at = slice(None) if rows is None else rows
        low, high = narrow(self.low[at], self.high[at], c, d)
        t = shared_bits(low, high)
        self.done[at] += t
        # All but the shared bits go on; the last number of the state stays below 2^48, its end may be that.
        self.low[at], self.high[at] = (low << t) & (WHOLE - 1), (((high - 1) << t) & (WHOLE - 1)) + (np.int64(1) << t)

    def sizes(self) -> np.ndarray:
        """Bits per row; rows that were taken out of step left theirs in `parts`."""
        out = self.done + finish(self.low, self.high)[0]
        for rows, _, t in self.parts:
            out += np.bincount(rows, t, len(out)).astype(np.int64)
        return out


class Steps:
    """What a node asks of an Encoder of n rows, to be taken by several of them."""

    def __init__(self, n: int):
        self.n, self.taken = n, []

    def put(self, c: np.ndarray, d: np.ndarray, rows: np.ndarray | None = None) -> None:
        # Rows are in order, so as many as there are are all of them.
        if rows is None or len(rows):
            self.taken.append((c, d, None if rows is None or len(rows) == self.n else rows))


class Decoder:
    """States of n rows that start at given bit places of a payload."""

    def __init__(self, payload: bytes, starts: np.ndarray):
        self.raw = bytes(payload) + bytes(16)
        self.bytes = np.frombuffer(self.raw, np.uint8)
        self.at = np.asarray(starts, np.int64).copy()
        n = len(self.at)
        self.start = self.at.copy()
        self.low, self.high = np.zeros(n, np.int64), np.full(n, WHOLE, np.int64)
        self.window = self.read(np.arange(n), np.full(n, STATE_BITS, np.int64))
        self.emitted = np.zeros(n, np.int64)

    def read(self, rows: np.ndarray, t: np.ndarray) -> np.ndarray:
        """The next t (at most 48) bits of rows; beyond the end there are zeros."""
        at = self.at[rows]
        byte = np.minimum(at >> 3, len(self.bytes) - 8)
        raw = np.zeros(len(rows), np.uint64)
        for k in range(8):
            raw = (raw << np.uint64(8)) | self.bytes[byte + k].astype(np.uint64)
        raw <<= (at & 7).astype(np.uint64)
        # At most 7 + 48 of the 64 bits are used.
        self.at[rows] = at + t
        shift = (64 - t).astype(np.uint64)
        return np.where(t > 0, raw >> np.minimum(shift, np.uint64(63)), 0).astype(np.int64)

    def position(self, rows: np.ndarray) -> np.ndarray:
        """Where the window stands in the state, in units of 2^-16: the mass to look up, give or take one."""
        w = (self.high[rows] - self.low[rows]).astype(np.uint64)
        return (((self.window[rows] - self.low[rows]).astype(np.uint64) << np.uint64(MASS_BITS)) // w).astype(np.int64)

    def bounds(self, rows: np.ndarray, c: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return narrow(self.low[rows], self.high[rows], c, d)

    def take(self, rows: np.ndarray, c: np.ndarray, d: np.ndarray) -> None:
        low, high = narrow(self.low[rows], self.high[rows], c, d)
        t = shared_bits(low, high)
        some = np.flatnonzero(t)
        window = self.window[rows]
        if len(some):
            base = (low[some] >> (STATE_BITS - t[some])) << (STATE_BITS - t[some])
            low[some], high[some] = (low[some] - base) << t[some], (high[some] - base) << t[some]
            window[some] = ((window[some] - base) << t[some]) | self.read(rows[some], t[some])
            self.emitted[rows[some]] += t[some]
        self.low[rows], self.high[rows], self.window[rows] = low, high, window

    def ends(self) -> np.ndarray:
        """Bit place after each row's code, known from the states alone."""
        return self.start + self.emitted + finish(self.low, self.high)[0]


def narrow_one(low: int, high: int, c: int, d: int) -> tuple[int, int]:
    """What `narrow` does, for one state."""
    q, rem = (high - low) >> MASS_BITS, (high - low) & (MASS - 1)
    a, b = low + q * c + ((rem * c + (MASS - 1)) >> MASS_BITS), low + q * d + ((rem * d) >> MASS_BITS)
    if a < HALF < b and b - a < NARROWEST:
        return (HALF, b) if b - HALF > HALF - a else (a, HALF)
    return a, b


class RowEncoder:
    """One row of an Encoder, taken out of step: where few rows are left, plain integers are faster than arrays."""

    def __init__(self, enc: Encoder, row: int):
        self.enc, self.row = enc, row
        self.low, self.high = int(enc.low[row]), int(enc.high[row])
        self.values: list[int] = []
        self.sizes: list[int] = []

    def put(self, c: int, d: int) -> None:
        low, high = narrow_one(self.low, self.high, c, d)
        t = STATE_BITS - (low ^ (high - 1)).bit_length()
        if t:
            head = low >> (STATE_BITS - t)
            self.values.append(head), self.sizes.append(t)
            base = head << (STATE_BITS - t)
            low, high = (low - base) << t, (high - base) << t
        self.low, self.high = low, high

    def put_uniform(self, value: int, bits: int) -> None:
        while bits > 0:
            t = min(bits, 14)
            part = (value >> (bits - t)) & ((1 << t) - 1)
            self.put(part << (MASS_BITS - t), (part + 1) << (MASS_BITS - t))
            bits -= t

    def close(self) -> None:
        self.enc.low[self.row], self.enc.high[self.row] = self.low, self.high
        if self.values:
            self.enc.parts.append((np.full(len(self.values), self.row), np.array(self.values, np.int64), np.array(self.sizes, np.int64)))


class RowDecoder:
    """One row of a Decoder, taken out of step."""

    def __init__(self, dec: Decoder, row: int):
        self.dec, self.row, self.bytes = dec, row, dec.raw
        self.low, self.high, self.window = int(dec.low[row]), int(dec.high[row]), int(dec.window[row])
        self.at, self.emitted = int(dec.at[row]), int(dec.emitted[row])

    def position(self) -> int:
        return ((self.window - self.low) << MASS_BITS) // (self.high - self.low)

    def holds(self, c: int, d: int) -> int:
        """-1, 0 or 1: whether the window lies before, in or behind masses [c, d)."""
        low, high = narrow_one(self.low, self.high, c, d)
        return -1 if self.window < low else 1 if self.window >= high else 0

    def take(self, c: int, d: int) -> None:
        low, high = narrow_one(self.low, self.high, c, d)
        t = STATE_BITS - (low ^ (high - 1)).bit_length()
        if t:
            base = (low >> (STATE_BITS - t)) << (STATE_BITS - t)
            low, high = (low - base) << t, (high - base) << t
            byte = min(self.at >> 3, len(self.bytes) - 8)
            raw = (int.from_bytes(self.bytes[byte: byte + 8], "big") << (self.at & 7)) & 0xFFFFFFFFFFFFFFFF
            self.window = ((self.window - base) << t) | (raw >> (64 - t))
            self.at += t
            self.emitted += t
        self.low, self.high = low, high

    def take_uniform(self, bits: int) -> int:
        out = 0
        while bits > 0:
            t = min(bits, 14)
            shift = MASS_BITS - t
            part = self.position() >> shift
            for _ in range(2):
                part = min(max(part + self.holds(part << shift, (part + 1) << shift), 0), (1 << t) - 1)
            self.take(part << shift, (part + 1) << shift)
            out, bits = (out << t) | part, bits - t
        return out

    def close(self) -> None:
        d, r = self.dec, self.row
        d.low[r], d.high[r], d.window[r], d.at[r], d.emitted[r] = self.low, self.high, self.window, self.at, self.emitted


class Masses:
    """Cumulative masses of many distributions: row g's symbols are sorted, their lows start at 0, and end at 2^16."""

    def __init__(self, first: np.ndarray, symbol: np.ndarray, low: np.ndarray, mass: np.ndarray):
        self.first, self.symbol, self.low, self.mass = first, symbol, low, mass
        own = np.repeat(np.arange(len(first) - 1), np.diff(first))
        self.width = int(symbol.max()) + 1 if len(symbol) else 1
        self.by_symbol = own * self.width + symbol
        self.by_low = own * MASS + low
        # Entries by number are looked up in a table where that is small.
        self.dense = (len(first) - 1) * (self.width + 1) <= DENSE and int(symbol.min(initial=0)) >= 0
        self.table: np.ndarray | None = None

    def find(self, group: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """Entry of (group, symbol), or -1."""
        if self.dense:
            if self.table is None:
                self.table = np.full((len(self.first) - 1, self.width + 1), -1, np.int32)
                self.table.ravel()[self.by_symbol + self.by_symbol // self.width] = np.arange(len(self.symbol))
            # The last column is that of strange symbols.
            return self.table[group, np.where((symbol >= 0) & (symbol < self.width), symbol, self.width)].astype(np.int64)
        key = group * self.width + symbol
        at = np.minimum(np.searchsorted(self.by_symbol, key), len(self.by_symbol) - 1)
        return np.where((symbol >= 0) & (symbol < self.width) & (self.by_symbol[at] == key), at, -1)

    def encode(self, enc: Encoder, entry: np.ndarray, rows: np.ndarray | None = None) -> None:
        enc.put(self.low[entry], self.low[entry] + self.mass[entry], rows)

    def decode(self, dec: Decoder, group: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Entries that hold the rows' windows."""
        at = np.searchsorted(self.by_low, group * MASS + dec.position(rows), side="right") - 1
        for _ in range(2):
            c, d = self.low[at], self.low[at] + self.mass[at]
            low, high = dec.bounds(rows, c, d)
            window = dec.window[rows]
            # Bounds are rounded inwards, so the first guess can be one off.
            at = at + (window >= high) - (window < low)
            at = np.clip(at, self.first[group], self.first[group + 1] - 1)
        dec.take(rows, self.low[at], self.low[at] + self.mass[at])
        return at


def put_uniform(enc: Encoder, value: np.ndarray, bits: np.ndarray | int, rows: np.ndarray | None = None) -> None:
    """value as `bits` equally likely bits, at most 14 to a step."""
    left = np.broadcast_to(np.asarray(bits, np.int64), value.shape).copy()
    names = np.arange(len(value)) if rows is None else rows
    while (left > 0).any():
        some = np.flatnonzero(left > 0)
        t = np.minimum(left[some], 14)
        part = (value[some] >> (left[some] - t)) & ((np.int64(1) << t) - 1)
        enc.put(part << (MASS_BITS - t), (part + 1) << (MASS_BITS - t), names[some])
        left[some] -= t


def take_uniform(dec: Decoder, bits: np.ndarray | int, rows: np.ndarray) -> np.ndarray:
    left = np.broadcast_to(np.asarray(bits, np.int64), rows.shape).copy()
    out = np.zeros(len(rows), np.int64)
    while (left > 0).any():
        some = np.flatnonzero(left > 0)
        t = np.minimum(left[some], 14)
        part = dec.position(rows[some]) >> (MASS_BITS - t)
        for _ in range(2):
            low, high = dec.bounds(rows[some], part << (MASS_BITS - t), (part + 1) << (MASS_BITS - t))
            window = dec.window[rows[some]]
            part = np.clip(part + (window >= high) - (window < low), 0, (np.int64(1) << t) - 1)
        dec.take(rows[some], part << (MASS_BITS - t), (part + 1) << (MASS_BITS - t))
        out[some] = (out[some] << t) | part
        left[some] -= t
    return out


def masses_of(counts: np.ndarray) -> np.ndarray:
    """Integer masses of 2^16 that give every symbol at least one; what rounding leaves goes to the most frequent
    (of equal ones the first)."""
    n, k = int(counts.sum()), len(counts)
    if n == 0:
        counts, n = np.ones(k, np.int64), k
    # counts * (2^16 - k) stays below 2^63 for tables of up to 2^47 rows.
    mass = 1 + counts.astype(np.int64) * (MASS - k) // n
    mass[int(np.argmax(counts))] += MASS - int(mass.sum())
    return mass


def masses_of_groups(counts: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(group, mass) of every entry: `masses_of` of each group counts[first[g]: first[g + 1]], of which none is empty or 0."""
    sizes = np.diff(first)
    own = np.repeat(np.arange(len(sizes)), sizes)
    mass = 1 + counts * (MASS - sizes)[own] // np.add.reduceat(counts, first[:-1])[own]
    most = np.flatnonzero(counts == np.maximum.reduceat(counts, first[:-1])[own])
    most = most[np.flatnonzero(np.diff(own[most], prepend=-1))]
    mass[most] += MASS - np.add.reduceat(mass, first[:-1])
    return own, mass


assert HALF * 2 == WHOLE
