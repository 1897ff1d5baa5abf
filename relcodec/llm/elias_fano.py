"""Elias-Fano sequences and a two-level n-gram trie over them, memory-mapped.

A non-decreasing sequence of n integers below u keeps floor(log2(u / n)) low bits of each value in a packed array and
the high parts as unary gaps in a bit vector, about 2 + log2(u / n) bits a value, with random access by select. The
trie keeps, level by level, the sorted keys of all nodes (children of a node are one run, made monotone by adding the
run's base), monotone pointers to the first child of each node, and quantised values. Looking up a word after a
context is a successor search within the context's run only. Levels live in one file that is mapped and unlinked, so
its pages belong to the page cache and vanish with the process.
"""

from __future__ import annotations

import tempfile

import numpy as np

_ONES = np.array([bin(i).count("1") for i in range(256)], np.uint8)
_SELECT = np.zeros((256, 8), np.uint8)
for _b in range(256):
    for _k, _p in enumerate([p for p in range(8) if _b >> p & 1]):
        _SELECT[_b, _k] = _p


class EliasFano:
    """A non-decreasing sequence of unsigned integers."""

    def __init__(self, low: np.ndarray, high: np.ndarray, ones: np.ndarray, bits: int, n: int):
        self.low, self.high, self.ones, self.bits, self.n = low, high, ones, bits, n

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        values = values.astype(np.uint64)
        n = len(values)
        top = int(values[-1]) + 1 if n else 1
        bits = max(0, (top // max(n, 1)).bit_length() - 1)
        places = (values >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        flags = np.zeros((int(places[-1]) + 8 if n else 8) // 8 * 8, np.uint8)
        flags[places] = 1
        high = np.packbits(flags, bitorder="little")
        each = np.unpackbits(values.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, :bits]
        packed = np.packbits(each.ravel(), bitorder="little")
        ones = np.concatenate([[0], np.cumsum(_ONES[high], dtype=np.int64)]).astype(np.uint32)
        return cls(np.concatenate([packed, np.zeros(16, np.uint8)]), high, ones, bits, n)

    def arrays(self) -> list[np.ndarray]:
        return [self.low, self.high, self.ones]

    def __getitem__(self, i: np.ndarray) -> np.ndarray:
        """Values at the given places, by select on the high bits."""
        i = np.asarray(i, np.int64)
        at = np.searchsorted(self.ones, i, side="right") - 1
        inside = _SELECT[self.high[at], i - self.ones[at].astype(np.int64)]
        value = (at * 8 + inside - i).astype(np.uint64) << np.uint64(self.bits)
        if self.bits:
            bit = i * self.bits
            byte, shift = bit >> 3, (bit & 7).astype(np.uint64)
            # The eight bytes from each place on, read as one number (`low` ends with spare bytes).
            low = np.ndarray(len(self.low) - 7, "<u8", self.low, 0, (1,))[byte] >> shift
            if self.bits > 57:
                spill = shift > 0
                low[spill] |= self.low[byte[spill] + 8].astype(np.uint64) << (np.uint64(64) - shift[spill])
            value |= low & np.uint64((1 << self.bits) - 1)
        return value

    def find(self, keys: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        """Place of each key in its own run [start, stop), or -1: all searches halve their runs in step."""
        low, high = np.array(start, np.int64), np.array(stop, np.int64)
        while True:
            open_ = np.flatnonzero(low < high)
            if not len(open_):
                break
            mid = (low[open_] + high[open_]) >> 1
            less = self[mid] < keys[open_]
            low[open_[less]] = mid[less] + 1
            high[open_[~less]] = mid[~less]
        ok = low < np.asarray(stop)
        found = np.full(len(low), -1, np.int64)
        hit = np.flatnonzero(ok)
        hit = hit[self[low[hit]] == keys[hit]]
        found[hit] = low[hit]
        return found


#: Codes of quantised base-10 logarithms: 0 is "absent", 1..65535 spread evenly over [FLOOR, 0].
FLOOR = -16.0


def quantise(log10: np.ndarray) -> np.ndarray:
    return (1 + np.rint((np.clip(log10, FLOOR, 0.0) - FLOOR) / -FLOOR * 65534)).astype(np.uint16)


def restore(codes: np.ndarray) -> np.ndarray:
    """Probabilities of codes; 0 for absent ones."""
    return np.where(codes == 0, 0.0, 10.0 ** ((codes.astype(np.float64) - 1) / 65534 * -FLOOR + FLOOR))


#: Successor keys have 40 bits, so a run's base of up to 2^24 contexts a shard fits above them.
KEY_BITS = 40


class Trie:
    """Contexts (64-bit keys) and their successors (KEY_BITS-bit keys), each node with a quantised value."""

    def __init__(self, contexts: EliasFano, pointers: EliasFano, successors: EliasFano, backoff: np.ndarray, probability: np.ndarray):
        self.contexts, self.pointers, self.successors, self.backoff, self.probability = contexts, pointers, successors, backoff, probability

    @classmethod
    def build(cls, contexts: np.ndarray, first_child: np.ndarray, successors: np.ndarray, backoff: np.ndarray, probability: np.ndarray) -> Trie:
        """contexts sorted; first_child has one more entry than contexts; successors sorted within each run."""
        own = np.repeat(np.arange(len(contexts), dtype=np.uint64), np.diff(first_child))
        return cls(EliasFano.build(contexts >> np.uint64(1)), EliasFano.build(first_child), EliasFano.build(successors + (own << np.uint64(KEY_BITS))), quantise(backoff), quantise(probability))

    def mapped(self) -> Trie:
        """The same trie with every array in one memory-mapped, already unlinked file."""
        parts = [*self.contexts.arrays(), *self.pointers.arrays(), *self.successors.arrays(), self.backoff, self.probability]
        with tempfile.TemporaryFile() as file:
            at = []
            for a in parts:
                file.write(b"\0" * (-file.tell() % 8))
                at.append(file.tell())
                file.write(np.ascontiguousarray(a).tobytes())
            file.write(b"\0" * 8)
            file.flush()
            # A plain view: it keeps the mapping alive without the cost of its class at every index.
            whole = np.asarray(np.memmap(file, np.uint8, "r"))
        parts = [whole[s: s + a.nbytes].view(a.dtype) for s, a in zip(at, parts, strict=True)]
        ef = [EliasFano(*parts[3 * k: 3 * k + 3], old.bits, old.n) for k, old in enumerate((self.contexts, self.pointers, self.successors))]
        return Trie(*ef, parts[9], parts[10])

    def find_contexts(self, keys: np.ndarray) -> np.ndarray:
        n = len(keys)
        return self.contexts.find(keys >> np.uint64(1), np.zeros(n, np.int64), np.full(n, self.contexts.n, np.int64))

    def find_successors(self, nodes: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """Place of each successor below its context node (-1 where the node is -1 or has no such child)."""
        out = np.full(len(nodes), -1, np.int64)
        some = np.flatnonzero(nodes >= 0)
        node = nodes[some]
        start, stop = self.pointers[node].astype(np.int64), self.pointers[node + 1].astype(np.int64)
        out[some] = self.successors.find(keys[some] + (node.astype(np.uint64) << np.uint64(KEY_BITS)), start, stop)
        return out
