"""Elias-Fano sequences and a memory-mapped n-gram trie over them."""

from __future__ import annotations

import mmap
import tempfile

import numpy as np

_BITS = (np.arange(256)[:, None] >> np.arange(8) & 1).astype(bool)
#: Place of the r-th set bit in each byte, at 8 * byte + r.
_NTH = np.array([np.pad(np.flatnonzero(b), (0, 8 - b.sum())) for b in _BITS], np.uint64).ravel()
_U = np.uint64
#: The same byte eight times over: 0x01, 0x80, 0x55, 0x33, 0x0F.
_X01, _X80, _X55, _X33, _X0F = (_U(b * 0x0101010101010101) for b in (0x01, 0x80, 0x55, 0x33, 0x0F))


def select(words: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The place of the rank-th set bit of each 64-bit word: byte counts summed by one product, then a table."""
    r = rank.astype(np.uint64)
    s = words - (words >> _U(1) & _X55)
    s = (s & _X33) + (s >> _U(2) & _X33)
    s = (s + (s >> _U(4)) & _X0F) * _X01
    before = ((r * _X01 | _X80) - s) & _X80  # one mark for each byte whose running count is at most the rank
    at = np.bitwise_count(before).astype(np.uint64) * _U(8)
    np.minimum(at, _U(56), out=at)
    left = r - ((s << _U(8)) >> at & _U(255))
    return (at + _NTH[(words >> at & _U(255)) * _U(8) + np.minimum(left, _U(7))]).astype(np.int64)


class Bits:
    """A bit vector with counts by 64-bit word: the place of the i-th one or zero, for many i at once."""

    def __init__(self, words: np.ndarray, counts: np.ndarray):
        self.words, self.counts = words, counts  # counts[k]: ones before word k

    @staticmethod
    def of(places: np.ndarray, size: int) -> Bits:
        b = np.zeros(-(-size // 64) * 8, np.uint8)
        for k in range(0, len(places), _READ):
            some = places[k : k + _READ]
            np.bitwise_or.at(b, some >> 3, (1 << (some & 7)).astype(np.uint8))
        words = b.view("<u8")
        return Bits(words, np.concatenate([[0], np.cumsum(np.bitwise_count(words).astype(np.int64))]).astype("<u4"))

    def one(self, i: np.ndarray) -> np.ndarray:
        k = np.searchsorted(self.counts, i, "right") - 1
        return k * 64 + select(self.words[k], i - self.counts[k])

    def zero(self, i: np.ndarray) -> np.ndarray:
        zeros = np.arange(len(self.counts), dtype=np.int64) * 64 - self.counts
        k = np.searchsorted(zeros, i, "right") - 1
        return k * 64 + select(~self.words[k], i - zeros[k])


#: Numbers whose low bits are spread out at once; a multiple of 64. Numbers read, and words of high bits, at once in a whole pass.
_AT_ONCE, _READ = 1 << 14, 1 << 16


class EliasFano:
    """A rising sequence of n numbers below `top`: high parts in unary, `low` low bits packed; about low + 2 bits a number."""

    def __init__(self, n: int, top: int, low: int, high: Bits, lows: np.ndarray):
        self.n, self.top, self.low, self.high, self.lows = n, top, low, high, lows

    @staticmethod
    def of(values: np.ndarray, top: int) -> EliasFano:
        n = len(values)
        low = max(0, int(top // max(1, n)).bit_length() - 1)
        bits = np.arange(low, dtype=np.uint64)
        parts = [np.packbits((values[k : k + _AT_ONCE, None].astype(np.uint64) >> bits & _U(1)).astype(np.uint8).ravel(), bitorder="little") for k in range(0, n if low else 0, _AT_ONCE)]
        packed = np.concatenate([*parts, np.zeros(0, np.uint8)])
        lows = np.concatenate([packed, np.zeros(16 - len(packed) % 8, np.uint8)]).view("<u8")  # one word more than is used
        ones = np.arange(n)
        for k in range(0, n, _READ):
            ones[k : k + _READ] += (values[k : k + _READ] >> low).astype(np.int64)
        return EliasFano(n, top, low, Bits.of(ones, n + (top >> low) + 2), lows)

    def _low(self, i: np.ndarray) -> np.ndarray:
        at = i * self.low
        k, shift = at >> 6, (at & 63).astype(np.uint64)
        word = self.lows[k] >> shift | (self.lows[k + 1] << _U(1)) << (_U(63) - shift)
        return (word & _U((1 << self.low) - 1)).astype(np.int64)

    def whole(self) -> np.ndarray:
        """All numbers in order: a single pass over the high bits and one over the low, in pieces; nothing but the numbers takes room."""
        out, at = np.empty(self.n, np.int64), 0
        for k in range(0, len(self.high.words), _READ):
            ones = np.flatnonzero(np.unpackbits(self.high.words[k : k + _READ].view(np.uint8), bitorder="little"))
            out[at : at + len(ones)] = ones + 64 * k
            at += len(ones)
        for k in range(0, self.n, _READ):
            i = np.arange(k, min(k + _READ, self.n))
            out[i] = (out[i] - i << self.low) | self._low(i)
        return out

    def find(self, x: np.ndarray, numbers: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(the place of the first number that is not below x, whether it is x).

        As many questions as there are numbers are answered from one pass over them, which numbers holds if it was made
        already; fewer by successor search each.
        """
        if numbers is None and 4 * len(x) > self.n:
            numbers = self.whole()
        at = self.successor(x) if numbers is None else np.searchsorted(numbers, x)
        equal = at < self.n
        equal[equal] = (self.get(at[equal]) if numbers is None else numbers[at[equal]]) == x[equal]
        return at, equal

    def get(self, i: np.ndarray) -> np.ndarray:
        if 4 * len(i) > self.n:
            return self.whole()[i]
        return (self.high.one(i) - i << self.low) | self._low(i)

    def successor(self, x: np.ndarray) -> np.ndarray:
        """The place of the first number that is not below x, n if there is none."""
        h = x >> self.low
        hi = self.high.zero(h) - h
        lo = np.where(h > 0, self.high.zero(np.maximum(h - 1, 0)) - h + 1, 0)
        want = x & ((1 << self.low) - 1)
        open_ = np.flatnonzero(lo < hi)
        while len(open_):  # within the numbers that share the high part
            mid = lo[open_] + hi[open_] >> 1
            less = self._low(mid) < want[open_]
            lo[open_[less]], hi[open_[~less]] = mid[less] + 1, mid[~less]
            open_ = open_[lo[open_] < hi[open_]]
        return lo

    def arrays(self) -> tuple[list[np.ndarray], list]:
        return [self.high.words, self.high.counts, self.lows], [self.n, self.top, self.low]

    @staticmethod
    def from_arrays(a: list[np.ndarray], meta: list) -> EliasFano:
        return EliasFano(*meta, Bits(a[0], a[1]), a[2])


def pack(arrays: list[np.ndarray]) -> tuple[bytes, list[tuple[str, int, int]]]:
    """All arrays in one block, each at a multiple of 8, and (kind, place, length) of each."""
    out, spec = bytearray(), []
    for a in arrays:
        out += bytes(-len(out) % 8)
        spec.append((a.dtype.str, len(out), len(a)))
        out += a.tobytes()
    return bytes(out), spec


class Mapped:
    """A block in an unlinked file, mapped to memory: its pages leave with the process and need no heap."""

    def __init__(self, block: bytes, spec: list[tuple[str, int, int]]):
        with tempfile.TemporaryFile() as f:
            f.write(block or b"\0")
            f.flush()
            self.map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        self.arrays = [np.frombuffer(self.map, kind, n, at) for kind, at, n in spec]


#: Shares are kept as 16-bit steps of a logarithm, rounded down: (code / STEPS - 1) * DECADES decades.
STEPS, DECADES = 65535, 9.0


def quantise(share: np.ndarray) -> np.ndarray:
    return np.clip(np.floor((np.log10(share) / DECADES + 1) * STEPS + 1e-9), 0, STEPS).astype("<u2")


_SHARE = 10 ** ((np.arange(STEPS + 1) / STEPS - 1) * DECADES)


def share(code: np.ndarray) -> np.ndarray:
    return _SHARE[code]


class Level:
    """One level: contexts, where each one's children start, the children, and the shares of both.

    A context is a rising number; a child is stored relative to its context, as the context's place
    times `classes` plus the child's class, so the whole level is one rising sequence.
    """

    def __init__(self, contexts: EliasFano, starts: EliasFano, children: EliasFano, own: np.ndarray, left: np.ndarray, classes: int):
        self.contexts, self.starts, self.children, self.own, self.left, self.classes = contexts, starts, children, own, left, classes

    @staticmethod
    def of(context: np.ndarray, child: np.ndarray, count: np.ndarray, top: int, classes: int) -> Level:
        """From sorted (context, child) with counts. A context seen n times before t different
        children keeps t / (n + t) for the level below; a child seen c times has c / (n + t)."""
        first = np.flatnonzero(np.concatenate([np.ones(min(1, len(context)), bool), context[1:] != context[:-1]]))
        ids, t = context[first], np.diff(np.append(first, len(context)))
        n, at = np.add.reduceat(count, first) if len(first) else count, np.repeat(np.arange(len(first)), t)
        own, whole = np.zeros(len(at), "<u2"), n + t
        for k in range(0, len(at), _READ):
            own[k : k + _READ] = quantise(count[k : k + _READ] / whole[at[k : k + _READ]])
        at *= classes
        at += child
        return Level(EliasFano.of(ids, top), EliasFano.of(np.append(first, len(child)), len(child) + 1), EliasFano.of(at, max(1, len(ids)) * classes), own, (t / (n + t)).astype("<f4"), classes)

    def whole(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All contexts, starts and children."""
        return self.contexts.whole(), self.starts.whole(), self.children.whole()

    def shares(self, context: np.ndarray, child: np.ndarray, whole: tuple | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(share of the child itself, share left for the level below) for each pair; a context that
        comes several times in a row is sought once. whole is what whole() gave, if many are asked in turns."""
        own, left = np.zeros(len(context)), np.ones(len(context))
        if not self.contexts.n or not len(context):
            return own, left
        new = np.concatenate([[True], context[1:] != context[:-1]])
        run, met = np.cumsum(new) - 1, context[new]
        contexts, starts, children = whole or (None, None, None)
        place, known = self.contexts.find(met, contexts)
        end = np.zeros(len(met), np.int64)
        end[known] = self.starts.get(place[known] + 1) if starts is None else starts[place[known] + 1]
        some = np.flatnonzero(known[run])
        k, w = place[run[some]], child[some]
        left[some] = self.left[k]
        at, found = self.children.find(k * self.classes + w, children)
        found &= at < end[run[some]]
        own[some[found]] = share(self.own[at[found]])
        return own, left

    def arrays(self) -> tuple[list[np.ndarray], list]:
        parts = [e.arrays() for e in (self.contexts, self.starts, self.children)]
        return [x for a, _ in parts for x in a] + [self.own, self.left], [self.classes, *(m for _, m in parts)]

    @staticmethod
    def from_arrays(a: list[np.ndarray], meta: list) -> Level:
        return Level(*(EliasFano.from_arrays(a[3 * k : 3 * k + 3], meta[1 + k]) for k in range(3)), a[9], a[10], meta[0])
