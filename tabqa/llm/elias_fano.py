"""Elias-Fano sequences of ascending integers, searched for many values at once.

The lower bits of every value are packed one after another; the upper parts are a bit vector in which each value is a one
and each step of the upper part a zero. A search finds the zeros around its upper part from counts by block and halves the values
between them by their lower bits, so that it stays short where values crowd. The arrays may lie in a memory-mapped file.
"""

from __future__ import annotations

from functools import cached_property

import numpy as np

_U = np.uint64
_BLOCK = 7  # the zeros before every 2**7 bits are counted


def _load(words: np.ndarray, bit: np.ndarray) -> np.ndarray:
    """64 bits from any bit place on."""
    at, shift = bit >> 6, (bit & 63).astype(_U)
    return (words[at] >> shift) | ((words[at + 1] << _U(1)) << (_U(63) - shift))


def pack_bits(values: np.ndarray, width: int) -> np.ndarray:
    """Values of at most `width` bits (below 64), one after another, with two words to spare."""
    n = len(values)
    out = np.zeros((n * width + 63) // 64 + 2, _U)
    if n and width:
        place = np.arange(n, dtype=np.int64) * width
        at, shift = place >> 6, (place & 63).astype(_U)
        low = values.astype(_U)
        words = int(at[-1]) + 1
        # values begin in every word, so each word's are one run
        out[:words] = np.bitwise_or.reduceat(low << shift, -(-(np.arange(words, dtype=np.int64) << 6) // width))
        spill = np.flatnonzero((place & 63) + width > 64)
        out[at[spill] + 1] |= (low[spill] >> _U(1)) >> (_U(63) - shift[spill])
    return out


def bits_at(packed: np.ndarray, i: np.ndarray, width: int) -> np.ndarray:
    """The packed values at places i."""
    if not width:
        return np.zeros(len(i), _U)
    return _load(packed, i * width) & _U((1 << width) - 1)


class EliasFano:
    def __init__(self, n: int, low_bits: int, lows: np.ndarray, uppers: np.ndarray, zeros: np.ndarray, steps: int):
        self.n, self.low_bits, self.lows, self.uppers, self.zeros, self.steps = n, low_bits, lows, uppers, zeros, steps

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        """From ascending values of 0 or more."""
        n = len(values)
        top = int(values[-1]) if n else 0
        low_bits = min(56, max(0, (top // max(1, n)).bit_length() - 1))
        highs = (values >> low_bits).astype(np.int64)
        steps = int(highs[-1]) + 1 if n else 1
        bits = np.zeros((n + steps + 64 + 63) // 64 * 64 + 64, np.uint8)
        bits[highs + np.arange(n)] = 1
        per_block = np.add.reduceat((bits == 0).astype(np.int64), np.arange(0, len(bits), 1 << _BLOCK))
        zeros = np.cumsum(per_block) - per_block
        return cls(n, low_bits, pack_bits(values & ((1 << low_bits) - 1), low_bits), np.packbits(bits, bitorder="little").view(_U), zeros, steps)

    def arrays(self) -> list[np.ndarray]:
        return [self.lows, self.uppers, self.zeros]

    def _low(self, i: np.ndarray) -> np.ndarray:
        return bits_at(self.lows, i, self.low_bits)

    @cached_property
    def ones(self) -> np.ndarray:
        """The ones before each block."""
        return (np.arange(len(self.zeros), dtype=np.int64) << _BLOCK) - self.zeros

    def _zero(self, k: np.ndarray, ones: bool = False) -> np.ndarray:
        """Bit place of the k-th zero, or one."""
        before = self.ones if ones else self.zeros
        block = np.searchsorted(before, k, "right") - 1
        at, left = block << _BLOCK, k - before[block]
        place, open_ = np.zeros(len(k), np.int64), np.arange(len(k))
        while len(open_):
            word = _load(self.uppers, at) if ones else ~_load(self.uppers, at)
            count = np.bitwise_count(word).astype(np.int64)
            inside = count > left
            if inside.any():
                w, r, off = word[inside], left[inside], np.zeros(int(inside.sum()), np.int64)
                for width in (32, 16, 8, 4, 2, 1):
                    below = np.bitwise_count(w & _U((1 << width) - 1)).astype(np.int64)
                    beyond = r >= below
                    r = np.where(beyond, r - below, r)
                    w = np.where(beyond, w >> _U(width), w)
                    off += np.where(beyond, width, 0)
                place[open_[inside]] = at[inside] + off
            stay = ~inside
            open_, at, left = open_[stay], at[stay] + 64, (left - count)[stay]
        return place

    def find(self, values: np.ndarray, at_least: bool = False) -> np.ndarray:
        """Place of each value, or -1 where it isn't held; with at_least, of the first value not smaller (n if none)."""
        values = values.astype(np.int64)
        high = values >> self.low_bits
        inside = np.flatnonzero((high < self.steps) & (values >= 0))
        out = np.full(len(values), self.n if at_least else -1, np.int64)
        if at_least:
            out[values < 0] = 0
        if not self.n or not len(inside):
            return out
        h = high[inside]
        first = np.where(h > 0, self._zero(np.maximum(h - 1, 0)) + 1, 0) - h
        end = self._zero(h) - h
        low = values[inside].astype(_U) & _U((1 << self.low_bits) - 1)
        left, right = first.copy(), end.copy()
        open_ = np.flatnonzero(left < right)
        while len(open_):  # halves what is left of each upper part's values, which ascend
            a, b = left[open_], right[open_]
            middle = (a + b) >> 1
            below = self._low(middle) < low[open_]
            a, b = np.where(below, middle + 1, a), np.where(below, b, middle)
            left[open_], right[open_] = a, b
            open_ = open_[a < b]
        if at_least:
            out[inside] = left
        else:
            held = np.flatnonzero(left < end)
            held = held[self._low(left[held]) == low[held]]
            out[inside[held]] = left[held]
        return out

    def at(self, i: np.ndarray) -> np.ndarray:
        """The values at places i."""
        return ((self._zero(i, ones=True) - i) << self.low_bits) | self._low(i).astype(np.int64)

    def values(self) -> np.ndarray:
        """All values, decoded."""
        bits = np.unpackbits(np.ascontiguousarray(self.uppers).view(np.uint8), bitorder="little")[: self.n + self.steps]
        ones = np.flatnonzero(bits)[: self.n]
        return ((ones - np.arange(self.n)) << self.low_bits) | self._low(np.arange(self.n)).astype(np.int64)
