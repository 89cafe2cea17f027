"""Content anchors of byte strings: every window of a text belongs to one anchor that its content alone chooses.

The anchor of a window is the leftmost of its grams with the least hash. Equal windows, wherever they stand, have
equal grams at equal places as anchors, so all copies of a window meet at their gram's hash, and only there. The
windows of an anchor start one after another; the bytes they cover are the anchor's context.
"""

from __future__ import annotations

import numpy as np

GRAM = 32
_rng = np.random.default_rng(977)
_BYTE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64)
_BASE = 0xD1342543DE82EF95
_INVERSE = pow(_BASE, -1, 1 << 64)
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        size = 1 << n.bit_length()
        for k, base in enumerate((_BASE, _INVERSE)):
            out = np.ones(1, np.uint64)
            with np.errstate(over="ignore"):
                while len(out) < size:
                    out = np.concatenate((out, out * np.uint64(pow(base, len(out), 1 << 64))))
            _POWERS[k] = out
    return _POWERS[0], _POWERS[1]


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads 64-bit values."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


class Prints:
    """Hashes of any stretches of a text, each in constant time."""

    def __init__(self, raw: bytes):
        letters = np.frombuffer(raw, np.uint8)
        self.power, self.inverse = _powers(len(letters) + 1)
        with np.errstate(over="ignore"):
            self.sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_BYTE[letters] * self.power[: len(letters)], dtype=np.uint64)))

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix((self.sums[ends] - self.sums[starts]) * self.inverse[starts] + (ends - starts).astype(np.uint64))


_PLACE_BITS = 24


def sliding_argmin(values: np.ndarray, width: int) -> np.ndarray:
    """Place of the leftmost least value of each window of `width` values, by their upper 40 bits."""
    if len(values) >> _PLACE_BITS:  # a very long text, in stretches that overlap
        step = (1 << _PLACE_BITS) - width
        return np.concatenate([at + sliding_argmin(values[at : at + step + width - 1], width) for at in range(0, len(values) - width + 1, step)])
    low = np.uint64((1 << _PLACE_BITS) - 1)
    best, reach = (values & ~low) | np.arange(len(values), dtype=np.uint64), 1
    while reach < width:  # windows of twice the reach, from two that may overlap
        step = min(reach, width - reach)
        best = np.minimum(best[: len(best) - step], best[step:])
        reach += step
    return (best & low).astype(np.int64)


def anchors(raw: bytes, window: int, gram: int = GRAM) -> tuple[Prints, np.ndarray, np.ndarray, np.ndarray] | None:
    """The text's hashes, and for each anchor: its place, its first and its last window. None for shorter texts."""
    if len(raw) < window:
        return None
    prints = Prints(raw)
    starts = np.arange(len(raw) - gram + 1)
    chosen = sliding_argmin(prints.of(starts, starts + gram), window - gram + 1)
    first = np.flatnonzero(np.concatenate(([True], chosen[1:] != chosen[:-1])))
    last = np.append(first[1:], len(chosen)) - 1
    return prints, chosen[first], first, last


def signatures(raw: bytes, window: int, gram: int = GRAM):
    """(gram hash, context hash, first window, last window) of every anchor; None for shorter texts.

    The context's hash also holds the anchor's place in it.
    """
    found = anchors(raw, window, gram)
    if found is None:
        return None
    prints, at, first, last = found
    with np.errstate(over="ignore"):
        context = mix(prints.of(first, last + window) + (at - first).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return prints.of(at, at + gram), context, first, last
