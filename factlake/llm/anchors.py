"""Content-defined anchors of byte strings, and hashes of byte ranges.

The anchor of a ``WIDTH``-byte window is the ``GRAM``-byte string in it with the least hash, the
leftmost of equals. It depends on the window's bytes alone, so equal windows have equal anchors at
equal places. Neighbouring windows mostly share their anchor; a stretch of such windows is a run.
"""

from __future__ import annotations

import numpy as np

WIDTH, GRAM = 100, 32
SPAN = WIDTH - GRAM + 1  # places of an anchor in a window
SLICE = (1 << 20) - 2 * WIDTH  # places fit in the low 20 bits of a selection key
_LOW = np.uint64((1 << 20) - 1)
_tables: dict[str, np.ndarray] = {}


def _powers() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte values, powers of an odd base, and of its inverse, modulo 2**64."""
    if not _tables:
        rng = np.random.default_rng(17)
        n = SLICE + 2 * WIDTH
        base = 0x9E3779B97F4A7C15
        for name, b in (("up", base), ("down", pow(base, -1, 1 << 64))):
            p = np.ones(n, np.uint64)
            p[1:] = np.uint64(b)
            _tables[name] = np.multiply.accumulate(p)
        _tables["value"] = rng.integers(1, 2**63, 256, dtype=np.uint64)
    return _tables["value"], _tables["up"], _tables["down"]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


def spread(h: np.ndarray) -> np.ndarray:
    """Even values again for hashes that were chosen for being small."""
    return _mixed(h * np.uint64(0x9E3779B97F4A7C15) + np.uint64(0x94D049BB133111EB))


class Sums:
    """Prefix sums of a byte string: hashes of any of its ranges in one step."""

    def __init__(self, data: np.ndarray):
        value, up, self.down = _powers()
        self.p = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(value[data] * up[: len(data)], out=self.p[1:])

    def hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mixed((self.p[end] - self.p[start]) * self.down[start])


def runs(data: np.ndarray) -> tuple[Sums, np.ndarray, np.ndarray, np.ndarray]:
    """Of at most SLICE bytes: their sums, and each run's anchor place, first window and last window."""
    sums, n = Sums(data), len(data)
    grams = n - GRAM + 1
    h = _mixed((sums.p[GRAM:] - sums.p[:grams]) * sums.down[:grams])
    key = (h & ~_LOW) | np.arange(grams, dtype=np.uint64)
    rows = -(-grams // SPAN) + 1
    k = np.full(rows * SPAN, np.iinfo(np.uint64).max, np.uint64)
    k[:grams] = key
    k = k.reshape(rows, SPAN)
    before = np.minimum.accumulate(k, axis=1).ravel()
    after = np.minimum.accumulate(k[:, ::-1], axis=1)[:, ::-1].ravel()
    windows = n - WIDTH + 1
    least = np.minimum(after[:windows], before[SPAN - 1 : SPAN - 1 + windows])
    at = (least & _LOW).astype(np.int64)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    return sums, at[first], first, np.concatenate((first[1:], [windows])) - 1
