"""Rolling polynomial hashes and window minimizers over bytes, in numpy."""

from __future__ import annotations

import numpy as np

#: Multiplier of the polynomial (odd, so it has an inverse modulo 2^64) and the seed of the byte table.
BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(BASE), -1, 1 << 64))
_TABLE = np.random.default_rng(20240).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[str, np.ndarray] = {}


def powers(n: int, inverse: bool = False) -> np.ndarray:
    name = "inverse" if inverse else "base"
    have = _POWERS.get(name, np.ones(1, np.uint64))
    while len(have) < n:
        step = np.uint64(pow(int(_INVERSE if inverse else BASE), len(have), 1 << 64))
        have = np.concatenate([have, have * step])
    if len(have) <= 1 << 21:
        _POWERS[name] = have
    return have[:n]


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


class PrefixHash:
    """Hash of any substring of data in constant time."""

    def __init__(self, data: np.ndarray):
        n = len(data)
        self.h = np.zeros(n + 1, np.uint64)
        np.cumsum(_TABLE[data] * powers(n), out=self.h[1:])
        self.inverse = powers(n + 1, inverse=True)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Raw value, equal for equal strings; not mixed."""
        return (self.h[end] - self.h[start]) * self.inverse[start]

    def grams(self, k: int) -> np.ndarray:
        return mixed((self.h[k:] - self.h[:-k]) * self.inverse[: len(self.h) - k])


def minimizer_runs(hashes: np.ndarray, starts: np.ndarray, sizes: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows that share their minimizer: (first window, windows, minimizer place), within each text.

    hashes: of the gram-byte strings at every place of the joined texts; a window's minimizer is its gram of the
    least upper 32 hash bits, the leftmost of equals.
    """
    n, w = len(hashes), window - gram + 1
    ok = sizes >= window
    starts, sizes = starts[ok], sizes[ok]
    if not len(starts) or n < w:
        return (np.empty(0, np.int64),) * 3
    least = (hashes & np.uint64(0xFFFFFFFF00000000)) | np.arange(n, dtype=np.uint64)
    span = 1
    while span * 2 <= w:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    least = np.minimum(least[: n - w + 1], least[w - span :]) if w > span else least
    place = (least & np.uint64(0xFFFFFFFF)).astype(np.int64)
    # a run ends where the minimizer changes and at each text's last window
    inside = np.zeros(len(place) + 1, np.int64)
    np.add.at(inside, starts, 1)
    np.add.at(inside, starts + sizes - window + 1, -1)
    valid = np.cumsum(inside)[:-1] > 0
    change = np.ones(len(place), bool)
    change[1:] = place[1:] != place[:-1]
    change[starts] = True
    change[1:] |= valid[1:] != valid[:-1]
    edge = np.flatnonzero(change)
    length = np.diff(np.append(edge, len(place)))
    keep = valid[edge]
    first = edge[keep]
    return first, length[keep], place[first]
