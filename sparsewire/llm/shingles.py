"""Hashes of word runs for whole Arrow batches of texts, without a call for each run.

The hash of a run is the sum of a random number for each byte times a power of an odd base, by its place, moved to
place zero. Sums over runs are differences of running sums, so a batch costs a few passes over its bytes. Places count
one byte between words however they are apart, so only words and their order matter.
"""

from __future__ import annotations

import numpy as np

BASE = 0x9E3779B97F4A7C15
LOW = 1 << 16
#: Bytes whose running sums are made at once.
PIECE = 1 << 18
_NUMBER = np.random.default_rng(5).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


class _Powers:
    """base ** j mod 2**64 from two tables."""

    def __init__(self, base: int) -> None:
        self.low = self._table(base)
        self.step = pow(base, LOW, 2**64)
        self.high = self._table(self.step)

    @staticmethod
    def _table(base: int) -> np.ndarray:
        out = np.full(LOW, base, np.uint64)
        out[0] = 1
        return np.cumprod(out)

    def __getitem__(self, j: np.ndarray) -> np.ndarray:
        return self.low[j & (LOW - 1)] * self.high[j >> 16]


_UP, _DOWN = _Powers(BASE), _Powers(pow(BASE, -1, 2**64))


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def shingles(texts: list[bytes | None], words: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of words, text after text, and the number of runs of each text.

    A text of fewer words is one run, a text without a word has none. A-Z count as a-z. Memory is about four times
    the bytes of the texts.
    """
    sizes = np.array([len(t or b"") + 1 for t in texts], np.int64)
    data = np.frombuffer(b"".join((t or b"") + b"\n" for t in texts).lower(), np.uint8)
    begin, end, place, where = [], [], [], []
    total, used, found, before = np.uint64(0), 0, 0, True
    for at in range(0, len(data), PIECE):
        part = data[at : at + PIECE]
        space = _SPACE[part]
        prior = np.concatenate(([before], space[:-1]))
        starts, stops = ~space & prior, space & ~prior
        j = used + np.cumsum(~space) + found + np.cumsum(starts)
        with np.errstate(over="ignore"):
            term = np.where(space, np.uint64(0), _NUMBER[part] * _UP[j])
            sums = np.cumsum(term, dtype=np.uint64) + total
            begin.append(sums[starts] - term[starts])
            end.append(np.concatenate(([total], sums[:-1]))[stops])
        place.append(j[starts])
        where.append(np.flatnonzero(starts) + at)
        total, used, found, before = sums[-1], used + int((~space).sum()), found + int(starts.sum()), bool(space[-1])
    if not begin:
        return np.zeros(0, np.uint64), np.zeros(len(texts), np.int64)
    first, last, shift = np.concatenate(begin), np.concatenate(end), np.concatenate(place)
    bounds = np.searchsorted(np.concatenate(where), np.concatenate(([0], np.cumsum(sizes))))
    n = np.diff(bounds)
    runs = np.where(n > 0, np.maximum(n - words + 1, 1), 0)
    at = np.repeat(bounds[:-1], runs) + np.arange(runs.sum()) - np.repeat(np.cumsum(runs) - runs, runs)
    stop = at + np.repeat(np.minimum(n, words), runs) - 1
    with np.errstate(over="ignore"):
        return mixed((last[stop] - first[at]) * _DOWN[shift[at]]), runs
