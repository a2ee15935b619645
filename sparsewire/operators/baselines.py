"""Stand-alone compressors that the codecs are compared with: ternary, sketched and entropy-coded quantiles."""

from __future__ import annotations

import numpy as np

from ..functions.hashing import hash_array

ZERO_BYTE, RUN_BASE, LONGEST_RUN = 121, 243, 14


def three_lc_encode(x: np.ndarray, multiplier: float = 1.0) -> tuple[float, bytes]:
    """Scale and bytes: values rounded to -1, 0 or 1 times the scale, five to a byte, runs of all-zero bytes folded."""
    scale = multiplier * float(np.abs(x).max(initial=0))
    digit = np.zeros(len(x), np.int64) if scale == 0 else np.clip(np.sign(x) * np.floor(np.abs(x) / scale + 0.5), -1, 1).astype(np.int64)
    digit = np.concatenate((digit, np.zeros(-len(digit) % 5, np.int64)))
    raw = ((digit + 1).reshape(-1, 5) @ np.array([81, 27, 9, 3, 1])).tolist()
    out, at = bytearray(), 0
    while at < len(raw):
        n = 1
        if raw[at] == ZERO_BYTE:
            while n < LONGEST_RUN and at + n < len(raw) and raw[at + n] == ZERO_BYTE:
                n += 1
        out.append(RUN_BASE + n - 2 if n > 1 else raw[at])
        at += n
    return scale, bytes(out)


def three_lc_decode(scale: float, data: bytes, d: int) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8).astype(np.int64)
    raw = np.repeat(np.where(raw >= RUN_BASE, ZERO_BYTE, raw), np.where(raw >= RUN_BASE, raw - RUN_BASE + 2, 1))
    digits = raw[:, None] // np.array([81, 27, 9, 3, 1]) % 3 - 1
    return scale * digits.ravel()[:d].astype(float)


def three_lc_encode_cells(keys: np.ndarray, values: np.ndarray, d: int, multiplier: float = 1.0) -> tuple[float, bytes]:
    """What three_lc_encode gives for a tensor of d indices, from its cells alone."""
    scale = multiplier * float(np.abs(values).max(initial=0))
    digit = np.zeros(len(keys), np.int64) if scale == 0 else np.clip(np.sign(values) * np.floor(np.abs(values) / scale + 0.5), -1, 1).astype(np.int64)
    keys, digit = keys[digit != 0], digit[digit != 0]
    at, which = np.unique(keys // 5, return_inverse=True)
    byte = np.full(len(at), ZERO_BYTE, np.int64)
    np.add.at(byte, which, digit * np.array([81, 27, 9, 3, 1])[keys % 5])
    # before each byte, and behind the last one, a run of all-zero bytes: longest runs first, then what is left
    gap = np.diff(np.concatenate((at, [-(-d // 5)])), prepend=-1) - 1
    whole, rest = np.divmod(gap, LONGEST_RUN)
    size = whole + (rest > 0) + 1
    end = np.cumsum(size)
    out = np.full(int(end[-1]) - 1, RUN_BASE + LONGEST_RUN - 2, np.uint8)
    out[end[:-1] - 1] = byte
    some = rest > 0
    out[end[some] - 2] = np.where(rest[some] == 1, ZERO_BYTE, RUN_BASE + rest[some] - 2)
    return scale, out.tobytes()


def three_lc_decode_cells(scale: float, data: bytes, d: int) -> tuple[np.ndarray, np.ndarray]:
    """The cells of what three_lc_decode gives."""
    raw = np.frombuffer(data, np.uint8).astype(np.int64)
    size = np.where(raw >= RUN_BASE, raw - RUN_BASE + 2, 1)
    some = np.flatnonzero((raw < RUN_BASE) & (raw != ZERO_BYTE))
    keys = ((np.cumsum(size) - size)[some][:, None] * 5 + np.arange(5)).ravel()
    digits = (raw[some][:, None] // np.array([81, 27, 9, 3, 1]) % 3 - 1).ravel()
    keep = (digits != 0) & (keys < d)
    return keys[keep], scale * digits[keep].astype(float)


class MinMaxSketch:
    """Bucket numbers under hashed cells: insertion keeps the least, a query takes the greatest over rows; never more than the truth."""

    def __init__(self, rows: int, cols: int, seed: int = 0) -> None:
        self.cells, self.seed = np.full((rows, cols), np.iinfo(np.int64).max), seed

    def _cols(self, keys: np.ndarray, row: int) -> np.ndarray:
        return hash_array(keys, row, self.seed, "minmax") % self.cells.shape[1]

    def insert(self, keys: np.ndarray, ids: np.ndarray) -> None:
        for r in range(len(self.cells)):
            np.minimum.at(self.cells[r], self._cols(keys, r), ids)

    def query(self, keys: np.ndarray) -> np.ndarray:
        return np.max([self.cells[r][self._cols(keys, r)] for r in range(len(self.cells))], axis=0)


class GroupedMinMaxSketch:
    """A sketch for each group of neighbouring bucket numbers, so that a query errs within its group only."""

    def __init__(self, buckets: int, groups: int, rows: int, cols: int, seed: int = 0) -> None:
        self.size = -(-buckets // groups)
        self.sketches = [MinMaxSketch(rows, max(1, cols // groups), seed) for _ in range(groups)]

    def group(self, ids: np.ndarray) -> np.ndarray:
        """Sent along with the keys: a query needs it."""
        return ids // self.size

    def insert(self, keys: np.ndarray, ids: np.ndarray) -> None:
        for g, s in enumerate(self.sketches):
            mine = self.group(ids) == g
            s.insert(keys[mine], ids[mine])

    def query(self, keys: np.ndarray, groups: np.ndarray) -> np.ndarray:
        out = np.zeros(len(keys), np.int64)
        for g, s in enumerate(self.sketches):
            if (groups == g).any():
                out[groups == g] = s.query(keys[groups == g])
        return out
