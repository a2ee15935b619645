"""Value codecs of one block: an array of values to bytes and back.

``encode`` may reorder: then it gives, for each rank, the position of its value, and the pipeline either writes explicit
keys in that order or packs the ranks of the positions as a map of ceil(log2 n) bits each.
"""

from __future__ import annotations

import math
import struct
import zlib
from abc import ABC, abstractmethod
from collections.abc import Iterable, Sequence
from dataclasses import dataclass

import numpy as np

from ..functions.hashing import PRIME, hash_array
from . import bits as b
from .curve import double_exponential, fit_double_exponential, fit_double_exponentials, gram_fit, gram_value, segments


@dataclass
class Packed:
    payload: bytes
    bits: int
    order: np.ndarray | None = None  # position of each rank


class ValueCodec(ABC):
    name = "value"
    reorders = False
    #: How many blocks encode_many gains from at once.
    together = 1

    @abstractmethod
    def encode(self, values: np.ndarray) -> Packed: ...

    def encode_many(self, values: Sequence[np.ndarray]) -> Iterable[Packed]:
        """What encode gives for each; codecs override it where blocks can share work."""
        return map(self.encode, values)

    @abstractmethod
    def decode(self, payload: bytes, n: int) -> np.ndarray:
        """n values, by rank if the codec reorders."""


class RawValues(ValueCodec):
    name = "none"

    def encode(self, values):
        return Packed(values.astype("<f4").tobytes(), 32 * len(values))

    def decode(self, payload, n):
        return np.frombuffer(payload, "<f4").astype(float)


class HalfValues(ValueCodec):
    """16-bit floats of the values over a 32-bit scale, so that none overflows."""

    name = "half"

    def encode(self, values):
        scale = np.float32(np.abs(values).max(initial=0) or 1)
        return Packed(scale.tobytes() + (values / float(scale)).astype("<f2").tobytes(), 16 * len(values) + 32)

    def decode(self, payload, n):
        return np.frombuffer(payload[4:], "<f2").astype(float) * float(np.frombuffer(payload[:4], "<f4")[0])


class Deflate(ValueCodec):
    name = "deflate"

    def __init__(self, level: int = 6) -> None:
        self.level = level

    def encode(self, values):
        payload = zlib.compress(values.astype("<f4").tobytes(), self.level)
        return Packed(payload, 8 * len(payload))

    def decode(self, payload, n):
        return np.frombuffer(zlib.decompress(payload), "<f4").astype(float)


class Qsgd(ValueCodec):
    """Levels of each value's share of its bucket's norm, rounded up with the probability of the rest."""

    def __init__(self, bits: int = 7, bucket: int = 512, seed: int = 0, rounding: str = "stochastic") -> None:
        self.width, self.bucket, self.seed, self.rounding = bits, bucket, seed, rounding
        self.name = f"qsgd({bits},{bucket})"

    def encode(self, values):
        n, s = len(values), 2 ** (self.width - 1) - 1
        some = np.flatnonzero(values)
        if 8 * len(some) < n:
            return self.encode_few(some, values[some], n)
        which = np.arange(n) // self.bucket
        norm = np.sqrt(np.bincount(which, values * values)).astype("<f4").astype(float) if n else np.zeros(0)
        u = (hash_array(np.arange(n), 0, self.seed, "qsgd") + 0.5) / PRIME if self.rounding == "stochastic" else 0.5
        scale = norm[which]
        level = np.minimum(s, np.floor(np.divide(s * np.abs(values), scale, out=np.zeros(n), where=scale > 0) + u)).astype(np.int64)
        level[scale == 0] = 0
        coded = level + (values < 0) * (s + 1)
        return Packed(norm.astype("<f4").tobytes() + b.pack(coded, self.width), self.width * n + 32 * len(norm))

    def encode_few(self, at: np.ndarray, values: np.ndarray, n: int) -> Packed:
        """The same for n values that are 0 except at some places, in order: the level of 0 is 0."""
        s, buckets = 2 ** (self.width - 1) - 1, -(-n // self.bucket)
        norm = np.sqrt(np.bincount(at // self.bucket, values * values, buckets)).astype("<f4").astype(float)
        u = (hash_array(at, 0, self.seed, "qsgd") + 0.5) / PRIME if self.rounding == "stochastic" else 0.5
        scale = norm[at // self.bucket]
        level = np.minimum(s, np.floor(np.divide(s * np.abs(values), scale, out=np.zeros(len(at)), where=scale > 0) + u)).astype(np.int64)
        level[scale == 0] = 0
        return Packed(norm.astype("<f4").tobytes() + b.pack_few(at, level + (values < 0) * (s + 1), self.width, n), self.width * n + 32 * buckets)

    def decode(self, payload, n):
        buckets, s = -(-n // self.bucket), 2 ** (self.width - 1) - 1
        norm = np.frombuffer(payload[: 4 * buckets], "<f4").astype(float)
        coded = b.unpack(payload[4 * buckets :], self.width, n)
        level = coded % (s + 1)
        return np.where(coded > s, -1, 1) * norm[np.arange(n) // self.bucket] * level / s if n else np.zeros(0)


    def decode_few(self, payload: bytes, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, values) of what decode gives, zeros left out."""
        buckets, s = -(-n // self.bucket), 2 ** (self.width - 1) - 1
        few = b.unpack_few(memoryview(payload)[4 * buckets :], self.width, n)
        if few is None:
            values = self.decode(payload, n)
            return np.flatnonzero(values), values[values != 0]
        at, coded = few
        norm = np.frombuffer(payload[: 4 * buckets], "<f4").astype(float)
        values = np.where(coded > s, -1, 1) * norm[at // self.bucket] * (coded % (s + 1)) / s
        return at[values != 0], values[values != 0]


def sorted_order(values: np.ndarray, order: str) -> np.ndarray:
    """Positions by value or magnitude, descending, ties by position."""
    key = np.abs(values) if order == "magnitude" else values
    return np.argsort(-key, kind="stable")


class FitPoly(ValueCodec):
    """Least squares of a degree on each segment of the sorted curve, positives and negatives apart.

    Wire: for each sign the ends of its segments and degree + 1 float32 coefficients of orthogonal polynomials each.
    """

    reorders = True

    def __init__(self, degree: int = 5, pieces: int = 8, order: str = "value", split: str = "largest") -> None:
        self.degree, self.pieces, self.order, self.split = degree, pieces, order, split
        self.name = f"fit_poly({degree},{pieces})"

    def encode(self, values):
        rank = sorted_order(values, self.order)
        y = values[rank]
        signs = None
        if self.order == "magnitude":
            signs, y = y < 0, np.abs(y)
        up = len(y) if signs is not None else int((y > 0).sum())
        out, size = [struct.pack("<I", up)], 0
        parts = [p for p in (y[:up], y[up:]) if len(p)]
        share = [max(1, round(self.pieces * len(p) / len(y))) for p in parts]
        for p, k in zip(parts, share, strict=True):
            ends = segments(p, k, self.degree + 1, self.split)
            out.append(struct.pack(f"<I{len(ends)}I", len(ends), *ends))
            for a, e in zip([0, *ends[:-1]], ends, strict=True):
                out.append(gram_fit(p[a:e], self.degree).astype("<f4").tobytes())
            size += 32 * (self.degree + 1) * len(ends) + 32 * (len(ends) - 1)
        if signs is not None:
            out.append(np.packbits(signs).tobytes())
            size += len(y)
        return Packed(b"".join(out), size, rank)

    def decode(self, payload, n):
        (up,), at, out = struct.unpack_from("<I", payload), 4, []
        for size in [x for x in (up, n - up) if x]:
            (k,) = struct.unpack_from("<I", payload, at)
            ends = struct.unpack_from(f"<{k}I", payload, at + 4)
            at += 4 + 4 * k
            for a, e in zip((0, *ends[:-1]), ends, strict=True):
                coef = np.frombuffer(payload, "<f4", self.degree + 1, at).astype(float)
                at += 4 * (self.degree + 1)
                out.append(gram_value(coef, e - a))
        y = np.concatenate(out) if out else np.zeros(0)
        if self.order == "magnitude" and n:
            y = np.where(np.unpackbits(np.frombuffer(payload[at:], np.uint8), count=n), -y, y)
        return y


class FitDoubleExp(ValueCodec):
    """Four numbers for the whole sorted curve; by magnitude with a sign bit each, or by value per sign."""

    reorders = True
    together = 32

    def __init__(self, order: str = "magnitude", iters: int = 40) -> None:
        if order not in ("magnitude", "value", "value_per_sign"):
            raise ValueError(order)
        self.order, self.iters = order, iters
        self.name = "fit_dexp" if order == "magnitude" else f"fit_dexp({order})"

    def _part(self, y: np.ndarray) -> tuple[bytes, int]:
        if len(y) < 5:
            return b"\0" + y.astype("<f4").tobytes(), 32 * len(y)
        return b"\1" + fit_double_exponential(y, self.iters).astype("<f4").tobytes(), 128

    def encode(self, values):
        rank = sorted_order(values, "magnitude" if self.order == "magnitude" else "value")
        y = values[rank]
        if self.order == "magnitude":
            body, size = self._part(np.abs(y))
            return Packed(body + np.packbits(y < 0).tobytes(), size + len(y), rank)
        up = int((y > 0).sum()) if self.order == "value_per_sign" else len(y)
        parts = [self._part(p) for p in (y[:up], y[up:]) if len(p)]
        return Packed(struct.pack("<I", up) + b"".join(p for p, _ in parts), sum(s for _, s in parts), rank)

    def encode_many(self, values):
        n = len(values[0])
        if self.order != "magnitude" or n < 5 or any(len(v) != n for v in values):
            return map(self.encode, values)
        ranks = [sorted_order(v, "magnitude") for v in values]
        fits = fit_double_exponentials(np.stack([np.abs(v[rank]) for v, rank in zip(values, ranks, strict=True)]), self.iters)
        return [Packed(b"\1" + fit.astype("<f4").tobytes() + np.packbits(v[rank] < 0).tobytes(), 128 + n, rank) for v, rank, fit in zip(values, ranks, fits, strict=True)]

    @staticmethod
    def _back(payload: bytes, at: int, n: int) -> tuple[np.ndarray, int]:
        if payload[at] == 0:
            return np.frombuffer(payload, "<f4", n, at + 1).astype(float), at + 1 + 4 * n
        return double_exponential(np.linspace(0, 1, n), np.frombuffer(payload, "<f4", 4, at + 1).astype(float)), at + 17

    def decode(self, payload, n):
        if not n:
            return np.zeros(0)
        if self.order == "magnitude":
            y, at = self._back(payload, 0, n)
            return np.where(np.unpackbits(np.frombuffer(payload[at:], np.uint8), count=n), -y, y)
        (up,), at, out = struct.unpack_from("<I", payload), 4, []
        for size in [x for x in (up, n - up) if x]:
            y, at = self._back(payload, at, size)
            out.append(y)
        return np.concatenate(out)


class SortedValues(ValueCodec):
    """Values down the sorted curve, as they are; what the map of their places costs is all that it adds."""

    name, reorders = "sorted", True

    def encode(self, values):
        order = np.argsort(-values, kind="stable")
        return Packed(values[order].astype("<f4").tobytes(), 32 * len(values), order)

    def decode(self, payload, n):
        return np.frombuffer(payload, "<f4").astype(float)


class QuantileBuckets(ValueCodec):
    """Buckets of equal count over the sorted values; a value becomes its bucket's mean.

    split_sign: half of the buckets for each sign, so no bucket holds both and no value changes its sign.
    """

    def __init__(self, q: int = 64, huffman: bool = False, split_sign: bool = False) -> None:
        self.q, self.huffman, self.split_sign = q, huffman, split_sign
        self.name = f"quantile{'_huffman' if huffman else ''}{'_signs' if split_sign else ''}({q})"

    def _sizes(self, values: np.ndarray) -> np.ndarray:
        parts = [(len(values), self.q)]
        if self.split_sign:
            below = int((values < 0).sum())
            parts = [(below, self.q // 2), (len(values) - below, self.q - self.q // 2)]
        return np.concatenate([n // q + (np.arange(q) < n % q) for n, q in parts]).astype(np.int64)

    def encode(self, values):
        from .index_codecs import canonical

        n = len(values)
        rank = np.argsort(values, kind="stable")
        sizes = self._sizes(values)
        bucket = np.empty(n, np.int64)
        bucket[rank] = np.repeat(np.arange(self.q), sizes)
        sums = np.bincount(bucket, values, self.q)
        table = np.divide(sums, sizes, out=np.zeros(self.q), where=sizes > 0).astype("<f4")
        width = max(1, math.ceil(math.log2(self.q)))
        if not self.huffman:
            return Packed(table.tobytes() + b.pack(bucket, width), width * n + 32 * self.q)
        lengths = b.prefix_lengths({k: int(s) for k, s in enumerate(sizes) if s}) if n else {}
        body, used = b.huffman_encode(bucket, canonical(lengths)) if n else (b"", 0)
        return Packed(table.tobytes() + bytes(lengths.get(k, 0) for k in range(self.q)) + body, used + 40 * self.q)

    def decode(self, payload, n):
        from .index_codecs import canonical

        table = np.frombuffer(payload[: 4 * self.q], "<f4").astype(float)
        body = payload[4 * self.q :]
        if not self.huffman:
            return table[b.unpack(body, max(1, math.ceil(math.log2(self.q))), n)]
        lengths = {k: x for k, x in enumerate(body[: self.q]) if x}
        return table[b.huffman_decode(body[self.q :], canonical(lengths), n)] if n else np.zeros(0)


def pack_map(order: np.ndarray) -> tuple[bytes, int]:
    """Rank of each position, in ceil(log2 n) bits."""
    n = len(order)
    width = max(0, math.ceil(math.log2(n))) if n > 1 else 0
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    return b.pack(rank, width), width * n


def unpack_map(payload: bytes, n: int) -> np.ndarray:
    return b.unpack(payload, max(0, math.ceil(math.log2(n))) if n > 1 else 0, n)
