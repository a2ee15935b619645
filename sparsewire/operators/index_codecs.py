"""Index codecs of one block: sorted keys in [0, d) to bytes and back.

Kernels for Arrow groups; the relational forms of the filters, bitmaps, runs and gaps are in bloom.py, sparsify.py and
relational.py. ``encode`` gives the payload, its size in bits, the indices whose values must be sent and, for the naive
policy, that the values are those of the true keys.
"""

from __future__ import annotations

import math
from abc import ABC, abstractmethod
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass

from functools import lru_cache

import numpy as np

from ..functions.hashing import hash_array
from . import bits as b
from .bloom import bloom_size


@dataclass
class Encoded:
    payload: bytes
    bits: int
    sent: np.ndarray
    meta_bits: int = 64


class IndexCodec(ABC):
    """Users add codecs by overriding encode and decode; explicit says whether keys may be sent in any order."""

    name = "index"
    explicit = False

    @abstractmethod
    def encode(self, keys: np.ndarray, d: int, block: int = 0) -> Encoded: ...

    @abstractmethod
    def decode(self, payload: bytes, d: int, r: int, n_values: int, block: int = 0) -> np.ndarray:
        """The indices that the values belong to, in the order in which values are sent."""

    def encode_many(self, keys: Sequence[np.ndarray], d: int, block: int = 0) -> Iterable[Encoded]:
        """What encode gives for each of equally many keys; codecs override it where blocks can share work."""
        return (self.encode(k, d, block) for k in keys)

    def decode_many(self, payloads: Sequence[bytes], d: int, r: int, n_values: Sequence[int], block: int = 0) -> Iterable[np.ndarray]:
        return (self.decode(p, d, r, n, block) for p, n in zip(payloads, n_values, strict=True))


class RawKeys(IndexCodec):
    name, explicit = "raw", True

    def __init__(self, width: int = 32) -> None:
        self.width = width

    def encode(self, keys, d, block=0):
        return Encoded(b.pack(keys, self.width), self.width * len(keys), keys)

    def decode(self, payload, d, r, n_values, block=0):
        return b.unpack(payload, self.width, r)


class BitmapKeys(IndexCodec):
    name = "bitmap"

    def encode(self, keys, d, block=0):
        data = np.zeros(-(-d // 8), np.uint8)
        np.bitwise_or.at(data, keys >> 3, (128 >> (keys & 7)).astype(np.uint8))
        return Encoded(data.tobytes(), d, keys)

    def decode(self, payload, d, r, n_values, block=0):
        data = np.frombuffer(payload, np.uint8)
        some = np.flatnonzero(data)
        byte, bit = np.divmod(np.flatnonzero(np.unpackbits(data[some])), 8)
        return some[byte] * 8 + bit


def runs_of(keys: np.ndarray, d: int) -> tuple[int, np.ndarray]:
    """First symbol and lengths of the alternating runs of the bitmap of sorted keys."""
    apart = np.flatnonzero(keys[1:] != keys[:-1] + 1)
    cut = np.stack((keys[np.concatenate(([0], apart + 1))], keys[np.concatenate((apart, [len(keys) - 1]))] + 1), axis=1).ravel() if len(keys) else np.zeros(0, np.int64)
    return int(len(keys) > 0 and keys[0] == 0), np.diff(np.concatenate(([0], cut[(cut > 0) & (cut < d)], [d])))


class RunLength(IndexCodec):
    name = "rle"

    def __init__(self, count: str = "gamma") -> None:
        if count not in ("gamma", "varint", "fixed32"):
            raise ValueError(count)
        self.count = count

    def encode(self, keys, d, block=0):
        first, runs = runs_of(keys, d)
        if self.count == "gamma":
            body, size = b.gamma_encode(runs), b.gamma_bits(runs)
        elif self.count == "varint":
            body = bytes(x for v in runs.tolist() for x in _varint(v))
            size = 8 * len(body)
        else:
            body, size = runs.astype("<u4").tobytes(), 32 * len(runs)
        return Encoded(bytes([first]) + len(runs).to_bytes(4, "little") + body, size + 1, keys)

    def decode(self, payload, d, r, n_values, block=0):
        first, n, body = payload[0], int.from_bytes(payload[1:5], "little"), payload[5:]
        if self.count == "gamma":
            runs = b.gamma_decode(body, n)
        elif self.count == "varint":
            runs = np.array(list(_varints(body)), np.int64)
        else:
            runs = np.frombuffer(body, "<u4").astype(np.int64)
        start, size = (np.cumsum(runs) - runs)[1 - first :: 2], runs[1 - first :: 2]
        return np.arange(size.sum()) + np.repeat(start - (np.cumsum(size) - size), size)


def _varint(v: int) -> list[int]:
    out = []
    while v > 127:
        out.append(v & 127 | 128)
        v >>= 7
    return [*out, v]


def _varints(data: bytes):
    v = shift = 0
    for x in data:
        v |= (x & 127) << shift
        shift += 7
        if x < 128:
            yield v
            v = shift = 0


class HuffmanKeys(IndexCodec):
    """Four bytes of each key under a code that both ends derive from d."""

    name, explicit = "huffman", True

    def encode(self, keys, d, block=0):
        payload, size = b.huffman_encode(keys.astype(">u4").view(np.uint8), b.huffman_code(b.byte_frequencies(d)))
        return Encoded(payload, size, keys)

    def decode(self, payload, d, r, n_values, block=0):
        got = b.huffman_decode(payload, b.huffman_code(b.byte_frequencies(d)), 4 * r)
        return got.astype(np.uint8).view(">u4").astype(np.int64)


def gap_bytes(gaps: np.ndarray) -> np.ndarray:
    return np.maximum(1, np.ceil(np.log2(gaps.astype(float) + 1) / 8 - 1e-12)).astype(np.int64)


def bytes_of(gaps: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The given number of bytes of each gap, least significant first, one gap after the other."""
    start, out = np.cumsum(size) - size, np.zeros(int(size.sum()), np.uint8)
    for i in range(int(size.max(initial=0))):
        some = size > i
        out[start[some] + i] = gaps[some] >> 8 * i & 255
    return out


def gaps_of(raw: np.ndarray, size: np.ndarray) -> np.ndarray:
    start, gaps = np.cumsum(size) - size, np.zeros(len(size), np.int64)
    for i in range(int(size.max(initial=0))):
        some = size > i
        gaps[some] |= raw[start[some] + i].astype(np.int64) << 8 * i
    return gaps


class DeltaKeys(IndexCodec):
    """Gaps to the previous key in as few bytes as each needs, with two bits for their number."""

    name = "delta"

    def encode(self, keys, d, block=0):
        gaps = np.diff(keys, prepend=-1)
        size = gap_bytes(gaps)
        body = bytes_of(gaps, size).tobytes()
        return Encoded(b.pack(size - 1, 2) + body, int(8 * size.sum() + 2 * len(keys)), keys)

    def decode(self, payload, d, r, n_values, block=0):
        head = -(-2 * r // 8)
        size = b.unpack(payload[:head], 2, r) + 1
        return np.cumsum(gaps_of(np.frombuffer(payload, np.uint8, offset=head), size)) - 1


class DeltaHuffmanKeys(IndexCodec):
    """Bytes of the gaps under a Huffman code that is sent along, a length for each byte value that occurs."""

    name = "delta_huffman"

    def encode(self, keys, d, block=0):
        gaps = np.diff(keys, prepend=-1)
        size = gap_bytes(gaps)
        raw = bytes_of(gaps, size)
        values, counts = np.unique(raw, return_counts=True)
        freqs = dict(zip(values.tolist(), counts.tolist(), strict=True))
        lengths = b.prefix_lengths(freqs) if freqs else {}
        body, n = b.huffman_encode(raw, canonical(lengths)) if len(raw) else (b"", 0)
        table = bytes(x for pair in lengths.items() for x in pair)
        head = b.pack(size - 1, 2)
        return Encoded(len(table).to_bytes(2, "little") + table + head + body, n + 2 * len(keys) + 8 * len(table), keys)

    def decode(self, payload, d, r, n_values, block=0):
        n = int.from_bytes(payload[:2], "little")
        lengths = dict(zip(payload[2 : 2 + n : 2], payload[3 : 2 + n : 2], strict=True))
        head = 2 + n + -(-2 * r // 8)
        size = b.unpack(payload[2 + n : head], 2, r) + 1
        raw = b.huffman_decode(payload[head:], canonical(lengths), int(size.sum())) if r else np.zeros(0, np.int64)
        return np.cumsum(gaps_of(raw, size)) - 1


def canonical(lengths: dict[int, int]) -> dict[int, str]:
    return dict(_canonical(tuple(lengths.items())))


@lru_cache(maxsize=1024)
def _canonical(lengths: tuple[tuple[int, int], ...]) -> dict[int, str]:
    code, last, out = 0, 0, {}
    for s, n in sorted(lengths, key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[s] = format(code, f"0{n}b")
        code, last = code + 1, n
    return out


POLICIES = ("naive", "p0", "p1", "p2", "left", "middle", "right")


#: Most bytes of a table of hashes; a larger domain is hashed each time.
TABLE_BYTES = 1 << 30


@lru_cache(maxsize=4)
def hash_table(d: int, k: int, seed: int, block: int) -> np.ndarray | None:
    """The k hashes of every index of [0, d), four bytes each, made once for a worker; none if it would be too large.

    Filters of any number of bits share it, since a position is the hash modulo that number.
    """
    if 4 * d * k > TABLE_BYTES:
        return None
    return np.stack([hash_array(np.arange(d), j, seed, "bloom", block).astype(np.uint32) for j in range(k)])


@lru_cache(maxsize=1)
def _domain(d: int, k: int, seed: int, block: int) -> np.ndarray:
    return np.stack([hash_array(np.arange(d), j, seed, "bloom", block).astype(np.uint32) for j in range(k)])


#: Most bytes of a domain's hashes that are kept from one scan to the next, indices of a stretch, filters of a word.
KEPT_BYTES, STRETCH, WORD = 128 << 20, 1 << 16, 64


def _places(j: int, lo: int, hi: int, m: int, d: int, k: int, seed: int, block: int) -> np.ndarray:
    """Bits that the j-th hash gives to a stretch of indices."""
    if 4 * d * k <= KEPT_BYTES:
        return (_domain(d, k, seed, block % 65_536)[j, lo:hi] % np.uint32(m)).astype(np.intp)
    return hash_array(np.arange(lo, hi), j, seed, "bloom", block) % m


def _words(flags: np.ndarray) -> np.ndarray:
    """A word for each bit of up to 64 filters."""
    columns = np.zeros((flags.shape[1], WORD), np.uint8)
    columns[:, : len(flags)] = flags.T
    return np.packbits(columns, axis=1, bitorder="little").view(np.uint64).ravel()


class Accepted:
    """The indices of [0, d) that a filter accepts, as a bit each: for filters that accept a large share of them."""

    def __init__(self, bits: np.ndarray) -> None:
        self.words = bits.view(np.uint64)
        count = np.bitwise_count(self.words)
        self.ends = np.cumsum(count, dtype=np.int64)
        self.starts = self.ends - count

    def __len__(self) -> int:
        return int(self.ends[-1])

    def rank(self, keys: np.ndarray) -> np.ndarray:
        """How many are less than each."""
        below = (np.uint64(1) << (keys & 63).astype(np.uint64)) - np.uint64(1)
        return self.starts[keys >> 6] + np.bitwise_count(self.words[keys >> 6] & below)

    def nth(self, rank: np.ndarray) -> np.ndarray:
        """The index of each rank."""
        word = np.searchsorted(self.ends, rank, "right")
        bits = np.unpackbits(self.words[word].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        seen = np.cumsum(bits, axis=1, dtype=np.uint8)
        return word * 64 + (seen <= (rank - self.starts[word])[:, None]).sum(axis=1)


def accepted_of(flags: np.ndarray, d: int, k: int, seed: int, block: int) -> Iterator[Accepted]:
    """What positives_of gives, in bits."""
    for a in range(0, len(flags), WORD):
        some = flags[a : a + WORD]
        w, bits = _words(some), np.zeros((len(some), -(-d // 64) * 8), np.uint8)
        for lo in range(0, d, STRETCH):
            hi = min(d, lo + STRETCH)
            held = w.take(_places(0, lo, hi, flags.shape[1], d, k, seed, block))
            for j in range(1, k):
                held &= w.take(_places(j, lo, hi, flags.shape[1], d, k, seed, block))
            rows = np.ascontiguousarray(held.view(np.uint8).reshape(-1, 8).T)
            for t in range(len(some)):
                bits[t, lo >> 3 : -(-hi // 8)] = np.packbits(rows[t >> 3] & np.uint8(1 << (t & 7)), bitorder="little")
        yield from map(Accepted, bits)


def positives_of(flags: np.ndarray, d: int, k: int, seed: int, block: int) -> Iterator[np.ndarray]:
    """The indices of [0, d) that each row's filter accepts.

    Filters of equally many bits hash an index to the same bits: hashes are made once, and 64 filters are tested at
    once by ANDs of words that hold one bit of each.
    """
    for a in range(0, len(flags), 4 * WORD):
        some = flags[a : a + 4 * WORD]
        words = [_words(some[b_ : b_ + WORD]) for b_ in range(0, len(some), WORD)]
        # about half of the bits are set: after so many tests few indices are left in any filter
        full = min(k, 1 + len(some[:WORD]).bit_length())
        found: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in words]
        for lo in range(0, d, STRETCH):
            hi = min(d, lo + STRETCH)
            places = [_places(j, lo, hi, flags.shape[1], d, k, seed, block) for j in range(k)]
            for w, out in zip(words, found, strict=True):
                held = w.take(places[0])
                for j in range(1, full):
                    held &= w.take(places[j])
                left = np.flatnonzero(held)
                held = held[left]
                for j in range(full, k):
                    held &= w.take(places[j].take(left))
                keep = np.flatnonzero(held)
                out.append((left[keep] + lo, held[keep]))
        for b_, out in zip(range(0, len(some), WORD), found, strict=True):
            at, held = (np.concatenate(x) for x in zip(*out, strict=True))
            rows = np.ascontiguousarray(held.view(np.uint8).reshape(-1, 8).T)
            for t in range(len(some[b_ : b_ + WORD])):
                yield at[np.flatnonzero(rows[t >> 3] & np.uint8(1 << (t & 7)))]


class BloomKeys(IndexCodec):
    """A filter of the keys; the receiver scans [0, d) and applies the same policy from the filter and seed alone.

    lookup: True reads hashes from a table of the whole domain instead of computing them; an array is a table of
    one's own, a row for each hash function.
    """

    #: A dict that codecs of one block share: what was chosen from a filter, by all that decides it.
    shared: dict | None = None

    def __init__(self, fpr: float, policy: str = "p0", seed: int = 0, lookup: bool | np.ndarray = False) -> None:
        if policy not in POLICIES:
            raise ValueError(policy)
        self.fpr, self.policy, self.seed, self.lookup = fpr, policy, seed, lookup
        self.name = f"bloom_{policy}({fpr:g})"

    def _table(self, d: int, k: int, block: int) -> np.ndarray | None:
        if isinstance(self.lookup, np.ndarray):
            return self.lookup
        return hash_table(d, k, self.seed, block % 65_536) if self.lookup else None

    def hashes(self, keys: np.ndarray, j: int, block: int, table: np.ndarray | None = None) -> np.ndarray:
        return hash_array(keys, j, self.seed, "bloom", block) if table is None else table[j].take(keys).astype(np.int64)

    def positions(self, keys: np.ndarray, m: int, k: int, block: int, table: np.ndarray | None = None) -> np.ndarray:
        return np.stack([self.hashes(keys, j, block, table) % m for j in range(k)])

    def _positives(self, flags: np.ndarray, d: int, k: int, block: int) -> np.ndarray:
        left, table = np.arange(d), self._table(d, k, block)
        for j in range(k):
            left = left[flags[self.hashes(left, j, block, table) % len(flags)] == 1]
        return left

    def encode(self, keys, d, block=0):
        if not len(keys):
            return Encoded(b"", 0, keys)
        m, k = bloom_size(len(keys), self.fpr)
        flags = np.zeros(m, np.uint8)
        flags[self.positions(keys, m, k, block, self._table(d, k, block)).ravel()] = 1
        sent = keys if self.policy == "naive" else self._choose(flags, d, len(keys), k, block)
        return Encoded(np.packbits(flags).tobytes(), m, sent, 256)

    def decode(self, payload, d, r, n_values, block=0):
        if not r:
            return np.zeros(0, np.int64)
        m, k = bloom_size(r, self.fpr)
        return self._choose(np.unpackbits(np.frombuffer(payload, np.uint8), count=m), d, r, k, block)

    @property
    def dense(self) -> bool:
        """Whether so many are sent that they are better known by bits."""
        return self.policy == "p0" and self.fpr >= 0.1 and not self._alone and self.shared is None

    def accepted_many(self, payloads: Sequence[bytes], d: int, r: int, block: int = 0) -> Iterator[Accepted]:
        m, k = bloom_size(r, self.fpr)
        return accepted_of(np.stack([np.unpackbits(np.frombuffer(p, np.uint8), count=m) for p in payloads]), d, k, self.seed, block)

    def filters(self, keys: Sequence[np.ndarray], block: int = 0) -> Iterator[tuple[bytes, int]]:
        """Bytes and bits of the filter of each of equally many keys."""
        m, k = bloom_size(len(keys[0]), self.fpr)
        flags, every = np.zeros((len(keys), m), np.uint8), np.stack(keys)
        for j in range(k):
            flags[np.arange(len(keys))[:, None], self.hashes(every, j, block) % m] = 1
        for f in np.packbits(flags, axis=1):
            yield f.tobytes(), m

    @property
    def _alone(self) -> bool:
        return self.lookup is not False

    def encode_many(self, keys, d, block=0):
        if self._alone or not len(keys[0]):
            yield from super().encode_many(keys, d, block)
            return
        made = list(self.filters(keys, block))
        chosen = keys if self.policy == "naive" else self.decode_many([p for p, _ in made], d, len(keys[0]), [], block)
        for (payload, m), sent in zip(made, chosen, strict=True):
            yield Encoded(payload, m, sent, 256)

    def decode_many(self, payloads, d, r, n_values, block=0):
        if self._alone or not r:
            return super().decode_many(payloads, d, r, n_values, block)
        m, k = bloom_size(r, self.fpr)
        return self._choose_many(np.stack([np.unpackbits(np.frombuffer(p, np.uint8), count=m) for p in payloads]), d, r, k, block)

    def _choose_many(self, flags: np.ndarray, d: int, r: int, k: int, block: int) -> Iterator[np.ndarray]:
        table = _domain(d, k, self.seed, block % 65_536) if 4 * d * k <= KEPT_BYTES else None
        if self.shared is None:
            for f, p in zip(flags, positives_of(flags, d, k, self.seed, block), strict=True):
                yield self._picked(p, f, d, r, k, block, table)
            return
        scans = [(self.seed, k, d, block, flags.shape[1], f.tobytes()) for f in np.packbits(flags, axis=1)]
        new = list({s: i for i, s in enumerate(scans) if s not in self.shared}.values())
        if new:
            self.shared |= zip([scans[i] for i in new], positives_of(flags[new], d, k, self.seed, block), strict=True)
        for f, scan in zip(flags, scans, strict=True):
            if (self.policy, r, scan) not in self.shared:
                self.shared[self.policy, r, scan] = self._picked(self.shared[scan], f, d, r, k, block, table)
            yield self.shared[self.policy, r, scan]

    def _choose(self, flags: np.ndarray, d: int, r: int, k: int, block: int) -> np.ndarray:
        if self.shared is None:
            return self._picked(self._positives(flags, d, k, block), flags, d, r, k, block)
        scan = (self.seed, k, d, block, flags.tobytes())
        if scan not in self.shared:
            self.shared[scan] = self._positives(flags, d, k, block)
        if (self.policy, r, scan) not in self.shared:
            self.shared[self.policy, r, scan] = self._picked(self.shared[scan], flags, d, r, k, block)
        return self.shared[self.policy, r, scan]

    def _picked(self, p: np.ndarray, flags: np.ndarray, d: int, r: int, k: int, block: int, table: np.ndarray | None = None) -> np.ndarray:
        if self.policy == "p0":
            return p
        if self.policy in ("left", "naive"):
            return p[:r]
        if self.policy == "right":
            return p[len(p) - r :]
        if self.policy == "middle":
            skip = (len(p) - r) // 2
            return p[skip : skip + r]
        if self.policy == "p1":
            return np.sort(p[np.lexsort((p, hash_array(p, 0, self.seed, "p1", block)))][:r])
        if len(p) == r:
            # all are drawn, in whatever order
            return p
        table = self._table(d, k, block) if table is None else table
        return np.sort(draw_by_conflicts(p, self.positions(p, len(flags), k, block, table), hash_array(p, 0, self.seed, "p2", block), r))


def draw_by_conflicts(p: np.ndarray, positions: np.ndarray, priority: np.ndarray, r: int) -> np.ndarray:
    """r positives by visits to the conflict sets of the bits, small sets first, round after round.

    A visit takes the set's unused member of least priority, if it has one; a set of one member, which must be a true
    key, is thus taken on the first round.
    """
    # members by priority, so that one sort of numbers orders the members of all bits
    rank = np.lexsort((p, priority))
    nth = np.empty(len(p), np.int64)
    nth[rank] = np.arange(len(p))
    shift = len(p).bit_length()
    pairs = np.sort((positions.astype(np.int64) << shift | nth).ravel())
    pairs = pairs[np.concatenate(([True], pairs[1:] != pairs[:-1]))]
    bit, member = pairs >> shift, rank[pairs & (1 << shift) - 1]
    cut = np.flatnonzero(np.diff(bit)) + 1
    start, stop = np.concatenate(([0], cut)), np.concatenate((cut, [len(bit)]))
    by_size = np.argsort(stop - start, kind="stable")
    # sets of one member come first, and a member of several of them is taken once
    alone = int(np.searchsorted((stop - start)[by_size], 1, "right"))
    single = member[start[by_size[:alone]]]
    out = single[np.sort(np.unique(single, return_index=True)[1])][:r].tolist()
    # views, not lists: a block has millions of sets and members
    at, stop, member = (memoryview(np.ascontiguousarray(x)) for x in (start[by_size], stop[by_size], member))
    used = bytearray(len(p))
    for m in out:
        used[m] = 1
    live: range | list[int] = range(alone, len(at))
    while len(out) < r:
        still = []
        for s in live:
            k, end = at[s], stop[s]
            while k < end and used[member[k]]:
                k += 1
            if k < end:
                used[member[k]] = 1
                out.append(member[k])
                if len(out) == r:
                    break
                still.append(s)
            at[s] = k
        live = still
    return p[np.array(out, np.int64)]
