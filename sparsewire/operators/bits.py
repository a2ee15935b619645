"""Bit packing and canonical prefix codes on numpy arrays."""

from __future__ import annotations

import heapq
from functools import lru_cache

import numpy as np


#: Values whose bits are spelled out at once; whole bytes at any width.
SPELLED = 1 << 15


def pack(values: np.ndarray, width: int) -> bytes:
    """Unsigned values in width bits each, most significant bit first."""
    if width == 0 or not len(values):
        return b""
    if len(values) > SPELLED:
        return b"".join(pack(values[a : a + SPELLED], width) for a in range(0, len(values), SPELLED))
    v = values.astype(np.uint64)[:, None] >> np.arange(width - 1, -1, -1, dtype=np.uint64) & np.uint64(1)
    return np.packbits(v.astype(np.uint8).ravel()).tobytes()


def pack_few(at: np.ndarray, values: np.ndarray, width: int, n: int) -> bytes:
    """What pack gives for n values that are 0 except at some places."""
    out = np.zeros(-(-n * width // 8) + 8, np.uint8)
    bit = at.astype(np.int64) * width
    word = values.astype(np.uint64) << (64 - width - (bit & 7)).astype(np.uint64)
    for i in range(-(-(width + 7) // 8)):
        np.bitwise_or.at(out, (bit >> 3) + i, (word >> np.uint64(56 - 8 * i) & np.uint64(255)).astype(np.uint8))
    return out[: -(-n * width // 8)].tobytes()


def unpack_few(data: bytes, width: int, n: int) -> tuple[np.ndarray, np.ndarray] | None:
    """(places, values) of what unpack gives, those left out being 0; nothing if too many are not."""
    raw = np.frombuffer(data, np.uint8)
    if len(raw) < 4096 or not 0 < width <= 56:
        return None
    words = np.flatnonzero(raw[: len(raw) // 8 * 8].view(np.uint64))
    if 64 * len(words) > len(raw):
        return None
    byte = np.concatenate(((words[:, None] * 8 + np.arange(8)).ravel(), np.arange(len(raw) // 8 * 8, len(raw))))
    byte = byte[raw[byte] != 0]
    at = np.unique(((byte * 8)[:, None] + np.arange(8)).ravel() // width)
    at = at[at < n]
    bit, value = at * width, np.zeros(len(at), np.uint64)
    for i in range(8):
        # behind the end come bits of no value
        value = value << np.uint64(8) | raw.take((bit >> 3) + i, mode="clip").astype(np.uint64)
    return at, (value >> (64 - width - (bit & 7)).astype(np.uint64) & np.uint64((1 << width) - 1)).astype(np.int64)


def unpack(data: bytes, width: int, n: int) -> np.ndarray:
    if width == 0:
        return np.zeros(n, np.int64)
    if n > SPELLED:
        step = SPELLED * width // 8
        return np.concatenate([unpack(data[a // SPELLED * step : (a // SPELLED + 1) * step], width, min(SPELLED, n - a)) for a in range(0, n, SPELLED)])
    bits = np.unpackbits(np.frombuffer(data, np.uint8), count=n * width).reshape(n, width)
    return bits.astype(np.int64) @ (1 << np.arange(width - 1, -1, -1, dtype=np.int64))


def prefix_lengths(freqs: dict[int, int]) -> dict[int, int]:
    """Code length of each symbol by greedy merging of the least frequent; ties by the smallest symbol inside."""
    return dict(_prefix_lengths(tuple(freqs.items())))


@lru_cache(maxsize=1024)
def _prefix_lengths(items: tuple[tuple[int, int], ...]) -> dict[int, int]:
    freqs = dict(items)
    if len(freqs) == 1:
        return dict.fromkeys(freqs, 1)
    heap = [(f, s, (s,)) for s, f in freqs.items()]
    heapq.heapify(heap)
    length = dict.fromkeys(freqs, 0)
    while len(heap) > 1:
        (fa, a, sa), (fb, b, sb) = heapq.heappop(heap), heapq.heappop(heap)
        for s in sa + sb:
            length[s] += 1
        heapq.heappush(heap, (fa + fb, min(a, b), sa + sb))
    return length


def huffman_code(freqs: dict[int, int]) -> dict[int, str]:
    """Canonical code words: by length, then symbol."""
    code, last, out = 0, 0, {}
    for s, n in sorted(prefix_lengths(freqs).items(), key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[s] = format(code, f"0{n}b")
        code, last = code + 1, n
    return out


def huffman_encode(symbols: np.ndarray, code: dict[int, str]) -> tuple[bytes, int]:
    text = "".join(map(code.__getitem__, symbols.tolist()))
    return np.packbits(np.frombuffer(text.encode(), np.uint8) - 48).tobytes() if text else b"", len(text)


@lru_cache(maxsize=1024)
def _starts(code: tuple[tuple[int, str], ...]) -> tuple[int, np.ndarray, np.ndarray, np.ndarray]:
    """Bits of the longest code word; for each one its bits, filled up to so many, its length and symbol, in order."""
    longest = max(len(w) for _, w in code)
    if longest > 62:
        raise ValueError("a code word has more than 62 bits")
    words = sorted((int(w, 2) << (longest - len(w)), len(w), s) for s, w in code)
    return longest, *(np.array(x, np.int64) for x in zip(*words, strict=True))


def huffman_decode(data: bytes, code: dict[int, str], n: int) -> np.ndarray:
    """n symbols: what starts at each bit is looked up for a stretch of bits at once, then followed from code to code."""
    if not n:
        return np.zeros(0, np.int64)
    longest, first, size, symbol = _starts(tuple(code.items()))
    bits = np.concatenate((np.unpackbits(np.frombuffer(data, np.uint8)), np.zeros(longest, np.uint8)))
    total, base, out, left = len(bits) - longest, 0, [], n
    while left and base < total:
        span = min(1 << 16, total - base)
        window = np.zeros(span, np.int64)
        for j in range(longest):
            window = window << 1 | bits[base + j : base + j + span]
        which = np.searchsorted(first, window, "right") - 1
        after, at, seen = (np.arange(span) + size[which]).tolist(), 0, []
        while at < span and len(seen) < left:
            seen.append(at)
            at = after[at]
        out.append(symbol[which[seen]])
        left -= len(seen)
        base += at
    got = np.concatenate(out) if out else np.zeros(0, np.int64)
    return got[:-1] if base > total else got


def gamma_bits(values: np.ndarray) -> int:
    """Bits of positive numbers in a self-delimiting code: twice the bit length less one."""
    return int((2 * np.floor(np.log2(np.maximum(values, 1))).astype(np.int64) + 1).sum())


def gamma_encode(values: np.ndarray) -> bytes:
    text = "".join("0" * (int(v).bit_length() - 1) + format(int(v), "b") for v in values)
    return np.packbits(np.frombuffer(text.encode(), np.uint8) - 48).tobytes() if text else b""


def gamma_decode(data: bytes, n: int) -> np.ndarray:
    text, at, out = "".join(map(str, np.unpackbits(np.frombuffer(data, np.uint8)).tolist())), 0, []
    for _ in range(n):
        zeros = text.index("1", at) - at
        out.append(int(text[at + zeros : at + 2 * zeros + 1], 2))
        at += 2 * zeros + 1
    return np.array(out, np.int64)


def byte_frequencies(d: int) -> dict[int, int]:
    """How often each byte value occurs among the four bytes of all keys below d, by counting, not by listing."""
    total = np.zeros(256, np.int64)
    for place in range(4):
        unit = 256**place
        whole, rest = divmod(d, unit * 256)
        counts = np.full(256, whole * unit, np.int64)
        full, part = divmod(rest, unit)
        counts[:full] += unit
        if full < 256:
            counts[full] += part
        total += counts
    return {b: int(f) for b, f in enumerate(total) if f}
