"""Suffix arrays by induced sorting, and permuted common prefixes, on numpy arrays.

Induction goes bucket by bucket. A bucket's members that induce into the bucket itself are those with a run of its
letter before them: they are laid out at once, those one letter away first, then those two letters away, and so on,
which is the order in which a scan would place them. Then all members induce into other buckets at once. So a bucket
takes a few array operations whatever runs it has.

The string of names is ordered by the same method where it has few different names, as repetitive texts have. Else
each bucket would hold a few members only, and names are joined two by two until all differ.
"""

from __future__ import annotations

import numpy as np


def suffix_types(t: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the one after it; the last suffix counts as such."""
    n = len(t)
    differs = np.empty(n, bool)
    differs[-1] = True
    np.not_equal(t[:-1], t[1:], out=differs[:-1])
    at = np.where(differs, np.arange(n), n - 1)
    at = np.minimum.accumulate(at[::-1])[::-1]
    after = np.minimum(at + 1, n - 1)
    return (t[at] < t[after]) | (at == n - 1)


#: Most different names for which the reduced string is ordered by induction.
FEW_NAMES = 2048


def _scatter(sa: np.ndarray, edge: np.ndarray, p: np.ndarray, ch: np.ndarray, step: int) -> None:
    """Place p at the edges of the buckets of ch, in order, outwards by step."""
    order = np.argsort(ch, kind="stable")
    p, ch = p[order], ch[order]
    count = np.bincount(ch, minlength=len(edge))
    rank = np.arange(len(p)) - (np.cumsum(count) - count)[ch]
    sa[edge[ch] + rank if step > 0 else edge[ch] - 1 - rank] = p
    edge += step * count


def runs_before(t: np.ndarray) -> np.ndarray:
    """For each position, how many letters right before it equal its own."""
    at = np.arange(len(t))
    new = np.ones(len(t), bool)
    np.not_equal(t[1:], t[:-1], out=new[1:])
    return at - np.maximum.accumulate(np.where(new, at, 0))


def _chain(x: np.ndarray, before: np.ndarray) -> np.ndarray:
    """What the members x, in order, induce into their own bucket: x - 1, x - 2, ... along each run."""
    n = before[x]
    total = int(n.sum())
    if not total:
        return x[:0]
    member = np.repeat(np.arange(len(x)), n)
    k = np.arange(total) - np.repeat(np.cumsum(n) - n, n) + 1
    order = np.argsort(k, kind="stable") if len(x) > 1 else slice(None)
    return (x[member] - k)[order]


def induce(t: np.ndarray, small: np.ndarray, seeds: np.ndarray, count: np.ndarray, before: np.ndarray) -> np.ndarray:
    """All suffixes from leftmost-smaller ones given in order."""
    n, letters = len(t), np.flatnonzero(count)
    end = np.cumsum(count)
    start = end - count
    sa = np.zeros(n, np.int64)
    head = start.copy()
    seed_end = np.cumsum(np.bincount(t[seeds], minlength=len(count)))
    seed_start = seed_end - np.bincount(t[seeds], minlength=len(count))
    for c in letters:
        own = _chain(sa[start[c] : head[c]], before)
        sa[head[c] : head[c] + len(own)] = own
        head[c] += len(own)
        x = np.concatenate((sa[start[c] : head[c]], seeds[seed_start[c] : seed_end[c]]))
        p = x[x > 0] - 1
        p = p[~small[p] & (t[p] != c)]
        if len(p):
            _scatter(sa, head, p, t[p], 1)
    tail = end.copy()
    sa[0], tail[0] = n - 1, 0
    for c in letters[::-1]:
        own = _chain(sa[tail[c] : end[c]][::-1], before)
        sa[tail[c] - len(own) : tail[c]] = own[::-1]
        tail[c] -= len(own)
        x = np.concatenate((sa[tail[c] : end[c]][::-1], sa[start[c] : head[c]][::-1])) if c else sa[:1]
        p = x[x > 0] - 1
        p = p[small[p] & (t[p] != c)]
        if len(p):
            _scatter(sa, tail, p, t[p], -1)
    return sa


#: Letters compared for all pairs at once; what is still equal then is compared pair by pair.
TOGETHER = 64


def _names(t: np.ndarray, ordered: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Names of leftmost-smaller substrings in sorted order: equal ones share a name."""
    a, b, la, lb = ordered[:-1], ordered[1:], length[:-1], length[1:]
    new = la != lb
    left = np.flatnonzero(~new)
    for k in range(TOGETHER):
        if not len(left):
            break
        same = t[a[left] + k] == t[b[left] + k]
        new[left[~same]] = True
        left = left[same & (la[left] > k + 1)]
    for i in left.tolist():
        x, y, n = int(a[i]), int(b[i]), int(la[i])
        new[i] = not np.array_equal(t[x : x + n], t[y : y + n])
    return np.concatenate(([0], np.cumsum(new)))


def _order_names(names: np.ndarray) -> np.ndarray:
    """Order of the suffixes of a string of names: names are joined two by two, again and again, until all differ."""
    rank, k, n = names.astype(np.int64), 1, len(names)
    while True:
        after = np.zeros(n, np.int64)
        after[:-k or n] = rank[k:] + 1 if k < n else 0
        key = rank * (n + 1) + after
        order = np.argsort(key, kind="stable")
        fresh = np.concatenate(([0], np.cumsum(np.diff(key[order]) != 0)))
        rank[order] = fresh
        k *= 2
        if fresh[-1] == n - 1 or k >= 2 * n:
            return order


def suffix_array(t: np.ndarray) -> np.ndarray:
    """t: small non-negative integers of which only the last is 0."""
    t = t.astype(np.uint16)
    if len(t) == 1:
        return np.zeros(1, np.int64)
    count, before = np.bincount(t), runs_before(t)
    small = suffix_types(t)
    leftmost = small.copy()
    leftmost[0] = False
    leftmost[1:] &= ~small[:-1]
    places = np.flatnonzero(leftmost)
    first = induce(t, small, places[np.argsort(t[places], kind="stable")], count, before)
    ordered = first[leftmost[first]]
    length = np.ones(len(t), np.int64)
    length[places[:-1]] = np.diff(places) + 1
    names = _names(t, ordered, length[ordered])
    if names[-1] < len(places) - 1:
        named = np.empty(len(t), np.int64)
        named[ordered] = names
        # the last place is the end mark, whose name 0 no other place has
        reduced = named[places]
        ordered = places[suffix_array(reduced) if names[-1] < FEW_NAMES else _order_names(reduced)]
    return induce(t, small, ordered, count, before)


def _common(t: np.ndarray, a: int, b: int) -> int:
    """Letters that the suffixes at a and b have in common."""
    most, known, step = len(t) - max(a, b), 0, 4 * TOGETHER
    while known < most:
        n = min(step, most - known)
        x, y = t[a + known : a + known + n], t[b + known : b + known + n]
        differ = x != y
        at = int(differ.argmax())
        if differ[at]:
            return known + at
        known, step = known + n, 2 * step
    return known


def permuted_common_prefixes(t: np.ndarray, sa: np.ndarray) -> np.ndarray:
    """For each position, how much its suffix has in common with the one before it in the suffix array.

    Only positions whose left neighbours differ are compared; each later one up to the next such has one less.
    """
    n = len(t)
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    fresh = np.ones(n, bool)
    inner = np.flatnonzero((before[1:] > 0)) + 1
    fresh[inner] = t[inner - 1] != t[before[inner] - 1]
    fresh &= before >= 0
    fresh[sa[0]] = True
    where = np.flatnonzero(fresh)
    i, j = where, before[where]
    pad = np.concatenate((t.astype(np.uint16), np.zeros(8, np.uint16)))
    words = np.lib.stride_tricks.sliding_window_view(pad, 4)
    packed = (words[:, 0].astype(np.uint64) << np.uint64(48)) | (words[:, 1].astype(np.uint64) << np.uint64(32)) | (words[:, 2].astype(np.uint64) << np.uint64(16)) | words[:, 3]
    common = np.zeros(len(where), np.int64)
    left = np.flatnonzero(j >= 0)
    a, b = i[left], j[left]
    for _ in range(TOGETHER):
        if not len(left):
            break
        same = (packed[a] == packed[b]) & (np.maximum(a, b) + 4 < n)
        common[left[same]] += 4
        done = ~same
        x, y, z = a[done], b[done], left[done]
        for _ in range(4):
            ok = (np.maximum(x, y) < n) & (pad[np.minimum(x, n)] == pad[np.minimum(y, n)])
            x, y, z = x[ok] + 1, y[ok] + 1, z[ok]
            common[z] += 1
        a, b, left = a[same] + 4, b[same] + 4, left[same]
    for k in left.tolist():
        common[k] = _common(t, int(i[k]), int(j[k]))
    last = np.maximum.accumulate(np.where(fresh, np.arange(n), 0))
    at = np.cumsum(fresh) - 1
    return np.maximum(common[np.maximum(at, 0)] - (np.arange(n) - last), 0)
