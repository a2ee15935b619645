"""One filter for each whole tensor, of any number of indices, scanned for many tensors at once.

Hashes of an index are the same for every tensor, and tensors of equally many keys have filters of equally many bits.
So such tensors are one Arrow group: a bit matrix holds a row for each filter bit and a column for each tensor, and an
index is tested in all of them by ANDs of k rows. Policies that take positives in an order (of indices, or of the seeded
hash) scan in that order and stop when all tensors of the group have enough.

A tensor of more than LARGE keys is no group: its filter is built in parts, its indices are scanned in stretches, and
policies rank its positives by ranks.py, so no task follows its size beyond the bits of the filter.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import hash_array
from ..sources.checkpoints import checkpointed, small_side
from . import bloom as bl

#: Offsets that the hash family takes: a tensor is one block of at most so many indices.
WHOLE = 1 << 31
#: Most keys of a tensor that is scanned with others in a group.
LARGE = 1 << 20
#: Most tensors, and about the most keys, of a group.
TENSORS, CELLS = 512, 1 << 19
#: Tests that a chunk of the scan makes at once.
CHUNK = 1 << 23
#: Bits of a part of a large filter.
PART = 1 << 20


def bits_of(r: int, fpr: float) -> int:
    """m of a filter, by the very arithmetic of the SQL."""
    return max(1, math.ceil(r * (-math.log(fpr) / bl.LN2**2) - 1e-9))


@lru_cache(maxsize=2)
def scan_order(kind: str, width: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """All indices in the order of a scan, and the place of each index in it."""
    every = np.arange(width)
    if kind == "idx":
        return every, every
    if kind == "right":
        return every[::-1], every[::-1]
    order = np.argsort(hash_array(every, 0, seed, kind), kind="stable")
    place = np.empty(width, np.int64)
    place[order] = every
    return order, place


@lru_cache(maxsize=2)
def _hashes(width: int, k: int, seed: int) -> np.ndarray:
    return np.stack([hash_array(np.arange(width), j, seed).astype(np.uint32) for j in range(k)])


class Group:
    """Tensors of r keys each under filters of m bits; columns of matrices are tensors, in the order of ids."""

    def __init__(self, t: pa.Table, fpr: float, seed: int, kind: str = "idx") -> None:
        self.ids, column = np.unique(t.column("tensor_id").to_numpy(), return_inverse=True)
        self.r, self.width, self.seed = t.column("r")[0].as_py(), t.column("width")[0].as_py(), seed
        self.m, self.k = bits_of(self.r, fpr), bl.hashes_for(fpr)
        idx, value = t.column("idx").to_numpy(), t.column("value").to_numpy()
        if len(idx) != self.r * len(self.ids):
            raise ValueError("a tensor has two cells of one index")
        self.order, place = scan_order(kind, self.width, seed)
        self.cols = 8 << max(0, (-(-len(self.ids) // 8) - 1).bit_length())
        self.step = max(1, CHUNK // self.cols)
        # cells by tensor and index, and in the order of the scan
        by = np.lexsort((idx, column))
        self.idx, self.value = idx[by], value[by]
        flat = place[idx] * self.cols + column
        by = np.argsort(flat)
        self.flat, self.scanned = flat[by], value[by]
        flags = np.zeros((self.m, self.cols), np.uint8)
        for j in range(self.k):
            flags[self.positions(idx, j), column] = 1
        self.flags = flags

    def positions(self, idx: np.ndarray, j: int) -> np.ndarray:
        if 4 * self.width * self.k <= 64 << 20:
            return (_hashes(self.width, self.k, self.seed)[j].take(idx) % np.uint32(self.m)).astype(np.int64)
        return hash_array(idx, j, self.seed) % self.m

    def chunks(self) -> Iterator[int]:
        return iter(range(0, self.width, self.step))

    def hits(self, lo: int) -> np.ndarray:
        """A row for each index of the chunk and a column for each tensor: 1 where the filter accepts it."""
        idx = self.order[lo : lo + self.step]
        held = None
        for j in range(self.k):
            row = self.packed.take(self.positions(idx, j), axis=0)
            held = row if held is None else np.bitwise_and(held, row, out=held)
        return np.unpackbits(held, axis=1, bitorder="little")

    @property
    def packed(self) -> np.ndarray:
        if not hasattr(self, "_packed"):
            self._packed = np.packbits(self.flags, axis=1, bitorder="little")
        return self._packed

    def found(self, lo: int, hits: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place in the chunk, column, number of the chunk's flat place) of each positive, in order of the scan."""
        at = np.flatnonzero(hits.ravel().view(bool))
        return at >> (self.cols.bit_length() - 1), at & (self.cols - 1), at

    def values(self, lo: int, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Values at positives, 0 where there is no key, and whether there is one."""
        a, b = np.searchsorted(self.flat, (lo * self.cols, (lo + self.step) * self.cols))
        own = self.flat[a:b] - lo * self.cols
        place = np.minimum(np.searchsorted(at, own), max(len(at) - 1, 0))
        same = at[place] == own if len(at) else np.zeros(len(own), bool)
        value, hit = np.zeros(len(at), self.value.dtype), np.zeros(len(at), bool)
        value[place[same]], hit[place[same]] = self.scanned[a:b][same], True
        return value, hit

    def counts(self, hits: np.ndarray) -> np.ndarray:
        n = len(hits) // 128 * 128
        whole = hits[:n].reshape(-1, 128, self.cols).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
        return whole + hits[n:].sum(axis=0, dtype=np.int64)

    def cells(self, policy: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(column, idx, value, is a key) of what a policy chooses, chunk by chunk."""
        n = len(self.ids)
        if policy == "p0":
            for lo in self.chunks():
                place, column, at = self.found(lo, self.hits(lo))
                yield column, self.order[lo + place], *self.values(lo, at)
            return
        skip, before = np.zeros(self.cols, np.int64), None
        starts = list(self.chunks())
        if policy == "middle":
            before = np.stack([self.counts(self.hits(lo)) for lo in starts])
            skip = (before.sum(axis=0) - self.r) // 2
            before = np.cumsum(before, axis=0) - before
        seen = np.zeros(self.cols, np.int64)
        for c, lo in enumerate(starts):
            if before is not None:
                after = before[c + 1] if c + 1 < len(starts) else np.full(self.cols, np.iinfo(np.int64).max)
                if not ((after > skip) & (before[c] < skip + self.r))[:n].any():
                    continue
                seen = before[c].copy()
            hits = self.hits(lo)
            place, column, at = self.found(lo, hits)
            size = np.bincount(column, minlength=self.cols)
            by = np.argsort(column.astype(np.uint16 if self.cols <= 1 << 16 else np.int64), kind="stable")
            nth = np.empty(len(at), np.int64)
            nth[by] = np.arange(len(at)) - np.repeat(np.cumsum(size) - size, size)
            nth += seen[column]
            keep = (nth >= skip[column]) & (nth < skip[column] + self.r)
            value, hit = self.values(lo, at)
            if policy == "naive":
                value = self.value.take(column * self.r + nth, mode="clip")
            yield column[keep], self.order[lo + place[keep]], value[keep], hit[keep]
            seen = seen + size
            if before is None and seen[:n].min() >= self.r:
                return

    def set_sizes(self) -> np.ndarray:
        """A row for each tensor, a column for each bit: the positives that hash to it."""
        sizes, held, total = np.zeros(len(self.ids) * self.m, np.int64), [], 0

        def flush() -> None:
            nonlocal sizes, total
            idx, column = (np.concatenate(x) for x in zip(*held, strict=True))
            seen: list[np.ndarray] = []
            for j in range(self.k):
                p = self.positions(idx, j)
                own = np.ones(len(p), bool)
                for other in seen:
                    own &= p != other
                seen.append(p)
                sizes += np.bincount((column * self.m + p)[own], minlength=len(sizes))
            held.clear()
            total = 0

        for lo in self.chunks():
            place, column, _ = self.found(lo, self.hits(lo))
            held.append((self.order[lo + place], column))
            total += len(place)
            if total >= 1 << 21:
                flush()
        if total:
            flush()
        return sizes.reshape(len(self.ids), self.m)

    def drawn(self, rounds: bool) -> Iterator[tuple[int, np.ndarray]]:
        """(column, r indices) of each tensor by its conflict sets: one visit after the other, or in rounds."""
        sizes = self.set_sizes()
        members = Members(self)
        few = max(1, min(64, (64 << 20) // self.width))
        for lo in range(0, len(self.ids), few):
            columns = np.arange(lo, min(lo + few, len(self.ids)))
            used = np.zeros((len(columns), self.width), np.uint8)
            (self._rounds if rounds else self._visits)(members, sizes[columns], columns, used)
            for c, row in zip(columns, used, strict=True):
                yield c, np.flatnonzero(row)

    def _visits(self, members: Members, sizes: np.ndarray, columns: np.ndarray, used: np.ndarray) -> None:
        """Every tensor visits its next set, again and again, until each has r; empty sets are passed over for good."""
        order = [np.lexsort((np.arange(self.m), s))[np.count_nonzero(s == 0) :] for s in sizes]
        still: list[list[int]] = [[] for _ in columns]
        at, need = np.zeros(len(columns), np.int64), np.full(len(columns), self.r)
        while (live := np.flatnonzero(need)).size:
            for i in live[at[live] >= np.array([len(order[i]) for i in live])]:
                order[i], still[i], at[i] = np.array(still[i], np.int64), [], 0
            bit = np.array([order[i][at[i]] for i in live])
            got = members.first(bit, columns[live], live, used)
            for i, b, x in zip(live.tolist(), bit.tolist(), got.tolist(), strict=True):
                if x >= 0:
                    used[i, x] = 1
                    still[i].append(b)
                    need[i] -= 1
            at[live] += 1

    def _rounds(self, members: Members, sizes: np.ndarray, columns: np.ndarray, used: np.ndarray) -> None:
        """Every set offers its unused member of least priority; offers are taken by (size, bit), each member once."""
        need = np.full(len(columns), self.r)
        while (live := np.flatnonzero(need)).size:
            row, bit = np.nonzero(sizes[live])
            row = live[row]
            got = members.first(bit, columns[row], row, used)
            row, bit, got = row[got >= 0], bit[got >= 0], got[got >= 0]
            for i in live:
                mine = row == i
                offer, by = got[mine], np.lexsort((bit[mine], sizes[i][bit[mine]]))
                once, first = np.unique(offer[by], return_index=True)
                take = once[np.argsort(first)][: need[i]]
                used[i, take] = 1
                need[i] -= len(take)


class Members:
    """The indices that hash to each bit, in order of priority; a tensor's members of the set are those it accepts."""

    SLICE = 24

    def __init__(self, g: Group) -> None:
        self.g = g
        order, _ = scan_order("p2", g.width, g.seed)
        bit = np.stack([g.positions(order, j) for j in range(g.k)], axis=1).ravel()
        by = np.argsort(bit.astype(np.uint16) if g.m <= 1 << 16 else bit, kind="stable")
        self.idx = order[by // g.k].astype(np.int32)
        self.start = np.concatenate(([0], np.cumsum(np.bincount(bit, minlength=g.m))))

    def first(self, bit: np.ndarray, column: np.ndarray, row: np.ndarray, used: np.ndarray) -> np.ndarray:
        """The unused member of least priority of each set, -1 where there is none."""
        g, out = self.g, np.full(len(bit), -1, np.int64)
        at, left = self.start[bit], np.arange(len(bit))
        while len(left):
            cells = at[left][:, None] + np.arange(self.SLICE)
            ok = cells < self.start[bit[left] + 1][:, None]
            idx = self.idx.take(cells, mode="clip").astype(np.int64)
            ok &= used[row[left][:, None], idx] == 0
            for j in range(g.k):
                ok &= g.flags[g.positions(idx.ravel(), j).reshape(idx.shape), column[left][:, None]] == 1
            got = ok.any(axis=1)
            out[left[got]] = idx[got, ok[got].argmax(axis=1)]
            at[left] += self.SLICE
            left = left[~got & (at[left] < self.start[bit[left] + 1])]
        return out


# ---- frames


def sized(coo: DataFrame, meta: DataFrame, fpr: float) -> DataFrame:
    """(tensor_id, width, r, m, k), written, one row a tensor."""
    if fpr <= 0 or fpr >= 1:
        raise ValueError("the rate is between 0 and 1")
    return checkpointed(bl.sizes(coo, meta, fpr, WHOLE).drop("block", "fpr"))


def _grouped(coo: DataFrame, rows: DataFrame, large: int) -> DataFrame:
    """Cells of tensors that are not large with r, width and slot, which name their group, dealt by them."""
    per = f"greatest(1L, least({TENSORS}L, {CELLS}L div r))"
    some = rows.where(F.col("r") <= large)
    slots = some.groupBy("r", "width").agg(F.count("*").alias("n")).selectExpr("r", "width", f"greatest(1L, (n + {per} - 1) div {per}) AS slots")
    side = small_side(some.join(slots, ["r", "width"]).selectExpr("tensor_id", "r", "width", "CAST(pmod(xxhash64(tensor_id), slots) AS INT) AS slot"))
    cells = coo.select("tensor_id", "idx", "value").join(side, "tensor_id")
    return cells.repartition(int(coo.sparkSession.conf.get("spark.sql.shuffle.partitions")), "r", "width", "slot")


def _run(cells: DataFrame, schema: str, emit: Callable[[pa.Table], Iterator[pa.RecordBatch]]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from emit(pa.Table.from_batches(list(batches)))

    return cells.groupBy("r", "width", "slot").applyInArrow(run, schema)


def _kind(policy: str) -> str:
    return policy if policy in ("right", "p1") else "idx"


def _value(coo: DataFrame) -> str:
    kind = coo.schema["value"].dataType.simpleString()
    return kind if kind in ("bigint", "double") else "double"


def _split(coo: DataFrame, meta: DataFrame, fpr: float, large: int) -> tuple[DataFrame, DataFrame | None]:
    """Grouped cells, and the sizes of the large tensors if there are any."""
    rows = sized(coo, meta, fpr)
    big = rows.where(F.col("r") > large)
    return _grouped(coo.withColumn("value", F.col("value").cast(_value(coo))), rows, large), None if big.isEmpty() else big


def _both(a: DataFrame, b: DataFrame | None) -> DataFrame:
    return a if b is None else a.unionByName(b)


def decode(coo: DataFrame, meta: DataFrame, fpr: float, policy: str, seed: int = 0, large: int = LARGE) -> DataFrame:
    """(tensor_id, idx, value) as a receiver rebuilds it by any policy; zeros at false positives are kept."""
    cells, big = _split(coo, meta, fpr, large)
    kind = pa.int64() if _value(coo) == "bigint" else pa.float64()

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        g = Group(t, fpr, seed, _kind(policy))
        if policy in ("p2", "p2_rounds"):
            for c, idx in g.drawn(policy == "p2_rounds"):
                mine = slice(c * g.r, (c + 1) * g.r)
                at = np.minimum(np.searchsorted(g.idx[mine], idx), g.r - 1)
                value = np.where(g.idx[mine][at] == idx, g.value[mine][at], 0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(idx), g.ids[c])), pa.array(idx), pa.array(value, kind)], names=["tensor_id", "idx", "value"])
            return
        for column, idx, value, _ in g.cells(policy):
            yield pa.RecordBatch.from_arrays([pa.array(g.ids[column]), pa.array(idx), pa.array(value, kind)], names=["tensor_id", "idx", "value"])

    out = _run(cells, f"tensor_id bigint, idx bigint, value {_value(coo)}", emit)
    if big is None:
        return out
    own = coo.join(F.broadcast(big.select("tensor_id")), "tensor_id", "left_semi").select("tensor_id", "idx", F.col("value").cast(_value(coo)).alias("value"))
    p, sizes = _large_positives(own, big, fpr, seed), big.selectExpr(f"{float(fpr)!r}D AS fpr", "tensor_id", "0L AS block", "width", "r", "m", "k")
    if policy == "naive":
        return out.unionByName(bl.decoded_naive(p, own, WHOLE))
    if policy in ("p2", "p2_rounds"):
        return out.unionByName(bl.fetched(bl.chosen_by_rounds(p, sizes, fpr, seed, WHOLE), own)) if policy == "p2_rounds" else out.unionByName(_large_draw(own, big, fpr, seed, kind))
    return out.unionByName(bl.fetched(bl.chosen(p, sizes, policy, seed, WHOLE), own))


def _large_draw(own: DataFrame, big: DataFrame, fpr: float, seed: int, kind: pa.DataType) -> DataFrame:
    """Visits to sets follow one another, so a tensor's draw is one task's, however large it is."""
    value = "bigint" if kind == pa.int64() else "double"

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        g = Group(t, fpr, seed)
        for c, idx in g.drawn(False):
            at = np.minimum(np.searchsorted(g.idx, idx), g.r - 1)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(idx), g.ids[c])), pa.array(idx), pa.array(np.where(g.idx[at] == idx, g.value[at], 0), kind)], names=["tensor_id", "idx", "value"])

    return _run(_grouped(own, big, WHOLE), f"tensor_id bigint, idx bigint, value {value}", emit)


def positives(coo: DataFrame, meta: DataFrame, fpr: float, seed: int = 0, large: int = LARGE) -> DataFrame:
    """(tensor_id, idx) of all indices that a tensor's filter accepts."""
    cells, big = _split(coo, meta, fpr, large)

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        g = Group(t, fpr, seed)
        for lo in g.chunks():
            place, column, _ = g.found(lo, g.hits(lo))
            yield pa.RecordBatch.from_arrays([pa.array(g.ids[column]), pa.array(g.order[lo + place])], names=["tensor_id", "idx"])

    own = None if big is None else coo.join(F.broadcast(big.select("tensor_id")), "tensor_id", "left_semi")
    return _both(_run(cells, "tensor_id bigint, idx bigint", emit), None if big is None else _large_positives(own, big, fpr, seed).select("tensor_id", "idx"))


TALLY = "fpr double, policy string, tensor_id bigint, chosen bigint, k1 bigint, k2 bigint, norm2 double, error2 double"


def tallies(coo: DataFrame, meta: DataFrame, fpr: float, policy: str, seed: int = 0, large: int = LARGE) -> DataFrame:
    """(tensor_id, chosen, k1, k2, norm2, error2) of a policy that keeps true values: chosen indices, those that are
    keys and those that are not, the squared norm and that of the keys left out."""
    return tallies_of(coo, meta, [(fpr, policy)], seed, large).drop("fpr", "policy")


def tallies_of(coo: DataFrame, meta: DataFrame, wanted: list[tuple[float, str]], seed: int = 0, large: int = LARGE) -> DataFrame:
    """The tallies of several rates and policies, with fpr and policy, from cells that are dealt once."""
    cells, big = _split(coo, meta, wanted[0][0], large)

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        for fpr, policy in wanted:
            g = Group(t, fpr, seed, _kind(policy))
            columns = (np.full(len(g.ids), float(fpr)), [policy] * len(g.ids), g.ids, *_tally(g, policy))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["fpr", "policy", "tensor_id", "chosen", "k1", "k2", "norm2", "error2"])

    out = _run(cells, TALLY, emit)
    if big is None:
        return out
    own = coo.join(F.broadcast(big.select("tensor_id")), "tensor_id", "left_semi")
    for fpr, policy in wanted:
        sizes = bl.sizes(own, meta, fpr, WHOLE)
        c = bl.chosen(_large_positives(own, sizes, fpr, seed), sizes, policy, seed, WHOLE).withColumn("taken", F.lit(1))
        rows = c.join(own.select("tensor_id", "idx", F.col("value").cast("double").alias("v"), F.lit(1).alias("hit")), ["tensor_id", "idx"], "full")
        square = F.coalesce(F.col("v") * F.col("v"), F.lit(0.0))
        sums = rows.groupBy("tensor_id").agg(F.count("taken").alias("chosen"), F.count(F.expr("CASE WHEN taken = 1 AND hit = 1 THEN 1 END")).alias("k1"), F.sum(square).alias("norm2"), F.sum(F.when(F.col("taken").isNull(), square).otherwise(0.0)).alias("error2"))
        out = out.unionByName(sums.select(F.lit(float(fpr)).alias("fpr"), F.lit(policy).alias("policy"), "*", (F.col("chosen") - F.col("k1")).alias("k2")))
    return out


def _tally(g: Group, policy: str) -> tuple[np.ndarray, ...]:
    n, squares = len(g.ids), g.value.astype(float) ** 2
    if policy == "p0":
        chosen = sum(g.counts(g.hits(lo)) for lo in g.chunks())[:n]
        held, column = np.ones(len(g.idx), bool), np.repeat(np.arange(n), g.r)
        for j in range(g.k):
            held &= g.flags[g.positions(g.idx, j), column] == 1
        k1, lost = held.reshape(n, g.r).sum(axis=1), np.where(held, 0.0, squares)
    else:
        chosen, k1, lost = np.zeros(n, np.int64), np.zeros(n, np.int64), squares.copy()
        at = np.repeat(np.arange(n), g.r) * g.width + g.idx
        for column, idx, _, hit in g.cells(policy):
            chosen += np.bincount(column, minlength=n)
            k1 += np.bincount(column[hit], minlength=n)
            lost[np.searchsorted(at, column[hit] * g.width + idx[hit])] = 0
    return chosen, k1, chosen - k1, squares.reshape(n, g.r).sum(axis=1), lost.reshape(n, g.r).sum(axis=1)


def words(coo: DataFrame, meta: DataFrame, fpr: float, seed: int = 0, large: int = LARGE) -> DataFrame:
    """(tensor_id, bits_set, sum_pos) of the filters."""
    cells, big = _split(coo, meta, fpr, large)

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        g = Group(t, fpr, seed)
        own = [np.flatnonzero(g.flags[:, c]) for c in range(len(g.ids))]
        yield pa.RecordBatch.from_arrays([pa.array(g.ids), pa.array([len(x) for x in own], pa.int64()), pa.array([int(x.sum()) for x in own], pa.int64())], names=["tensor_id", "bits_set", "sum_pos"])

    out = _run(cells, "tensor_id bigint, bits_set bigint, sum_pos bigint", emit)
    if big is None:
        return out
    parts = _parts(coo, big, fpr, seed)
    return out.unionByName(parts.groupBy("tensor_id").agg(F.sum("n").alias("bits_set"), F.sum("sum_pos").alias("sum_pos")))


def conflict_sizes(coo: DataFrame, meta: DataFrame, fpr: float, seed: int = 0, large: int = LARGE) -> DataFrame:
    """(tensor_id, bit, size) of the conflict sets."""
    cells, big = _split(coo, meta, fpr, large)

    def emit(t: pa.Table) -> Iterator[pa.RecordBatch]:
        g = Group(t, fpr, seed)
        sizes = g.set_sizes()
        for lo in range(0, len(g.ids), 64):
            row, bit = np.nonzero(sizes[lo : lo + 64])
            yield pa.RecordBatch.from_arrays([pa.array(g.ids[lo + row]), pa.array(bit), pa.array(sizes[lo + row, bit])], names=["tensor_id", "bit", "size"])

    out = _run(cells, "tensor_id bigint, bit bigint, size bigint", emit)
    if big is None:
        return out
    p = _large_positives(coo.join(F.broadcast(big.select("tensor_id")), "tensor_id", "left_semi"), big, fpr, seed)
    pairs = p.join(big.select("tensor_id", "m"), "tensor_id").select("tensor_id", F.explode(F.array_distinct(bl.hash_positions("idx", bl.hashes_for(fpr), "m", seed))).alias("bit"))
    return out.unionByName(pairs.groupBy("tensor_id", "bit").agg(F.count("*").alias("size")))


# ---- large tensors


def _parts(coo: DataFrame, big: DataFrame, fpr: float, seed: int) -> DataFrame:
    """(tensor_id, part, bits, n, sum_pos): the filters of large tensors in parts of PART bits."""
    k = bl.hashes_for(fpr)
    keys = coo.join(F.broadcast(big.select("tensor_id", "m")), "tensor_id").select("tensor_id", "idx", "m")

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            tensor, idx, m = (b.column(c).to_numpy() for c in ("tensor_id", "idx", "m"))
            for one in np.unique(tensor):
                mine, bits = idx[tensor == one], m[tensor == one][0]
                pos = np.unique(np.concatenate([hash_array(mine, j, seed) % bits for j in range(k)]))
                part, start = np.unique(pos // PART, return_index=True)
                pieces = [x.astype("<u4").tobytes() for x in np.split(pos % PART, start[1:])]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), one)), pa.array(part), pa.array(pieces, pa.binary())], names=["tensor_id", "part", "bits"])

    def merge(t: pa.Table) -> pa.Table:
        flags = np.zeros(PART, np.uint8)
        for x in t.column("bits"):
            flags[np.frombuffer(x.as_py(), "<u4")] = 1
        tensor, part = t.column("tensor_id")[0].as_py(), t.column("part")[0].as_py()
        n = int(flags.sum())
        return pa.table({"tensor_id": pa.array([tensor], pa.int64()), "part": pa.array([part], pa.int64()), "bits": pa.array([np.packbits(flags).tobytes()], pa.binary()), "n": pa.array([n], pa.int64()), "sum_pos": pa.array([int(np.flatnonzero(flags).sum()) + n * part * PART], pa.int64())})

    pieces = keys.mapInArrow(spread, "tensor_id bigint, part bigint, bits binary")
    return pieces.groupBy("tensor_id", "part").applyInArrow(merge, "tensor_id bigint, part bigint, bits binary, n bigint, sum_pos bigint")


def _large_positives(coo: DataFrame, big: DataFrame, fpr: float, seed: int) -> DataFrame:
    """(fpr, tensor_id, block, idx): stretches of a large tensor, each with its filter, scanned by tasks of their own.

    A stretch is no shorter than a 32nd of the filter's bits, so the copies of the filters take a few bytes an index.
    """
    k = bl.hashes_for(fpr)
    each = big.selectExpr("tensor_id", "m", "width", "greatest(1048576L, m div 32) AS len").selectExpr("tensor_id", "m", "width", "len", "explode(sequence(0L, (width - 1) div len)) AS stretch")
    rows = _parts(coo, big, fpr, seed).select("tensor_id", "part", "bits").join(F.broadcast(each), "tensor_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = None
        for b in batches:
            for x in b.to_pylist():
                if bits is None:
                    one = x
                    bits = np.zeros(-(-x["m"] // PART) * PART // 8, np.uint8)
                bits[x["part"] * PART // 8 : (x["part"] + 1) * PART // 8] = np.frombuffer(x["bits"], np.uint8)
        lo, hi = one["stretch"] * one["len"], min(one["width"], (one["stretch"] + 1) * one["len"])
        for a in range(lo, hi, 1 << 18):
            left = np.arange(a, min(hi, a + (1 << 18)))
            for j in range(k):
                pos = hash_array(left, j, seed) % one["m"]
                left = left[(bits[pos >> 3] >> (7 - (pos & 7)).astype(np.uint8)) & 1 == 1]
            n = len(left)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, float(fpr))), pa.array(np.full(n, one["tensor_id"])), pa.array(np.zeros(n, np.int64)), pa.array(left)], names=["fpr", "tensor_id", "block", "idx"])

    n = int(coo.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(n, "tensor_id", "stretch").groupBy("tensor_id", "stretch").applyInArrow(run, "fpr double, tensor_id bigint, block bigint, idx bigint")
