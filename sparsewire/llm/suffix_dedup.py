"""Removal of repeated 50-byte strings by sharded suffix arrays.

1. Documents are dealt to blocks. Every string of ``length`` bytes is represented by the smallest hash among its
   grams of 16 bytes, so equal strings have equal representatives wherever they stand. Blocks send the distinct
   representatives to shards, which answer with those that occur in two documents at least.
2. For each run of strings with such a representative, blocks send the bytes of the run to the representative's
   shard: all equal strings meet in one shard. A shard sorts the suffixes of its distinct runs by induced sorting,
   finds equal strings by the permuted common prefixes and the smallest document of each, and answers with the spans
   that a smaller document also has.
3. Blocks join the spans and drop their bytes.

Documents with the text of a smaller one are found first, by a digest of the text: all their strings start in that
one, and none of theirs is ever the smallest, so they take no part in the suffix arrays and go as a whole.

A shard leaves out runs none of whose strings has a 64-bit hash that occurs twice: a frequent gram in many different
surroundings costs its hashes only. Rows between blocks and shards are packed arrays, so a gram or document that
fills a third of the input makes rows of even number.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .common import NO_ID, any_names, block_count, id_or_last, table, tidy
from .suffix_array import permuted_common_prefixes, suffix_array

LENGTH = 50
GRAM = 16
BLOCK_BYTES = 2 << 20
BLOCK, KEY, SAME = "sw__block", "sw__id", "sw__same"
#: A fixed random word for each byte.
WORD = np.random.default_rng(20).integers(1, 2**63, 256, dtype=np.uint64)
ODD = np.uint64(0x9E3779B97F4A7C15)


def _hashes(data: np.ndarray, sizes: list[int]) -> np.ndarray:
    """Rolling hashes of strings of sum(sizes) bytes, each size a power of two, from hashes of half the size."""
    by_size = {1: WORD[data]}
    k = 1
    while k < max(sizes):
        h = by_size[k]
        by_size[2 * k] = h[: len(h) - k] * (ODD + np.uint64(2 * k)) + h[k:] if len(h) > k else h[:0]
        k *= 2
        if k // 2 not in sizes:
            del by_size[k // 2]
    n = len(data) - sum(sizes) + 1
    out, at = np.zeros(max(n, 0), np.uint64), 0
    for s in sizes:
        out = out * ODD + by_size[s][at : at + max(n, 0)]
        at += s
    out ^= out >> np.uint64(31)
    out *= np.uint64(0xBF58476D1CE4E5B9)
    out ^= out >> np.uint64(29)
    return out


def _binary(n: int) -> list[int]:
    return [1 << k for k in range(n.bit_length())[::-1] if n >> k & 1]


def _minima(h: np.ndarray, width: int) -> np.ndarray:
    k = 1
    while 2 * k <= width:
        h = np.minimum(h[:-k], h[k:])
        k *= 2
    return np.minimum(h[: len(h) - (width - k)], h[width - k :]) if width > k else h


class Block:
    """The documents of a block in a fixed order, as one array of bytes."""

    def __init__(self, docs: pa.Table, text_col: str) -> None:
        marks, ids = docs.column(SAME).to_pylist(), docs.column(KEY).to_pylist()
        raw = docs.column(text_col).cast(pa.binary()).to_pylist()
        self.rows = [i for i, m in enumerate(marks) if m is None]
        self.order = sorted(self.rows, key=lambda i: (ids[i], raw[i] or b""))
        self.texts = [raw[i] or b"" for i in self.order]
        self.ids = np.array([ids[i] for i in self.order], np.int64)
        self.ends = np.cumsum([len(t) for t in self.texts], dtype=np.int64)
        self.starts = self.ends - np.array([len(t) for t in self.texts], np.int64)
        self.data = np.frombuffer(b"".join(self.texts), np.uint8)
        marked = {(i, m) for i, m in zip(ids, marks, strict=True) if m is not None}
        some = {i for i, _ in marked}
        self.copy = np.array([i in some and (i, hashlib.md5(t).hexdigest()) in marked for i, t in zip(self.ids.tolist(), self.texts, strict=True)], bool)

    def runs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Representative, document, first string and past-the-last string of each run."""
        n = len(self.data) - LENGTH + 1
        if n < 1:
            return np.zeros(0, np.uint64), *(np.zeros(0, np.int64) for _ in range(3))
        m = _minima(_hashes(self.data, _binary(GRAM)), LENGTH - GRAM + 1)
        inside = np.ones(n, bool)
        for s, e, copy in zip(self.starts.tolist(), self.ends.tolist(), self.copy.tolist(), strict=True):
            inside[s if copy else max(s, e - LENGTH + 1) : e] = False
        new = inside.copy()
        new[1:] &= ~inside[:-1] | (m[1:] != m[:-1])
        first = np.flatnonzero(new)
        stop = inside.copy()
        stop[:-1] &= ~inside[1:] | (m[1:] != m[:-1])
        return m[first], np.searchsorted(self.ends, first, side="right"), first, np.flatnonzero(stop) + 1



def _split(keys: np.ndarray, *cols: np.ndarray) -> Iterator[tuple[int, list[np.ndarray]]]:
    order = np.argsort(keys, kind="stable")
    keys, cols = keys[order], [c[order] for c in cols]
    cut = np.flatnonzero(np.diff(keys)) + 1
    for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(keys)], strict=True):
        if b > a:
            yield int(keys[a]), [c[a:b] for c in cols]


def _find_shared(t: pa.Table) -> pa.Table:
    """Of the representatives that blocks sent, those that were sent twice."""
    sent = [np.frombuffer(x, np.uint64) for x in t.column("h").to_pylist()]
    everything = np.sort(np.concatenate(sent))
    twice = everything[:-1][everything[1:] == everything[:-1]]
    out = {"block": [], "h": []}
    for block, h in zip(t.column("block").to_pylist(), sent, strict=True):
        at = np.searchsorted(twice, h)
        found = np.unique(h[(at < len(twice)) & (twice[np.minimum(at, max(len(twice) - 1, 0))] == h)]) if len(twice) else h[:0]
        if len(found):
            out["block"].append(block)
            out["h"].append(found.tobytes())
    return pa.table({"block": pa.array(out["block"], pa.int64()), "h": pa.array(out["h"], pa.binary())})


def smallest_owner(data: bytes, sizes: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """For each byte of runs laid end to end, the smallest owner of the string there; no meaning where none fits."""
    apart = np.repeat(np.arange(len(sizes)), sizes) + np.arange(len(data))
    t = np.ones(len(data) + len(sizes) + 1, np.uint16)
    t[apart] = np.frombuffer(data, np.uint8).astype(np.uint16) + 2
    t[-1] = 0
    sa = suffix_array(t)
    fresh = permuted_common_prefixes(t, sa)[sa] < LENGTH
    fresh[0] = True
    whose = np.append(np.repeat(owner, sizes + 1), NO_ID)
    # what is too short for a string has a separator among its bytes, so no string shares its group
    least = np.empty(len(t), np.int64)
    least[sa] = np.minimum.reduceat(whose[sa], np.flatnonzero(fresh))[np.cumsum(fresh) - 1]
    return least[apart]


def _repeated(h: np.ndarray) -> np.ndarray:
    """Whether each hash occurs twice at least."""
    s = np.sort(h)
    twice = s[:-1][s[1:] == s[:-1]]
    return twice[np.minimum(np.searchsorted(twice, h), len(twice) - 1)] == h if len(twice) else np.zeros(len(h), bool)


def _find_spans(t: pa.Table) -> pa.Table:
    """Spans of strings that a smaller document has, for the runs that blocks sent to one shard."""
    number: dict[bytes, int] = {}
    at_block, at_run, at_row, at_id, at_pos = [], [], [], [], []
    for row in t.select(["block", "data", "sizes", "run", "row", "id", "pos"]).to_batches():
        for block, data, sizes, run, doc, ids, pos in zip(*(c.to_pylist() for c in row.columns), strict=True):
            stops = np.cumsum(np.frombuffer(sizes, np.int32)).tolist()
            local = [number.setdefault(data[a:b], len(number)) for a, b in zip([0, *stops[:-1]], stops, strict=True)]
            run = np.frombuffer(run, np.int32)
            at_block.append(np.full(len(run), block, np.int64))
            at_run.append(np.array(local, np.int64)[run])
            at_row.append(np.frombuffer(doc, np.int32))
            at_id.append(np.frombuffer(ids, np.int64))
            at_pos.append(np.frombuffer(pos, np.int32))
    block, run, row, ids, pos = (np.concatenate(x) for x in (at_block, at_run, at_row, at_id, at_pos))
    runs = list(number)
    del number
    owner, most = np.full(len(runs), NO_ID, np.int64), np.full(len(runs), -(2**63), np.int64)
    np.minimum.at(owner, run, ids)
    np.maximum.at(most, run, ids)
    sizes = np.array([len(r) for r in runs], np.int64)
    # runs of one document whose strings all have hashes of their own take no part
    starts, which = np.cumsum(sizes) - sizes, np.repeat(np.arange(len(runs)), sizes)
    fits = (np.arange(len(which)) - starts[which] <= sizes[which] - LENGTH)[: len(which) - LENGTH + 1]
    hit = np.zeros(len(fits), bool)
    hit[fits] = _repeated(_hashes(np.frombuffer(b"".join(runs), np.uint8), _binary(LENGTH))[fits])
    use = np.flatnonzero((most > owner) | (np.bincount(which[: len(fits)][hit], minlength=len(runs)) > 0))
    out: list[tuple] = []
    if len(use):
        size = sizes[use]
        least = smallest_owner(b"".join([runs[i] for i in use]), size, owner[use])
        start = np.cumsum(size) - size
        of_run = np.repeat(np.arange(len(use)), size)
        place = np.arange(len(of_run)) - start[of_run]
        fits = place <= size[of_run] - LENGTH
        of_run, place, least = of_run[fits], place[fits], least[fits]
        # stretches of strings with the same smallest owner
        new = np.concatenate(([True], (of_run[1:] != of_run[:-1]) | (least[1:] != least[:-1])))
        begin = np.flatnonzero(new)
        s_run, s_first, s_least = use[of_run[begin]], place[begin], least[begin]
        s_stop = place[np.append(begin[1:], len(place)) - 1] + LENGTH
        count = np.bincount(s_run, minlength=len(runs))
        first = np.cumsum(count) - count
        times = count[run]
        one = np.repeat(first[run], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        of = np.repeat(np.arange(len(run)), times)
        keep = s_least[one] < ids[of]
        one, of = one[keep], of[keep]
        out = [(b, *(c.tobytes() for c in cols)) for b, cols in _split(block[of], row[of], (pos[of] + s_first[one]).astype(np.int32), (pos[of] + s_stop[one]).astype(np.int32))]
    return pa.table({n: pa.array([x[k] for x in out], pa.int64() if k == 0 else pa.binary()) for k, n in enumerate(("block", "row", "first", "stop"))})


def _kept(block: Block, spans: pa.Table) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """What is left of each document, the bytes removed and the number of spans."""
    n = len(block.data)
    step = np.zeros(n + 1, np.int32)
    for row, first, stop in zip(*(spans.column(c).to_pylist() for c in ("row", "first", "stop")), strict=True):
        base = block.starts[np.frombuffer(row, np.int32)]
        np.add.at(step, base + np.frombuffer(first, np.int32), 1)
        np.add.at(step, base + np.frombuffer(stop, np.int32), -1)
    gone = np.cumsum(step[:n]) > 0
    for s, e in zip(block.starts[block.copy].tolist(), block.ends[block.copy].tolist(), strict=True):
        gone[s:e] = e - s >= LENGTH
    opens = gone.copy()
    opens[1:] &= ~gone[:-1]
    opens[block.starts[block.starts < n]] = gone[block.starts[block.starts < n]]
    total, begun = np.concatenate(([0], np.cumsum(gone))), np.concatenate(([0], np.cumsum(opens)))
    removed, count = total[block.ends] - total[block.starts], begun[block.ends] - begun[block.starts]
    kept = [block.data[s:e][~gone[s:e]].tobytes() if r else t for t, s, e, r in zip(block.texts, block.starts.tolist(), block.ends.tolist(), removed.tolist(), strict=True)]
    return kept, removed, count


def _spans(docs: DataFrame, text_col: str, blocks: int) -> DataFrame:
    """(block, row, first, stop) arrays; row counts the block's documents by id and text."""
    shards = blocks

    def send(t: pa.Table) -> pa.Table:
        b = Block(t, text_col)
        h, doc, _, _ = b.runs()
        # twice if two documents of the block have it
        pairs = np.unique(np.stack([h.view(np.int64), doc]), axis=1)[0].view(np.uint64) if len(h) else h
        first = np.concatenate(([True], pairs[1:] != pairs[:-1])) if len(pairs) else np.zeros(0, bool)
        nth = np.arange(len(pairs)) - np.maximum.accumulate(np.where(first, np.arange(len(pairs)), 0)) if len(pairs) else pairs
        pairs = pairs[nth < 2] if len(pairs) else pairs
        name = t.column(BLOCK)[0].as_py()
        got = list(_split((pairs >> np.uint64(33)) % np.uint64(shards), pairs))
        return pa.table({"shard": pa.array([s for s, _ in got], pa.int64()), "block": pa.array([name] * len(got), pa.int64()), "h": pa.array([c[0].tobytes() for _, c in got], pa.binary())})

    def contexts(t: pa.Table, shared: pa.Table) -> pa.Table:
        names = {"shard": pa.int64(), "block": pa.int64(), "data": pa.binary(), "sizes": pa.binary(), "run": pa.binary(), "row": pa.binary(), "id": pa.binary(), "pos": pa.binary()}
        out = {n: [] for n in names}
        if t.num_rows and shared.num_rows:
            b = Block(t, text_col)
            h, doc, first, stop = b.runs()
            known = np.sort(np.concatenate([np.frombuffer(x, np.uint64) for x in shared.column("h").to_pylist()]))
            at = np.minimum(np.searchsorted(known, h), len(known) - 1)
            hit = known[at] == h
            h, doc, first, stop = h[hit], doc[hit], first[hit], stop[hit]
            raw = b.data.tobytes()
            name = t.column(BLOCK)[0].as_py()
            for s, (d, f, e) in _split((h >> np.uint64(33)) % np.uint64(shards), doc, first, stop):
                number: dict[bytes, int] = {}
                run = [number.setdefault(raw[x:y], len(number)) for x, y in zip(f.tolist(), (e + LENGTH - 1).tolist(), strict=True)]
                for n, v in zip(names, (s, name, b"".join(number), np.array([len(r) for r in number], np.int32).tobytes(), np.array(run, np.int32).tobytes(), d.astype(np.int32).tobytes(), b.ids[d].tobytes(), (f - b.starts[d]).astype(np.int32).tobytes()), strict=True):
                    out[n].append(v)
        return pa.table({n: pa.array(out[n], k) for n, k in names.items()})

    shared = docs.groupBy(BLOCK).applyInArrow(tidy(send), "shard bigint, block bigint, h binary").groupBy("shard").applyInArrow(tidy(_find_shared), "block bigint, h binary")
    sent = docs.groupBy(BLOCK).cogroup(shared.groupBy("block")).applyInArrow(tidy(contexts), "shard bigint, block bigint, data binary, sizes binary, run binary, row binary, id binary, pos binary")
    return sent.groupBy("shard").applyInArrow(tidy(_find_spans), "block bigint, row binary, first binary, stop binary")


def _dealt(docs: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, int]:
    """docs with block and id, and a row with a digest for each document that has the text of a smaller one."""
    blocks = block_count(docs.sparkSession, docs, text_col, BLOCK_BYTES)
    key, block = id_or_last(id_col), lambda k: F.pmod(F.xxhash64(k), F.lit(blocks)).cast("bigint")
    digest = docs.where(F.octet_length(text_col) >= LENGTH).select(key.alias(KEY), F.md5(F.encode(text_col, "UTF-8")).alias(SAME))
    groups = digest.groupBy(SAME).agg(F.min(KEY).alias("least"), F.max(KEY).alias("most")).where("least < most")
    copies = digest.join(groups, SAME).where(F.col(KEY) > F.col("least")).select(KEY, SAME)
    empty = [F.lit(None).cast(f.dataType).alias(f.name) for f in docs.schema.fields]
    marks = copies.select(*empty, KEY, SAME)
    rows = docs.select("*", key.alias(KEY), F.lit(None).cast("string").alias(SAME))
    return rows.union(marks).withColumn(BLOCK, block(F.col(KEY))), blocks


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256.

    A byte goes if a 50-byte string over it also starts in a row with a smaller id. Null texts count as empty; rows
    without an id come after all others; rows with the same id never count as smaller to each other.
    """
    dealt, blocks = _dealt(docs.select(id_col, text_col), id_col, text_col)

    def drop(t: pa.Table, spans: pa.Table) -> pa.Table:
        b = Block(t, text_col)
        kept, removed, count = _kept(b, spans)
        ids = t.column(id_col).to_pylist()
        cols = {"doc_id": pa.array([ids[i] for i in b.order], pa.int64()), "n_bytes": b.ends - b.starts, "n_removed": removed, "n_spans": count, "kept_sha256": [hashlib.sha256(k).hexdigest() for k in kept]}
        return pa.table({k: pa.array(v, None if k == "doc_id" else (pa.string() if k == "kept_sha256" else pa.int64())) for k, v in cols.items()})

    spans = _spans(dealt, text_col, blocks)
    return dealt.groupBy(BLOCK).cogroup(spans.groupBy("block")).applyInArrow(tidy(drop), "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


@any_names
def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", count_col: str | None = "n_chars") -> DataFrame:
    """docs with repeated spans cut out of the texts; columns as before, count_col the new number of characters.

    A character of which a byte goes is dropped as a whole. Null texts stay null.
    """
    dealt, blocks = _dealt(docs, id_col, text_col)
    schema = StructType([f for f in docs.schema.fields])

    def drop(t: pa.Table, spans: pa.Table) -> pa.Table:
        b = Block(t, text_col)
        kept, removed, _ = _kept(b, spans)
        old = t.column(text_col).to_pylist()
        new = list(old)
        for i, k, r in zip(b.order, kept, removed.tolist(), strict=True):
            if r:
                new[i] = k.decode("utf-8", "ignore")
        out = t.drop_columns([BLOCK, KEY, SAME])
        out = out.set_column(out.schema.get_field_index(text_col), text_col, pa.array(new, pa.string()))
        if count_col in out.schema.names:
            k = out.schema.get_field_index(count_col)
            size = [old_n if new_t is None or not r else len(new_t) for new_t, old_n, r in zip(new, out.column(k).to_pylist(), _by_row(b, removed, t.num_rows), strict=True)]
            out = out.set_column(k, count_col, pa.array(size, out.schema.field(k).type))
        return out.take(pa.array(b.rows, pa.int64()))

    spans = _spans(dealt, text_col, blocks)
    return dealt.groupBy(BLOCK).cogroup(spans.groupBy("block")).applyInArrow(tidy(drop), schema)


def _by_row(b: Block, values: np.ndarray, rows: int) -> list[int]:
    out = [0] * rows
    for i, v in zip(b.order, values.tolist(), strict=True):
        out[i] = v
    return out


def op2_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats(table(spark, sf_dir, "documents"))
