"""SimHash near-duplicates by a byte-position inverted index with count filtering.

A fingerprint has eight bytes. Two fingerprints that differ in at most four bits differ in at most four bytes, so
they share at least four of the eight (position, byte) postings. Merging single-byte lists would meet a fixed share
of all pairs, so the index lists fingerprints under three positional bytes at a time; the twenty triples in
``TRIPLES`` are chosen so that every set of four positions holds at least one of them, hence no pair that reaches
four shared bytes is missed. Where two fingerprints meet in a list, their shared positional bytes are tallied; pairs
with four or more are kept and verified by their differing bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, connected_components, cut, id_back, id_or_last, shuffle_partitions, table, tidy

BITS, SEED, WORDS, RADIUS = 64, 42, 4, 4
BYTES = 8
LEAST_SHARED = BYTES - RADIUS
#: Lists up to this long are compared pair by pair; longer ones by a search that leaves only a spanning tree.
SHORT_LIST = 48
#: Shingles hashed before their bits are counted; bounds a task's memory.
CHUNK = 1 << 19


def _triples() -> list[tuple[int, ...]]:
    groups = [(0, 1, 2), (3, 4, 5), (6, 7)]
    inside = [g for g in groups if len(g) == 3]
    across = [(*two, one) for k, g in enumerate(groups) for two in combinations(g, 2) for one in groups[(k + 1) % 3]]
    return inside + across


TRIPLES = _triples()
MASKS = [sum(0xFF << (8 * p) for p in t) for t in TRIPLES]
BIT_TABLE = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.float64)


def shingle_hashes(text: bytes, words: int = WORDS, seed: int = SEED) -> list[int]:
    """XXH64 of each run of words, of the whole sequence if it is shorter, nothing if there is no word."""
    parts = text.lower().split()
    if not parts:
        return []
    joined = b" ".join(parts)
    n = max(1, len(parts) - words + 1)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1)
    starts = np.concatenate(([0], ends[: n - 1])).tolist()
    stops = (ends[-n:] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    return [digest(joined[a:b], seed) for a, b in zip(starts, stops, strict=True)]


def _fold(hashes: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """Times that each of the 64 bits is set, for each of n owners."""
    out = np.empty((n, BITS))
    raw = hashes.view(np.uint8).reshape(-1, BYTES)
    for p in range(BYTES):
        counts = np.bincount(owner * 256 + raw[:, p], minlength=n * 256).reshape(n, 256)
        out[:, 8 * p : 8 * p + 8] = counts @ BIT_TABLE
    return out


def majority(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """uint64 fingerprints of owners with so many hashes each, in order."""
    ones = np.zeros((len(sizes), BITS))
    owner = np.repeat(np.arange(len(sizes)), sizes)
    for at in range(0, len(hashes), CHUNK):
        low, high = owner[at], owner[min(at + CHUNK, len(owner)) - 1] + 1
        ones[low:high] += _fold(hashes[at : at + CHUNK], owner[at : at + CHUNK] - low, high - low)
    return np.packbits((ones * 2 > np.asarray(sizes)[:, None]).astype(np.uint8), axis=1, bitorder="little").view(np.uint64).ravel()


def fingerprint_array(texts: list[bytes | None]) -> np.ndarray:
    """uint64 fingerprints; a bit is set if more than half of the shingles have it."""
    ones, totals = np.zeros((len(texts), BITS)), np.zeros(len(texts))
    held: list[int] = []
    sizes: list[tuple[int, int]] = []

    def flush() -> None:
        if held:
            rows = np.array([i for i, _ in sizes])
            owner = np.repeat(np.arange(len(rows)), [k for _, k in sizes])
            np.add.at(ones, rows, _fold(np.array(held, dtype=np.uint64), owner, len(rows)))
            held.clear()
            sizes.clear()

    for i, text in enumerate(texts):
        got = shingle_hashes(text or b"")
        totals[i] = len(got)
        for at in range(0, len(got), CHUNK):
            part = got[at : at + CHUNK]
            held += part
            sizes.append((i, len(part)))
            if len(held) >= CHUNK or len(sizes) >= 1024:
                flush()
    flush()
    bits = (ones * 2 > totals[:, None]).astype(np.uint8)
    return np.packbits(bits, axis=1, bitorder="little").view(np.uint64).ravel()


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp bigint) of every row; null texts count as empty, null ids stay null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 1024):
                part = b.slice(at, 1024)
                fp = fingerprint_array(part.column(1).to_pylist()).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fp)], names=["id", "fp"])

    return bounded_batches(docs.select(F.col(id_col).cast("bigint").alias("id"), F.encode(F.col(text_col), "UTF-8").alias("b"))).mapInArrow(tidy(run), "id bigint, fp bigint")


def _short(fp: np.ndarray, rep: np.ndarray, run: np.ndarray, size: np.ndarray) -> Iterator[np.ndarray]:
    s = 1
    while True:
        keep = size > s
        fp, rep, run, size = fp[keep], rep[keep], run[keep], size[keep]
        if len(fp) <= s:
            return
        x = fp[:-s] ^ fp[s:]
        shared = (x.view(np.uint8).reshape(-1, BYTES) == 0).sum(axis=1)
        hit = (run[:-s] == run[s:]) & (shared >= LEAST_SHARED) & (np.bitwise_count(x) <= RADIUS)
        if hit.any():
            yield np.stack([rep[:-s][hit], rep[s:][hit]])
        s += 1


def _long(fp: np.ndarray, rep: np.ndarray) -> Iterator[np.ndarray]:
    """Spanning trees of the links in one list: what is reached leaves the set that later steps compare with."""
    left_fp, left_rep = fp, rep
    while len(left_fp):
        frontier = [(left_fp[0], left_rep[0])]
        left_fp, left_rep = left_fp[1:], left_rep[1:]
        while frontier and len(left_fp):
            f, r = frontier.pop()
            x = left_fp ^ f
            near = np.bitwise_count(x) <= RADIUS
            near &= (x.view(np.uint8).reshape(-1, BYTES) == 0).sum(axis=1) >= LEAST_SHARED
            if near.any():
                found = left_rep[near]
                yield np.stack([np.full(len(found), r), found])
                frontier += zip(left_fp[near], found, strict=True)
                left_fp, left_rep = left_fp[~near], left_rep[~near]


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (t, v, fp, rep) sorted by list; yields links."""

    def links(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        t, v, fp, rep = cols
        if len(t) < 2:
            return
        new = np.concatenate(([True], (t[1:] != t[:-1]) | (v[1:] != v[:-1])))
        start = np.flatnonzero(new)
        size = np.diff(np.append(start, len(t)))
        run = np.cumsum(new) - 1
        each = size[run]
        fp = np.ascontiguousarray(fp).view(np.uint64)
        few = (each > 1) & (each <= SHORT_LIST)
        found = _short(fp[few], rep[few], run[few], each[few])
        for p in found:
            yield pa.RecordBatch.from_arrays([pa.array(p.min(axis=0)), pa.array(p.max(axis=0))], names=["a", "b"])
        for k in np.flatnonzero(size > SHORT_LIST):
            part = slice(start[k], start[k] + size[k])
            for p in _long(fp[part], rep[part]):
                yield pa.RecordBatch.from_arrays([pa.array(p.min(axis=0)), pa.array(p.max(axis=0))], names=["a", "b"])

    held: list[np.ndarray] | None = None
    for b in batches:
        cols = [c.to_numpy() for c in b.columns]
        if not len(cols[0]):
            continue
        if held is not None:
            cols = [np.concatenate(x) for x in zip(held, cols, strict=True)]
        t, v = cols[:2]
        last = (t == t[-1]) & (v == v[-1])
        at = len(t) if not last.any() else int(np.argmax(last))
        yield from links([c[:at] for c in cols])
        held = [c[at:] for c in cols]
    if held is not None:
        yield from links(held)


def links(classes: DataFrame) -> DataFrame:
    """Links (a, b) between representatives of (fp, rep): enough to connect all that are within the radius.

    Each list of up to SHORT_LIST fingerprints gives all its verified pairs, a longer one a spanning tree of each of
    its connected parts, so a large group of copies gives about as many rows as members.
    """
    n = shuffle_partitions(classes.sparkSession)
    masks = F.array(*[F.lit(m if m < 2**63 else m - 2**64).cast("bigint") for m in MASKS])
    lists = classes.select("fp", "rep", F.posexplode(masks).alias("t", "m")).select("t", F.col("fp").bitwiseAND(F.col("m")).alias("v"), "fp", "rep")
    return lists.repartition(n, "t", "v").sortWithinPartitions("t", "v", "fp").mapInArrow(tidy(_scan), "a bigint, b bigint").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row of docs.

    Rows with equal fingerprints form a class of which one representative enters the index; components are found
    over representatives. Null and empty texts have fingerprint zero; a null id never names a component unless all
    members lack one (nor does the greatest number that an id can be); repeated rows give repeated results.
    """
    fps = cut(fingerprints(docs, id_col, text_col))
    classes = fps.groupBy("fp").agg(F.min(id_or_last("id")).alias("rep"))
    comp = connected_components(links(classes))
    named = classes.join(comp, classes.rep == comp.node, "left").select("fp", F.coalesce("component", "rep").alias("component"))
    out = fps.join(named, "fp")
    return out.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), id_back("component").alias("component_id"))


def op9_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The pipeline's stage: one document of each group of five-word similarity 0.8; op9's index, then an exact join."""
    from .similar_sets import keep_one as stage

    return stage(docs, id_col, text_col)
