"""Benchmark decontamination by SimHash over item-sized windows.

Words are runs of letters and digits in lower case (characters beyond ASCII count as letters); a shingle is five of
them. The items' fingerprints are kept by the number of their words, in a multi-index of five blocks of bits: two
fingerprints that differ in at most RADIUS bits differ in at most RADIUS // 5 bits of some block, so each item is
listed under all values that near to its own in each block, and looking up the five blocks of a window finds every item
within the radius. Each pair found is then measured exactly: shingles weighted by how often they occur, the sum of
smaller weights over the sum of larger.

A window is fingerprinted if it holds a shingle of an item of its length; any other has similarity zero to them all.
At similarity 0.8 about ten of 64 bits differ, with a deviation of three; RADIUS lies more than three deviations beyond.
Benchmarks are broadcast in portions of bounded size, one pass over the documents for each.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import any_names, bounded_batches, cut, table, tidy

SHINGLE, SIMILAR = 5, 0.8
BITS, RADIUS = 64, 19
#: Width of each block of bits, and the shift of its first.
WIDTHS = (13, 13, 13, 13, 12)
SHIFTS = tuple(sum(WIDTHS[:k]) for k in range(len(WIDTHS)))
#: Text of the items that are broadcast at once; an item's listings take about forty times its text.
PORTION_BYTES = 2 << 20
#: Windows whose sums of signs are held at once.
HELD = 4096
#: Bytes that end a word become spaces.
APART = bytes(b if b >= 128 or chr(b).isalnum() else 32 for b in range(256))


def _near(width: int) -> np.ndarray:
    """All differences of at most RADIUS // len(WIDTHS) bits."""
    return np.array([sum(1 << k for k in some) for n in range(RADIUS // len(WIDTHS) + 1) for some in combinations(range(width), n)], np.uint64)


NEAR = {w: _near(w) for w in set(WIDTHS)}


def words_of(text: str | None) -> list[bytes]:
    return text.lower().encode().translate(APART).split() if text else []


def signs(words: list[bytes], k: int) -> np.ndarray:
    """One row of 64 signs for each shingle of k words."""
    hashes = np.array([xxhash.xxh64_intdigest(b" ".join(words[i : i + k])) for i in range(len(words) - k + 1)], np.uint64)
    return np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1).astype(np.int32) * 2 - 1


def simhash(sums: np.ndarray) -> np.ndarray:
    """Fingerprints of rows of summed signs."""
    return np.packbits(sums > 0, axis=-1).view(np.uint64).ravel()


def block_values(prints: np.ndarray) -> list[np.ndarray]:
    return [(prints >> np.uint64(s)) & np.uint64((1 << w) - 1) for s, w in zip(SHIFTS, WIDTHS, strict=True)]


@dataclass
class Item:
    id: int
    n: int
    k: int
    shingles: Counter


class BlockIndex:
    """Fingerprints listed, block by block, under every value near to their own."""

    def __init__(self, prints: np.ndarray, items: np.ndarray) -> None:
        self.prints, self.items = prints, items
        self.lists = []
        for values, width in zip(block_values(prints), WIDTHS, strict=True):
            near = (values[:, None] ^ NEAR[width][None, :]).ravel().astype(np.uint16)
            order = np.argsort(near, kind="stable")
            self.lists.append((near[order], (order // len(NEAR[width])).astype(np.int32)))

    def lookup(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """(window, item) of all pairs within the radius, and the number of pairs that the blocks proposed."""
        pairs = []
        for values, (keys, owner) in zip(block_values(windows), self.lists, strict=True):
            values = values.astype(np.uint16)
            lo, hi = np.searchsorted(keys, values, "left"), np.searchsorted(keys, values, "right")
            n = hi - lo
            at = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(n.sum())
            pairs.append(np.repeat(np.arange(len(windows)), n) * len(self.prints) + owner[at])
        found = np.unique(np.concatenate(pairs))
        w, i = np.divmod(found, len(self.prints))
        near = np.bitwise_count(windows[w] ^ self.prints[i]) <= RADIUS
        return w[near], self.items[i[near]], len(found)


class BenchmarkIndex:
    """Items by the blocks of their fingerprints, and the lengths of the items that hold each shingle."""

    def __init__(self, rows: list[tuple[int, str | None]]) -> None:
        self.items: list[Item] = []
        self.vocabulary: dict[bytes, int] = {}
        self.lengths: dict[int, dict[tuple[int, ...], set[int]]] = {}
        self.windows = self.proposed = 0
        prints: dict[int, list[tuple[np.uint64, int]]] = {}
        for item_id, text in rows:
            words = words_of(text)
            if not words:
                continue
            k = min(SHINGLE, len(words))
            ids = [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words]
            counts = Counter(tuple(ids[i : i + k]) for i in range(len(ids) - k + 1))
            for s in counts:
                self.lengths.setdefault(k, {}).setdefault(s, set()).add(len(words))
            prints.setdefault(len(words), []).append((simhash(signs(words, k).sum(axis=0))[0], len(self.items)))
            self.items.append(Item(item_id, len(words), k, counts))
        self.blocks = {n: BlockIndex(np.array([p for p, _ in x], np.uint64), np.array([i for _, i in x])) for n, x in prints.items()}
        self.codes = {k: np.sort(np.array([self._code(np.array(s, np.int64), k)[0] for s in known])) for k, known in self.lengths.items()}

    @staticmethod
    def _code(ids: np.ndarray, k: int) -> np.ndarray:
        """A number for each run of k word ids; equal runs have equal numbers."""
        n = len(ids) - k + 1
        out = np.zeros(max(n, 0), np.int64)
        with np.errstate(over="ignore"):
            for j in range(k):
                out = out * np.int64(1_000_003) + ids[j : j + max(n, 0)]
        return out

    def matches(self, text: str | None) -> list[tuple[int, int, int, float, int]]:
        """(item id, first word, words, similarity, differing bits) of the best window for each item that is met.

        A text shorter than an item is one window for it.
        """
        words = words_of(text)
        if not words:
            return []
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(-1)), np.int64, len(words))
        best: dict[int, tuple[float, int, int, int]] = {}
        for k, known in self.lengths.items():
            if len(words) < k:
                continue
            unknown = np.concatenate(([0], np.cumsum(ids < 0)))
            alive = np.flatnonzero(unknown[k:] == unknown[:-k])
            if not len(alive):
                continue
            codes, sure = self._code(ids, k)[alive], self.codes[k]
            alive = alive[sure[np.minimum(np.searchsorted(sure, codes), len(sure) - 1)] == codes]
            places: dict[int, list[int]] = {}
            at: dict[int, tuple[int, ...]] = {}
            for p in alive.tolist():
                s = tuple(ids[p : p + k].tolist())
                for n in known.get(s, ()):
                    places.setdefault(n, []).append(p)
                    at[p] = s
            every = np.array(sorted(at), np.int64)
            for n, held in places.items():
                self._windows(k, n, held, every, at, words, best)
        return [(self.items[i].id, first, n, sim, bits) for i, (sim, first, n, bits) in sorted(best.items())]

    def _windows(self, k: int, length: int, held: list[int], every: np.ndarray, at: dict[int, tuple[int, ...]], words: list[bytes], best: dict) -> None:
        """Windows of an item length that hold one of the shingles at held; every: all places of known shingles."""
        index, total = self.blocks[length], len(words)
        n = min(length, total)
        stretches: list[list[int]] = []
        for p in held:
            a, b = max(0, p + k - n), min(p, total - n)
            if stretches and a <= stretches[-1][1] + 1:
                stretches[-1][1] = max(stretches[-1][1], b)
            elif a <= b:
                stretches.append([a, b])
        size = n - k + 1
        for a, stop in stretches:
            for a in range(a, stop + 1, HELD):  # noqa: PLW2901
                b = min(a + HELD - 1, stop)
                sums = np.vstack((np.zeros((1, BITS), np.int64), np.cumsum(signs(words[a : b + n], k), axis=0)))
                prints = simhash(sums[size:] - sums[:-size])
                window, item, proposed = index.lookup(prints)
                self.windows, self.proposed = self.windows + len(prints), self.proposed + proposed
                for w, i in zip((window + a).tolist(), item.tolist(), strict=True):
                    inside = every[np.searchsorted(every, w) : np.searchsorted(every, w + size)].tolist()
                    common = sum((Counter(at[p] for p in inside) & self.items[i].shingles).values())
                    sim = common / (size + self.items[i].shingles.total() - common)
                    if sim >= SIMILAR and (i not in best or sim > best[i][0]):
                        best[i] = (sim, w, n, int(np.bitwise_count(prints[w - a] ^ index.prints[index.items == i][0])))


def _portions(benchmark: DataFrame) -> list[DataFrame]:
    """Items in parts of bounded text; of items with the same words, the one of the smallest id stands for all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            text = pa.array([b" ".join(words_of(t)).decode() for t in b.column(1).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), text], names=["item_id", "text"])

    rows = bounded_batches(benchmark.select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").alias("text"))).mapInArrow(tidy(run), "item_id bigint, text string")
    items = cut(rows.where("text <> ''").groupBy("text").agg(F.min("item_id").alias("item_id")))
    n = int(items.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // PORTION_BYTES + 1
    return [items.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k).select("item_id", "text") for k in range(n)]


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, item_id, first_word, n_words, similarity, differing_bits), one row per document and item met.

    The best window of each pair, the first of equals. Null and empty texts meet nothing; items without a word are
    met by nothing; items of fewer than five words are one shingle. Items with the same words count as one, that with
    the smallest id, so copies in a benchmark make no copies of rows.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    schema = {"doc_id": pa.int64(), "item_id": pa.int64(), "first_word": pa.int64(), "n_words": pa.int64(), "similarity": pa.float64(), "differing_bits": pa.int32()}

    def pass_over(part: DataFrame) -> DataFrame:
        some = docs.sparkSession.sparkContext.broadcast([(r.item_id, r.text) for r in part.collect()])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = BenchmarkIndex(some.value)
            for b in batches:
                for at in range(0, b.num_rows, 512):
                    cut = b.slice(at, 512)
                    got = [(d, *m) for d, t in zip(cut.column(0).to_pylist(), cut.column(1).to_pylist(), strict=True) for m in index.matches(t)]
                    yield pa.RecordBatch.from_arrays([pa.array([g[k] for g in got], t) for k, t in enumerate(schema.values())], names=list(schema))

        return bounded_batches(rows).mapInArrow(tidy(run), "doc_id bigint, item_id bigint, first_word bigint, n_words bigint, similarity double, differing_bits int")

    return reduce(DataFrame.unionByName, map(pass_over, _portions(benchmark)))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


@any_names
def keep_clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Rows of docs whose text meets no item.

    Each row is judged by its own text in the pass that reads it, so rows that share an id, or have none, do not
    decide about each other.
    """
    parts = _portions(benchmark)
    text = docs.columns.index("text")

    def pass_over(rows: DataFrame, part: DataFrame) -> DataFrame:
        some = docs.sparkSession.sparkContext.broadcast([(r.item_id, r.text) for r in part.collect()])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = BenchmarkIndex(some.value)
            for b in batches:
                for at in range(0, b.num_rows, 512):
                    cut_ = b.slice(at, 512)
                    yield cut_.filter(pa.array([not index.matches(t) for t in cut_.column(text).to_pylist()], pa.bool_()))

        return bounded_batches(rows).mapInArrow(tidy(run), docs.schema)

    for k, part in enumerate(parts):
        docs = pass_over(cut(docs) if k else docs, part)
    return docs
