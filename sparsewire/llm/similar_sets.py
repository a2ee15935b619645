"""Groups of documents whose sets of word runs are alike: SimHash links first, an exact set join for the rest.

Two documents are linked if the Jaccard similarity of their sets of WORDS-word shingles is NUM / DEN or more.

1. The byte-position index of simhash_dedup gives pairs of fingerprints within its radius; pairs whose sets are found
   alike are links. No radius of fingerprints meets every pair of that similarity, so this alone would lose links.
2. In any fixed order of shingles, linked sets of sizes m and n share a shingle among the first
   m - ceil(m * NUM / DEN) + 1 of one and the first n - ceil(n * NUM / DEN) + 1 of the other, so lists over these
   prefixes meet every linked pair. Pairs that step 1 has joined already are passed over. Shingles that a sample of
   documents repeats come last in the order, which keeps lists short and has no influence on what is found.

Short lists give all their pairs. A long one first gives each member's pairs with its neighbour by size and with its
middle; once these are verified and joined to components, it gives the pairs that lie in different components, so a
large group of near copies does not cost the square of its size.

Sets are never stored: each step reads the texts again, which costs less than the disk for eight bytes a word. Pairs
are first tested by parity bits of their sets, which proves most chance meetings unlike, and only then by the sets.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, bounded_batches, connected_components, cut, id_or_last, shuffle_partitions, small_side, tidy
from .shingles import shingles
from .simhash_dedup import links as fingerprint_links
from .simhash_dedup import majority

WORDS, NUM, DEN = 5, 4, 5
SHORT_LIST = 48
#: Classes whose shingles are counted for the order, and most shingles that the order knows.
SAMPLE, ORDERED = 5_000, 100_000
#: Pairs that a long list yields at once; classes that a task remembers, to send a class's shingles once.
CHUNK, REMEMBERED = 1 << 16, 1 << 18
#: Least number of parity bits, as a power of two.
LEAST_BITS = 8


def _named(part: pa.RecordBatch) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """Set, and hash of the set, of each text in the second column; all shingle hashes and how many each text has."""
    h, n = shingles(part.column(1).to_pylist(), WORDS)
    stops = np.cumsum(n).tolist()
    sets = [np.unique(h[a:b]) for a, b in zip([0, *stops[:-1]], stops, strict=True)]
    k = np.array([xxhash.xxh64_intdigest(s.tobytes()) for s in sets], np.uint64).view(np.int64)
    return sets, k, h, n


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(id_or_last(id_col).alias("id"), F.encode(F.col(text_col), "UTF-8").alias("b"))


def parities(s: np.ndarray) -> bytes:
    """A bit for each of a power of two of buckets, two a hash at least, set if an odd number of the hashes fall into it."""
    bits = 1 << max(LEAST_BITS, (2 * max(len(s), 1) - 1).bit_length())
    odd = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def _base(rows: DataFrame) -> DataFrame:
    """(id, k, fp, n, bits) of each row: a hash of its set of shingles, the fingerprint of all of them, the size and
    the parities of the set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                sets, k, h, n = _named(part)
                cols = [part.column(0), pa.array(k), pa.array(majority(h, n).view(np.int64)), pa.array([len(s) for s in sets], pa.int64()), pa.array([parities(s) for s in sets], pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, names=["id", "k", "fp", "n", "bits"])

    return bounded_batches(rows).mapInArrow(tidy(run), "id bigint, k bigint, fp bigint, n bigint, bits binary")


def _may_be_alike(pairs: DataFrame, classes: DataFrame) -> DataFrame:
    """The pairs (a, b) but those whose parities prove them unlike.

    Each hash that only one set has turns one bit, so the sets differ in as many hashes at least as their parities
    differ in bits; of unequal lengths the longer is folded. No alike pair is lost, and two to four bits for a shingle
    travel where its set would take sixty-four.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y, m, n in zip(*(batch.column(c).to_pylist() for c in ("x", "y", "m", "n")), strict=True):
                u, v = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                least = min(len(u), len(v))
                apart = np.bitwise_count(np.bitwise_xor.reduce(u.reshape(-1, least)) ^ np.bitwise_xor.reduce(v.reshape(-1, least))).sum()
                keep.append(bool((NUM + DEN) * apart <= (DEN - NUM) * (m + n)))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    own = classes.select("k", "n", "bits")
    both = pairs.join(own.select(F.col("k").alias("a"), F.col("n").alias("m"), F.col("bits").alias("x")), "a")
    both = both.join(own.select(F.col("k").alias("b"), "n", F.col("bits").alias("y")), "b")
    return both.select("a", "b", "m", "n", "x", "y").mapInArrow(tidy(run), "a bigint, b bigint")


def _sets(rows: DataFrame) -> DataFrame:
    """(k, tokens): the sorted set of each class, once for each task that meets it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                sets, k, _, _ = _named(b.slice(at, 256))
                new = []
                for i, name in enumerate(k.tolist()):
                    if name not in seen:
                        seen.add(name)
                        new.append(i)
                if len(seen) > REMEMBERED:
                    seen.clear()
                if new:
                    ends = np.cumsum([0, *(len(sets[i]) for i in new)]).astype(np.int32)
                    tokens = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([sets[i] for i in new]).view(np.int64)))
                    yield pa.RecordBatch.from_arrays([pa.array(k[new]), tokens], names=["k", "tokens"])
        seen.clear()

    return bounded_batches(rows).mapInArrow(tidy(run), "k bigint, tokens array<bigint>")


def _lists(sets: DataFrame, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(token, k, n, pos): the prefix of each set of n tokens, in the order by (count in the sample, token)."""
    known = sets.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        token, count = known.value
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                n = np.asarray(part.column(1).value_lengths(), np.int64)
                flat = part.column(1).flatten().to_numpy(zero_copy_only=False)
                owner = np.repeat(np.arange(len(n)), n)
                rank = np.zeros(len(flat), np.int64)
                if len(token) and len(flat):
                    near = np.minimum(np.searchsorted(token, flat), len(token) - 1)
                    rank = np.where(token[near] == flat, count[near], 0)
                order = np.lexsort((flat, rank, owner))
                pos = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)
                keep = pos <= (n - -(-n * NUM // DEN))[owner]
                k = part.column(0).to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array(flat[order][keep]), pa.array(k[owner[keep]]), pa.array(n[owner[keep]]), pa.array(pos[keep])], names=["token", "k", "n", "pos"])

    return sets.mapInArrow(tidy(run), "token bigint, k bigint, n bigint, pos bigint")


def _may(n: np.ndarray, pos: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Whether sizes, and what is left behind the shared token, allow the similarity; true at a pair's first token."""
    left = np.minimum(n[i] - pos[i], n[j] - pos[j])
    return (DEN * np.minimum(n[i], n[j]) >= NUM * np.maximum(n[i], n[j])) & ((NUM + DEN) * left >= NUM * (n[i] + n[j]))


def _first_pairs(start: np.ndarray, size: np.ndarray, cols: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    each = np.repeat(size, size)
    last = np.repeat(start + size, size)
    at = np.arange(len(each))
    for s in range(1, SHORT_LIST):
        i = at[(each <= SHORT_LIST) & (at + s < last)]
        if not len(i):
            break
        yield i, i + s
    for a, m in zip(start[size > SHORT_LIST].tolist(), size[size > SHORT_LIST].tolist(), strict=True):
        i = np.arange(a, a + m)
        yield i[:-1], i[1:]
        yield i, np.full(m, a + m // 2)


def _other_pairs(start: np.ndarray, size: np.ndarray, cols: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs in different components: each member outside the list's largest component with all others."""
    for a, m in zip(start.tolist(), size.tolist(), strict=True):
        comp = cols[4][a : a + m]
        names, back, counts = np.unique(comp, return_inverse=True, return_counts=True)
        outside = np.flatnonzero(back != counts.argmax())
        step = max(1, CHUNK // m)
        for at in range(0, len(outside), step):
            i, j = np.divmod(np.arange(len(outside[at : at + step]) * m), m)
            i = outside[at : at + step][i]
            keep = comp[i] != comp[j]
            yield a + i[keep], a + j[keep]


def _folded(bits: np.ndarray, words: int) -> np.ndarray:
    """Parities of one list's members, in so many 64-bit words; zeros where a member has fewer."""
    out = np.zeros((len(bits), words), np.uint64)
    for i, x in enumerate(bits):
        if len(x) >= 8 * words:
            out[i] = np.bitwise_xor.reduce(np.frombuffer(x, np.uint64).reshape(-1, words))
    return out


def _parities_allow(bits: np.ndarray, n: np.ndarray, i: np.ndarray, j: np.ndarray, kept: dict[int, np.ndarray]) -> np.ndarray:
    """What _may_be_alike tests, for pairs of members of one list; kept holds the list's folded parities."""
    if 0 not in kept:
        kept[0] = np.array([len(x) // 8 for x in bits], np.int64)
    words = np.minimum(kept[0][i], kept[0][j])
    ok = np.zeros(len(i), bool)
    for w in np.unique(words).tolist():
        at = np.flatnonzero(words == w)
        if w not in kept:
            kept[w] = _folded(bits, w)
        m = kept[w]
        apart = np.bitwise_count(m[i[at]] ^ m[j[at]]).sum(axis=1)
        ok[at] = (NUM + DEN) * apart <= (DEN - NUM) * (n[i[at]] + n[j[at]])
    return ok


def _pairs(lists: DataFrame, choose: Callable) -> DataFrame:
    """Distinct (a, b, kind): keys that may be alike with kind 0; a long list's token with kind 1.

    Where lists carry the parities of their members, pairs that these prove unlike go no further than this task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def batch(a: np.ndarray, b: np.ndarray, kind: int) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(np.full(len(a), kind, np.int32))], names=["a", "b", "kind"])

        def scan(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            # a class that several tasks met is there several times, side by side
            once = np.concatenate(([True], (cols[0][1:] != cols[0][:-1]) | (cols[1][1:] != cols[1][:-1])))
            cols = [c[once] for c in cols]
            token, k, n, pos = cols[:4]
            start = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1])))
            size = np.diff(np.append(start, len(token)))
            if len(long := token[start[size > SHORT_LIST]]):
                yield batch(long, long, 1)
            of, kept = -1, {}
            for i, j in choose(start, size, cols):
                hit = _may(n, pos, i, j) & (cols[4][i] != cols[4][j])
                if len(cols) > 5 and hit.any():
                    # pairs of one list at a time
                    list_ = int(np.searchsorted(start, i[0], side="right")) - 1
                    if list_ != of:
                        of, kept = list_, {}
                    part = slice(start[of], start[of] + size[of])
                    hit[hit] = _parities_allow(cols[5][part], n[part], i[hit] - start[of], j[hit] - start[of], kept)
                if hit.any():
                    x, y = k[i[hit]], k[j[hit]]
                    yield batch(np.minimum(x, y), np.maximum(x, y), 0)

        held: list[np.ndarray] | None = None
        for b in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
            if not len(cols[0]):
                continue
            if held is not None:
                cols = [np.concatenate(x) for x in zip(held, cols, strict=True)]
            at = int(np.argmax(cols[0] == cols[0][-1]))
            if at:
                yield from scan([c[:at] for c in cols])
            held = [c[at:] for c in cols]
        if held is not None:
            yield from scan(held)

    dealt = lists.repartition(shuffle_partitions(lists.sparkSession), "token").sortWithinPartitions("token", "n", "k")
    return cut(dealt.mapInArrow(tidy(run), "a bigint, b bigint, kind int").distinct())


def _verified(pairs: DataFrame, rows: DataFrame, classes: DataFrame) -> DataFrame:
    """The pairs (a, b) of classes whose sets are alike: by parities what can be, and by the sets what is."""
    pairs = cut(_may_be_alike(pairs, classes))
    touched = small_side(pairs.select(F.explode(F.array("a", "b")).alias("k")).distinct())
    ids = classes.join(touched, "k", "left_semi").select(F.col("id").alias("sw__id")).distinct()
    some = _sets(rows.join(small_side(ids), rows.id == F.col("sw__id"), "left_semi")).join(touched, "k", "left_semi").dropDuplicates(["k"])
    both = pairs.join(some.select(F.col("k").alias("a"), F.col("tokens").alias("x")), "a").join(some.select(F.col("k").alias("b"), F.col("tokens").alias("y")), "b")
    return both.where((NUM + DEN) * F.size(F.array_intersect("x", "y")) >= NUM * (F.size("x") + F.size("y"))).select("a", "b")


def _order(rows: DataFrame, classes: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that the sample repeats, and their counts."""
    ids = classes.where(F.pmod(F.xxhash64("k"), F.lit(max(1, classes.count() // SAMPLE))) == 0).select(F.col("id").alias("sw__id")).distinct()
    some = _sets(rows.join(small_side(ids), rows.id == F.col("sw__id"), "left_semi")).select(F.explode("tokens").alias("token"))
    seen = sorted(some.groupBy("token").count().where("count > 2").orderBy(F.desc("count"), "token").limit(ORDERED).collect())
    return np.array([r[0] for r in seen], np.int64), np.array([r[1] for r in seen], np.int64)


def _alike(classes: DataFrame) -> DataFrame:
    """Pairs (a, b) of classes with fingerprints within the radius: each class with the first of its fingerprint, and
    links between the first ones."""
    first = cut(classes.groupBy("fp").agg(F.min("k").alias("rep"), F.count("*").alias("n")))
    many = small_side(first.where("n > 1").select("fp", "rep"))
    equal = classes.join(many, "fp").where("k <> rep").select(F.least("k", "rep").alias("a"), F.greatest("k", "rep").alias("b"))
    return cut(equal.unionByName(fingerprint_links(first.select("fp", "rep"))).distinct())


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, least) of every row: its id and the smallest id of its group, NO_ID for null ids.

    Groups are connected components of links. Rows with equal sets are one node, so texts without a word are one group.
    """
    rows = _rows(docs, id_col, text_col)
    base = cut(_base(rows))
    classes = cut(base.groupBy("k").agg(F.min("id").alias("id"), *[F.first(c).alias(c) for c in ("fp", "n", "bits")]))
    near = cut(_verified(_alike(classes), rows, classes))
    comp = cut(connected_components(near))
    lists = _lists(_sets(rows), _order(rows, classes)).join(small_side(comp.select(F.col("node").alias("k"), "component")), "k", "left")
    lists = lists.select("token", "k", "n", "pos", F.coalesce("component", "k").alias("component"))
    found = _pairs(lists, _first_pairs)
    met = found.where("kind = 0").select("a", "b")
    links = cut(near.unionByName(_verified(met, rows, classes)))
    comp = cut(connected_components(links))
    long = found.where("kind = 1").select(F.col("a").alias("token"))
    if not long.isEmpty():
        again = lists.drop("component").join(small_side(long), "token", "left_semi").join(comp, F.col("k") == F.col("node"), "left")
        again = again.select("token", "k", "n", "pos", F.coalesce("component", "k").alias("component"))
        more = _pairs(again.join(classes.select("k", "bits"), "k").select("token", "k", "n", "pos", "component", "bits"), _other_pairs)
        comp = connected_components(links.unionByName(_verified(more.where("kind = 0").select("a", "b").join(met, ["a", "b"], "left_anti"), rows, classes)))
    named = cut(classes.join(comp, classes.k == comp.node, "left").select("k", "id", F.coalesce("component", "k").alias("component")))
    least = named.groupBy("component").agg(F.min("id").alias("least"))
    return base.select("id", "k").join(named.join(least, "component").select("k", "least"), "k").select("id", "least")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the ids of which no row is the smallest of its group.

    Rows without an id cannot be told apart and stay; rows with equal id stay or go together. The ids that go are
    broadcast if they are measured small, so texts need no shuffle.
    """
    marks = groups(docs, id_col, text_col).where(F.col("id") != NO_ID)
    gone = marks.groupBy(F.col("id").alias("sw__gone")).agg(F.max((F.col("id") == F.col("least")).cast("int")).alias("first")).where("first = 0").select("sw__gone")
    return docs.join(small_side(gone), docs[id_col] == F.col("sw__gone"), "left_anti")
