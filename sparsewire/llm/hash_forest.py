"""Approximate nearest neighbours by a forest of hash prefixes.

Every tree is a sorted array of long hash strings: 64 of a pool of random-hyperplane bits, in an order of its own. A
query descends each tree to its longest-prefix match, which may be of a different length in each, and then ascends
all trees together, one bit at a time, until enough rows are met under its prefixes. Rows are tallied by the trees
that met them, since a near row shares prefixes with the query in far more trees than a chance one; those of most
trees are the candidates, ranked by their exact cosine.

Vectors are dealt to shards of bounded size, each with a forest of its own over all its vectors; the query set goes
to every shard and the best of all shards are kept. Equal vectors are one entry with their smallest ids, so a vector
that fills a third of the table costs one entry. The number of candidates is a share of a shard.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shuffle_partitions, table

TREES, BITS, POOL, SEED = 256, 64, 512, 29
#: Candidates as a share of a shard, and at least so many; rows met in all trees for each candidate.
SHARE, LEAST_CANDIDATES, MET = 0.08, 256, 50
SHARD_ROWS, LEAST_SHARD_ROWS = 1 << 15, 1 << 13


class Forest:
    """Sorted hash strings of the rows of x (unit vectors), one array per tree."""

    def __init__(self, x: np.ndarray, trees: int = TREES, seed: int = SEED) -> None:
        rng = np.random.default_rng(seed)
        self.n, self.planes = len(x), rng.standard_normal((x.shape[1], POOL))
        self.chosen = [rng.permutation(POOL)[:BITS] for _ in range(trees)]
        self.order, self.strings = [], []
        bits = x @ self.planes > 0
        for t in range(trees):
            codes = self._tree(bits, t)
            order = np.argsort(codes, kind="stable")
            self.order.append(order.astype(np.int32))
            self.strings.append(codes[order])

    def _tree(self, bits: np.ndarray, t: int) -> np.ndarray:
        return np.ascontiguousarray(np.packbits(bits[:, self.chosen[t]], axis=1)).view(">u8").ravel().astype(np.uint64)

    def hash(self, x: np.ndarray) -> list[np.ndarray]:
        bits = x @ self.planes > 0
        return [self._tree(bits, t) for t in range(len(self.chosen))]

    @staticmethod
    def _common(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Leading bits that two strings share."""
        x, out = a ^ b, np.zeros(len(a), np.int64)
        for k in (32, 16, 8, 4, 2, 1):
            free = x >> np.uint64(64 - k) == 0
            out += np.where(free, k, 0)
            x = np.where(free, x << np.uint64(k), x)
        return out + (x == 0) * (out == 63)

    def candidates(self, queries: np.ndarray, wanted: int) -> list[np.ndarray]:
        """For each query the rows that most trees have under its prefixes, at the deepest common level where the trees
        meet MET rows for each wanted one; rows of equal tally come together, so there may be more than wanted."""
        n, codes = self.n, self.hash(queries)
        wanted = min(wanted, n)
        longest = np.zeros((len(codes), len(queries)), np.int64)
        for t, (c, s) in enumerate(zip(codes, self.strings, strict=True)):
            at = np.searchsorted(s, c)
            longest[t] = np.maximum(self._common(s[np.minimum(at, n - 1)], c), self._common(s[np.maximum(at - 1, 0)], c))
        found: list[np.ndarray] = [np.arange(n)] * len(queries)
        if wanted == n:
            return found

        def ranges(some: np.ndarray, level: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Where the rows under each query's prefix of its level begin and end in each tree."""
            low = np.where(level > 0, (np.uint64(1) << (64 - np.maximum(level, 1)).astype(np.uint64)) - np.uint64(1), np.uint64(2**64 - 1))
            lo = np.stack([np.searchsorted(s, c[some] & ~low, "left") for c, s in zip(codes, self.strings, strict=True)])
            hi = np.stack([np.searchsorted(s, c[some] | low, "right") for c, s in zip(codes, self.strings, strict=True)])
            return lo, hi

        # rows met only grow on the way up, so the level to stop at is found by halving
        up, down = np.zeros(len(queries), np.int64), longest.max(axis=0)
        every = np.arange(len(queries))
        while (up < down).any():
            mid = (up + down + 1) // 2
            lo, hi = ranges(every, mid)
            enough = (hi - lo).sum(axis=0) >= min(MET * wanted, n * len(codes))
            up, down = np.where(enough, mid, up), np.where(enough, down, mid - 1)
        open_ = every[up > 0]
        while len(open_):
            lo, hi = ranges(open_, up[open_])
            for k, q in enumerate(open_.tolist()):
                met = np.concatenate([order[a:b] for order, a, b in zip(self.order, lo[:, k].tolist(), hi[:, k].tolist(), strict=True)])
                tally = np.bincount(met, minlength=n)
                least = np.partition(tally, n - wanted)[n - wanted]
                # too few different rows: one level further up
                up[q] = 0 if least else up[q] - 1
                if least:
                    found[q] = np.flatnonzero(tally >= least)
            open_ = open_[up[open_] > 0]
        return found


def usable(df: DataFrame, vec_col: str) -> DataFrame:
    """Rows whose vector has no null or non-finite component, is not zero and has the common number of components."""
    v = F.col(vec_col)
    fine = v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = df.where(fine)
    size = rows.groupBy(F.size(vec_col).alias("s")).count().orderBy(F.desc("count"), "s").first()
    return rows.where(F.size(vec_col) == (size["s"] if size else 0))


def search(vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vec_col: str = "embedding", share: float = SHARE, trees: int = TREES) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest found to each query other than the row of its own id.

    Score is the cosine in double precision; ties go to the smaller id. Rows without an id take no part.
    """
    spark = vectors.sparkSession
    good = usable(vectors, vec_col).select(F.col(id_col).cast("bigint").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).where("id IS NOT NULL")
    asked = usable(queries, vec_col).select(F.col(id_col).cast("bigint").alias("query_id"), F.col(vec_col).cast("array<double>").alias("v")).where("query_id IS NOT NULL").distinct()
    n = good.count()
    shards = max(1, math.ceil(n / SHARD_ROWS), min(shuffle_partitions(spark), math.ceil(n / LEAST_SHARD_ROWS)))
    # of equal vectors, the k + 1 smallest ids can be answers
    first = good.distinct().withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("r") <= k + 1)
    entries = first.groupBy("v").agg(F.sort_array(F.collect_list("id")).alias("ids")).withColumn("shard", F.pmod(F.xxhash64("v"), F.lit(shards)).cast("int"))
    sent = asked.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))

    def run(mine: pa.Table, theirs: pa.Table) -> pa.Table:
        out: dict[str, list] = {"query_id": [], "vec_id": [], "score": []}
        if mine.num_rows and theirs.num_rows:
            raw, ids = np.array(mine.column("v").to_pylist()), mine.column("ids").to_pylist()
            q, names = np.array(theirs.column("v").to_pylist()), theirs.column("query_id").to_pylist()
            norms, q_norms = np.linalg.norm(raw, axis=1), np.linalg.norm(q, axis=1)
            forest = Forest(raw / norms[:, None], trees)
            wanted = max(LEAST_CANDIDATES, math.ceil(share * len(raw)))
            for at in range(0, len(q), 512):
                for j, rows in enumerate(forest.candidates(q[at : at + 512] / q_norms[at : at + 512, None], wanted), at):
                    cos = (raw[rows] * q[j]).sum(axis=1) / (norms[rows] * q_norms[j])
                    near = np.argpartition(-cos, k)[: k + 1] if len(cos) > k + 1 else np.arange(len(cos))
                    near = np.flatnonzero(cos >= cos[near].min())
                    got = sorted((-float(cos[i]), d) for i in near for d in ids[rows[i]] if d != names[j])[:k]
                    out["query_id"] += [names[j]] * len(got)
                    out["vec_id"] += [d for _, d in got]
                    out["score"] += [-s for s, _ in got]
        return pa.table({"query_id": pa.array(out["query_id"], pa.int64()), "vec_id": pa.array(out["vec_id"], pa.int64()), "score": pa.array(out["score"], pa.float64())})

    found = entries.groupBy("shard").cogroup(sent.groupBy("shard")).applyInArrow(run, "query_id bigint, vec_id bigint, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_hash_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return search(rows, rows.where(F.col("vec_id") % 50 == 0))
