"""Bloom filters over the index sets of many tensors at once, and the policies for false positives.

A tensor has a filter for each block of 2^20 indices that holds keys, as its containers have: (fpr, tensor_id, block,
words array<bigint>) with m bits. Building merges single bits by bit_or before the shuffle, so repeated and
speculative tasks do no harm. The scan tests k bits of an array that stays beside the generated indices of its block
in one code-generated stage; policies rank the positives of a block. So no row, task or window follows a tensor's
size. Several rates can be built and scanned at once.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_of, hash_positions, hash_sql
from ..sources.checkpoints import checkpointed
from .sparsify import BLOCK

LN2 = math.log(2)
KEYS = ["fpr", "tensor_id", "block"]


def bloom_size(r: int, fpr: float) -> tuple[int, int]:
    """Bits and hashes for r keys at a false-positive rate."""
    m = max(1, math.ceil(-r * math.log(fpr) / LN2**2 - 1e-9))
    return m, hashes_for(fpr)


def hashes_for(fpr: float) -> int:
    return max(1, round(-math.log2(fpr)))


def bloom_k(m: int, r: int) -> int:
    return max(1, round(m / r * LN2))


def fpr_of(m: int, k: int, r: int) -> float:
    return (1 - math.exp(-k * r / m)) ** k


def bits_sql(r: str, fpr: float) -> str:
    """m of a filter as SQL over r."""
    return f"greatest(1, CAST(ceil({r} * {-math.log(fpr) / LN2**2!r}D - 1e-9D) AS BIGINT))"


def sizes(coo: DataFrame, meta: DataFrame, fpr: float | Sequence[float], block: int = BLOCK) -> DataFrame:
    """(fpr, tensor_id, block, width, r, m, k) of each block that has keys, for one rate or several."""
    rates = [fpr] if isinstance(fpr, (int, float)) else list(fpr)
    kept = coo.groupBy("tensor_id", F.expr(f"idx div {block}").alias("block")).agg(F.count("*").alias("r"))
    kept = kept.join(meta.select("tensor_id", "d"), "tensor_id").selectExpr("tensor_id", "block", f"least({block}L, d - block * {block}L) AS width", "r")
    rate = F.explode(F.array(*[F.struct(F.lit(float(f)).alias("fpr"), F.expr(bits_sql("r", f)).alias("m"), F.lit(hashes_for(f)).alias("k")) for f in rates]))
    return kept.select("tensor_id", "block", "width", "r", rate.alias("s")).select("s.fpr", "tensor_id", "block", "width", "r", "s.m", "s.k")


def filters(coo: DataFrame, meta: DataFrame, fpr: float | Sequence[float], seed: int = 0, block: int = BLOCK) -> DataFrame:
    """(fpr, tensor_id, block, width, r, m, k, words): a filter for each block of a tensor that has keys.

    Blocks bound a row by what the filter of ``block`` keys takes, whatever the tensor's size, and are dealt to tasks
    by the shuffle that merges the words. The keys of a block are hashed by their place in it.
    """
    rates = [fpr] if isinstance(fpr, (int, float)) else list(fpr)
    most = max(map(hashes_for, rates))
    sized = sizes(coo, meta, rates, block)
    keys = coo.select("tensor_id", F.expr(f"idx div {block}").alias("block"), F.expr(f"idx % {block}").alias("place"))
    at = hash_positions("place", most, "m", seed, "block")
    bits = keys.join(sized, ["tensor_id", "block"]).select(*KEYS, F.explode(F.slice(at, F.lit(1), F.col("k")) if len(rates) > 1 else at).alias("pos"))
    set_ = bits.selectExpr(*KEYS, "pos div 64 AS word_no", "shiftleft(1L, CAST(pos % 64 AS INT)) AS word")
    unset = sized.selectExpr(*KEYS, "explode(sequence(0L, (m - 1) div 64)) AS word_no").withColumn("word", F.lit(0).cast("bigint"))
    words = set_.unionByName(unset).groupBy(*KEYS, "word_no").agg(F.bit_or("word").alias("word"))
    arrays = words.groupBy(*KEYS).agg(F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("w")).select(*KEYS, F.col("w.word").alias("words"))
    return sized.join(arrays, KEYS)


def contains(idx: str, k: int, seed: int = 0, words: str = "words", m: str = "m", block: str = "0", own_k: str | None = None) -> Column:
    """Whether all k bits are set; one test after the other, so most misses stop at the first. own_k: a column with
    the number of hashes of the row's filter, at most k."""
    tests = []
    for j in range(k):
        pos = f"({hash_sql(idx, j, seed, 'bloom', block)} % {m})"
        test = f"getbit({words}[CAST({pos} div 64 AS INT)], CAST({pos} % 64 AS INT)) = 1"
        tests.append(f"({own_k} <= {j} OR {test})" if own_k else test)
    return F.expr(" AND ".join(tests))


def positives(filters_: DataFrame, fpr: float | Sequence[float], seed: int = 0, block: int = BLOCK) -> DataFrame:
    """(fpr, tensor_id, block, idx) of all indices in [0, d) that a filter accepts, each block scanned by one task."""
    rates = [fpr] if isinstance(fpr, (int, float)) else list(fpr)
    cells = filters_.select(*KEYS, "m", "k", "words", F.explode(F.expr("sequence(0L, width - 1)")).alias("place"))
    hit = contains("place", max(map(hashes_for, rates)), seed, block="block", own_k="k" if len(rates) > 1 else None)
    return cells.where(hit).select(*KEYS, (F.col("block") * block + F.col("place")).alias("idx"))


def chosen(p: DataFrame, sized: DataFrame, policy: str, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """The chosen indices among the positives of each block: all for p0, r of them for p1, left, middle and right."""
    if policy == "p0":
        return p.select("tensor_id", "idx")
    rows = _nth(p, KEYS, policy, seed, block)
    if policy == "middle":
        rows = rows.join(p.groupBy(*KEYS).agg(F.count("*").alias("skip")), KEYS).join(sized.select(*KEYS, "r"), KEYS)
        rows = rows.withColumn("skip", F.expr("(skip - r) div 2"))
        return rows.where("n > skip AND n <= skip + r").select("tensor_id", "idx")
    return rows.join(sized.select(*KEYS, "r"), KEYS).where("n <= r").select("tensor_id", "idx")


def _nth(rows: DataFrame, keys: list[str], policy: str, seed: int, block: int, name: str = "n") -> DataFrame:
    """rows with name, their row number in a policy's order. A block beyond BLOCK is ranked in stretches of the order."""
    if block <= BLOCK:
        return rows.withColumn(name, F.row_number().over(Window.partitionBy(*keys).orderBy(*_order(policy, seed, block))))
    from .ranks import ranked

    if policy == "p1":
        stretch = F.expr(f"{hash_sql(f'(idx % {block})', 0, seed, 'p1', 'block')} div {1 << 21}")
    else:
        stretch = F.expr(f"idx div {BLOCK}")
    cut = rows.withColumn("sw__stretch", -stretch if policy == "right" else stretch)
    return ranked(cut, keys, ["sw__stretch"], _order(policy, seed, block), name).drop("sw__stretch", f"{name}_total")


def _order(policy: str, seed: int, block: int) -> list[Column]:
    """The order in which a policy takes positives of a block."""
    if policy == "p1":
        return [hash_of(f"(idx % {block})", 0, seed, "p1", "block"), F.col("idx")]
    return [F.col("idx").desc()] if policy == "right" else [F.col("idx")]


def chosen_by_rounds(p: DataFrame, sized: DataFrame, fpr: float, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """(tensor_id, idx) by conflict sets, for many blocks at once.

    Each round, every set offers its unused member of least priority; offers are taken by (size, bit), members offered
    twice once, until r are chosen. It differs from the sequential draw within a round only: a set there sees what the
    sets before it took. A round takes one member at least of each block that lacks any, and a block has r true keys
    among its positives, so rounds end. They are checkpointed in the shared folder.
    """
    sets = conflict_sets(p, sized, fpr, seed, block).select(*KEYS, "bit", "size", F.explode("members").alias("idx"))
    pairs = checkpointed(sets.withColumn("priority", hash_of(f"(idx % {block})", 0, seed, "p2", "block")))
    got = pairs.select(*KEYS, "idx").limit(0)
    while True:
        have = got.groupBy(*KEYS).agg(F.count("*").alias("have"))
        left = sized.select(*KEYS, "r").join(have, KEYS, "left").select(*KEYS, (F.col("r") - F.coalesce("have", F.lit(0))).alias("need")).where("need > 0")
        open_ = pairs.join(got, [*KEYS, "idx"], "left_anti").join(left, KEYS)
        offers = open_.groupBy(*KEYS, "bit", "size", "need").agg(F.min(F.struct("priority", "idx")).alias("o"))
        once = offers.groupBy(*KEYS, "need", F.col("o.idx").alias("idx")).agg(F.min(F.struct("size", "bit")).alias("at"))
        taken = checkpointed(once.withColumn("n", F.row_number().over(Window.partitionBy(*KEYS).orderBy("at"))).where("n <= need").select(*KEYS, "idx"))
        if taken.isEmpty():
            return got.select("tensor_id", "idx")
        got = checkpointed(got.unionByName(taken))


def fetched(chosen_: DataFrame, g: DataFrame) -> DataFrame:
    """Values at the chosen indices, 0 where g has none. g dense: originals; g sparse: zeros at false positives."""
    return chosen_.join(g, ["tensor_id", "idx"], "left").select("tensor_id", "idx", F.coalesce("value", F.lit(0)).alias("value"))


def handed_out(p: DataFrame, coo: DataFrame, block: int = BLOCK) -> DataFrame:
    """p with n, its place among the block's positives, and handed: the n-th true value of the block, null beyond."""
    keys = _nth(p, KEYS, "left", 0, block)
    values = coo.select("tensor_id", F.expr(f"idx div {block}").alias("block"), "idx", F.col("value").alias("handed"))
    values = _nth(values, ["tensor_id", "block"], "left", 0, block).drop("idx")
    return keys.join(values, ["tensor_id", "block", "n"], "left")


def decoded_naive(p: DataFrame, coo: DataFrame, block: int = BLOCK) -> DataFrame:
    """What a receiver rebuilds that hands the true values of a block to its positives in order, until they run out."""
    return handed_out(p, coo, block).where("handed IS NOT NULL").select("tensor_id", "idx", F.col("handed").alias("value"))


def conflict_sets(p: DataFrame, sized: DataFrame, fpr: float, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """(fpr, tensor_id, block, bit, size, members): the positives that hash to each set bit of a block's filter."""
    rows = p.join(sized.select(*KEYS, "m"), KEYS).withColumn("place", F.expr(f"idx % {block}"))
    pairs = rows.select(*KEYS, "idx", F.explode(F.array_distinct(hash_positions("place", hashes_for(fpr), "m", seed, "block"))).alias("bit"))
    return pairs.groupBy(*KEYS, "bit").agg(F.count("*").alias("size"), F.array_sort(F.collect_list("idx")).alias("members"))


def decode(coo: DataFrame, meta: DataFrame, fpr: float, policy: str, seed: int = 0, g: DataFrame | None = None, block: int = BLOCK) -> DataFrame:
    """Encode and decode by a filter and a policy other than p2; g defaults to the sparse tensor."""
    p = positives(filters(coo, meta, fpr, seed, block), fpr, seed, block)
    if policy == "naive":
        return decoded_naive(p, coo, block)
    return fetched(chosen(p, sizes(coo, meta, fpr, block), policy, seed, block), coo if g is None else g)


POLICIES = ("p0", "p1", "left", "middle", "right", "naive")


def policy_errors(coo: DataFrame, meta: DataFrame, rates: Sequence[float], seed: int = 0, block: int = BLOCK, p: DataFrame | None = None) -> DataFrame:
    """(fpr, policy, tensor_id, error, rel_volume) of every rate and policy from one scan and one ranked frame.

    Every key is a positive, so a policy's error is what it leaves out: the squares of keys that it does not choose,
    and for the naive hand-out the squared gaps between what a positive holds and what it is given. p: the positives,
    where they are known.
    """
    sized = sizes(coo, meta, rates, block)
    p = positives(filters(coo, meta, rates, seed, block), rates, seed, block) if p is None else p
    rows = handed_out(p, coo, block).join(coo, ["tensor_id", "idx"], "left")
    rows = _nth(rows, KEYS, "p1", seed, block, "drawn").join(p.groupBy(*KEYS).agg(F.count("*").alias("c")), KEYS)
    rows = rows.join(sized.select(*KEYS, "r", "m"), KEYS).withColumn("v", F.coalesce(F.col("value").cast("double"), F.lit(0.0)))
    kept = {"p0": "true", "p1": "drawn <= r", "left": "n <= r", "middle": "n > (c - r) div 2 AND n <= (c - r) div 2 + r", "right": "n > c - r"}
    lost = {**{k: f"CASE WHEN {c} THEN 0D ELSE v * v END" for k, c in kept.items()}, "naive": "pow(v - coalesce(CAST(handed AS DOUBLE), 0D), 2)"}
    sums = [F.sum(F.expr(e)).alias(f"lost_{k}") for k, e in lost.items()]
    blocks = rows.groupBy(*KEYS, "r", "m").agg(*sums, F.sum(F.col("v") * F.col("v")).alias("norm2"), F.count("*").alias("c"))
    total = blocks.groupBy("fpr", "tensor_id").agg(*[F.sum(f"lost_{k}").alias(f"lost_{k}") for k in POLICIES], *[F.sum(c).alias(c) for c in ("norm2", "c", "r", "m")]).join(meta.select("tensor_id", "d"), "tensor_id")
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("policy"), (F.col(f"lost_{k}") / F.col("norm2")).alias("error"), ((F.col("m") + 32 * F.col("c" if k == "p0" else "r")) / (32 * F.col("d"))).alias("rel_volume")) for k in POLICIES]))
    return total.select("fpr", "tensor_id", each.alias("x")).select("fpr", "x.policy", "tensor_id", "x.error", "x.rel_volume")


def hybrid_counts(true: DataFrame, chosen_: DataFrame) -> DataFrame:
    """(tensor_id, k1, k2): chosen true keys and chosen false positives."""
    marked = chosen_.join(true.select("tensor_id", "idx", F.lit(1).alias("hit")), ["tensor_id", "idx"], "left")
    return marked.groupBy("tensor_id").agg(F.count("hit").alias("k1"), (F.count("*") - F.count("hit")).alias("k2"))


#: Bits of a filter that is broadcast.
BROADCAST_BITS = 32 << 23


def semi_join(left: DataFrame, right: DataFrame, on: str, fpr: float = 0.01, seed: int = 0) -> DataFrame:
    """left_semi on an integer key below 2**31, with left cut down by a broadcast filter of right's keys before the
    shuffle.

    The keys are counted first. Where the filter would take more than BROADCAST_BITS it is held to that size with the
    hashes that suit it, and where that leaves less than two bits a key the plain join is all there is.
    """
    keys = checkpointed(right.select(F.col(on).cast("bigint").alias("idx")).where("idx IS NOT NULL").distinct())
    n = max(1, keys.count())
    m = min(bloom_size(n, fpr)[0], BROADCAST_BITS)
    if m < 2 * n:
        return left.join(right.select(on).distinct(), on, "left_semi").select(*left.columns)
    k = min(hashes_for(fpr), bloom_k(m, n))
    bits = keys.select(F.explode(hash_positions("idx", k, str(m), seed)).alias("pos")).selectExpr("pos div 64 AS word_no", "shiftleft(1L, CAST(pos % 64 AS INT)) AS word")
    words = bits.unionByName(left.sparkSession.range((m + 63) // 64).select(F.col("id").alias("word_no"), F.lit(0).cast("bigint").alias("word")))
    row = words.groupBy("word_no").agg(F.bit_or("word").alias("word")).agg(F.array_sort(F.collect_list(F.struct("word_no", "word"))).alias("w")).select(F.col("w.word").alias("sw__words"))
    beside = left.withColumn("sw__one", F.lit(0)).join(F.broadcast(row.withColumn("sw__one", F.lit(0))), "sw__one")
    passed = beside.where(contains(f"CAST({on} AS BIGINT)", k, seed, "sw__words", str(m))).select(*left.columns)
    return passed.join(right.select(on).distinct(), on, "left_semi").select(*left.columns)
