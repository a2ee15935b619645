"""Sparsifiers and tensor plumbing as window and aggregate expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_of

BLOCK = 1 << 20


def r_of(d: int, ratio: float) -> int:
    return max(1, int(d * ratio))


def top_r(coo: DataFrame, r: int | str) -> DataFrame:
    """The r largest magnitudes of each tensor, ties by idx; Spark trims to r rows a task before the shuffle."""
    w = Window.partitionBy("tensor_id").orderBy(F.abs("value").desc(), "idx")
    return _first(coo, w, r)


def random_r(coo: DataFrame, r: int | str, seed: int = 0) -> DataFrame:
    """The r cells of least seeded priority: uniform over seeds, the same in every attempt."""
    w = Window.partitionBy("tensor_id").orderBy(hash_of("idx", 0, seed, "random_r"), "idx")
    return _first(coo, w, r)


def _first(coo: DataFrame, w: Window, r: int | str) -> DataFrame:
    return coo.withColumn("n", F.row_number().over(w)).where(F.col("n") <= (F.lit(r) if isinstance(r, int) else F.expr(r))).drop("n")


def top_r_by_threshold(coo: DataFrame, r: int) -> DataFrame:
    """Top-r of one huge tensor without a sort of all cells: a quantile of the magnitudes, then an exact trim above it."""
    n = coo.count()
    if n <= r:
        return coo
    share = max(0.0, 1 - 1.1 * r / n - 1e-3)
    cut = coo.agg(F.percentile_approx(F.abs("value"), share, 10_000)).first()[0]
    above = coo.where(F.abs("value") >= cut)
    return top_r(above if above.count() >= r else coo, r)


def identity(coo: DataFrame) -> DataFrame:
    return coo.where("value <> 0")


def threshold(coo: DataFrame, tau: float) -> DataFrame:
    return coo.where(F.abs("value") >= tau)


def densify(coo: DataFrame, meta: DataFrame) -> DataFrame:
    """All d cells, zeros included; blocks keep the generated sequences short."""
    cells = universe(meta)
    return cells.join(coo, ["tensor_id", "idx"], "left").select("tensor_id", "idx", F.coalesce("value", F.lit(0)).alias("value"))


def universe(meta: DataFrame, block: int = BLOCK) -> DataFrame:
    """All indices of each tensor; its blocks are dealt to tasks before they are spelled out."""
    starts = meta.select("tensor_id", "d", F.explode(F.expr(f"sequence(0L, d - 1, {block}L)")).alias("lo")).repartition("tensor_id", "lo")
    return starts.select("tensor_id", F.explode(F.expr(f"sequence(lo, least(lo + {block}L, d) - 1)")).alias("idx"))


def split(coo: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Index set and value array, in order of idx."""
    from .ranks import by_idx

    rows = by_idx(coo, "pos").withColumn("pos", F.col("pos") - 1)
    return rows.select("tensor_id", "pos", "idx"), rows.select("tensor_id", "pos", "value")


def to_bitmap(coo: DataFrame) -> DataFrame:
    """(tensor_id, word_no, word): 64 cells to a word, merged before the shuffle."""
    return coo.groupBy("tensor_id", F.expr("idx div 64").alias("word_no")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(idx % 64 AS INT))")).alias("word"))


def from_bitmap(words: DataFrame) -> DataFrame:
    rows = words.select("tensor_id", "word_no", "word", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("bit"))
    return rows.where("getbit(word, bit) = 1").selectExpr("tensor_id", "word_no * 64 + bit AS idx")


def blocked(coo: DataFrame, size: int = BLOCK) -> DataFrame:
    return coo.withColumn("block", F.expr(f"CAST(idx div {size} AS INT)"))


def aggregate(coo: DataFrame, n: int) -> DataFrame:
    """Mean over n workers of (worker or tensor_id, idx) cells; the shuffle carries one partial sum a task and cell."""
    return coo.groupBy("idx").agg((F.sum("value") / n).alias("value")).select(F.lit(0).cast("bigint").alias("tensor_id"), "idx", "value")


def accumulate(steps: DataFrame) -> DataFrame:
    """Sum of the gradients of several steps, per tensor."""
    return steps.groupBy("tensor_id", "idx").agg(F.sum("value").alias("value"))
