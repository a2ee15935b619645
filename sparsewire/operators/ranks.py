"""Ranks, neighbours and cuts of tensors that no single task should sort.

A tensor is cut into buckets that keep the order: blocks of indices, or stretches between quantiles of the values.
Windows run over (tensor, bucket); what a bucket needs to know of those before and after it comes from one row a
bucket.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.checkpoints import small_side
from .sparsify import BLOCK

#: Stretches that the values of a large tensor are cut into.
CUTS = 256


def ranked(rows: DataFrame, keys: Sequence[str], buckets: Sequence[str], order: Sequence[Column], name: str = "n") -> DataFrame:
    """rows with name, the row number from 1 within keys by buckets and then order, and name_total, the rows of keys."""
    at = [*keys, *buckets]
    counts = rows.groupBy(*at).agg(F.count("*").alias("sw__count"))
    whole = Window.partitionBy(*keys)
    before = F.coalesce(F.sum("sw__count").over(whole.orderBy(*buckets).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = counts.select(*at, before.alias("sw__before"), F.sum("sw__count").over(whole).alias(f"{name}_total"))
    local = rows.withColumn(name, F.row_number().over(Window.partitionBy(*at).orderBy(*order)))
    return local.join(offsets, at).withColumn(name, F.col(name) + F.col("sw__before")).drop("sw__before")


def by_idx(coo: DataFrame, name: str = "n", block: int = BLOCK) -> DataFrame:
    """coo with name, the row number of each cell of a tensor by idx, and name_total."""
    rows = coo.withColumn("sw__block", F.expr(f"idx div {block}"))
    return ranked(rows, ["tensor_id"], ["sw__block"], [F.col("idx")], name).drop("sw__block")


def neighbours(coo: DataFrame, block: int = BLOCK) -> DataFrame:
    """coo with the indices of the cells before and after, null at the ends of a tensor."""
    at, whole = ["tensor_id", "sw__block"], Window.partitionBy("tensor_id").orderBy("sw__block")
    rows = coo.withColumn("sw__block", F.expr(f"idx div {block}"))
    ends = rows.groupBy(*at).agg(F.min("idx").alias("sw__min"), F.max("idx").alias("sw__max"))
    ends = ends.select(*at, F.lag("sw__max").over(whole).alias("sw__prev"), F.lead("sw__min").over(whole).alias("sw__next"))
    w = Window.partitionBy(*at).orderBy("idx")
    rows = rows.withColumn("prev", F.lag("idx").over(w)).withColumn("next", F.lead("idx").over(w)).join(ends, at)
    return rows.withColumn("prev", F.coalesce("prev", "sw__prev")).withColumn("next", F.coalesce("next", "sw__next")).drop("sw__block", "sw__prev", "sw__next")


def by_value(rows: DataFrame, keys: Sequence[str], value: str, descending: bool = False, name: str = "n", large: int = BLOCK) -> DataFrame:
    """rows with name, the row number within keys by (value, idx) or by (value descending, idx), and name_total.

    Where keys have more than ``large`` rows, their values are cut at CUTS quantiles of one sketch, which is written,
    so that every reader sees the same cuts. Rows that equal a cut are a bucket of their own and are cut further by
    blocks of indices, so one value that fills a third of the tensor does not land in one task.
    """
    share = F.array(*[F.lit(k / CUTS) for k in range(1, CUTS)])
    sketch = rows.groupBy(*keys).agg(F.count("*").alias("sw__n"), F.percentile_approx(value, share, 20_000).alias("sw__cuts"))
    cuts = small_side(sketch.where(F.col("sw__n") > large).select(*keys, F.array_distinct("sw__cuts").alias("sw__cuts")))
    none = F.lit(0).cast("bigint")
    below = F.size(F.filter("sw__cuts", lambda c: c < F.col(value))).cast("bigint")
    equal = F.array_contains("sw__cuts", F.col(value))
    place = F.when(F.col("sw__cuts").isNull(), none).otherwise(2 * below + F.when(equal, 1).otherwise(0))
    inner = F.when(equal, F.expr(f"idx div {BLOCK}")).otherwise(none)
    both = rows.join(cuts, list(keys), "left").withColumn("sw__a", -place if descending else place).withColumn("sw__b", F.coalesce(inner, none)).drop("sw__cuts")
    order = [F.col(value).desc() if descending else F.col(value), F.col("idx")]
    return ranked(both, keys, ["sw__a", "sw__b"], order, name).drop("sw__a", "sw__b")


def ntile(n: str, total: str, q: int) -> Column:
    """The bucket of row number n among total rows, as ntile(q) gives it, without a window."""
    base, more = f"({total} div {q})", f"({total} % {q})"
    wide = f"({more} * ({base} + 1))"
    return F.expr(f"CAST(CASE WHEN {n} <= {wide} THEN ({n} - 1) div ({base} + 1) + 1 ELSE {more} + ({n} - 1 - {wide}) div greatest({base}, 1) + 1 END AS INT)")

