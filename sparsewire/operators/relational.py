"""Codecs as window and aggregate expressions, for tensors that no single task should hold; ranks.py cuts them.

They give the same codes as the block kernels where a kernel exists; both are tested against SQL.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, hash_sql
from ..sources.checkpoints import checkpointed, small_side
from .ranks import by_idx, by_value, neighbours, ntile


def delta_keys(coo: DataFrame) -> DataFrame:
    """(tensor_id, idx, gap, gap_bytes): gaps to the previous key, the first from -1."""
    rows = neighbours(coo).withColumn("gap", F.col("idx") - F.coalesce("prev", F.lit(-1)))
    return rows.select("tensor_id", "idx", "gap", F.expr("CASE WHEN gap < 256 THEN 1 WHEN gap < 65536 THEN 2 WHEN gap < 16777216 THEN 3 WHEN gap < 4294967296 THEN 4 ELSE 5 END").alias("gap_bytes"))


def runs(coo: DataFrame, meta: DataFrame) -> DataFrame:
    """(tensor_id, first, symbol, length) of the alternating runs of each bitmap."""
    island = by_idx(coo).withColumn("g", F.col("idx") - F.col("n"))
    ones = island.groupBy("tensor_id", "g").agg(F.min("idx").alias("first"), F.count("*").alias("length")).select("tensor_id", "first", F.lit(1).alias("symbol"), "length")
    ends = neighbours(coo).join(meta.select("tensor_id", "d"), "tensor_id")
    after = ends.select("tensor_id", (F.col("idx") + 1).alias("first"), F.lit(0).alias("symbol"), (F.coalesce("next", "d") - F.col("idx") - 1).alias("length"))
    head = ends.where("prev IS NULL").select("tensor_id", F.lit(0).cast("bigint").alias("first"), F.lit(0).alias("symbol"), F.col("idx").alias("length"))
    return ones.unionByName(after).unionByName(head).where("length > 0")


def gamma_bits(col: str) -> Column:
    return F.expr(f"2 * (length(bin({col})) - 1) + 1")


def key_bytes(coo: DataFrame) -> DataFrame:
    """(tensor_id, byte, n): byte values of four-byte keys."""
    parts = F.expr("array(idx div 16777216, (idx div 65536) % 256, (idx div 256) % 256, idx % 256)")
    return coo.select("tensor_id", F.explode(parts).alias("byte")).groupBy("tensor_id", "byte").agg(F.count("*").alias("n"))


def qsgd(coo: DataFrame, bits: int = 7, bucket: int = 512, seed: int = 0) -> DataFrame:
    """(tensor_id, idx, bucket, level, decoded): stochastic levels of a bucket's norm; positions count by idx."""
    s = 2 ** (bits - 1) - 1
    pos = by_idx(coo, "pos").withColumn("pos", F.col("pos") - 1).withColumn("bucket", F.expr(f"pos div {bucket}"))
    norms = pos.groupBy("tensor_id", "bucket").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
    u = f"(({hash_sql('pos', 0, seed, 'qsgd')}) + 0.5D) / {PRIME}D"
    rows = pos.join(norms, ["tensor_id", "bucket"]).withColumn("level", F.expr(f"CAST(CASE WHEN norm = 0 THEN 0 ELSE least({s}, floor({s} * abs(CAST(value AS DOUBLE)) / norm + {u})) END AS BIGINT)"))
    return rows.select("tensor_id", "idx", "bucket", "level", (F.signum(F.col("value").cast("double")) * F.col("norm") * F.col("level") / s).alias("decoded"))


def skcompress_bits(coo: DataFrame, bits: int = 7) -> DataFrame:
    """(tensor_id, r, bits_idx, bits_val) of whole tensors under the codec of gap bytes and of bucket numbers by Huffman.

    A code's length follows from counts alone: of the byte values of the gaps, and of the buckets, which r fixes. The
    counts of a tensor, a few hundred, are all that one task sees of it.
    """
    import pyarrow as pa

    from .bits import prefix_lengths

    size = 2**bits
    parts = F.expr("transform(sequence(0, gap_bytes - 1), k -> shiftright(gap, 8 * k) & 255)")
    bytes_ = delta_keys(coo).select("tensor_id", F.explode(parts).alias("byte")).groupBy("tensor_id", "byte").agg(F.count("*").alias("n"))
    kept = coo.groupBy("tensor_id").agg(F.count("*").alias("r"))

    def cost(counts: dict[int, int]) -> int:
        return sum(counts[s] * length for s, length in prefix_lengths(counts).items())

    def run(t: pa.Table) -> pa.Table:
        r, counts = t.column("r")[0].as_py(), dict(zip(t.column("byte").to_pylist(), t.column("n").to_pylist(), strict=True))
        buckets = {k: r // size + (k < r % size) for k in range(size) if k < r}
        row = {"tensor_id": t.column("tensor_id")[0].as_py(), "r": r, "bits_idx": cost(counts) + 2 * r + 16 * len(counts), "bits_val": cost(buckets) + 40 * size}
        return pa.table({k: pa.array([v], pa.int64()) for k, v in row.items()})

    return bytes_.join(kept, "tensor_id").groupBy("tensor_id").applyInArrow(run, "tensor_id bigint, r bigint, bits_idx bigint, bits_val bigint")


def quantile_buckets(coo: DataFrame, q: int) -> DataFrame:
    """(tensor_id, idx, bucket, decoded): buckets of equal count over (value, idx); decoded is the bucket's mean."""
    rows = by_value(coo, ["tensor_id"], "value").withColumn("bucket", ntile("n", "n_total", q))
    means = rows.groupBy("tensor_id", "bucket").agg(F.avg("value").alias("decoded"))
    return rows.join(means, ["tensor_id", "bucket"]).select("tensor_id", "idx", "bucket", "decoded")


def sketched_quantiles(coo: DataFrame, q: int) -> DataFrame:
    """Bucket edges of one pass over huge tensors: (tensor_id, edges)."""
    share = F.array(*[F.lit(k / q) for k in range(1, q)])
    return coo.groupBy("tensor_id").agg(F.percentile_approx(F.col("value").cast("double"), share, 20_000).alias("edges"))


def sorted_curve(coo: DataFrame, order: str = "value") -> DataFrame:
    """(tensor_id, sign, rank, idx, y): ranks from 1 down the sorted curve of each sign, or of the magnitudes (sign 0)."""
    if order == "magnitude":
        rows = coo.select("tensor_id", F.lit(0).alias("sign"), "idx", F.abs("value").alias("y"))
    else:
        rows = coo.select("tensor_id", F.when(F.col("value") > 0, 1).otherwise(-1).alias("sign"), "idx", F.col("value").alias("y"))
    return by_value(rows, ["tensor_id", "sign"], "y", descending=True, name="rank").select("tensor_id", "sign", F.col("rank").cast("bigint").alias("rank"), "idx", "y")


SEGMENT = ["tensor_id", "sign", "seg"]


def segment_level(curve: DataFrame, least: int) -> DataFrame:
    """One round of chord splitting: curve with a segment number seg (0 at first) to curve with finer numbers.

    Segments keep their order; a segment without a gap, or with children of fewer than least points, stays. The curve
    is aggregated twice and never shuffled: a segment's ends and knot are one row, broadcast if measured small.
    """
    if "seg" not in curve.columns:
        curve = curve.withColumn("seg", F.lit(0).cast("bigint"))
    ends = small_side(curve.groupBy(*SEGMENT).agg(F.min("rank").alias("lo"), F.max("rank").alias("hi"), F.max_by("y", F.col("rank")).alias("y_hi"), F.min_by("y", F.col("rank")).alias("y_lo")))
    gap = F.expr("CASE WHEN hi = lo THEN 0D ELSE pow(y - (y_lo + (y_hi - y_lo) * (rank - lo) / CAST(hi - lo AS DOUBLE)), 2) END")
    knots = curve.join(ends, SEGMENT).withColumn("gap", gap).groupBy(*SEGMENT).agg(F.max(F.struct(F.round("gap", 3).alias("gap"), (-F.col("rank")).alias("at"))).alias("k"), F.first("lo").alias("lo"), F.first("hi").alias("hi"))
    knots = small_side(knots.select(*SEGMENT, F.expr(f"CASE WHEN k.gap > 0 AND -k.at - lo + 1 >= {least} AND hi + k.at >= {least} THEN -k.at END").alias("knot")))
    return curve.join(knots, SEGMENT).select("tensor_id", "sign", (F.col("seg") * 2 + F.expr("CASE WHEN rank > knot THEN 1 ELSE 0 END")).alias("seg"), "rank", "idx", "y")


def segmented(curve: DataFrame, least: int, rounds: int) -> DataFrame:
    """curve after rounds of splitting; it is written once, since every round reads it twice."""
    curve = checkpointed(curve)
    for _ in range(rounds):
        curve = segment_level(curve, least)
    return curve


def basis_sql(n: str, t: str, degree: int) -> list[str]:
    """Orthogonal polynomials on t = 0..n-1 as SQL expressions, by their recurrence."""
    u = f"({t} - ({n} - 1) / 2e0)"
    out = ["1e0", u]
    for k in range(1, degree):
        out.append(f"({u} * {out[k]} - {k * k} * (CAST({n} AS DOUBLE) * {n} - {k * k}) / {4 * (4 * k * k - 1)}e0 * {out[k - 1]})")
    return out[: degree + 1]


def gram_fit(curve: DataFrame, degree: int) -> DataFrame:
    """(tensor_id, sign, seg, lo, n, c0, c1, ...): least squares of a degree on each segment, by sums in one pass."""
    keys = SEGMENT
    size = small_side(curve.groupBy(*keys).agg(F.min("rank").alias("lo"), F.count("*").alias("n")))
    rows = curve.join(size, keys).withColumn("t", F.col("rank") - F.col("lo"))
    base = basis_sql("n", "t", degree)
    for k, b in enumerate(base):
        rows = rows.withColumn(f"b{k}", F.expr(b))
    sums = [(F.sum(F.col(f"b{k}") * F.col("y")) / F.nullif(F.sum(F.col(f"b{k}") * F.col(f"b{k}")), F.lit(0.0))).alias(f"c{k}") for k in range(degree + 1)]
    out = rows.groupBy(*keys, "lo", "n").agg(*sums)
    return out.select(*keys, "lo", "n", *[F.when(F.col("n") > k, F.coalesce(f"c{k}", F.lit(0.0))).otherwise(0.0).alias(f"c{k}") for k in range(degree + 1)])


def gram_values(curve: DataFrame, fit: DataFrame, degree: int) -> DataFrame:
    """curve with y_hat."""
    rows = curve.join(small_side(fit), SEGMENT).withColumn("t", F.col("rank") - F.col("lo"))
    terms = " + ".join(f"c{k} * {b}" for k, b in enumerate(basis_sql("n", "t", degree)))
    return rows.select("tensor_id", "sign", "seg", "rank", "idx", "y", F.expr(terms).alias("y_hat"))


def ternary(coo: DataFrame, multiplier: float = 1.0) -> DataFrame:
    """(tensor_id, byte_no, byte): five ternary digits a byte, of the bytes that hold a non-zero digit."""
    scale = coo.groupBy("tensor_id").agg((F.max(F.abs("value")) * multiplier).alias("scale"))
    digit = F.expr("CAST(signum(CAST(value AS DOUBLE)) * floor(abs(value) / scale + 0.5D) AS BIGINT)")
    rows = coo.join(scale, "tensor_id").withColumn("digit", digit).where("digit <> 0")
    cells = rows.select("tensor_id", F.expr("idx div 5").alias("byte_no"), (F.col("digit") * F.expr("element_at(array(81, 27, 9, 3, 1), CAST(idx % 5 AS INT) + 1)")).alias("part"))
    return cells.groupBy("tensor_id", "byte_no").agg((F.sum("part") + 121).alias("byte"))


def minmax_sketch(ids: DataFrame, rows: int, cols: int, seed: int = 0) -> DataFrame:
    """(tensor_id, row, cell, least) of bucket numbers under hashed keys."""
    cells = F.array(*[F.struct(F.lit(r).alias("row"), F.expr(f"{hash_sql('idx', r, seed, 'minmax')} % {cols}").alias("cell")) for r in range(rows)])
    return ids.select("tensor_id", "bucket", F.explode(cells).alias("c")).groupBy("tensor_id", F.col("c.row").alias("row"), F.col("c.cell").alias("cell")).agg(F.min("bucket").alias("least"))


def minmax_query(keys: DataFrame, sketch: DataFrame, rows: int, cols: int, seed: int = 0) -> DataFrame:
    """(tensor_id, idx, bucket): the greatest of the rows' cells."""
    cells = F.array(*[F.struct(F.lit(r).alias("row"), F.expr(f"{hash_sql('idx', r, seed, 'minmax')} % {cols}").alias("cell")) for r in range(rows)])
    asked = keys.select("tensor_id", "idx", F.explode(cells).alias("c")).select("tensor_id", "idx", F.col("c.row").alias("row"), F.col("c.cell").alias("cell"))
    return asked.join(sketch, ["tensor_id", "row", "cell"]).groupBy("tensor_id", "idx").agg(F.max("least").alias("bucket"))


def error_feedback(gradient: DataFrame, residual: DataFrame) -> DataFrame:
    """g + e over the union of their cells."""
    return gradient.unionByName(residual).groupBy("tensor_id", "idx").agg(F.sum("value").alias("value")).where("value <> 0")


def residual_after(sent: DataFrame, compensated: DataFrame) -> DataFrame:
    """(g + e) less what was sent."""
    return compensated.unionByName(sent.withColumn("value", -F.col("value"))).groupBy("tensor_id", "idx").agg(F.sum("value").alias("value")).where("value <> 0")


def apply_update(params: DataFrame, gradient: DataFrame, rate: float, optimizer: str = "sgd", step: int = 1, momentum: float = 0.9, betas: tuple[float, float] = (0.9, 0.999), eps: float = 1e-8) -> DataFrame:
    """params (idx, x, m, v) after one step; parameters without a gradient see zero."""
    rows = params.join(gradient.select("idx", F.col("value").alias("g")), "idx", "left").withColumn("g", F.coalesce("g", F.lit(0.0)))
    x, g, m, v = (F.col(c) for c in "xgmv")
    if optimizer == "sgd":
        return rows.select("idx", (x - rate * g).alias("x"), "m", "v")
    if optimizer == "sgd_momentum":
        return rows.withColumn("m", momentum * m + g).select("idx", (x - rate * F.col("m")).alias("x"), "m", "v")
    if optimizer == "adam":
        b1, b2 = betas
        rows = rows.withColumn("m", b1 * m + (1 - b1) * g).withColumn("v", b2 * v + (1 - b2) * g * g)
        return rows.select("idx", (x - rate * (F.col("m") / (1 - b1**step)) / (F.sqrt(F.col("v") / (1 - b2**step)) + eps)).alias("x"), "m", "v")
    raise ValueError(optimizer)
