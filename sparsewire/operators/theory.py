"""Closed forms: bounds on errors, counts and volumes."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bloom import bloom_k, bloom_size, fpr_of  # noqa: F401  part of this surface
from .ranks import by_idx
from .relational import sorted_curve


def delta_bound(r: int, d: int) -> float:
    return r / d


def random_r_error(r: int, d: int, norm2: float) -> float:
    return (1 - r / d) * norm2


def positives_bound(r: int, d: int, fpr: float) -> int:
    """Expected number of positives, rounded up; single draws can exceed it."""
    return math.ceil(r + fpr * (d - r))


def positives_spread(r: int, d: int, fpr: float) -> float:
    """Deviation of the number of positives; filter loads vary too, so twice the binomial one."""
    return 2 * math.sqrt(fpr * (1 - fpr) * (d - r))


def p0_beta(positives: int, d: int) -> float:
    return positives / d


def p0_error(positives: int, d: int, norm2: float, inherent: bool) -> float:
    return 0.0 if inherent else (1 - p0_beta(positives, d)) * norm2


def pd_error(i1: int, r: int, d: int, norm2: float, inherent: bool) -> float:
    """Deterministic choice that keeps i1 of r true keys."""
    return (1 - i1 / r) * norm2 if inherent else (1 - r / d) * norm2


def p1_error(k1: int, k2: int, r: int, m0: int, norm_s: float, norm_fp: float, kind: str = "exact") -> float:
    """Expected error of a random choice of k1 true keys and k2 false positives among m0 positives.

    exact splits each norm by its own share; printed takes the share of missed true keys for all positives.
    """
    out1 = 1 - k1 / r
    out2 = 1 - k2 / (m0 - r) if m0 > r else 0.0
    if kind == "exact":
        return out1 * norm_s + out2 * norm_fp
    return out1 * (norm_s + norm_fp) + out2 * (norm_s + norm_fp)


def moment_bound(delta: float, norm2: float, biased: bool) -> float:
    return (2 if biased else 1) * (2 - delta) * norm2


def fit_bound(m: float, p: int, d: int, kind: str = "linear", norm: str = "max") -> float:
    """Largest error of the best spline of p pieces on a curve of variation m, or its l2 form over d points."""
    top = m / (2 * p + 2) if kind == "constant" else 2 * m / p**2
    return top if norm == "max" else math.sqrt(d) * top


def fit_moment_bound(delta: float, cos1: float, cos2: float, d: int, m: float, p: int, norm2: float, biased: bool, kind: str = "rederived") -> float:
    """Bound on the second moment after sorting and fitting; see SURVEY A9 for the two forms of the biased case."""
    tail = 32 * (1 - cos1) * (2 - delta) * norm2 + 64 * d * m * m / p**4 + 256 * (1 - cos2) * d * m * m / p**4 + 128 * (1 - cos2) * (2 - delta) * norm2
    half = 16 * (1 - cos1) * (2 - delta) * norm2 + 32 * d * m * m / p**4 + 128 * (1 - cos2) * d * m * m / p**4 + 64 * (1 - cos2) * (2 - delta) * norm2
    if not biased:
        return 2 * (2 - delta) * norm2 + half
    return (2 * (2 - delta) * norm2 + tail) if kind == "printed" else (2 * (3 - 2 * delta) * norm2 + tail)


def bits_per_key(fpr: float) -> float:
    return -math.log(fpr) / math.log(2) ** 2


def volume_fit(r: int, numbers: int, map_bits: float = 0.0) -> float:
    """Volume against plain pairs of explicit keys and a fit of so many numbers."""
    return (32 * r + 32 * numbers + map_bits * r) / (64 * r)


def volume_p0_qsgd(density: float, fpr: float, bits: int = 7, bucket: int = 512) -> float:
    """Relative volume of all positives of a filter with quantised values."""
    return ((density + fpr * (1 - density)) * (bits + 32 / bucket) + bits_per_key(fpr) * density) / 32


def p0_crossover(r: int, d: int) -> float:
    """Rate above which sending all positives costs more than plain pairs."""
    lo, hi = 1e-9, 0.999
    for _ in range(200):
        mid = math.sqrt(lo * hi)
        lo, hi = (mid, hi) if 32 * mid * (d / r - 1) < 32 - bits_per_key(mid) else (lo, mid)
    return lo


def sort_angle(coo: DataFrame) -> DataFrame:
    """(tensor_id, cosine, distance2, twice): the squared distance to the sorted tensor is 2 (1 - cosine) norm2."""
    place = by_idx(coo.select("tensor_id", "idx", "value"), "rank").drop("rank_total")
    curve = sorted_curve(coo.withColumn("value", F.col("value").cast("double")))
    full = curve.join(curve.where("sign = 1").groupBy("tensor_id").agg(F.count("*").alias("up")), "tensor_id", "left")
    ranks = full.select("tensor_id", F.expr("CASE WHEN sign = 1 THEN rank ELSE rank + coalesce(up, 0) END").alias("rank"), "y")
    both = place.join(ranks, ["tensor_id", "rank"]).withColumn("x", F.col("value").cast("double"))
    out = both.groupBy("tensor_id").agg(F.sum(F.col("x") * F.col("y")).alias("dot"), F.sum(F.col("x") ** 2).alias("norm2"), F.sum((F.col("x") - F.col("y")) ** 2).alias("distance2"))
    return out.select("tensor_id", (F.col("dot") / F.col("norm2")).alias("cosine"), "distance2", (2 * (F.col("norm2") - F.col("dot"))).alias("twice"))
