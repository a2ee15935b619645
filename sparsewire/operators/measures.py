"""Volumes, errors and quality measures."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

def all_bits() -> Column:
    return F.col("bits_idx") + F.col("bits_val") + F.col("bits_map")



def volume_split(containers: DataFrame, *by: str) -> DataFrame:
    """Bits by part, and the ratios to a dense and to a plain sparse tensor of 32-bit numbers."""
    sums = [F.sum(c).alias(c) for c in ("bits_idx", "bits_val", "bits_map", "bits_meta")]
    out = containers.groupBy(*by).agg(*sums, F.sum("d").alias("d"), F.sum("r").alias("r"))
    return out.withColumn("relative_volume", all_bits() / (32 * F.col("d"))).withColumn("volume_vs_sparse", all_bits() / (64 * F.col("r")))


def relative_volume(containers: DataFrame) -> float:
    return volume_split(containers).first()["relative_volume"]


def volume_vs_sparse(containers: DataFrame) -> float:
    return volume_split(containers).first()["volume_vs_sparse"]


def compression_error(g: DataFrame, c: DataFrame) -> DataFrame:
    """(tensor_id, norm2, error2, error, delta): the squared distance as a share of the squared norm."""
    a = g.select("tensor_id", "idx", F.col("value").cast("double").alias("a"), F.lit(0.0).alias("b"))
    b = c.select("tensor_id", "idx", F.lit(0.0).alias("a"), F.col("value").cast("double").alias("b"))
    cells = a.unionByName(b).groupBy("tensor_id", "idx").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    out = cells.groupBy("tensor_id").agg(F.sum(F.col("a") * F.col("a")).alias("norm2"), F.sum((F.col("a") - F.col("b")) ** 2).alias("error2"))
    return out.withColumn("error", F.col("error2") / F.col("norm2")).withColumn("delta", 1 - F.col("error"))


def fit_error(values: DataFrame, *by: str) -> DataFrame:
    """(max_norm, l2) of y - y_hat."""
    gap = F.col("y") - F.col("y_hat")
    return values.groupBy(*by).agg(F.max(F.abs(gap)).alias("max_norm"), F.sqrt(F.sum(gap * gap)).alias("l2"))


def bloom_stats(p: DataFrame, true: DataFrame, meta: DataFrame) -> DataFrame:
    """(tensor_id, positives, false_positives, observed_fpr)."""
    marked = p.join(true.select("tensor_id", "idx", F.lit(1).alias("hit")), ["tensor_id", "idx"], "left")
    counts = marked.groupBy("tensor_id").agg(F.count("*").alias("positives"), (F.count("*") - F.count("hit")).alias("false_positives"))
    return counts.join(meta, "tensor_id").select("tensor_id", "positives", "false_positives", (F.col("false_positives") / F.expr("nullif(d - r, 0)")).alias("observed_fpr"))


def top1(scores: DataFrame) -> DataFrame:
    """Share of rows (id, label, class, score) whose best class is the label; ties to the smaller class."""
    best = scores.groupBy("id", "label").agg(F.max(F.struct("score", (-F.col("class")).alias("c"))).alias("b"))
    return best.agg(F.avg((-F.col("b.c") == F.col("label")).cast("double")).alias("top1"))


def hit_rate(candidates: DataFrame, k: int = 10) -> DataFrame:
    """Share of users whose held-out item (held = 1) is among the k best of its candidates (user, item, score, held)."""
    w = Window.partitionBy("user").orderBy(F.desc("score"), "item")
    held = candidates.withColumn("n", F.row_number().over(w)).where("held = 1")
    return held.agg(F.avg((F.col("n") <= k).cast("double")).alias("hit_rate"))


def timeline(runs: dict[str, DataFrame]) -> DataFrame:
    """Rows of all runs with their method."""
    frames = [df.withColumn("method", F.lit(name)) for name, df in runs.items()]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def epochs_to(timeline_: DataFrame, target: float) -> DataFrame:
    return timeline_.where(F.col("metric") >= target).groupBy("method").agg(F.min("epoch").alias("epochs"))


def time_codec(codec, blocks: DataFrame, reps: int = 1) -> tuple[float, float]:
    """Least seconds of the jobs that encode blocks and decode them, into a sink that keeps nothing."""
    enc = dec = float("inf")
    for _ in range(reps):
        start = time.perf_counter()
        held = codec.encode_held(blocks).persist()
        held.count()
        enc = min(enc, time.perf_counter() - start)
        start = time.perf_counter()
        codec.decode_held(held).write.format("noop").mode("overwrite").save()
        dec = min(dec, time.perf_counter() - start)
        held.unpersist()
    return enc, dec
