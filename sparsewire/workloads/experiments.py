"""The experiments, one query each, on the given tables."""

from __future__ import annotations

import itertools
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import bits as bt
from ..operators import bloom as bl
from ..operators import curve as cv
from ..operators import measures as ms
from ..operators import ranks as rk
from ..operators import relational as rl
from ..operators import scan as sc
from ..operators import sparsify as sp
from ..operators import theory as th
from ..operators.index_codecs import BloomKeys, DeltaHuffmanKeys, RunLength, hash_table, runs_of
from ..operators.value_codecs import FitDoubleExp, FitPoly, HalfValues, Qsgd, QuantileBuckets
from ..plans.network import comm_bytes, iteration_time
from ..plans.pipeline import ARROW, BITS_OF, HELD, Codec, ThreeLC, alike, blocks_of, catalogue, sketchml, skcompress
from ..sources import tensors as ts
from ..sources.checkpoints import checkpointed
from . import sql as q
from . import train as tr
from .queries import FPR, ORACLE, SEED, conv_volumes, dim, query, small, with_meta

LINE_SQL = f"SELECT tensor_id, CAST(count(*) AS DOUBLE) AS r, CAST(sum(n) AS DOUBLE) AS sx, CAST(sum(value) AS DOUBLE) AS sy, CAST(sum(n * value) AS DOUBLE) AS sxy, CAST(sum(n * n) AS DOUBLE) AS sxx FROM (SELECT *, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) AS n FROM ({q.small('supp_part')})) GROUP BY 1"


@query("e01_worked_example", f"SELECT tensor_id, 32 * {q.DIMENSIONS['supp_part']} AS dense, CAST(64 * r AS BIGINT) AS pairs, {q.DIMENSIONS['supp_part']} + 64 AS compressed, round(slope, 6) AS slope, round((sy - slope * sx) / r, 6) AS start FROM (SELECT *, CASE WHEN r > 1 THEN (r * sxy - sx * sy) / (r * sxx - sx * sx) ELSE 0 END AS slope FROM ({LINE_SQL}))")
def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of each tensor as a dense array, as key-value pairs, and as a bitmap with the two parameters of the line
    that fits its values best."""
    coo, d = small(spark, sf_dir, "supp_part"), dim(spark, sf_dir, "supp_part")
    cells = rk.by_idx(coo.select("tensor_id", "idx", "value"))
    sums = {"r": F.count("*"), "sx": F.sum("n"), "sy": F.sum("value"), "sxy": F.sum(F.col("n") * F.col("value")), "sxx": F.sum(F.col("n") * F.col("n"))}
    line = cells.groupBy("tensor_id").agg(*[x.cast("double").alias(n) for n, x in sums.items()])
    line = line.withColumn("slope", F.expr("CASE WHEN r > 1 THEN (r * sxy - sx * sy) / (r * sxx - sx * sx) ELSE 0D END"))
    return line.select("tensor_id", F.lit(32 * d).cast("bigint").alias("dense"), (64 * F.col("r")).cast("bigint").alias("pairs"), F.lit(d + 64).cast("bigint").alias("compressed"), F.round("slope", 6).alias("slope"), F.round(F.expr("(sy - slope * sx) / r"), 6).alias("start"))


FLAGS_SQL = (
    "WITH x AS (SELECT l_suppkey AS tensor_id, l_returnflag AS f, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_returnflag) AS n FROM lineitem), "
    "y AS (SELECT tensor_id, n - row_number() OVER (PARTITION BY tensor_id, f = 'R' ORDER BY n) AS g, f = 'R' AS s FROM x), z AS (SELECT tensor_id, count(*) AS length FROM y GROUP BY tensor_id, g, s), "
    "c AS (SELECT tensor_id, count(*) AS n FROM x GROUP BY tensor_id, f), b AS (SELECT tensor_id, CAST(CASE WHEN count(*) = 3 THEN 2 * sum(n) - max(n) ELSE sum(n) END AS BIGINT) AS bits FROM c GROUP BY 1) "
    "SELECT tensor_id, count(*) AS runs, max(length) AS longest, any_value(bits) AS bits FROM z JOIN b USING (tensor_id) GROUP BY 1"
)


@query("e02_runs_and_codes", FLAGS_SQL)
def runs_and_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each supplier's lines in order: the runs of returned and other ones, and the bits of their flags, of which
    there are three, in a prefix code."""
    lines = ts.load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("tensor_id"), "l_orderkey", "l_linenumber", "l_returnflag")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("l_orderkey", "ascending"), ("l_linenumber", "ascending"), ("l_returnflag", "ascending")])
        flags = t.column("l_returnflag").to_pylist()
        _, runs = runs_of(np.flatnonzero([f == "R" for f in flags]), len(flags))
        freqs = {ord(f): flags.count(f) for f in set(flags)}
        size = bt.prefix_lengths(freqs)
        cols = (t.column("tensor_id")[0].as_py(), len(runs), int(runs.max()), sum(n * size[s] for s, n in freqs.items()))
        return pa.table({k: pa.array([x], pa.int64()) for k, x in zip(("tensor_id", "runs", "longest", "bits"), cols, strict=True)})

    return lines.groupBy("tensor_id").applyInArrow(run, "tensor_id bigint, runs bigint, longest bigint, bits bigint")


@query("e03_membership", f"WITH {q.filter_ctes(q.small('supp_part'), q.DIMENSIONS['supp_part'], 0.15, SEED)} SELECT p.tensor_id, count(t.idx) AS member, {q.DIMENSIONS['supp_part']} - count(*) AS other, count(*) - count(t.idx) AS false_positive FROM p LEFT JOIN t ON t.tensor_id = p.tensor_id AND t.idx = p.idx GROUP BY 1")
def membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a filter of three hashes says of every index: keys that it holds, others, and false positives."""
    counts = sc.tallies(*with_meta(spark, sf_dir, "supp_part"), 0.15, "p0", SEED)
    return counts.select("tensor_id", F.col("k1").alias("member"), (F.lit(dim(spark, sf_dir, "supp_part")) - F.col("chosen")).alias("other"), F.col("k2").alias("false_positive"))


@query(
    "e04_conflict_draw",
    f"SELECT tensor_id, sets, singles, drawn, k1 FROM (SELECT tensor_id, count(*) AS sets, count(CASE WHEN size = 1 THEN 1 END) AS singles FROM ({ORACLE['q_conflict_sets']}) GROUP BY 1) "
    f"JOIN (SELECT tensor_id, count(*) AS drawn, count(CASE WHEN value <> 0 THEN 1 END) AS k1 FROM ({ORACLE['q_bloom_p2']}) GROUP BY 1) USING (tensor_id)",
)
def conflict_draw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conflict sets of each tensor's positives, those of one member, which must be a key and is drawn first, and how
    many of the drawn are keys."""
    coo, meta = with_meta(spark, sf_dir, "supp_part")
    sets = sc.conflict_sizes(coo, meta, 0.05, SEED).groupBy("tensor_id").agg(F.count("*").alias("sets"), F.count(F.when(F.col("size") == 1, 1)).alias("singles"))
    drawn = sc.decode(coo, meta, 0.05, "p2", SEED).groupBy("tensor_id").agg(F.count("*").alias("drawn"), F.count(F.when(F.col("value") != 0, 1)).alias("k1"))
    return sets.join(drawn, "tensor_id").select("tensor_id", "sets", "singles", "drawn", "k1")


@query("e05_naive_shift", f"WITH {q.filter_ctes(q.TENSORS['user_hour'], q.DIMENSIONS['user_hour'], 0.1, SEED)}, c AS ({q.decoded('naive', SEED)}) SELECT coalesce(t.idx, c.idx) AS idx, coalesce(t.value, 0) AS truth, coalesce(c.value, 0) AS rebuilt FROM t FULL JOIN c ON t.tensor_id = c.tensor_id AND t.idx = c.idx")
def naive_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each false positive shifts the values behind it; the last true keys get none."""
    coo, meta = with_meta(spark, sf_dir, "user_hour", exact=False)
    rebuilt = sc.decode(coo, meta, 0.1, "naive", SEED).select("tensor_id", "idx", F.col("value").alias("rebuilt"))
    out = coo.select("tensor_id", "idx", F.col("value").alias("truth")).join(rebuilt, ["tensor_id", "idx"], "full")
    return out.select("idx", F.coalesce("truth", F.lit(0)).alias("truth"), F.coalesce("rebuilt", F.lit(0)).alias("rebuilt"))


@query(
    "e06_random_policy",
    f"WITH {q.filter_ctes(q.small('supp_part'), q.DIMENSIONS['supp_part'], 0.05, SEED)}, c AS ({q.chosen('p1', SEED)}), k AS (SELECT c.tensor_id, count(t.idx) AS k1, count(*) - count(t.idx) AS k2 FROM c LEFT JOIN t ON t.tensor_id = c.tensor_id AND t.idx = c.idx GROUP BY 1), "
    "e AS (SELECT t.tensor_id, sum(CASE WHEN c.idx IS NULL THEN value * value ELSE 0 END) / CAST(sum(value * value) AS DOUBLE) AS error FROM t LEFT JOIN c ON t.tensor_id = c.tensor_id AND t.idx = c.idx GROUP BY 1) "
    "SELECT tensor_id, k1, k2, round(error, 6) AS error, round(k2 / CAST(k1 + k2 AS DOUBLE), 6) AS expected FROM k JOIN e USING (tensor_id)",
)
def random_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of kept true keys and the expected error of the rest, against the error of one draw."""
    rows = sc.tallies(*with_meta(spark, sf_dir, "supp_part"), 0.05, "p1", SEED)
    return rows.select("tensor_id", "k1", "k2", F.round(F.col("error2") / F.col("norm2"), 6).alias("error"), F.round(F.col("k2") / (F.col("k1") + F.col("k2")), 6).alias("expected"))


def _policy_rows(g: DataFrame, picked: dict[str, DataFrame], d: int, rates: list[float], policies: list[str]) -> DataFrame:
    """(sparsifier, policy, fpr, rel_volume, volume_vs_sparse, error): each block is read once, and encoded and decoded
    there for all sparsifiers, policies and rates, values at false positives fetched from the block of g."""
    cells, names = g, list(picked)
    for n, coo in picked.items():
        cells = cells.join(coo.select("tensor_id", "idx", F.lit(True).alias(n)), ["tensor_id", "idx"], "left")
    cells = sp.blocked(cells.select("tensor_id", "idx", F.col("value").cast("double").alias("value"), *[F.coalesce(n, F.lit(False)).alias(n) for n in names]))

    def run(t: pa.Table) -> pa.Table:
        idx, value = (t.column(c).to_numpy() for c in ("idx", "value"))
        order, block = np.argsort(idx), t.column("block")[0].as_py()
        local, value, width, out = idx[order] - block * sp.BLOCK, value[order], min(sp.BLOCK, d - block * sp.BLOCK), []
        full = np.zeros(width)
        full[local] = value
        for n in names:
            hit = t.column(n).to_numpy()[order]
            for f in rates:
                for p in policies:
                    codec = Codec(BloomKeys(f, p, SEED))
                    c = codec.encode_block(local[hit], value[hit], width, block, full.__getitem__)
                    keys, values = codec.decode_block(c, block)
                    gap = full.copy()
                    gap[keys] -= values
                    out.append((n, p, f, sum(c[x] for x in BITS_OF), width, int(hit.sum()), float(full @ full), float(gap @ gap)))
        cols = ("sparsifier", "policy", "fpr", "bits", "d", "r", "norm2", "error2")
        return pa.table({k: pa.array(x) for k, x in zip(cols, zip(*out, strict=True), strict=True)})

    rows = cells.groupBy("tensor_id", "block").applyInArrow(run, "sparsifier string, policy string, fpr double, bits bigint, d bigint, r bigint, norm2 double, error2 double")
    total = rows.groupBy("sparsifier", "policy", "fpr").agg(*[F.sum(c).alias(c) for c in ("bits", "d", "r", "norm2", "error2")])
    return total.select("sparsifier", "policy", "fpr", (F.col("bits") / (32 * F.col("d"))).alias("rel_volume"), (F.col("bits") / (64 * F.col("r"))).alias("volume_vs_sparse"), (F.col("error2") / F.col("norm2")).alias("error"))


SWEEP = [1e-4, 1e-3, 1e-2, 1e-1]


@query("e07_rate_sweep")
def rate_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Volume and error by policy, sparsifier and rate on the dense stand-in, values fetched from the original."""
    g, d = ts.conv(spark, sf_dir), dim(spark, sf_dir, "conv")
    r = sp.r_of(d, 0.01)
    return _policy_rows(g, {"top_r": sp.top_r(g, r), "random_r": sp.random_r(g, r, SEED)}, d, [1e-4, 1e-3, 4e-3, 1e-2, 1e-1], ["p0", "p1", "p2"])


@query("e07b_rate_sweep_accuracy")
def rate_sweep_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Balanced accuracy of the text classifier by policy, sparsifier and rate, beside the bits a worker sends."""
    methods = {"none": tr.Method(), **{f"{s}/{p}/{f:g}": tr.Method(Codec(BloomKeys(f, p)), 0.05, True, s) for s in ("top_r", "random_r") for p in ("p0", "p1", "p2") for f in SWEEP}}
    return tr.train_text(spark, sf_dir, methods, epochs=4)


@query("e08_policy_convergence")
def policy_convergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    bloom = {f"bloom_{p}": tr.Method(Codec(BloomKeys(0.001, p)), 0.1, False) for p in ("naive", "p0", "p1", "p2")}
    return tr.train_softmax(spark, sf_dir, {"none": tr.Method(memory=False), "top_r": tr.Method(Codec(), 0.1, False), **bloom}, epochs=8)


@query("e08b_policy_convergence_text")
def policy_convergence_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    bloom = {f"bloom_{p}": tr.Method(Codec(BloomKeys(0.001, p)), 0.05, False) for p in ("naive", "p0", "p1", "p2")}
    return tr.train_text(spark, sf_dir, {"none": tr.Method(memory=False), "top_r": tr.Method(Codec(), 0.05, False), **bloom}, epochs=6)


@query("e09_fit_convergence")
def fit_convergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    methods = {"none": tr.Method(memory=False), "top_r": tr.Method(Codec(), 0.1, False), "fit_poly": tr.Method(Codec(None, FitPoly()), 0.1, False), "fit_dexp": tr.Method(Codec(None, FitDoubleExp()), 0.1, False)}
    return tr.train_softmax(spark, sf_dir, methods, epochs=8)


@query("e09b_fit_convergence_text")
def fit_convergence_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    methods = {"none": tr.Method(), "top_r": tr.Method(Codec(), 0.05), "fit_poly": tr.Method(Codec(None, FitPoly()), 0.05), "fit_dexp": tr.Method(Codec(None, FitDoubleExp()), 0.05)}
    return tr.train_text(spark, sf_dir, methods, epochs=6)


@query("q_train_softmax")
def train_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three optimizers' workload without compression, with plain pairs and with quantised values."""
    return tr.train_softmax(spark, sf_dir, {"none": tr.Method(), "top_r": tr.Method(Codec(), 0.1), "qsgd": tr.Method(Codec(None, Qsgd()), 0.1)}, epochs=6, rate=1.0, optimizer="sgd_momentum")


@query("q_train_text")
def train_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tr.train_text(spark, sf_dir, {"none": tr.Method(), "top_r": tr.Method(Codec(), 0.05), "random_r": tr.Method(Codec(), 0.05, True, "random_r")}, epochs=6, optimizer="adam", rate=0.2)


@query("q_train_recommender")
def train_recommender(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tr.train_recommender(spark, sf_dir, {"none": tr.Method(memory=False), "topr_pairs": tr.Method(Codec(), None, False)}, epochs=4)


@query("e10_eight_pieces")
def eight_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight chords' segments of one layer's sorted positive values, fitted with degree 5."""
    # one layer, the first, is the experiment's input
    layer = ts.layers(spark, sf_dir).where("tensor_id = 0 AND value > 0")
    y = np.array([r.value for r in layer.orderBy(F.desc("value")).select("value").toLocalIterator()])
    ends = cv.segments(y, 8, 6)
    rows = [(k, a + 1, b, float(np.abs(cv.gram_value(cv.gram_fit(y[a:b], 5), b - a) - y[a:b]).max())) for k, (a, b) in enumerate(zip([0, *ends[:-1]], ends, strict=True))]
    return spark.createDataFrame(rows, "seg int, lo int, hi int, max_error double")


@query("e11_stand_alone")
def stand_alone(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Volume, loss and accuracy of twelve steps with memory, beside stand-alone compressors."""
    codecs = {"none": (None, None), "top_r": (Codec(), 0.01), "bloom_p0": (Codec(BloomKeys(0.001, "p0")), 0.01), "bloom_p2": (Codec(BloomKeys(0.001, "p2")), 0.01), "fit_poly": (Codec(None, FitPoly()), 0.01), "fit_dexp": (Codec(None, FitDoubleExp()), 0.01), "3lc": (ThreeLC(), None), "sketchml": (sketchml(64), 0.01), "skcompress": (skcompress(), 0.01), "skcompress_signs": (skcompress(7, True), 0.01)}
    return tr.train_text(spark, sf_dir, {n: tr.Method(c, r) for n, (c, r) in codecs.items()}, epochs=12)


def inherent_codecs() -> dict[str, Codec]:
    return {"bloom_p2(0.01)+fit_poly": Codec(BloomKeys(0.01, "p2", SEED), FitPoly()), "skcompress(7)": skcompress(7), "bloom_p0(0.6)+qsgd(7,512)": Codec(BloomKeys(0.6, "p0", SEED), Qsgd(7, 512, SEED))}


@query("e12_inherently_sparse")
def inherently_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Volumes on the recommender stand-in, and the closed form for all positives with quantised values."""
    coo, meta = with_meta(spark, sf_dir, "nation_part")
    density = meta.first()["r"] / meta.first()["d"]
    rows = [("none", 1.0, None)]
    for n, c in inherent_codecs().items():
        rows.append((n, float(ms.relative_volume(c.encode(coo, meta))), th.volume_p0_qsgd(density, bl.fpr_of(*bl.bloom_size(10_000, 0.6), 10_000)) if "qsgd" in n else None))
    return spark.createDataFrame(rows, "method string, rel_volume double, closed_form double")


@query("e12b_recommender_training")
def recommender_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hit rate of the uncompressed run and of all three methods, by adam."""
    return tr.train_recommender(spark, sf_dir, {"none": tr.Method(memory=False), **{n: tr.Method(c, None, False) for n, c in inherent_codecs().items()}}, epochs=5)


@query("e13_convolution_volumes")
def convolution_volumes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return conv_volumes(spark, sf_dir)


def _kernel_seconds(coo: DataFrame, d: int, codecs: dict[str, Codec], reps: int) -> DataFrame:
    """(method, enc_s, dec_s): seconds of the kernels, block by block in the tasks that hold them, added up."""
    rows = sp.blocked(coo.select("tensor_id", "idx", F.col("value").cast("double").alias("value")))

    def run(t: pa.Table) -> pa.Table:
        idx, value = (t.column(c).to_numpy() for c in ("idx", "value"))
        order, block = np.argsort(idx), t.column("block")[0].as_py()
        keys, values, width, out = idx[order] - block * sp.BLOCK, value[order], min(sp.BLOCK, d - block * sp.BLOCK), []
        for name, codec in codecs.items():
            c = codec.encode_block(keys, values, width, block)
            start = time.perf_counter()
            for _ in range(reps):
                c = codec.encode_block(keys, values, width, block)
            mid = time.perf_counter()
            for _ in range(reps):
                codec.decode_block(c, block)
            out.append((name, (mid - start) / reps, (time.perf_counter() - mid) / reps))
        return pa.table({k: pa.array(x) for k, x in zip(("method", "enc_s", "dec_s"), zip(*out, strict=True), strict=True)})

    held = checkpointed(rows.groupBy("tensor_id", "block").applyInArrow(run, "method string, enc_s double, dec_s double"))
    return held.groupBy("method").agg(F.sum("enc_s").alias("enc_s"), F.sum("dec_s").alias("dec_s"))


@query("e14_codec_seconds")
def codec_seconds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to encode and decode the blocks of the dense stand-in's top 1%, by codec: the kernels alone."""
    d = dim(spark, sf_dir, "conv")
    return _kernel_seconds(sp.top_r(ts.conv(spark, sf_dir), sp.r_of(d, 0.01)), d, catalogue(0.001, SEED), 5)


@query("e14c_sparse_codec_seconds")
def sparse_codec_seconds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for the three methods of the inherently sparse recommender stand-in."""
    return _kernel_seconds(small(spark, sf_dir, "nation_part"), dim(spark, sf_dir, "nation_part"), inherent_codecs(), 1)


@query("e14b_job_seconds")
def job_seconds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of whole Spark jobs that encode and decode all of supp_part, for the methods that are compared by time.

    The cells are at hand when the clock starts. Every method's first step, which is the same, puts them together to
    blocks; it is run once, and its seconds count for each method.
    """
    d, n = dim(spark, sf_dir, "supp_part"), int(spark.conf.get("spark.sql.shuffle.partitions"))
    coo = ts.supp_part(spark, sf_dir, block=sp.BLOCK).selectExpr("tensor_id", "block", "idx", "value div 1000 AS value").where("value <> 0").persist()
    coo.count()
    start = time.perf_counter()
    grouped = blocks_of(coo, d).persist()
    grouped.count()
    blocks = grouped.repartitionByRange(n, "block", "r", "tensor_id").sortWithinPartitions("block", "r", "tensor_id").persist()
    blocks.count()
    first = time.perf_counter() - start
    coo.unpersist(), grouped.unpersist()
    codecs = {n: c for n, c in catalogue(0.001, SEED).items() if n in ("topr", "bloom_p0", "bloom_p2", "qsgd", "fit_poly", "fit_dexp", "sketchml", "skcompress", "3lc")} | {"bloom_p0(0.6)+qsgd": inherent_codecs()["bloom_p0(0.6)+qsgd(7,512)"]}
    rows = []
    for name, codec in codecs.items():
        enc, dec = ms.time_codec(codec, blocks)
        rows.append((name, first + enc, dec))
    blocks.unpersist()
    return spark.createDataFrame(rows, "method string, enc_s double, dec_s double")


def accumulated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums of ten gradients on each of four workers, to which all rows are dealt by order."""
    steps = ts.nation_part(spark, sf_dir, "pmod(l_orderkey, 4) * 10 + pmod(l_orderkey div 4, 10)")
    total = sp.accumulate(steps.selectExpr("tensor_id div 10 AS tensor_id", "idx", "value"))
    return total.selectExpr("tensor_id", "idx", "value div 1000 AS value").where("value <> 0")


@query("e15_iteration_breakdown")
def iteration_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Iteration time on four workers: compute and codec measured, communication modelled from measured bytes."""
    d = dim(spark, sf_dir, "worker8")
    start = time.perf_counter()
    coo = accumulated(spark, sf_dir).persist()
    coo.groupBy("tensor_id").count().collect()
    compute = time.perf_counter() - start
    top = sp.top_r(coo, sp.r_of(d, 0.1)).persist()
    plans = {"none": (None, coo), "top_r": (Codec(), top), "bloom_p2": (Codec(BloomKeys(0.01, "p2")), top), "bloom_p0+qsgd": (Codec(BloomKeys(0.6, "p0"), Qsgd()), coo), "fit_poly": (Codec(None, FitPoly()), top), "skcompress": (skcompress(), top), "top_r_fp16": (Codec(None, HalfValues()), top)}
    rows = []
    for name, (codec, tensor) in plans.items():
        if codec is None:
            size, half, codec_s = 4.0 * d, 2.0 * d, 0.0
        else:
            meta = ts.meta(tensor, d)
            start = time.perf_counter()
            held = codec.encode(tensor, meta).persist()
            split = ms.volume_split(held).first()
            size = sum(split[c] for c in ("bits_idx", "bits_val", "bits_map")) / 8 / 4
            # raw values are halved; what codecs write of values has a precision of its own
            raw = codec.value.name == "none"
            half = size - (split["bits_val"] / 2 / 8 / 4 if raw else 0)
            codec.decode(held).write.format("noop").mode("overwrite").save()
            codec_s = (time.perf_counter() - start) / 4
            held.unpersist()
        for mbit in (100, 1000, 10_000):
            for precision, sent in (("fp32", size), ("fp16", half)):
                t = iteration_time(compute, codec_s, "allreduce" if codec is None else "allgather", 4, sent, mbit * 1e6)
                rows.append((mbit, precision, name, t["compute"], t["codec"], t["comm"], t["total"], comm_bytes("allgather", 4, sent)))
    return spark.createDataFrame(rows, "mbit int, precision string, method string, compute double, codec double, comm double, total double, bytes double")


@query("e16_every_codec", "SELECT * FROM (VALUES " + ", ".join(f"('{n}', true)" for n in catalogue()) + ") v(method, ok)")
def every_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each instantiation encodes and decodes all tensors; lossless ones give them back.

    A block is read once for all of them, blocks of equally many keys are coded together, and what is chosen from a
    filter is shared by those whose filters are equal. Errors are summed over the cells of either side: others are 0.
    """
    d, n = dim(spark, sf_dir, "supp_part"), int(spark.conf.get("spark.sql.shuffle.partitions"))
    coo = ts.supp_part(spark, sf_dir, block=sp.BLOCK).selectExpr("tensor_id", "block", "idx", "value div 1000 AS value").where("value <> 0")
    codecs = catalogue(FPR, SEED)
    lossless = ("topr", "bitmap", "rle", "huffman", "delta", "bloom_p0", "deflate")
    # blocks of equally many keys meet, some thousand tensors of them at most
    some = F.pmod(F.xxhash64("tensor_id"), F.lit(1 + ts.load(spark, sf_dir, "supplier").count() // 8192))
    blocks = blocks_of(coo, d).repartition(4 * n, "block", "r", some).sortWithinPartitions("block", "r", "tensor_id")
    fields = [c for c in HELD if c not in ("tensor_id", "block")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in alike(b):
                block, width = (b.column(c)[at[0]].as_py() for c in ("block", "d"))
                keys, values = ([b.column(c)[i].values.to_numpy() for i in at] for c in ("keys", "values"))
                keys, shared = [k.astype(np.int64) for k in keys], {}
                gap, first = np.zeros(width), np.zeros(width, np.int64)
                norms = [float(v @ v) for v in values]
                for name, codec in codecs.items():
                    if isinstance(codec.index, BloomKeys):
                        codec.index.shared = shared
                    errors, made = [], codec.encode_many(keys, values, width, block)
                    for part in itertools.batched(made, 128):
                        # what a receiver has is the containers' rows
                        part = pa.table({c: pa.array([x[c] for x in part], ARROW[c]) for c in fields}).to_pylist()
                        for got, rebuilt in codec.decode_many(part, block):
                            k, v = keys[len(errors)], values[len(errors)]
                            gap[k] = v
                            np.subtract.at(gap, got, rebuilt)
                            missed = gap[k]
                            gap[k] = 0
                            first[got] = np.arange(len(got))
                            extra = gap[got[first[got] == np.arange(len(got))]]
                            gap[got] = 0
                            errors.append(float(missed @ missed + extra @ extra))
                    tensors = b.column("tensor_id").take(pa.array(at))
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(at)), tensors, pa.array(norms), pa.array(errors, pa.float64())], names=["method", "tensor_id", "norm2", "error2"])

    errors = blocks.mapInArrow(run, "method string, tensor_id bigint, norm2 double, error2 double")
    error = errors.groupBy("method", "tensor_id").agg((F.sum("error2") / F.sum("norm2")).alias("error"))
    good = F.when(F.col("method").isin(*lossless), F.col("error") == 0).otherwise(~F.isnan("error") & (F.col("error") < float("inf")))
    return error.groupBy("method").agg(F.coalesce(F.every(good), F.lit(False)).alias("ok"))


@query("e17_bounds")
def bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is observed on all tensors of supp_part beside its bound, one row a lemma and kind.

    observed and limit are sums over all tensors of the left and right side; worst is the largest quotient of the two in
    any tensor, for bounds that hold tensor by tensor.
    """
    coo, meta = with_meta(spark, sf_dir, "supp_part")
    coo, meta = coo.persist(), meta.persist()
    d = F.col("d")
    norm = ms.compression_error(coo, coo).select("tensor_id", "norm2").join(meta, "tensor_id").persist()
    rows: list[DataFrame] = []

    def add(name: str, got: DataFrame, observed: F.Column, limit: F.Column, slack: float = 1e-9) -> None:
        both = got.select("tensor_id", observed.cast("double").alias("o"), limit.cast("double").alias("l"))
        rows.append(both.agg(F.lit(name).alias("bound"), F.sum("o").alias("observed"), F.sum("l").alias("limit"), F.max(F.when(F.col("l") > 0, F.col("o") / F.col("l")).otherwise(F.when(F.col("o") > slack, 9e9).otherwise(0.0))).alias("worst")))

    r = F.least(F.lit(100), F.col("r"))
    top = ms.compression_error(coo, sp.top_r(coo, 100)).drop("norm2").join(norm, "tensor_id")
    add("top-r error <= (1 - r/d) norm2", top, F.col("error2"), (1 - r / d) * F.col("norm2"))
    seeds = None
    for seed in range(5):
        e = ms.compression_error(coo, sp.random_r(coo, 100, seed)).select("tensor_id", "error2")
        seeds = e if seeds is None else seeds.unionByName(e)
    mean = seeds.groupBy("tensor_id").agg(F.avg("error2").alias("error2")).join(norm, "tensor_id")
    add("random-r error ~ (1 - r/n) norm2", mean, F.col("error2"), (1 - r / F.col("r")) * F.col("norm2"))
    policies = ("p0", "p1", "left", "middle", "right")
    counted = checkpointed(sc.tallies_of(coo, meta, [(0.1, "p0"), (0.01, "p0"), *((0.05, p) for p in policies)], SEED))
    for fpr in (0.1, 0.01):
        n = counted.where(F.col("fpr") == fpr).select("tensor_id", "chosen").join(norm, "tensor_id")
        spread = 4 * 2 * F.sqrt(F.lit(fpr * (1 - fpr)) * (d - F.col("r")))
        add(f"positives({fpr}) <= expectation and spread", n, F.col("chosen"), F.ceil(F.col("r") + fpr * (d - F.col("r"))) + spread)
    for policy in policies:
        e = counted.where((F.col("fpr") == 0.05) & (F.col("policy") == policy)).select("tensor_id", "k1", "error2").join(norm, "tensor_id")
        expected = F.lit(0.0) if policy == "p0" else (1 - F.col("k1") / F.col("r")) * F.col("norm2")
        add(f"{policy} error ~ (1 - k1/r) norm2", e, F.col("error2"), expected)
    for seed in (1, 2):
        q_ = ms.compression_error(coo, Codec(None, Qsgd(7, 512, seed)).decode(Codec(None, Qsgd(7, 512, seed)).encode(coo, meta))).select("tensor_id", "error2").join(norm, "tensor_id")
        add(f"quantiser({seed}) error <= min(n/s^2, sqrt(n)/s) norm2", q_, F.col("error2"), F.least(F.least(F.col("r"), F.lit(512)) / (63.0 * 63), F.sqrt(F.least(F.col("r"), F.lit(512))) / 63) * F.col("norm2"))
    angle = th.sort_angle(coo)
    add("sorting: distance2 = 2 (1 - cos) norm2", angle, F.col("distance2"), F.col("twice"))
    g = error_memory(spark, sf_dir)
    add("memory: sent and kept are all of it", g, F.col("gap"), F.col("whole") * 1e-12)
    out = rows[0]
    for x in rows[1:]:
        out = out.unionByName(x)
    return out


def error_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(tensor_id, gap, whole): what a top-r compressor sends and keeps against its input."""
    coo = small(spark, sf_dir, "supp_part")
    sent = sp.top_r(coo, 100)
    both = sent.unionByName(rl.residual_after(sent, coo))
    return ms.compression_error(coo, both).select("tensor_id", F.col("error2").alias("gap"), F.col("norm2").alias("whole"))


def chord_error(y: np.ndarray, pieces: int) -> tuple[float, float]:
    """Largest error of chords on a curve over [0, 1], and its bound: half of the knots are even, half share the
    variation of the slope evenly."""
    x, slope = np.linspace(0, 1, len(y)), np.diff(y) * (len(y) - 1)
    varied = np.concatenate(([0.0], np.cumsum(np.abs(np.diff(slope)))))
    share = np.arange(1, pieces // 2) / (pieces // 2)
    by_slope = np.minimum(np.searchsorted(varied, share * varied[-1]), len(y) - 1)
    at = np.unique(np.concatenate(([0, len(y) - 1], np.round(share * (len(y) - 1)).astype(np.int64), by_slope)))
    return float(np.abs(np.interp(x, x[at], y[at]) - y).max()), float(th.fit_bound(varied[-1], pieces, len(y)))


@query("e17b_spline_bounds")
def spline_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chord splines of the sorted values of each tensor against their bound."""

    def run(t: pa.Table) -> pa.Table:
        y, tensor = np.sort(t.column("value").to_numpy())[::-1], t.column("tensor_id")[0].as_py()
        rows = [(tensor, p, *chord_error(y, p)) for p in (2, 4, 8)] if len(y) > 2 else []
        rows = [(*r, r[2] <= r[3] + 1e-9 * float(np.abs(y).max())) for r in rows]
        kinds = {"tensor_id": pa.int64(), "pieces": pa.int32(), "observed": pa.float64(), "bound": pa.float64(), "holds": pa.bool_()}
        return pa.table({n: pa.array([r[k] for r in rows], kind) for k, (n, kind) in enumerate(kinds.items())})

    cells = small(spark, sf_dir, "supp_part").select("tensor_id", F.col("value").cast("double").alias("value"))
    return cells.groupBy("tensor_id").applyInArrow(run, "tensor_id bigint, pieces int, observed double, bound double, holds boolean")


def _layouts_sql() -> str:
    scattered = q.small("supp_part")
    clustered = f"SELECT tensor_id, row_number() OVER (PARTITION BY tensor_id ORDER BY idx) - 1 AS idx, value FROM ({scattered})"
    out = []
    for layout, cells in (("scattered", scattered), ("clustered", clustered)):
        runs = f"SELECT tensor_id, count(*) AS length FROM (SELECT tensor_id, symbol, idx - row_number() OVER (PARTITION BY tensor_id, symbol ORDER BY idx) AS g FROM (SELECT u.tensor_id, u.idx, CASE WHEN t.idx IS NULL THEN 0 ELSE 1 END AS symbol FROM (SELECT s AS tensor_id, unnest(range(0, {q.DIMENSIONS['supp_part']})) AS idx FROM (SELECT DISTINCT tensor_id AS s FROM t)) u LEFT JOIN t ON t.tensor_id = u.tensor_id AND t.idx = u.idx)) GROUP BY tensor_id, symbol, g"
        out.append(
            f"SELECT * FROM (WITH RECURSIVE t AS MATERIALIZED ({cells}), runs AS MATERIALIZED ({runs}), {q.delta_huffman_bits('SELECT * FROM t')} "
            f"SELECT '{layout}' AS layout, 'rle' AS codec, (SELECT count(*) FROM runs) AS runs, CAST((SELECT sum(2 * floor(log2(length)) + 1) FROM runs) + (SELECT count(DISTINCT tensor_id) FROM t) AS BIGINT) AS bits_idx "
            f"UNION ALL SELECT '{layout}', 'delta_huffman', (SELECT count(*) FROM runs), CAST((SELECT sum(bits) FROM dh) AS BIGINT))"
        )
    return " UNION ALL ".join(out)


@query("e18_index_layouts", _layouts_sql())
def index_layouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs and bits of the same number of keys, clustered and scattered."""
    coo, meta = with_meta(spark, sf_dir, "supp_part")
    clustered = rk.by_idx(coo.select("tensor_id", "idx", "value")).selectExpr("tensor_id", "CAST(n - 1 AS BIGINT) AS idx", "value")
    rows = None
    for name, t in (("scattered", coo), ("clustered", clustered)):
        runs = rl.runs(t, meta).groupBy().agg(F.count("*").alias("runs"))
        for codec in (RunLength(), DeltaHuffmanKeys()):
            row = ms.volume_split(Codec(codec).encode(t, meta)).crossJoin(runs).select(F.lit(name).alias("layout"), F.lit(codec.name).alias("codec"), "runs", "bits_idx")
            rows = row if rows is None else rows.unionByName(row)
    return rows


@query("e19_lookup_table")
def lookup_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encoding and decoding by computed hashes against a table of the whole domain, block by block in tasks: seconds,
    the table's bytes, and whether both give the same keys."""
    rows, d, k = sp.blocked(small(spark, sf_dir, "nation_part").select("tensor_id", "idx")), dim(spark, sf_dir, "nation_part"), bl.hashes_for(0.01)

    def run(t: pa.Table) -> pa.Table:
        block = t.column("block")[0].as_py()
        keys, width = np.sort(t.column("idx").to_numpy()) - block * sp.BLOCK, min(sp.BLOCK, d - block * sp.BLOCK)
        start = time.perf_counter()
        table = hash_table(width, k, SEED, block)
        built, out, found = time.perf_counter() - start, [], []
        for name, codec in (("computed", BloomKeys(0.01, "p0", SEED)), ("table", BloomKeys(0.01, "p0", SEED, lookup=True))):
            start = time.perf_counter()
            for _ in range(3):
                e = codec.encode(keys, width, block)
                found.append(codec.decode(e.payload, width, len(keys), len(e.sent), block))
            own = name == "table"
            out.append((name, (time.perf_counter() - start) / 3, built if own else 0.0, int(table.nbytes) if own else 0, bool(np.array_equal(found[0], found[-1]) and np.array_equal(e.sent, found[0]))))
        return pa.table({c: pa.array(x) for c, x in zip(("method", "seconds", "built_s", "bytes", "same"), zip(*out, strict=True), strict=True)})

    held = checkpointed(rows.groupBy("tensor_id", "block").applyInArrow(run, "method string, seconds double, built_s double, bytes bigint, same boolean"))
    return held.groupBy("method").agg(F.sum("seconds").alias("seconds"), F.sum("built_s").alias("built_s"), F.sum("bytes").alias("bytes"), F.expr("every(same)").alias("same"))


@query("e20_quantile_means")
def quantile_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of bucket means by number of buckets."""
    coo = small(spark, sf_dir, "supp_part")
    meta = ts.meta(coo, dim(spark, sf_dir, "supp_part"))
    rows = None
    for n in (16, 64, 128):
        codec = Codec(None, QuantileBuckets(n))
        row = ms.compression_error(coo, codec.decode(codec.encode(coo, meta))).agg(F.avg("error").alias("error")).select(F.lit(n).alias("buckets"), "error")
        rows = row if rows is None else rows.unionByName(row)
    return rows
