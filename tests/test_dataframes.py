"""Relational operators, containers, sources, streams and SQL functions on small inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsewire.functions import extensions as ex
from sparsewire.functions.hashing import hash_array, hash_of
from sparsewire.operators import bloom as bl
from sparsewire.operators import measures as ms
from sparsewire.operators import ranks as rk
from sparsewire.operators import relational as rl
from sparsewire.operators import sparsify as sp
from sparsewire.operators import theory as th
from sparsewire.operators.baselines import GroupedMinMaxSketch
from sparsewire.operators.index_codecs import BitmapKeys, BloomKeys
from sparsewire.operators.value_codecs import FitPoly, Qsgd, QuantileBuckets
from sparsewire.plans.pipeline import Codec, ThreeLC, catalogue
from sparsewire.sources import tensors as ts
from sparsewire.streaming import gradients as gr
from sparsewire.workloads import experiments, queries
from sparsewire.workloads import train as tr


@pytest.fixture(scope="module")
def coo(spark):
    rng = np.random.default_rng(6)
    rows = [(t, int(i), float(v)) for t in range(3) for i, v in zip(np.sort(rng.choice(3000, 150, replace=False)), rng.standard_normal(150))]
    return spark.createDataFrame(rows, "tensor_id bigint, idx bigint, value double").persist()


def rows_of(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def test_hash_is_the_same_in_numpy(spark):
    got = [r.h for r in spark.range(1000).select(hash_of("id", 2, 5, "x", "7").alias("h")).collect()]
    assert got == hash_array(np.arange(1000), 2, 5, "x", 7).tolist()


def test_block_size_changes_no_lossless_result(coo):
    meta = ts.meta(coo, 3000)
    exact = coo.withColumn("value", F.round(F.col("value") * 64) / 64).where("value <> 0")
    want = rows_of(exact, "tensor_id", "idx", "value")
    for codec in (Codec(BitmapKeys(), block=512), Codec(BloomKeys(0.05, "p0")), Codec(BloomKeys(0.05, "p0"), block=700)):
        assert rows_of(codec.decode(codec.encode(exact.repartition(5), meta)), "tensor_id", "idx", "value") == want


def test_relational_filter_equals_kernel(coo):
    meta = ts.meta(coo, 3000)
    p = bl.positives(bl.filters(coo, meta, 0.05), 0.05)
    for t in range(3):
        keys = np.array([r.idx for r in coo.where(F.col("tensor_id") == t).orderBy("idx").collect()])
        for policy in ("p0", "p1", "left", "middle", "right"):
            got = [r.idx for r in bl.chosen(p, bl.sizes(coo, meta, 0.05), policy).where(F.col("tensor_id") == t).orderBy("idx").collect()]
            assert got == BloomKeys(0.05, policy).encode(keys, 3000).sent.tolist(), policy


def test_dense_values_at_false_positives(spark):
    g = spark.range(500).select(F.lit(0).cast("bigint").alias("tensor_id"), F.col("id").alias("idx"), (F.col("id") % 37 + 1).cast("double").alias("value"))
    top = sp.top_r(g, 40)
    codec = Codec(BloomKeys(0.1, "p0"))
    got = codec.decode(codec.encode(top, ts.meta(top, 500), g))
    assert got.count() > 40 and got.join(g, ["tensor_id", "idx", "value"]).count() == got.count()
    assert ms.compression_error(g, got).first()["error"] <= ms.compression_error(g, top).first()["error"]


def test_memory_keeps_what_was_not_sent(coo):
    sent = sp.top_r(coo, 20)
    e = rl.residual_after(sent, coo)
    total = e.unionByName(sent).groupBy("tensor_id", "idx").agg(F.sum("value").alias("value"))
    assert ms.compression_error(coo, total).agg(F.max("error2")).first()[0] < 1e-20


def test_quantised_and_fitted_volumes(coo):
    meta = ts.meta(coo, 3000)
    assert ms.volume_vs_sparse(Codec(None, Qsgd()).encode(coo, meta)) == pytest.approx((32 * 150 + 7 * 150 + 32) / (64 * 150))
    fit = Codec(None, FitPoly())
    c = fit.encode(coo, meta)
    assert ms.volume_split(c).first()["bits_map"] == 0 and ms.compression_error(coo, fit.decode(c)).agg(F.max("error")).first()[0] < 0.01
    dense = ThreeLC()
    assert dense.decode(dense.encode(coo, meta)).count() > 0


def test_sorting_identity(coo):
    r = th.sort_angle(coo).first()
    assert r["distance2"] == pytest.approx(r["twice"])


def test_containers_read_back(spark, coo, tmp_path):
    c = Codec(BitmapKeys()).encode(coo, ts.meta(coo, 3000), step=4)
    ts.write_containers(c, str(tmp_path / "c"))
    assert ts.read_containers(spark, str(tmp_path / "c")).where("step = 4").count() == 3


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv"])
def test_formats(spark, coo, tmp_path, fmt):
    coo.write.format(fmt).option("header", "true").save(str(tmp_path / fmt))
    assert ts.read_coo(spark, str(tmp_path / fmt), fmt).count() == coo.count()


def test_bad_cells_raise(spark):
    bad = spark.createDataFrame([(0, 1, float("nan"))], "tensor_id bigint, idx bigint, value double")
    with pytest.raises(Exception, match="not finite"):
        ts.checked(bad).collect()
    twice = spark.createDataFrame([(0, 1, 1.0), (0, 1, 2.0)], "tensor_id bigint, idx bigint, value double")
    with pytest.raises(Exception, match="two cells"):
        Codec().encode(twice, ts.meta(twice, 5)).collect()


def test_empty_tensor(spark):
    none = spark.createDataFrame([], "tensor_id bigint, idx bigint, value double")
    assert all(c.decode(c.encode(none, ts.meta(none, 5))).count() == 0 for c in list(catalogue().values())[:3])


def test_optimizer_steps(spark):
    params = spark.createDataFrame([(0, 1.0, 0.0, 0.0), (1, 1.0, 0.0, 0.0)], "idx bigint, x double, m double, v double")
    g = spark.createDataFrame([(0, 2.0)], "idx bigint, value double")
    assert rows_of(rl.apply_update(params, g, 0.5), "idx", "x") == [(0, 0.0), (1, 1.0)]
    assert rl.apply_update(params, g, 0.1, "adam").where("idx = 0").first()["x"] == pytest.approx(0.9)


def test_sql_functions(spark):
    ex.register(spark)
    assert [r.idx for r in spark.sql("SELECT * FROM run_expand(0, array(2, 3, 1, 1))").collect()] == [2, 3, 4, 6]
    assert {r.symbol: len(r.code) for r in spark.sql("SELECT * FROM huffman_codes(array(1, 2, 3), array(9, 2, 1))").collect()} == {1: 1, 2: 2, 3: 2}
    row = spark.sql("SELECT huffman_decode(huffman_encode(array(5, 5, 7, 5))) AS x, half_cast(array(CAST(0.5 AS FLOAT))) AS h").first()
    assert list(row.x) == [5, 5, 7, 5] and row.h == [0.5]


def test_stream_windows_and_memory(spark, sf, tmp_path):
    cells = gr.windowed(gr.read_stream(spark, f"{sf}/events.parquet"))
    q = gr.encode_windows(cells, Codec(BitmapKeys()), 200, str(tmp_path / "out"), str(tmp_path / "cp"))
    q.awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out"))
    ev = spark.read.parquet(f"{sf}/events.parquet").selectExpr("CAST(ts AS TIMESTAMP) AS ts")
    closed = ev.groupBy(F.window("ts", "1 day").alias("w")).count().join(ev.agg((F.max("ts") - F.expr("INTERVAL 1 HOUR")).alias("m"))).where("w.end <= m").count()
    assert got.select("tensor_id").distinct().count() == closed
    folder = str(tmp_path / "cells")
    spark.createDataFrame([(1, 5, 3.0), (1, 6, 1.0), (2, 5, 2.0)], "worker int, idx bigint, value double").coalesce(1).write.parquet(folder)
    stream = spark.readStream.schema("worker int, idx bigint, value double").parquet(folder)
    sent = gr.collected(gr.compensated(stream, 1), "sent_cells", "append")
    assert rows_of(sent, "worker", "idx", "value") == [(1, 5, 3.0), (2, 5, 2.0)]


def test_rounds_choose_between_random_and_sequential(spark, coo):
    meta = ts.meta(coo, 3000)
    p = bl.positives(bl.filters(coo, meta, 0.05), 0.05)
    got = bl.chosen_by_rounds(p, bl.sizes(coo, meta, 0.05), 0.05)
    assert got.distinct().groupBy("tensor_id").count().where("count = 150").count() == 3
    kept = lambda c: bl.hybrid_counts(coo, c).agg(F.sum("k1")).first()[0]
    assert kept(got) > kept(bl.chosen(p, bl.sizes(coo, meta, 0.05), "p1"))


def test_quality_measures(spark):
    s = spark.createDataFrame([(1, 0, 0, 0.9), (1, 0, 1, 0.1), (2, 1, 0, 0.5), (2, 1, 1, 0.5)], "id int, label int, class int, score double")
    assert ms.top1(s).first()[0] == 0.5
    c = spark.createDataFrame([(1, 1, 0.5, 1), (1, 2, 0.7, 0), (2, 1, 0.9, 1), (2, 3, 0.1, 0)], "user int, item int, score double, held int")
    assert ms.hit_rate(c, 1).first()[0] == 0.5 and ms.hit_rate(c, 2).first()[0] == 1.0
    t = ms.timeline({"a": spark.createDataFrame([(1, 0.2), (2, 0.6)], "epoch int, metric double")})
    assert ms.epochs_to(t, 0.5).first()["epochs"] == 2


def test_conflict_set_queries_draw_for_every_supplier(spark, sf):
    want = {r.tensor_id: r["count"] for r in queries.small(spark, sf, "supp_part").groupBy("tensor_id").count().collect()}
    drawn = {r.tensor_id: r["count"] for r in queries.QUERIES["q_bloom_p2"](spark, sf).groupBy("tensor_id").count().collect()}
    assert drawn == want and len(want) > 3
    assert {r.tensor_id for r in queries.QUERIES["q_conflict_sets"](spark, sf).select("tensor_id").distinct().collect()} == set(want)


def test_experiments_cover_every_tensor_and_row(spark, sf, monkeypatch):
    seen, error = [], ms.compression_error
    monkeypatch.setattr(ms, "compression_error", lambda a, b: (seen.append(a.select("tensor_id").distinct().count()), error(a, b))[1])
    monkeypatch.setattr(experiments, "catalogue", lambda *_: {"topr": Codec()})
    assert queries.QUERIES["e16_every_codec"](spark, sf).first().ok
    queries.QUERIES["e20_quantile_means"](spark, sf)
    assert seen == [10] * 4
    dealt = ts.nation_part(spark, sf, "pmod(l_orderkey, 4)").selectExpr("tensor_id", "idx", "value div 1000 AS value").where("value <> 0")
    assert rows_of(experiments.accumulated(spark, sf), "tensor_id", "idx", "value") == rows_of(dealt, "tensor_id", "idx", "value")


def test_training_runs_of_several_methods(spark, sf, monkeypatch):
    methods = {"none": tr.Method(memory=False), "top_r": tr.Method(Codec(), 0.1), "p2": tr.Method(Codec(BloomKeys(0.01, "p2")), 0.1)}
    rows = tr.train_softmax(spark, sf, methods, workers=3, epochs=3).collect()
    assert [(r.method, r.epoch) for r in rows] == [(m, e) for m in methods for e in (1, 2, 3)]
    loss = {(r.method, r.epoch): r.loss for r in rows}
    assert all(loss[m, 3] < loss[m, 1] for m in methods)
    # one step by hand: mean over workers of their mean gradients
    p = spark.read.parquet(f"{sf}/embeddings.parquet").toPandas()
    x, y, w = np.array(p.embedding.tolist(), float), p.label.to_numpy(), p.vec_id.to_numpy()
    parts = []
    for k in range(3):
        mine = (w % 3 == k) & (w % 5 != 0)
        g = np.full((mine.sum(), 10), 0.1)
        g[np.arange(mine.sum()), y[mine]] -= 1
        parts.append((x[mine].T @ g).ravel() / mine.sum())
    first = {r.method: r for r in rows if r.epoch == 1}
    assert first["none"].grad_norm == pytest.approx(np.linalg.norm(np.mean(parts, axis=0))) and first["none"].worker_bits == 32 * 640
    assert first["top_r"].worker_bits == 64 * 64 and first["none"].loss == pytest.approx(np.log(10))
    seen = []
    monkeypatch.setattr(tr, "train_recommender", lambda s, d, methods, **k: seen.append(set(methods)))
    experiments.recommender_training(spark, sf)
    assert seen == [{"none", *experiments.inherent_codecs()}]


def test_memory_returns_in_the_next_step():
    p = np.array([3.0, -1.0, 0.5, 0.0])
    keys, values, bits = tr.sent_of(p, tr.Method(Codec(), 0.25), 0)
    assert keys.tolist() == [0] and values.tolist() == [3.0] and bits == 64
    keys, _, bits = tr.sent_of(p, tr.Method(), 0)
    assert keys.tolist() == [0, 1, 2] and bits == 128


def test_lookup_table_gives_the_same_keys(spark, sf):
    rows = experiments.lookup_table(spark, sf).collect()
    assert all(r.same for r in rows) and rows[1].bytes == 4 * 7 * 25 * ts.load(spark, sf, "part").count()
    keys = np.arange(0, 5000, 9)
    for policy in ("p0", "p1", "p2", "right"):
        a, b = (BloomKeys(0.02, policy, 3, lookup=x).encode(keys, 5000, 4) for x in (False, True))
        assert a.payload == b.payload and np.array_equal(a.sent, b.sent)


def test_small_blocks_equal_kernels(spark):
    """Filters, policies, ranks, gaps and runs over several blocks."""
    rng = np.random.default_rng(5)
    keys = np.sort(rng.choice(5000, 600, replace=False))
    coo = spark.createDataFrame([(0, int(k), float(v)) for k, v in zip(keys, rng.integers(-9, 9, 600) + 0.5)], "tensor_id bigint, idx bigint, value double").repartition(5)
    meta = ts.meta(coo, 5000)
    sized = bl.sizes(coo, meta, 0.05, 512)
    p = bl.positives(bl.filters(coo, meta, 0.05, 1, 512), 0.05, 1, 512)
    for policy in ("p0", "p1", "left", "middle", "right"):
        want = []
        for b in range(10):
            mine = keys[keys // 512 == b] - 512 * b
            want += (BloomKeys(0.05, policy, 1).encode(mine, min(512, 5000 - 512 * b), b).sent + 512 * b).tolist()
        assert sorted(r.idx for r in bl.chosen(p, sized, policy, 1, 512).collect()) == sorted(want), policy
    errors = {(r.fpr, r.policy): r for r in bl.policy_errors(coo, meta, [0.05, 0.2], 1, 512).collect()}
    for policy in bl.POLICIES:
        one = ms.compression_error(coo, bl.decode(coo, meta, 0.05, policy, 1, block=512)).first()["error"]
        assert errors[0.05, policy].error == pytest.approx(one) and errors[0.2, policy].rel_volume < 1
    n = {r.idx: r.n for r in rk.by_idx(coo, block=100).collect()}
    assert n == {int(k): i + 1 for i, k in enumerate(keys)}
    got = {r.idx: (r.prev, r.next) for r in rk.neighbours(coo, 64).collect()}
    assert got == {int(k): (int(keys[i - 1]) if i else None, int(keys[i + 1]) if i < 599 else None) for i, k in enumerate(keys)}


def test_values_are_ranked_over_cuts(spark):
    rng = np.random.default_rng(6)
    v = np.concatenate((rng.standard_normal(3000).round(2), np.zeros(1500)))
    rows = spark.createDataFrame([(0, i, float(x)) for i, x in enumerate(v)], "tensor_id bigint, idx bigint, value double").repartition(4)
    up = np.lexsort((np.arange(len(v)), v))
    got = {r.idx: (r.n, r.n_total) for r in rk.by_value(rows, ["tensor_id"], "value", large=100).collect()}
    assert got == {int(i): (k + 1, 4500) for k, i in enumerate(up)}
    down = np.lexsort((np.arange(len(v)), -v))
    got = {r.idx: r.n for r in rk.by_value(rows, ["tensor_id"], "value", True, large=100).collect()}
    assert got == {int(i): k + 1 for k, i in enumerate(down)}
    t = spark.range(1, 24).selectExpr("id AS n", "23L AS total").select("n", rk.ntile("n", "total", 5).alias("b")).collect()
    want = [r[0] for r in spark.range(1, 24).selectExpr("ntile(5) OVER (ORDER BY id) AS b").collect()]
    assert [r.b for r in sorted(t)] == want


def test_semi_join_with_little_room(spark, monkeypatch):
    left = spark.range(0, 4000).select(F.col("id").alias("k"), (F.col("id") % 7).alias("x"))
    right = spark.range(0, 4000, 13).select(F.col("id").alias("k"))
    for room in (1 << 20, 800, 100):
        monkeypatch.setattr(bl, "BROADCAST_BITS", room)
        assert bl.semi_join(left, right, "k").count() == right.count()


def test_grouped_sketch_and_signs():
    rng = np.random.default_rng(7)
    keys, ids = np.arange(400), rng.integers(0, 64, 400)
    s = GroupedMinMaxSketch(64, 8, 2, 512, 3)
    s.insert(keys, ids)
    got = s.query(keys, s.group(ids))
    assert (got <= ids).all() and (s.group(got) == s.group(ids)).all() and (got == ids).mean() > 0.2
    v = np.concatenate((-rng.random(10), rng.random(300)))
    c = QuantileBuckets(16, huffman=True, split_sign=True)
    back = c.decode(c.encode(v).payload, len(v))
    assert (np.sign(back) == np.sign(v)).all()
