"""Filters and codecs of tensors wider than a block, against SQL and against one another."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__  # noqa: F401  adds the experiments

from sparsewire.operators import bloom as bl
from sparsewire.operators import scan as sc
from sparsewire.sources import tensors as ts
from sparsewire.workloads.queries import ORACLE, QUERIES

SUPP = ("q_bloom_words", "q_bloom_fpr", "q_bloom_naive", "q_bloom_p0", "q_bloom_p1", "q_bloom_p2", "q_bloom_left", "q_bloom_middle", "q_bloom_right", "q_conflict_sets", "q_p1_hybrid_counts", "e06_random_policy", "q_qsgd_bits", "q_sql_decode_container")
NATION = ("q_bloom_positives", "q_skcompress", "q_policy_error_volume")


def tables(folder, parts):
    """Few lines, whose parts lie on both sides of a block's end."""
    con = duckdb.connect()
    for name, rows in {
        "part": f"SELECT i AS p_partkey FROM range({parts}) t(i)",
        "supplier": "SELECT CAST(i AS BIGINT) AS s_suppkey, CAST(i * 12 AS INT) AS s_nationkey FROM range(3) t(i)",
        "lineitem": f"SELECT i % 4 AS l_orderkey, (i * 7919 + i * i * 31) % {parts} AS l_partkey, i % 3 AS l_suppkey, 900.0 + i AS l_extendedprice, CASE WHEN i % 2 = 0 THEN 0.02 ELSE 0.09 END AS l_discount FROM range(400) t(i)",
        "embeddings": "SELECT CAST(i AS BIGINT) AS vec_id, [CAST(sin(i * 64 + j) AS FLOAT) FOR j IN range(64)] AS embedding FROM range(17000) t(i)",
    }.items():
        con.execute(f"COPY ({rows}) TO '{folder}/{name}.parquet' (FORMAT parquet)")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{folder}/{name}.parquet'")
    return str(folder), con


@pytest.fixture(scope="module")
def wide(tmp_path_factory):
    return tables(tmp_path_factory.mktemp("wide"), 1_100_000)


@pytest.fixture(scope="module")
def broad(tmp_path_factory):
    return tables(tmp_path_factory.mktemp("broad"), 50_000)


def same(spark, where, name):
    sf, con = where
    got, want = QUERIES[name](spark, sf).toPandas(), con.execute(ORACLE[name]).df()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols and len(got) == len(want)
    got, want = (x[cols].sort_values(cols, ignore_index=True) for x in (got, want))
    for c in cols:
        assert (got[c] == want[c]).all(), c


@pytest.mark.parametrize("name", SUPP)
def test_tensors_wider_than_a_block(spark, wide, name):
    same(spark, wide, name)


@pytest.mark.parametrize("name", NATION)
def test_one_tensor_wider_than_a_block(spark, broad, name):
    same(spark, broad, name)


@pytest.mark.parametrize("name", ("q_volume_split", "q_bloom_dense"))
def test_dense_tensor_wider_than_a_block(spark, wide, name):
    same(spark, wide, name)


@pytest.mark.parametrize("large", (0, sc.LARGE))
def test_large_tensors_and_groups_equal_the_relational_form(spark, large):
    coo = spark.range(4000).selectExpr("id % 7 AS tensor_id", "id * 37 % 3001 + id % 7 AS idx", "id + 1 AS value").dropDuplicates(["tensor_id", "idx"])
    meta = ts.meta(coo, 3100)
    rows = lambda df: sorted(map(tuple, df.collect()))
    for policy in ("p0", "p1", "left", "middle", "right", "naive"):
        assert rows(sc.decode(coo, meta, 0.05, policy, 3, large).select("tensor_id", "idx", "value")) == rows(bl.decode(coo, meta, 0.05, policy, 3)), policy
    p, sized = bl.positives(bl.filters(coo, meta, 0.05, 3), 0.05, 3), bl.sizes(coo, meta, 0.05)
    assert rows(sc.positives(coo, meta, 0.05, 3, large)) == rows(p.select("tensor_id", "idx"))
    assert rows(sc.conflict_sizes(coo, meta, 0.05, 3, large)) == rows(bl.conflict_sets(p, sized, 0.05, 3).select("tensor_id", "bit", "size"))
    by_rounds = bl.fetched(bl.chosen_by_rounds(p, sized, 0.05, 3), coo)
    assert rows(sc.decode(coo, meta, 0.05, "p2_rounds", 3, large).select("tensor_id", "idx", "value")) == rows(by_rounds)
    counts = bl.hybrid_counts(coo, bl.chosen(p, sized, "p1", 3))
    assert rows(sc.tallies(coo, meta, 0.05, "p1", 3, large).select("tensor_id", "k1", "k2")) == rows(counts.select("tensor_id", "k1", "k2"))
    bits = bl.filters(coo, meta, 0.05, 3).select("tensor_id", F.expr("aggregate(words, 0L, (n, w) -> n + bit_count(w))").alias("bits_set"))
    assert rows(sc.words(coo, meta, 0.05, 3, large).select("tensor_id", "bits_set")) == rows(bits)


def test_timings_add_up_over_blocks(spark, broad):
    """Kernels are timed in the tasks that hold the blocks: the driver collects no cells."""
    sf, _ = broad
    t = {r.method: r for r in QUERIES["e19_lookup_table"](spark, sf).collect()}
    assert t["table"].bytes == 25 * 50_000 * 7 * 4 and t["table"].same and t["computed"].same
    seconds = QUERIES["e14c_sparse_codec_seconds"](spark, sf).collect()
    assert len(seconds) == 3 and all(r.enc_s > 0 and r.dec_s > 0 for r in seconds)


def test_rate_sweep_of_several_blocks(spark, wide):
    """Every key is a positive and comes back, so p0 errs least, and a looser rate sends more values."""
    rows = {(r.sparsifier, r.policy, r.fpr): r for r in QUERIES["e07_rate_sweep"](spark, wide[0]).collect()}
    assert len(rows) == 30
    for s in ("top_r", "random_r"):
        for f in (1e-4, 1e-3, 4e-3, 1e-2, 1e-1):
            assert rows[s, "p0", f].error <= rows[s, "p1", f].error + 1e-12
        assert rows[s, "p0", 1e-1].error < rows[s, "p0", 1e-4].error


def test_a_task_makes_one_partial_for_each_method_and_worker(spark):
    """However many Arrow batches its rows come in."""
    from sparsewire.workloads import train as tr

    rows = spark.range(0, 25_000, 1, 1).selectExpr("CAST(id % 2 AS INT) AS worker", "id AS x")
    count = lambda params, b: ((k, params * (b.column(0).to_numpy() == k).sum(), 0.0, int((b.column(0).to_numpy() == k).sum())) for k in (0, 1))
    got = tr._partials(rows, {"a": np.ones(3)}, count).collect()
    assert sorted((r.worker, r.n, r["values"]) for r in got) == [(0, 12_500, [12_500.0] * 3), (1, 12_500, [12_500.0] * 3)]


@pytest.mark.parametrize("name", ("q_bloom_size", "q_bloom_bits_theory", "q_comm_model", "e01_worked_example", "e02_runs_and_codes", "e03_membership", "e04_conflict_draw", "e05_naive_shift", "e17b_spline_bounds", "q_theory"))
def test_closed_forms_read_a_table(spark, sf, name):
    assert QUERIES[name](spark, sf).inputFiles()


def test_every_codec_reads_each_block_once(spark, broad):
    """All instantiations in one pass over the cells, and filters that are shared choose as those that are not."""
    from sparsewire.operators.index_codecs import POLICIES, BloomKeys

    out = QUERIES["e16_every_codec"](spark, broad[0])
    assert {(r.method, r.ok) for r in out.collect()} == set(broad[1].execute(ORACLE["e16_every_codec"]).fetchall())
    assert out._jdf.queryExecution().optimizedPlan().toString().count("FlatMapGroupsInArrow") == 1
    keys, shared = np.unique(np.arange(0, 40_000, 57) ** 2 % 30_000), {}
    for p in POLICIES:
        plain, own = BloomKeys(0.01, p), BloomKeys(0.01, p)
        own.shared = shared
        e, f = plain.encode(keys, 30_000), own.encode(keys, 30_000)
        assert e.payload == f.payload and np.array_equal(e.sent, f.sent)
        assert np.array_equal(plain.decode(e.payload, 30_000, len(keys), len(e.sent)), own.decode(f.payload, 30_000, len(keys), len(f.sent)))


def test_policies_sum_the_cells_once(spark, sf):
    """Sizes of filters and groups read what was written, not lineitem again."""
    assert not any("lineitem" in f for f in QUERIES["q_bloom_naive"](spark, sf).inputFiles())


def test_policies_deal_rows_before_they_are_summed(spark, sf):
    """No reading task holds a map of partial sums of cells that seldom repeat."""
    plan = ts.supp_part(spark, sf, dealt=True)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and plan.index("HashAggregate") < plan.index("Exchange") < plan.index("FileScan")
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(ts.supp_part(spark, sf, dealt=True)) == rows(ts.supp_part(spark, sf))
