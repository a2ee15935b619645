"""Blocks that are encoded and decoded together, against the same one by one."""

import numpy as np
import pytest

from sparsewire.operators import bits as b
from sparsewire.operators import index_codecs as ix
from sparsewire.operators.baselines import three_lc_decode, three_lc_decode_cells, three_lc_encode, three_lc_encode_cells
from sparsewire.operators.curve import fit_double_exponential, fit_double_exponentials
from sparsewire.operators.index_codecs import BloomKeys
from sparsewire.operators.value_codecs import Qsgd
from sparsewire.plans.pipeline import Codec, blocks_of, catalogue
from sparsewire.sources import tensors as ts
from sparsewire.workloads.experiments import inherent_codecs
from sparsewire.workloads.queries import QUERIES


def blocks(d, r, n, seed=0):
    rng = np.random.default_rng(seed)
    keys = [np.sort(rng.choice(d, r, replace=False)) for _ in range(n)]
    return keys, [rng.integers(1, 4000, r) * rng.choice([-1.0, 1.0], r) for _ in range(n)]


@pytest.mark.parametrize("d, r, n", [(150_000, 300, 3), (5001, 40, 70), (2000, 1900, 2), (7, 3, 3), (1, 1, 2)])
def test_together_equals_one_by_one(d, r, n):
    keys, values = blocks(d, r, n)
    for name, codec in (catalogue(0.001) | inherent_codecs()).items():
        one = [codec.encode_block(k, v, d, 2) for k, v in zip(keys, values)]
        many = list(codec.encode_many(keys, values, d, 2))
        assert many == one, name
        for c, (k, v) in zip(one, codec.decode_many(many, 2), strict=True):
            k_one, v_one = codec.decode_block(c, 2)
            assert k[v != 0].tolist() == k_one[v_one != 0].tolist() and v[v != 0].tolist() == v_one[v_one != 0].tolist(), name


def test_a_domain_is_hashed_once_for_all_tensors(monkeypatch):
    d, n = 70_000, 100
    keys, values = blocks(d, 50, n)
    for codec in (Codec(BloomKeys(0.001, "p0", 91)), Codec(BloomKeys(0.6, "p0", 91), Qsgd())):
        real, hashed = ix.hash_array, []
        monkeypatch.setattr(ix, "hash_array", lambda x, *a, **k: hashed.append(x.size) or real(x, *a, **k))
        list(codec.decode_many(list(codec.encode_many(keys, values, d)), 0))
        monkeypatch.setattr(ix, "hash_array", real)
        assert sum(hashed) <= 10 * (d + 50 * n)


def test_accepted_bits_rank_and_find():
    flags = (np.random.default_rng(1).random((66, 40)) < 0.6).astype(np.uint8)
    for d in (1, 64, 70_001):
        for a, p in zip(ix.accepted_of(flags, d, 1, 3, 0), ix.positives_of(flags, d, 1, 3, 0), strict=True):
            assert len(a) == len(p) and a.nth(np.arange(len(p))).tolist() == p.tolist() and a.rank(p).tolist() == list(range(len(p)))


def test_few_values_pack_like_all():
    rng = np.random.default_rng(2)
    for width in (1, 3, 7, 8, 12):
        values = np.zeros(100_003, np.int64)
        at = np.sort(rng.choice(len(values), 200, replace=False))
        values[at] = rng.integers(1, 1 << width, 200)
        values[-1] = 1
        at = np.flatnonzero(values)
        assert b.pack_few(at, values[at], width, len(values)) == b.pack(values, width)
        back = b.unpack_few(b.pack(values, width), width, len(values))
        full = np.zeros(len(values), np.int64)
        if back is not None:
            full[back[0]] = back[1]
        assert (full == values).all() if back is not None else width == 1


@pytest.mark.parametrize("d", [1, 4, 5, 71, 700, 4999])
def test_ternary_code_of_cells(d):
    for r in {0, 1, d // 3, d}:
        keys, (values,) = blocks(d, r, 1, r)[0][0], blocks(d, r, 1, r)[1]
        x = np.zeros(d)
        x[keys] = values
        scale, data = three_lc_encode(x, 1.5)
        assert three_lc_encode_cells(keys, values, d, 1.5) == (scale, data)
        dense, (k, v) = three_lc_decode(scale, data, d), three_lc_decode_cells(scale, data, d)
        assert k.tolist() == np.flatnonzero(dense).tolist() and v.tolist() == dense[k].tolist()


def test_prefix_code_across_stretches():
    symbols = np.random.default_rng(3).geometric(0.3, 60_000)
    code = b.huffman_code(dict(zip(*(x.tolist() for x in np.unique(symbols, return_counts=True)), strict=True)))
    data, _ = b.huffman_encode(symbols, code)
    assert b.huffman_decode(data, code, len(symbols)).tolist() == symbols.tolist()


def test_curves_side_by_side():
    ys = np.sort(np.abs(np.random.default_rng(4).standard_normal((9, 80))))[:, ::-1]
    assert all((one == fit_double_exponential(y)).all() for one, y in zip(fit_double_exponentials(ys), ys))


def test_held_blocks_give_the_same_cells(spark, sf):
    coo = ts.supp_part(spark, sf)
    d = 700
    held = blocks_of(coo, d, 64).persist()
    for codec in (Codec(block=64), Codec(BloomKeys(0.05, "p2"), block=64), Codec(BloomKeys(0.6, "p0"), Qsgd(), block=64)):
        want = codec.decode(codec.encode(coo, ts.meta(coo, d)))
        got = codec.decode_held(codec.encode_held(held))
        assert sorted(got.collect()) == sorted(want.collect()) and got.count() > 0


def test_two_cells_of_one_index_are_refused(spark):
    coo = spark.createDataFrame([(0, 3, 1.0), (0, 3, 2.0)], "tensor_id bigint, idx bigint, value double")
    with pytest.raises(Exception, match="two cells of one index"):
        blocks_of(coo, 10).collect()


def test_dealing_by_block_keeps_the_cells(spark, sf):
    dealt = ts.supp_part(spark, sf, block=64)
    assert dealt.where("block <> idx div 64").count() == 0
    assert sorted(dealt.drop("block").collect()) == sorted(ts.supp_part(spark, sf).collect())


def test_job_seconds_of_ten_methods(spark, sf):
    rows = QUERIES["e14b_job_seconds"](spark, sf).collect()
    assert len({r.method for r in rows}) == 10 and all(r.enc_s > 0 and r.dec_s > 0 for r in rows)
