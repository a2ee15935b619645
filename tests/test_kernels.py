"""Worked examples, round trips and closed forms of the block kernels."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sparsewire.operators import bits as b
from sparsewire.operators import curve as cv
from sparsewire.operators import theory as th
from sparsewire.operators.baselines import MinMaxSketch, three_lc_decode, three_lc_encode
from sparsewire.operators.bloom import bloom_size, fpr_of
from sparsewire.operators.index_codecs import BitmapKeys, BloomKeys, DeltaHuffmanKeys, DeltaKeys, HuffmanKeys, RawKeys, RunLength, draw_by_conflicts
from sparsewire.operators.value_codecs import Deflate, FitDoubleExp, FitPoly, HalfValues, Qsgd, QuantileBuckets, pack_map, unpack_map
from sparsewire.plans import planner
from sparsewire.plans.network import comm_bytes, iteration_time
from sparsewire.plans.pipeline import Codec, catalogue, register, registered

LOSSLESS = [RawKeys(), BitmapKeys(), RunLength("gamma"), RunLength("varint"), RunLength("fixed32"), HuffmanKeys(), DeltaKeys(), DeltaHuffmanKeys()]


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 3000), st.data())
def test_index_codecs_give_keys_back(d, data):
    keys = np.array(sorted(data.draw(st.sets(st.integers(0, d - 1), max_size=60))), np.int64)
    for codec in LOSSLESS:
        e = codec.encode(keys, d)
        assert codec.decode(e.payload, d, len(keys), len(keys)).tolist() == keys.tolist(), codec.name


def test_byte_frequencies_count_all_keys():
    for d in (1, 255, 256, 257, 70_000):
        raw, n = np.unique(np.arange(d).astype(">u4").view(np.uint8), return_counts=True)
        assert b.byte_frequencies(d) == dict(zip(raw.tolist(), n.tolist()))


def test_huffman_string():
    text = "aaaabaacaabaa"
    lengths = b.prefix_lengths({ord(c): text.count(c) for c in "abc"})
    assert {chr(s): n for s, n in lengths.items()} == {"a": 1, "b": 2, "c": 2}
    assert sum(lengths[ord(c)] for c in text) == 16


@pytest.mark.parametrize("policy", ["p0", "p1", "p2", "left", "middle", "right"])
def test_filter_policies(policy):
    keys = np.sort(np.random.default_rng(3).choice(4000, 200, replace=False))
    codec = BloomKeys(0.02, policy)
    e = codec.encode(keys, 4000)
    assert codec.decode(e.payload, 4000, 200, len(e.sent)).tolist() == e.sent.tolist()
    assert policy == "p0" or len(e.sent) == 200
    if policy == "p0":
        assert set(keys.tolist()) <= set(e.sent.tolist())


def test_conflict_draw_keeps_more_than_a_random_draw():
    kept = {"p1": [], "p2": [], "naive": []}
    for seed in range(20):
        keys = np.sort(np.random.default_rng(seed).choice(2000, 60, replace=False))
        for p in kept:
            kept[p].append(len(np.intersect1d(BloomKeys(0.05, p, seed).encode(keys, 2000).sent if p != "naive" else BloomKeys(0.05, "left", seed).encode(keys, 2000).sent, keys)))
    assert np.mean(kept["p2"]) > np.mean(kept["p1"])


def test_singletons_are_drawn_first():
    positions = np.array([[0, 2, 4, 2], [1, 3, 5, 4], [6, 7, 1, 3]])
    drawn = draw_by_conflicts(np.arange(4), positions, np.array([3, 1, 2, 0]), 3)
    assert sorted(drawn.tolist()) == [0, 1, 2]


def test_mean_positives_follow_the_rate():
    d, r, fpr = 20_000, 400, 0.05
    seen = [len(BloomKeys(fpr, "p0", s).encode(np.sort(np.random.default_rng(s).choice(d, r, replace=False)), d).sent) for s in range(20)]
    assert abs(np.mean(seen) - th.positives_bound(r, d, fpr)) < 6 * th.positives_spread(r, d, fpr) / math.sqrt(20)


def test_gram_fit_is_least_squares():
    y = np.random.default_rng(1).standard_normal(50)
    x = np.arange(50)
    assert np.allclose(cv.gram_value(cv.gram_fit(y, 5), 50), np.polyval(np.polyfit(x, y, 5), x))
    assert np.allclose(cv.gram_value(cv.gram_fit(y[:3], 5), 3), y[:3])


def test_two_lines_are_found():
    y = np.concatenate((np.linspace(10, 5, 20), np.linspace(5, 4, 30)[1:]))
    ends = cv.segments(y, 2, 2)
    assert ends[0] == 20 and ends[-1] == 49


def test_planted_double_exponential():
    x = np.linspace(0, 1, 200)
    y = 3 * np.exp(-4 * x) - 0.5 * np.exp(2 * x)
    assert np.abs(cv.double_exponential(x, cv.fit_double_exponential(y)) - y).max() < 1e-6


def test_error_falls_with_pieces():
    y = np.sort(np.random.default_rng(2).standard_normal(400))[::-1]
    errors = []
    for p in (1, 4, 8):
        ends = cv.segments(y, p, 6)
        errors.append(sum(((cv.gram_value(cv.gram_fit(y[a:e], 1), e - a) - y[a:e]) ** 2).sum() for a, e in zip([0, *ends[:-1]], ends)))
    assert errors[0] > errors[1] > errors[2]


def test_quantiser_is_unbiased_and_bounded():
    v = np.random.default_rng(4).standard_normal(600)
    mean = np.mean([Qsgd(7, 512, s).decode(Qsgd(7, 512, s).encode(v).payload, 600) for s in range(300)], axis=0)
    assert np.abs(mean - v).max() < 0.12
    assert Qsgd(7, 512).encode(v).bits == 7 * 600 + 64


@pytest.mark.parametrize("n", [0, 1, 3, 5, 40])
@pytest.mark.parametrize("codec", [Deflate(), HalfValues(), Qsgd(), FitPoly(), FitPoly(order="magnitude"), FitPoly(split="level"), FitDoubleExp(), FitDoubleExp("value"), FitDoubleExp("value_per_sign"), QuantileBuckets(8), QuantileBuckets(8, True)], ids=lambda c: c.name)
def test_value_codecs_at_small_sizes(codec, n):
    v = np.random.default_rng(n).standard_normal(n) * 1e5
    p = codec.encode(v)
    back = codec.decode(p.payload, n)
    assert len(back) == n and np.isfinite(back).all()
    if p.order is not None and n:
        packed, size = pack_map(p.order)
        rank = unpack_map(packed, n)
        assert np.array_equal(p.order[rank], np.arange(n)) and size == n * (math.ceil(math.log2(n)) if n > 1 else 0)


def test_equal_and_one_signed_values():
    for v in (np.full(30, 2.5), -np.arange(1.0, 31)):
        back = FitPoly().decode(FitPoly().encode(v).payload, 30)
        assert np.allclose(np.sort(back), np.sort(v), atol=1e-4)


def test_ternary_bytes_and_runs():
    x = np.zeros(100)
    x[[0, 51]] = [2.0, -1.5]
    scale, data = three_lc_encode(x)
    back = three_lc_decode(scale, data, 100)
    assert back[0] == 2.0 and back[51] == -2.0 and np.count_nonzero(back) == 2 and len(data) == 4


def test_sketch_never_overestimates():
    keys, ids = np.arange(500), np.random.default_rng(5).integers(0, 64, 500)
    s = MinMaxSketch(3, 128)
    s.insert(keys, ids)
    assert (s.query(keys) <= ids).all()


def test_closed_forms():
    assert round(th.bits_per_key(0.001), 3) == 14.378 and round(th.bits_per_key(0.01), 3) == 9.585 and round(th.bits_per_key(0.6), 3) == 1.063
    assert round(th.volume_fit(368, 4), 3) == 0.505 and round(th.volume_fit(368, 48), 3) == 0.565
    assert abs(th.volume_p0_qsgd(0.608, 0.6) - 0.2063) < 2e-4
    assert abs(th.p0_crossover(368, 36_864) - 0.0068) < 3e-4
    assert fpr_of(bloom_size(1000, 0.01)[0], 7, 1000) == pytest.approx(0.01, rel=0.05)
    assert th.p1_error(3, 1, 4, 6, 1.0, 0.0) == 0.25
    assert th.fit_moment_bound(0.1, 0.9, 0.9, 10, 1, 4, 1, True, "rederived") > th.fit_moment_bound(0.1, 0.9, 0.9, 10, 1, 4, 1, True, "printed")


def test_exact_choice_error_by_enumeration():
    from itertools import combinations

    g, true = np.array([3.0, 2, 1, 0.5, 0.25, 2.5]), {0, 1, 2}
    k1, k2 = 2, 1
    total = [sum(g[i] ** 2 for i in range(6) if i not in (*a, *c)) for a in combinations(sorted(true), k1) for c in combinations([3, 4, 5], k2)]
    s, f = (g[:3] ** 2).sum(), (g[3:] ** 2).sum()
    assert np.mean(total) == pytest.approx(th.p1_error(k1, k2, 3, 6, s, f, "exact"))


def test_codec_edges_and_registry():
    for d, r in ((1, 1), (50, 0), (50, 50)):
        keys, values = np.arange(r), np.arange(1.0, r + 1)
        for name, codec in catalogue(0.01).items():
            k, v = codec.decode_block(codec.encode_block(keys, values, d))
            assert len(k) == len(v), name
    with pytest.raises(ValueError):
        Codec().encode_block(np.array([0]), np.array([np.nan]), 1)

    @register("doubled")
    class Doubled(HalfValues):
        name = "doubled"

    assert registered("doubled").name == "doubled"


def test_planner_and_network():
    assert planner.key_form(100, 1000).name == "bitmap" and planner.key_form(10, 1000).name == "raw"
    assert planner.choose_codec(300, 30_000, lossless=True)[1] == "none"
    assert planner.p0_allowed(0.001, 368, 36_864) and not planner.p0_allowed(0.05, 368, 36_864)
    assert planner.Plan(("identity", "pack_map", "raw_value")).without_bypasses().without_map(True).steps == ()
    assert comm_bytes("allreduce", 4, 8) == 12 and iteration_time(1, 2, "allgather", 4, 1e6, 8e6)["comm"] == 3
