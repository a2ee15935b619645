"""Factors trained block by block against the model as a whole."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsewire.operators import index_codecs as ix
from sparsewire.plans.pipeline import Codec
from sparsewire.workloads import recommender as rc
from sparsewire.workloads import train as tr


@pytest.fixture
def data(spark, sf, monkeypatch):
    monkeypatch.setattr(rc, "BLOCK", 512)
    monkeypatch.setattr(rc, "SHARD", 3000)
    monkeypatch.setattr(rc, "TABLES", 1)
    made = rc.Data(spark, sf, 3, 8, 0)
    assert made.slices > 1 and made.blocks > 3 and made.users % made.height
    yield made
    made.drop()


def test_blocks_train_as_the_whole_model_does(data):
    methods = {"none": tr.Method(memory=False), "pairs": tr.Method(Codec(), None, True)}
    got = rc.train(data, methods, 2, 0.05)
    whole = tr._recommender_whole(data, methods, 2, 0.05).collect()
    assert [n for n, rows in got.items() for _ in rows] == [r.method for r in whole]
    for a, b in zip((x for rows in got.values() for x in rows), whole, strict=True):
        assert a == pytest.approx(tuple(b)[1:], rel=1e-7)


def test_no_task_has_the_model(data):
    with rc.bounded(data.spark):
        partials = rc.gradients(data, data.start(1), 1, True, True)
        rows = partials.select("block", "worker", F.octet_length("x").alias("size"), "n").collect()
    assert max(r.size or 0 for r in rows) <= 8 * 512 and {r.block for r in rows} == {-1, *range(data.blocks)}
    assert sum(r.n or 0 for r in rows) == data.baskets.where("held IS NOT NULL").count()
    start = sorted((r.block, r.x) for r in data.start(1).collect())
    assert np.array_equal(np.concatenate([np.frombuffer(x) for _, x in start]), np.random.default_rng(0).standard_normal((data.users + data.items) * 8) * 0.1)


def test_filters_of_many_blocks_are_scanned_once_for_all_policies(monkeypatch):
    rng, scans, scan = np.random.default_rng(3), [], ix.positives_of
    monkeypatch.setattr(ix, "positives_of", lambda flags, *a: (scans.append(len(flags)), scan(flags, *a))[1])
    keys, shared = [np.sort(rng.choice(20_000, 90, replace=False)) for _ in range(70)], {}
    for p in ix.POLICIES:
        own, plain = ix.BloomKeys(0.01, p), ix.BloomKeys(0.01, p)
        own.shared = shared
        made = list(own.encode_many(keys, 20_000, 2))
        back = list(own.decode_many([e.payload for e in made], 20_000, 90, [90] * 70, 2))
        for k, e, b in zip(keys, made, back, strict=True):
            one = plain.encode(k, 20_000, 2)
            assert one.payload == e.payload and np.array_equal(one.sent, e.sent)
            assert np.array_equal(b, plain.decode(one.payload, 20_000, 90, 90, 2))
    assert sum(scans) == 70


def test_a_draw_of_all_positives_is_all_of_them():
    keys = np.arange(3000)
    codec = ix.BloomKeys(0.01, "p2")
    codec._table = None  # not reached
    assert np.array_equal(codec._picked(keys, np.ones(64, np.uint8), 3000, 3000, 7, 0), keys)


@pytest.mark.parametrize("keys", ([], [0], [9], [0, 1, 2, 7, 9], list(range(10)), [3, 4, 8]))
def test_runs_and_bitmaps_follow_the_keys(keys):
    """Work on 2^40 indices is that of their keys; on ten it gives what the flags of all indices give."""
    keys, flags = np.array(keys, np.int64), np.zeros(10, np.int8)
    flags[keys] = 1
    first, runs = ix.runs_of(keys, 10)
    assert first == flags[0] and np.array_equal(np.repeat((np.arange(len(runs)) + first) % 2, runs), flags)
    assert ix.BitmapKeys().encode(keys, 10).payload == np.packbits(flags).tobytes()
    for codec, d in ((ix.BitmapKeys(), 10), (ix.RunLength(), 10), (ix.RunLength(), 1 << 40)):
        assert np.array_equal(codec.decode(codec.encode(keys, d).payload, d, len(keys), len(keys)), keys)


@pytest.mark.parametrize("width", (1, 7, 19, 32))
def test_packing_takes_memory_for_a_stretch(width):
    import tracemalloc

    from sparsewire.operators import bits as bt

    values = np.random.default_rng(0).integers(0, 1 << width, 200_003)
    spelled = np.packbits((values[:, None] >> np.arange(width - 1, -1, -1) & 1).astype(np.uint8).ravel()).tobytes()
    tracemalloc.start()
    data = bt.pack(values, width)
    assert np.array_equal(bt.unpack(data, width, len(values)), values) and data == spelled
    # the values, their parts and a stretch's bits as words
    assert tracemalloc.get_traced_memory()[1] < 4 * values.nbytes + 3 * 8 * width * (1 << 15)
    tracemalloc.stop()
