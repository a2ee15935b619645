"""Training of customer and part factors, block by block.

A factor table is cut into blocks of about 2^20 parameters. A step of one method has two passes. In the first, a task
has a shard, some of one worker's customers with all their items: the blocks stream by in order, first those of its
customers' factors, then those of the items, and each is done with before the next one comes. In the second, a task has
a block: the workers' gradients stream by, each is compressed and rebuilt, and their mean moves the block's parameters.
So no task and no driver holds the model. Methods whose tables of parameters are large train one after the other, since
the disk holds those of the methods that train at once.
"""

from __future__ import annotations

import contextlib
import ctypes
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sparsify import BLOCK
from ..sources import tensors as ts
from ..sources.checkpoints import stored
from .train import Method, Optimizer, sent_of

#: Items and tested candidates of one shard, about; pairs that are worked on at once; bytes of an Arrow batch.
SHARD, CHUNK, BATCH_BYTES = 8 << 20, 1 << 18, 4 << 20
#: Most blocks of methods that train at once, if there is more than one of them.
TABLES = 8
NEGATIVES, CANDIDATES = 4, 99

PACKED = "shard int, kind int, method int, block int, a binary, b binary, c binary, d binary"
PARTIAL = "method int, block int, kind int, worker int, lo int, at binary, x binary, m binary, v binary, loss double, n bigint, hits bigint"
STATE = "method int, block int, kind int, worker int, lo int, at binary, x binary, m binary, v binary, bits bigint, norm2 double"
ARROW = {"int": pa.int32(), "bigint": pa.int64(), "binary": pa.binary(), "double": pa.float64()}


def _batch(schema: str, **cols: object) -> pa.RecordBatch:
    kinds = dict(c.split() for c in schema.split(", "))
    return pa.RecordBatch.from_arrays([pa.array([x.tobytes() if isinstance(x := cols.get(n), np.ndarray) else x], ARROW[k]) for n, k in kinds.items()], names=list(kinds))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows whose bytes are views."""
    for b in batches:
        for i in range(b.num_rows):
            yield {n: (memoryview(v.as_buffer()) if v.as_buffer() is not None else None) if isinstance(v := c[i], pa.BinaryScalar) else v.as_py() for n, c in zip(b.schema.names, b.columns, strict=True)}


def _give_back() -> None:
    """Returns free memory to the system: a worker lives on after its task."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


class Data:
    """What all methods share: the sizes, and each shard's customers, numbers of items, items and held-out items."""

    def __init__(self, spark: SparkSession, sf_dir: str, workers: int, factors: int, seed: int) -> None:
        self.spark, self.workers, self.factors, self.seed = spark, workers, factors, seed
        self.users, self.items, lines = (ts.load(spark, sf_dir, t).count() for t in ("customer", "part", "lineitem"))
        self.slices = max(1, math.ceil((lines + (CANDIDATES + 1) // 4 * self.users) / workers / SHARD))
        self.shards, self.height = workers * self.slices, max(1, BLOCK // factors)
        self.blocks = -(-(self.users + self.items) // self.height)
        parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        lines = ts.load(spark, sf_dir, "lineitem").join(ts.load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        one = F.struct("o_orderdate", "o_orderkey", "l_partkey")
        seen = lines.select("o_custkey", "l_partkey", one.alias("one")).repartition(parts, "o_custkey").groupBy("o_custkey")
        seen = seen.agg(F.max("one").alias("last"), F.min("one").alias("first"), F.collect_set("l_partkey").alias("parts"))
        worker = F.pmod(F.xxhash64("o_custkey"), F.lit(workers)).cast("int")
        held = F.when(F.col("first") != F.col("last"), F.col("last.l_partkey"))
        self.baskets = seen.select(worker.alias("worker"), "o_custkey", "parts", held.alias("held"))
        shard = F.col("worker") * self.slices + F.pmod(F.xxhash64("o_custkey", F.lit(1)), F.lit(self.slices)).cast("int")
        users, items = self.users, self.items

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                which, cust = b.column(0).to_numpy(), b.column(1).to_numpy()
                held = b.column(3).fill_null(-1).to_numpy()
                lens, flat = b.column(2).value_lengths().to_numpy().astype(np.int64), b.column(2).flatten().to_numpy()
                owner = np.repeat(np.arange(len(cust)), lens)
                keep = flat != held[owner]
                owner, flat = owner[keep], flat[keep]
                if len(cust) and (cust.min() < 0 or cust.max() >= users or held.max() >= items or len(flat) and (flat.min() < 0 or flat.max() >= items)):
                    raise ValueError("an order's customer or a line's part is not within its table's rows")
                for k in np.unique(which).tolist():
                    mine = np.flatnonzero(which == k)
                    yield _batch(PACKED, shard=k, kind=0, method=0, block=0, a=cust[mine], b=np.bincount(owner, minlength=len(cust))[mine].astype(np.int32), c=flat[which[owner] == k].astype(np.int32 if items <= 1 << 31 else np.int64), d=held[mine])

        with bounded(spark):
            self.packed, self.drop = stored(self.baskets.select(shard, "o_custkey", "parts", "held").mapInArrow(pack, PACKED))
            width = 4 if items <= 1 << 31 else 8
            own = self.packed.groupBy(F.expr(f"shard div {self.slices}").cast("int").alias("worker")).agg(F.sum(F.expr(f"octet_length(c) div {width}")).alias("n"))
            #: Rows of each worker that has some.
            self.counts = {r.worker: r.n for r in own.collect() if r.n}

    def width(self, block: int) -> int:
        """Parameters of a block."""
        return min(self.height, self.users + self.items - block * self.height) * self.factors

    def start(self, methods: int) -> DataFrame:
        """For each method, the blocks of one stream of random numbers, whose state before each block the driver knows."""
        rng, states = np.random.default_rng(self.seed), []
        for k in range(self.blocks):
            states.append(rng.bit_generator.state)
            rng.standard_normal(self.width(k))
        width = [self.width(k) for k in range(self.blocks)]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for m, k in (divmod(i, len(states)) for i in b.column(0).to_pylist()):
                    own = np.random.default_rng(0)
                    own.bit_generator.state = states[k]
                    yield _batch(STATE, method=m, block=k, kind=0, worker=-1, x=own.standard_normal(width[k]) * 0.1)

        return self.spark.range(0, methods * self.blocks, 1, min(methods * self.blocks, 32)).mapInArrow(run, STATE)


class bounded:  # noqa: N801
    """Arrow batches of few bytes while the loop runs; shuffle files go when a step is done."""

    def __init__(self, spark: SparkSession) -> None:
        self.conf, self.was = spark.conf, {}

    def __enter__(self) -> None:
        for k, v in (("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES)), ("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")):
            self.was[k] = self.conf.get(k, None)
            self.conf.set(k, v)

    def __exit__(self, *_: object) -> None:
        for k, v in self.was.items():
            self.conf.unset(k) if v is None else self.conf.set(k, v)


class Shard:
    """One shard's rows, the factors of its customers and their gradient."""

    def __init__(self, rows: list[dict], data: dict, epoch: int, learn: bool, test: bool) -> None:
        self.__dict__ |= data
        self.epoch, self.learn, self.test = epoch, learn, test
        self.cust, lens, held = (np.concatenate([np.frombuffer(r[c], t) for r in rows]) for c, t in (("a", np.int64), ("b", np.int32), ("d", np.int64)))
        self.p = np.concatenate([np.frombuffer(r["c"], np.int32 if self.items <= 1 << 31 else np.int64) for r in rows])
        self.owner = np.repeat(np.arange(len(lens), dtype=np.int32), lens)
        kind = np.min_scalar_type(self.blocks)
        if learn:
            self.at = np.empty((NEGATIVES + 1, len(self.p)), kind)
            for t, lo in ((t, lo) for t in range(NEGATIVES + 1) for lo in range(0, len(self.p), CHUNK)):
                self.at[t, lo : lo + CHUNK] = (self.users + self.item(t, slice(lo, lo + CHUNK))) // self.height
        if test:
            self.tested = np.flatnonzero(held >= 0)
            self.held, n = held[self.tested], len(self.tested)
            self.other_at = np.empty(n * CANDIDATES, kind)
            for lo in range(0, n * CANDIDATES, CHUNK):
                pair = np.arange(lo, min(lo + CHUNK, n * CANDIDATES))
                self.other_at[pair] = (self.users + self.candidate(pair)) // self.height

    def begin(self, method: int) -> None:
        """The next method's factors come."""
        self.method, self.loss, n = method, 0.0, len(self.cust)
        self.u, self.gu = np.zeros((self.factors, n)), np.zeros((self.factors, n if self.learn else 0))
        if self.test:
            self.mine, self.scores = np.zeros(len(self.tested)), np.zeros(len(self.other_at))

    def item(self, t: int, rows: np.ndarray | slice) -> np.ndarray:
        """The items of rows, or a negative one of each."""
        p = self.p[rows].astype(np.int64)
        return p if t == 0 else (p * 7919 + self.cust[self.owner[rows]] * 104_729 + (t + 5 * self.epoch) * 15_485_863) % self.items

    def candidate(self, pair: np.ndarray) -> np.ndarray:
        i, j = np.divmod(pair, CANDIDATES)
        return (self.held[i] + 1 + (j * 7919 + self.cust[self.tested[i]] * 31) % (self.items - 1)) % self.items

    def dot(self, us: np.ndarray, v: np.ndarray, it: np.ndarray) -> np.ndarray:
        return sum(u[us] * w[it] for u, w in zip(self.u, v, strict=True))

    def block(self, k: int, x: np.ndarray) -> tuple[int, np.ndarray] | None:
        """Takes a block's factors; the gradient of the items of it, from a row of the block."""
        lo, hi = k * self.height, k * self.height + len(x)
        mine = np.flatnonzero((self.cust >= lo) & (self.cust < hi))
        self.u[:, mine] = x[self.cust[mine] - lo].T
        if hi <= self.users:
            return None
        first = max(lo, self.users)
        v = np.ascontiguousarray(x[first - lo :].T)
        g, begin = np.zeros_like(v), first - self.users
        for t in range(NEGATIVES + 1) if self.learn else ():
            here = np.flatnonzero(self.at[t] == k)
            for c in (here[a : a + CHUNK] for a in range(0, len(here), CHUNK)):
                us, it = self.owner[c], self.item(t, c) - begin
                s = 1 / (1 + np.exp(-self.dot(us, v, it)))
                e = s - (t == 0)
                self.loss -= float(np.log(np.maximum(s if t == 0 else 1 - s, 1e-300)).sum())
                for f in range(self.factors):
                    self.gu[f] += np.bincount(us, e * v[f][it], self.gu.shape[1])
                    g[f] += np.bincount(it, e * self.u[f][us], g.shape[1])
        if self.test:
            here = np.flatnonzero((self.held >= begin) & (self.held < hi - self.users))
            self.mine[here] = self.dot(self.tested[here], v, self.held[here] - begin)
            here = np.flatnonzero(self.other_at == k)
            for c in (here[a : a + CHUNK] for a in range(0, len(here), CHUNK)):
                self.scores[c] = self.dot(self.tested[c // CANDIDATES], v, self.candidate(c) - begin)
        return (first - lo, g.T) if self.learn else None

    def ends(self) -> Iterator[pa.RecordBatch]:
        """The gradient of the customers' factors by block, and the sums."""
        hits = int(((self.scores.reshape(-1, CANDIDATES) > self.mine[:, None]).sum(axis=1) < 10).sum()) if self.test else 0
        which = self.cust // self.height
        for k in np.unique(which).tolist() if self.learn else ():
            mine = np.flatnonzero(which == k)
            yield _batch(PARTIAL, method=self.method, block=k, kind=2, worker=self.worker, at=self.cust[mine] - k * self.height, x=self.gu[:, mine].T)
        yield _batch(PARTIAL, method=self.method, block=-1, kind=3, worker=self.worker, loss=self.loss, n=len(self.tested) if self.test else 0, hits=hits)


def gradients(data: Data, state: DataFrame, epoch: int, learn: bool, test: bool) -> DataFrame:
    """Each shard's gradient by block; hits of the given parameters, and their loss."""
    of = {n: getattr(data, n) for n in ("users", "items", "factors", "height", "blocks")}
    slices = data.slices

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, own = [], None
        for r in _rows(batches):
            if r["kind"] == 0:
                rows.append(r)
            elif rows or own is not None:
                if own is None:
                    own, rows = Shard(rows, of | {"worker": rows[0]["shard"] // slices}, epoch, learn, test), []
                    own.begin(r["method"])
                if r["method"] != own.method:
                    yield from own.ends()
                    own.begin(r["method"])
                got = own.block(r["block"], np.frombuffer(r["a"]).reshape(-1, own.factors))
                if got is not None:
                    yield _batch(PARTIAL, method=r["method"], block=r["block"], kind=2, worker=own.worker, lo=got[0], x=got[1])
        if own is not None:
            yield from own.ends()
        own = None
        _give_back()

    none = F.lit(None).cast("binary")
    x = state.where("kind = 0").select(F.explode(F.sequence(F.lit(0), F.lit(data.shards - 1))).alias("shard"), F.lit(1).alias("kind"), "method", "block", F.col("x").alias("a"), none.alias("b"), none.alias("c"), none.alias("d"))
    rows = data.packed.unionByName(x).repartitionById(data.shards, F.col("shard"))
    return rows.sortWithinPartitions("shard", "kind", "method", "block").mapInArrow(run, PARTIAL)


def updated(data: Data, state: DataFrame, partials: DataFrame, methods: list[Method], epoch: int, rate: float) -> DataFrame:
    """Each block after the workers' gradients are sent, with the bits of all workers and the mean's squared norm;
    residuals that workers keep."""
    counts, width = data.counts, [data.width(k) for k in range(data.blocks)]
    factors = data.factors

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine: dict = {}

        def send() -> Iterator[pa.RecordBatch]:
            """One worker's gradient is whole."""
            if (g := mine.pop("g", None)) is None:
                return
            p = g.ravel() / counts.get(mine["worker"], 1)
            if (left := mine.pop("left", None)) is not None:
                p = p + left
            method = methods[mine["method"]]
            if method.codec is not None and not p.any():
                return
            keys, values, bits = sent_of(p, method, 1000 * epoch + mine["worker"], mine["block"])
            mine["mean"][keys] += values
            mine["bits"] += bits if method.codec is not None else 0
            if method.memory:
                p[keys] -= values
                yield _batch(STATE, method=mine["method"], block=mine["block"], kind=1, worker=mine["worker"], x=p)

        def close() -> Iterator[pa.RecordBatch]:
            yield from send()
            if "mean" in mine:
                mean, opt = mine["mean"] / len(counts), Optimizer("adam", rate)
                opt.t, opt.m, opt.v = epoch - 1, mine["m"], mine["v"]
                x = opt.step(mine["x"], mean)
                bits = mine["bits"] if methods[mine["method"]].codec is not None else 32 * len(x) * len(counts)
                yield _batch(STATE, method=mine["method"], block=mine["block"], kind=0, worker=-1, x=x, m=opt.m, v=opt.v, bits=bits, norm2=float(mean @ mean))
            mine.clear()

        for r in _rows(batches):
            if r["kind"] == 0:
                yield from close()
                m, v = (0.0 if r[c] is None else np.frombuffer(r[c]) for c in "mv")
                mine |= {"method": r["method"], "block": r["block"], "x": np.frombuffer(r["x"]), "m": m, "v": v, "mean": np.zeros(width[r["block"]]), "bits": 0}
                continue
            if "g" not in mine or r["worker"] != mine["worker"]:
                yield from send()
                mine |= {"worker": r["worker"], "g": np.zeros((width[r["block"]] // factors, factors))}
            x = np.frombuffer(r["x"])
            if r["kind"] == 1:
                mine["left"] = x
            elif r["at"] is not None:
                mine["g"][np.frombuffer(r["at"], np.int64)] += x.reshape(-1, factors)
            else:
                x = x.reshape(-1, factors)
                mine["g"][r["lo"] : r["lo"] + len(x)] += x
        yield from close()
        _give_back()

    cols = ("method", "block", "kind", "worker", "lo", "at", "x", "m", "v")
    rows = state.select(*cols).unionByName(partials.where("kind = 2").select(*cols)).repartitionById(len(methods) * data.blocks, F.col("method") * data.blocks + F.col("block"))
    return rows.sortWithinPartitions("method", "block", "worker", "kind").mapInArrow(run, STATE)


def train(data: Data, methods: dict[str, Method], epochs: int, rate: float) -> dict[str, list[tuple[int, int, float, float, float]]]:
    """(epoch, worker_bits, metric, loss, grad_norm) of each method."""
    few, names, out = max(1, TABLES // data.blocks), list(methods), {}
    with bounded(data.spark):
        for a in range(0, len(names), few):
            some = names[a : a + few]
            out |= dict(zip(some, _train(data, [methods[n] for n in some], epochs, rate), strict=True))
    return out


def _train(data: Data, methods: list[Method], epochs: int, rate: float) -> list[list[tuple]]:
    """The same for methods that train at once. The first pass of a step also grades the step before."""
    out: list[list[list]] = [[] for _ in methods]
    state, drop = stored(data.start(len(methods)))
    for epoch in range(1, epochs + 2):
        learn = epoch <= epochs
        partials, drop_partials = stored(gradients(data, state, epoch, learn, epoch > 1))
        sums = partials.where("kind = 3").groupBy("method").agg(F.sum("loss").alias("loss"), F.sum("n").alias("n"), F.sum("hits").alias("hits")).collect()
        loss = {r.method: r.loss / max(1, sum(data.counts.values())) for r in sums}
        if epoch > 1:
            for r in sums:
                out[r.method][-1][2] = r.hits / r.n if r.n else float("nan")
        if learn:
            new, drop_new = stored(updated(data, state, partials, methods, epoch, rate))
            for r in new.where("kind = 0").groupBy("method").agg(F.sum("bits").alias("bits"), F.sum("norm2").alias("norm2")).collect():
                out[r.method].append([epoch, int(r.bits / max(1, len(data.counts))), 0.0, loss[r.method], math.sqrt(r.norm2)])
        drop_partials(), drop()
        if learn:
            state, drop = new, drop_new
    return [[tuple(r) for r in rows] for rows in out]
