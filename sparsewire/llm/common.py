"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import inspect
import math
import re
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null id while rows are compared; it sorts after every real id.
NO_ID = 2**63 - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir.

    Where it is unset a local session, as in tests, gets one of its own; on a cluster that is an error.
    """
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", "") or ""
    if not found:
        jsc = spark.sparkContext._jsc.sc()
        if jsc.getCheckpointDir().isDefined():
            return jsc.getCheckpointDir().get()
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = f"file:///tmp/sparsewire-{uuid.uuid4().hex}"
        spark.sparkContext.setCheckpointDir(found)
    return found


def fresh_dir(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared folder, with the lineage cut."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def bounded_batches(df: DataFrame) -> DataFrame:
    """df, with the session's Arrow batches held to BATCH_BYTES: whole texts of any length travel in them."""
    conf = df.sparkSession.conf
    for key in ("spark.sql.execution.arrow.maxBytesPerBatch",):
        now = conf.get(key, None)
        if now is None or not now.isdigit() or int(now) > BATCH_BYTES:
            conf.set(key, str(BATCH_BYTES))
    return df


def give_back() -> None:
    """Returns what Arrow and the C library hold free; workers live on after a task, and their idle memory counts."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidy(f: Callable) -> Callable:
    """A function for mapInArrow or applyInArrow that gives back what it freed, after a task or a group.

    Spark tells the kinds of function apart by their parameters, so these stay.
    """
    if inspect.isgeneratorfunction(f):

        def batches_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield from f(batches)
            give_back()

        return batches_of

    def group(t: pa.Table) -> pa.Table:
        out = f(t)
        give_back()
        return out

    def cogroup(t: pa.Table, other: pa.Table) -> pa.Table:
        out = f(t, other)
        give_back()
        return out

    return group if len(inspect.signature(f).parameters) == 1 else cogroup


def any_names(stage: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """A stage whose documents may have columns with dots, spaces or quotes in their names: Arrow calls refuse these."""

    @functools.wraps(stage)
    def run(docs: DataFrame, *args: object, **named: object) -> DataFrame:
        plain = [c if re.fullmatch(r"\w+", c) else f"sw__c{i}" for i, c in enumerate(docs.columns)]
        if plain == docs.columns:
            return stage(docs, *args, **named)
        old = dict(zip(plain, docs.columns, strict=True))
        out = stage(docs.toDF(*plain), *args, **named)
        return out.toDF(*[old.get(c, c) for c in out.columns])

    return run


def id_or_last(col: str | Column) -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(NO_ID)).cast("bigint")


def id_back(col: str) -> Column:
    return F.when(F.col(col) != NO_ID, F.col(col))


def block_count(spark: SparkSession, texts: DataFrame, text_col: str, block_bytes: int) -> int:
    """Blocks of about block_bytes each, and at least two for each shuffle partition; grows with the data."""
    total = texts.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    return max(math.ceil(total / block_bytes), 2 * shuffle_partitions(spark))


#: Most bytes of an Arrow batch of texts, where Spark can bound it.
BATCH_BYTES = 4 << 20
#: A side of a join is broadcast only if it has been written and found no larger than this.
BROADCAST_BYTES = 32 << 20


def small_side(df: DataFrame) -> DataFrame:
    """df, checkpointed, with a broadcast hint if its rows are measured to be within BROADCAST_BYTES."""
    rows = cut(df)
    width = sum((F.coalesce(F.octet_length(F.col(f"`{f.name}`").cast("string")), F.lit(0)) + 16 for f in rows.schema.fields), F.lit(0))
    total = rows.agg(F.sum(width)).first()[0] or 0
    return F.broadcast(rows) if total <= BROADCAST_BYTES else rows


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) with component the smallest node reachable; nodes without an edge do not appear.

    Alternates two star contractions over (larger, smaller) pairs until a round changes nothing. Minima are
    aggregated before the shuffle, and hubs meet their edges again in a join that Spark can split. Each round's
    pairs are checkpointed, so lost executors repeat one round at most. Every round that changes something lowers the
    sum of the pairs' smaller ends, so rounds end; they are about the logarithm of the longest path.
    """
    big, small = F.greatest("u", "v"), F.least("u", "v")
    pairs = cut(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v").select(big.alias("u"), small.alias("v")).distinct())
    seen = None
    while True:
        state = pairs.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
        if state == seen:
            break
        seen = state
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        pairs = cut(moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct())
    roots = pairs.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return pairs.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component")).unionByName(roots)
