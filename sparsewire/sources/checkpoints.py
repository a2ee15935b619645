"""Lineage cuts in the folder that driver and executors share."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A side of a join is broadcast only if it has been written and found no larger than this.
BROADCAST_BYTES = 32 << 20

#: Rows of many MB are written as they come, not gathered to large groups first.
STREAMED = {"compression": "none", "parquet.block.size": 8 << 20, "parquet.block.size.row.check.min": 1, "parquet.page.size.row.check.min": 1, "parquet.enable.dictionary": False}


def checkpointed(df: DataFrame) -> DataFrame:
    """df written to spark.checkpoint.dir and read again.

    Where no folder is set, a temporary one serves a local session; on a cluster that is an error, since executors
    would write to their own disks.
    """
    _shared(df)
    return df.checkpoint(eager=True)


def _shared(df: DataFrame) -> None:
    sc = df.sparkSession.sparkContext
    if not (sc.getConf().get("spark.checkpoint.dir", "") or sc._jsc.sc().getCheckpointDir().isDefined()):
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(f"file://{tempfile.mkdtemp()}")


def stored(df: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """df written to a folder of its own in that folder and read again, and what removes it: for the rows of a loop,
    which a checkpoint would keep for as long as the session."""
    _shared(df)
    sc = df.sparkSession.sparkContext
    folder = f"{sc._jsc.sc().getCheckpointDir().get()}/stored-{uuid.uuid4()}"
    df.write.options(**STREAMED).parquet(folder)

    def drop() -> None:
        path = sc._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)
        # shuffle files go with the plans that made them
        gc.collect()
        sc._jvm.System.gc()

    return df.sparkSession.read.schema(df.schema).parquet(folder), drop


def small_side(df: DataFrame) -> DataFrame:
    """df, checkpointed, with a broadcast hint if its rows are measured to be within BROADCAST_BYTES."""
    rows = checkpointed(df)
    width = sum((F.coalesce(F.octet_length(F.col(f"`{f.name}`").cast("string")), F.lit(0)) + 16 for f in rows.schema.fields), F.lit(0))
    total = rows.agg(F.sum(width)).first()[0] or 0
    return F.broadcast(rows) if total <= BROADCAST_BYTES else rows
