"""A store of immutable shards with size-tiered compaction and a versioned manifest, by DataFrame operations only.

An append writes the rows that arrive as a run of small files. Runs whose sizes fall into the same tier are merged,
``FAN_IN`` at a time, into files of the target size; a merge reads and writes rows without a shuffle. The list of live
runs is a manifest of which each version is a file of its own: it is written whole under another name and then takes
its own name in one step that fails if another writer has made that version, so readers see one whole version or the
next, and of two writers one starts anew. Local folders do that by a link, others by a rename that never replaces; a
store of objects that has no such rename can take one writer at a time. Files that no version from the latest on needs
are removed by ``vacuum``.

Rows are kept as they come: nulls in any column, repeated rows, empty and very long texts. An append casts the columns
of the store's schema and leaves out others; names are matched as Spark matches them, so rows with two columns of one
name are refused. An empty append is a run without rows.
"""

from __future__ import annotations

import json
import math
import uuid
from dataclasses import asdict, dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .common import fresh_dir, table

FAN_IN = 4
TARGET_BYTES = 32 << 20
LEAST_BYTES = 1 << 20
ARRIVALS = 8


@dataclass(frozen=True)
class Run:
    path: str
    bytes: int
    files: int

    def tier(self, least: int = LEAST_BYTES, fan_in: int = FAN_IN) -> int:
        return max(0, int(math.log(max(self.bytes, 1) / least, fan_in)) + 1) if self.bytes >= least else 0


class ShardStore:
    """Runs under a root folder that all executors reach."""

    def __init__(self, spark: SparkSession, root: str, schema: StructType, target_bytes: int = TARGET_BYTES, fan_in: int = FAN_IN) -> None:
        self.spark, self.root, self.schema, self.target_bytes, self.fan_in = spark, root.rstrip("/"), schema, target_bytes, fan_in
        jvm = spark._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(f"{self.root}/_manifests"))

    def version(self) -> int:
        """The latest version; 0 for an empty store."""
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(f"{self.root}/_manifests"))]
        return max((int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")), default=0)

    def runs(self, version: int | None = None) -> list[Run]:
        v = self.version() if version is None else version
        if not v:
            return []
        name = self._path(f"{self.root}/_manifests/v{v:010d}.json")
        stream = self._fs.open(name)
        try:
            text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [Run(**r) for r in json.loads(text)["runs"]]

    def commit(self, base: int, runs: list[Run]) -> int:
        """Makes version base + 1 with these runs, or fails if it exists."""
        new = self._path(f"{self.root}/_manifests/v{base + 1:010d}.json")
        held = self._path(f"{self.root}/_manifests/.{uuid.uuid4().hex}")
        stream = self._fs.create(held, False)
        stream.write(bytearray(json.dumps({"version": base + 1, "runs": [asdict(r) for r in runs]}).encode()))
        stream.close()
        try:
            self._publish(held, new)
        except Py4JJavaError as e:
            self._fs.delete(held, False)
            raise RuntimeError(f"version {base + 1} exists: read the manifest again") from e
        return base + 1

    def _publish(self, held: object, new: object, by_link: bool | None = None) -> None:
        """Gives a written file the name that no other may have taken."""
        jvm, uri = self.spark._jvm, self._fs.makeQualified(new).toUri()
        if uri.getScheme() == "file" if by_link is None else by_link:
            local = lambda p: jvm.java.nio.file.Paths.get(self._fs.makeQualified(p).toUri())
            jvm.java.nio.file.Files.createLink(local(new), local(held))
            self._fs.delete(held, False)
            return
        rename = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
        options = self.spark.sparkContext._gateway.new_array(rename, 1)
        options[0] = rename.NONE
        jvm.org.apache.hadoop.fs.FileContext.getFileContext(uri, self.spark._jsc.hadoopConfiguration()).rename(held, new, options)

    def measured(self, path: str) -> Run:
        files = [s for s in self._fs.listStatus(self._path(path)) if s.getPath().getName().startswith("part-")]
        return Run(path, sum(s.getLen() for s in files), len(files))

    def append(self, rows: DataFrame) -> Run:
        """A new run with these rows; live when the manifest names it."""
        path = f"{self.root}/data/{uuid.uuid4().hex}"
        rows.select(*[F.col(f.name).cast(f.dataType) for f in self.schema.fields]).write.parquet(path)
        return self.adopt(path)

    def adopt(self, path: str) -> Run:
        run, v = self.measured(path), self.version()
        self.commit(v, [*self.runs(v), run])
        return run

    def append_parts(self, rows: DataFrame, part_col: str) -> list[Run]:
        """One run for each value of a column of few values, all written in one pass and adopted one after another."""
        top = f"{self.root}/data/{uuid.uuid4().hex}"
        rows.write.partitionBy(part_col).parquet(top)
        return [self.adopt(s.getPath().toString()) for s in self._fs.listStatus(self._path(top)) if s.isDirectory()]

    def read(self, version: int | None = None) -> DataFrame:
        return self._rows(self.runs(version))

    def _rows(self, runs: list[Run]) -> DataFrame:
        if not runs:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*[r.path for r in runs])

    def due(self) -> list[Run]:
        """The runs of the lowest tier that holds fan_in runs; runs of target-sized files alone are merged no more."""
        tiers: dict[int, list[Run]] = {}
        for r in self.runs():
            tiers.setdefault(r.tier(LEAST_BYTES, self.fan_in), []).append(r)
        full = [t for t, runs in tiers.items() if len(runs) >= self.fan_in and any(r.files and r.bytes / r.files < self.target_bytes / 2 for r in runs)]
        return sorted(tiers[min(full)], key=lambda r: r.bytes)[: self.fan_in] if full else []

    def compact(self) -> int:
        """Merges until no tier is full; gives the number of merges."""
        n = 0
        while runs := self.due():
            total = sum(r.bytes for r in runs)
            path = f"{self.root}/data/{uuid.uuid4().hex}"
            self._rows(runs).coalesce(max(1, math.ceil(total / self.target_bytes))).write.parquet(path)
            v = self.version()
            gone = {r.path for r in runs}
            live = self.runs(v)
            if not gone <= {r.path for r in live}:
                raise RuntimeError("a run that was merged is no longer live")
            self.commit(v, [r for r in live if r.path not in gone] + [self.measured(path)])
            n += 1
        return n

    def vacuum(self, keep: int = 1) -> int:
        """Removes the runs that only versions before the last keep ones name, and those versions."""
        v = self.version()
        live = {r.path for k in range(max(1, v - keep + 1), v + 1) for r in self.runs(k)}
        gone = {r.path for k in range(1, v - keep + 1) if self._fs.exists(self._path(f"{self.root}/_manifests/v{k:010d}.json")) for r in self.runs(k)} - live
        for p in gone:
            self._fs.delete(self._path(p), True)
        for k in range(1, v - keep + 1):
            self._fs.delete(self._path(f"{self.root}/_manifests/v{k:010d}.json"), False)
        return len(gone)


def op8_size_tiered_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents, arriving in ARRIVALS parts, appended and compacted; every row as read from the latest version."""
    docs = table(spark, sf_dir, "documents")
    store = ShardStore(spark, fresh_dir(spark, "shards"), docs.schema)
    arriving = docs.withColumn("sw__arrival", F.pmod(F.xxhash64("doc_id", "text"), F.lit(ARRIVALS)))
    store.append_parts(arriving, "sw__arrival")
    store.compact()
    store.vacuum()
    return store.read().select("doc_id", F.md5(F.coalesce("text", F.lit(""))).alias("text_md5"), F.octet_length(F.coalesce("text", F.lit(""))).cast("bigint").alias("n_bytes"), "lang", "source", "n_chars")


OP8_SQL = """
SELECT doc_id, md5(coalesce(text, '')) AS text_md5, octet_length(encode(coalesce(text, ''))) AS n_bytes, lang, source, n_chars FROM documents
"""
