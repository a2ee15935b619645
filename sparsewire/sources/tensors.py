"""Tensors carried by the given tables, and generic builders.

A tensor is a DataFrame (tensor_id bigint, idx bigint, value double) of its non-zero cells; ``weight`` tensors hold
exact integers so that sums are the same in any order. ``meta`` is (tensor_id, d, r).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType

TABLES = ("region", "nation", "supplier", "customer", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
HASHED = 65_536


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_coo(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """A user's tensor in any format that Spark reads, with the schema fixed."""
    schema = "tensor_id bigint, idx bigint, value double"
    return checked(spark.read.format(fmt).schema(schema).options(**({"header": "true"} if fmt == "csv" else {})).load(path))


def checked(coo: DataFrame) -> DataFrame:
    """Cells without zeros; nulls and non-finite values raise when they are met."""
    bad = F.col("idx").isNull() | F.col("value").isNull() | F.isnan("value") | (F.abs("value") == float("inf")) | (F.col("idx") < 0)
    value = F.when(bad, F.raise_error(F.lit("a tensor cell is null, negative or not finite")).cast("double")).otherwise(F.col("value"))
    return coo.withColumn("value", value).where("value <> 0")


def tensor_from(df: DataFrame, tensor: str, idx: str, value: str, dealt: bool = False, block: int | None = None) -> DataFrame:
    """Cells from any table: SQL expressions for tensor, index and value; equal cells are summed.

    dealt: rows go to the task of their cell before any sum, for tables whose cells seldom repeat; sums by reading
    tasks would hold nearly all rows in their maps and merge none. block: they go to the task of their block of so many
    indices, whose number is a column then.
    """
    rows = df.select(F.expr(tensor).cast("bigint").alias("tensor_id"), F.expr(idx).cast("bigint").alias("idx"), F.expr(value).alias("value"))
    if block:
        rows = rows.withColumn("block", F.expr(f"CAST(idx div {block} AS INT)"))
        rows = rows.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "tensor_id", "block")
        return rows.groupBy("tensor_id", "block", "idx").agg(F.sum("value").alias("value")).where("value <> 0")
    if dealt:
        rows = rows.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "tensor_id", "idx")
    return rows.groupBy("tensor_id", "idx").agg(F.sum("value").alias("value")).where("value <> 0")


WEIGHT = "CAST(round(l_extendedprice * 100) AS BIGINT) * (CAST(round(l_discount * 100) AS BIGINT) - 5)"


def _parts(spark: SparkSession, sf_dir: str) -> int:
    """The number of parts: a count from file footers."""
    return load(spark, sf_dir, "part").count()


def nation_part(spark: SparkSession, sf_dir: str, tensor: str = "0") -> DataFrame:
    rows = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return tensor_from(rows, tensor, f"CAST(s_nationkey AS BIGINT) * {_parts(spark, sf_dir)} + l_partkey", WEIGHT)


def worker8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nation_part(spark, sf_dir, "pmod(l_orderkey, 8)")


def supp_part(spark: SparkSession, sf_dir: str, dealt: bool = False, block: int | None = None) -> DataFrame:
    return tensor_from(load(spark, sf_dir, "lineitem"), "l_suppkey", "l_partkey", WEIGHT, dealt, block)


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return tensor_from(rows, "0", f"o_custkey * {_parts(spark, sf_dir)} + l_partkey", WEIGHT)


def conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "x"))
    return rows.select(F.lit(0).cast("bigint").alias("tensor_id"), (F.col("vec_id") * 64 + F.col("pos")).cast("bigint").alias("idx"), F.col("x").cast("double").alias("value")).where("value <> 0")


def layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings")
    ranked = rows.selectExpr("CAST(label AS BIGINT) AS tensor_id", "row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS nth", "embedding")
    cells = ranked.select("tensor_id", "nth", F.posexplode("embedding").alias("pos", "x"))
    return cells.selectExpr("tensor_id", "CAST(nth * 64 + pos AS BIGINT) AS idx", "CAST(x AS DOUBLE) AS value").where("value <> 0")


def user_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    hour = "CAST(floor((unix_timestamp(CAST(ts AS TIMESTAMP)) - unix_timestamp(TIMESTAMP '2024-01-01 00:00:00')) / 3600) AS BIGINT)"
    return tensor_from(load(spark, sf_dir, "events"), "0", f"user_id * 720 + {hour}", "CAST(round(value * 100) AS BIGINT)")


def text(spark: SparkSession, sf_dir: str, width: int = HASHED) -> DataFrame:
    """Counts of hashed words of each document."""
    words = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''")
    return words.groupBy(F.col("doc_id").alias("tensor_id"), F.expr(f"CAST(conv(substring(md5(w), 1, 7), 16, 10) AS BIGINT) % {width}").alias("idx")).agg(F.count("*").alias("value"))


def from_arrays(df: DataFrame, tensor: str, array: str) -> DataFrame:
    """Dense arrays to cells."""
    if not isinstance(df.schema[array].dataType, ArrayType):
        raise TypeError(f"{array} is not an array")
    return df.select(F.col(tensor).cast("bigint").alias("tensor_id"), F.posexplode(array).alias("idx", "value")).selectExpr("tensor_id", "CAST(idx AS BIGINT) AS idx", "CAST(value AS DOUBLE) AS value").where("value <> 0")


def to_arrays(coo: DataFrame) -> DataFrame:
    """Cells to one (keys, values) pair of arrays per tensor, by idx."""
    cells = F.array_sort(F.collect_list(F.struct("idx", "value")))
    return coo.groupBy("tensor_id").agg(cells.alias("c")).select("tensor_id", F.col("c.idx").alias("keys"), F.col("c.value").alias("values"))


def meta(coo: DataFrame, d: int | str) -> DataFrame:
    """(tensor_id, d, r)."""
    return coo.groupBy("tensor_id").agg(F.count("*").alias("r")).select("tensor_id", F.expr(str(d)).cast("bigint").alias("d"), "r")


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (nation_part, supp_part, cust_part, conv, layers, user_hour, text, worker8)}


def write_containers(containers: DataFrame, path: str, mode: str = "errorifexists") -> None:
    containers.write.mode(mode).partitionBy("step").parquet(path)


def read_containers(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)
