"""The given tables and raw edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE_SCHEMA = T.StructType([T.StructField("src_key", T.LongType()), T.StructField("dst_key", T.LongType())])


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    table = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return table.select(*columns) if columns else table


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """Text with one edge a line; comment lines are skipped."""
    return spark.read.schema(EDGE_SCHEMA).option("sep", sep).option("comment", comment).csv(path)


def read_edges(spark: SparkSession, path: str, fmt: str, **options) -> DataFrame:
    """Edge lists in csv, json, orc or parquet with columns src_key, dst_key."""
    return spark.read.schema(EDGE_SCHEMA).options(**options).format(fmt).load(path)


def read_init(spark: SparkSession, path: str, attribute: str = "double") -> DataFrame:
    """External start values: raw key, attribute, active flag."""
    return spark.read.schema(f"raw_key long, attr {attribute}, active boolean").parquet(path)


def lattice_edges(spark: SparkSession, side: int) -> DataFrame:
    """A triangulated ``side`` x ``side`` mesh of any size, both directions, keys from 0."""
    n = side * side
    cell = spark.range(n).select(F.col("id").alias("k"), (F.col("id") % side).alias("x"))
    steps = [(1, F.col("x") < side - 1), (side, F.lit(True)), (side + 1, F.col("x") < side - 1)]
    half = cell.select("k", F.explode(F.array(*[F.struct((F.col("k") + d).alias("to"), ok.alias("ok")) for d, ok in steps])).alias("s")).filter(F.col("s.ok") & (F.col("s.to") < n))
    return half.select(F.col("k").alias("src_key"), F.col("s.to").alias("dst_key")).unionByName(half.select(F.col("s.to").alias("src_key"), F.col("k").alias("dst_key")))
