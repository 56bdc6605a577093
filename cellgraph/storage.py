"""Written tables in the shared folder: they cut lineage and outlive lost executors."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def work_dir(spark: SparkSession, label: str) -> str:
    """A fresh folder in ``spark.checkpoint.dir``; our own only where that isn't set."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no shared folder; a machine's own is not seen by the others")
        base = os.path.join(tempfile.gettempdir(), "cellgraph-work")
        os.makedirs(base, exist_ok=True)
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"


def write_table(df: DataFrame, path: str, *partitions: str) -> DataFrame:
    """Write ``df`` as Parquet and read it back."""
    out = df.write.mode("overwrite")
    (out.partitionBy(*partitions) if partitions else out).parquet(path)
    spark = df.sparkSession
    return spark.read.schema(df.schema).parquet(path).select(*df.columns)


def delete(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


_tables: dict[str, str] = {}  # path of a bucketed table -> its name in the catalog


def write_bucketed(df: DataFrame, path: str, key: str | tuple[str, ...], buckets: int, *partitions: str, sort: tuple[str, ...] = ()) -> DataFrame:
    """Write ``df`` as an external table bucketed by ``key`` and read it back: joins and folds
    on the key need no exchange, filters on ``partitions`` open no other folder."""
    name = "cellgraph_" + uuid.uuid4().hex
    keys = (key,) if isinstance(key, str) else key
    out = df.write.mode("overwrite").format("parquet").option("path", path).bucketBy(buckets, *keys)
    if sort:
        out = out.sortBy(*sort)
    if partitions:
        out = out.partitionBy(*partitions)
    out.saveAsTable(name)
    _tables[path] = name
    return df.sparkSession.table(name).select(*df.columns)


def forget(spark: SparkSession, path: str) -> None:
    """Delete a folder, and drop its table if it is a bucketed one."""
    if path in _tables:
        spark.sql(f"DROP TABLE IF EXISTS `{_tables.pop(path)}`")
    delete(spark, path)
