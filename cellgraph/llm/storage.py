"""Shared-folder helpers: every intermediate that outlives a stage is a table there.

The folder is the one the cluster names in ``spark.checkpoint.dir``.  Only when that
setting is absent (unit tests, notebooks) a folder of our own is created.
"""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession, label: str) -> str:
    """A fresh sub-folder of the shared checkpoint folder, as a URI or absolute path."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no shared folder; a machine's own is not seen by the others")
        base = os.path.join(tempfile.gettempdir(), "cellgraph-shared")
        os.makedirs(base, exist_ok=True)
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"


def materialise(df: DataFrame, path: str) -> DataFrame:
    """Write ``df`` to ``path`` and reread it: cuts lineage, survives lost executors."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder that :func:`shared_dir` named, through Hadoop's file systems."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def fresh_names(df: DataFrame, *labels: str) -> list[str]:
    """Column names for inner use that no column of ``df`` has, in any case of letters."""
    taken, out = {c.lower() for c in df.columns}, []
    for label in labels:
        name = f"_{label}"
        while name in taken:
            name += "_"
        taken.add(name)
        out.append(name)
    return out
