"""Raw keys to dense vertex ids 1..n, degrees, and edges in ids."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import work_dir, write_table


@dataclass
class VidMap:
    """``table``: vid, raw_key, out_deg, in_deg; ``edges``: src, dst; n vertices, m edges."""

    table: DataFrame
    n: int


def degrees(edges: DataFrame) -> DataFrame:
    """(raw_key, out_deg, in_deg) of every key that has an edge, in one aggregation."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src_key").alias("raw_key"), F.lit(1).cast("long").alias("o"), F.lit(0).cast("long").alias("i")), F.struct(F.col("dst_key").alias("raw_key"), F.lit(0).cast("long").alias("o"), F.lit(1).cast("long").alias("i")))).alias("e"))
    return ends.select("e.*").groupBy("raw_key").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"))


def densify_ids(edges: DataFrame, folder: str | None = None) -> VidMap:
    """Ids in key order, without a global window: keys are range-partitioned and *written*
    (range borders are sampled, so counts and ids must come from the same rows), partitions
    are counted, and each numbers its own rows from the sum of the counts before it."""
    spark = edges.sparkSession
    folder = folder or work_dir(spark, "vids")
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = degrees(edges).repartitionByRange(parts, "raw_key").withColumn("part", F.spark_partition_id())
    held = write_table(ranged, f"{folder}/ranged")
    counts = sorted((r["part"], r["n"]) for r in held.groupBy("part").agg(F.count("*").alias("n")).collect())
    offsets, total = [], 0
    for part, n in counts:
        offsets.append((part, total))
        total += n
    starts = spark.createDataFrame(offsets or [(0, 0)], "part int, start long")
    numbered = held.join(F.broadcast(starts), "part").withColumn("vid", F.col("start") + F.row_number().over(Window.partitionBy("part").orderBy("raw_key")))
    return VidMap(write_table(numbered.select("vid", "raw_key", "out_deg", "in_deg"), f"{folder}/map"), total)


def to_vid_edges(edges: DataFrame, vids: VidMap) -> DataFrame:
    """(src, dst) in ids."""
    key = vids.table.select("vid", "raw_key")
    return edges.join(key.withColumnsRenamed({"vid": "src", "raw_key": "src_key"}), "src_key").join(key.withColumnsRenamed({"vid": "dst", "raw_key": "dst_key"}), "dst_key").select("src", "dst")


def to_raw(result: DataFrame, vids: VidMap) -> DataFrame:
    """Results keyed by vid, keyed by raw key instead."""
    return result.join(vids.table.select("vid", "raw_key"), "vid").drop("vid")
