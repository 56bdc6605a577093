"""Connected components of a link table by alternating star contraction, in DataFrames.

A round is a large-star and a small-star step; each costs one aggregation with map-side
combine and one equi-join, whose hot keys adaptive execution can split.  Rounds are written
to the shared folder, so lineage stays short and a lost executor costs a reread.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import materialise, remove, shared_dir


def _star(links: DataFrame) -> DataFrame:
    """Each node's larger neighbours move to the least of the node and its neighbours."""
    both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")


def _small_star(links: DataFrame) -> DataFrame:
    """Each node and its smaller neighbours move to the least of these."""
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
    return moved.unionByName(least.select("a", F.col("m").alias("b")))


def connected_components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) of every node of ``links`` (a long, b long) but the least of its
    component; ``component`` is the least node reachable."""
    spark = links.sparkSession
    folder = shared_dir(spark, "components")
    now = materialise(links.select("a", "b").filter("a <> b").distinct(), f"{folder}/r0")
    stamp = None
    for k in range(1, max_rounds + 1):
        nxt = materialise(_small_star(_star(now)).distinct(), f"{folder}/r{k}")
        seen = nxt.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0)).alias("h")).first()
        remove(spark, f"{folder}/r{k - 1}")
        now = nxt
        if (seen["n"], seen["h"]) == stamp:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component"))
        stamp = seen["n"], seen["h"]
    raise RuntimeError(f"components not settled after {max_rounds} rounds")
