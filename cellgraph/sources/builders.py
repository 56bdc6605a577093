"""Graphs that the given tables carry: (spark, sf_dir) -> distinct edges without loops."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..storage import work_dir, write_table
from .tables import read_table

#: Keeps the keys of the second side of a bipartite graph apart from the first side's.
OFFSET = 1_000_000_000


def clean_edges(edges: DataFrame, dedup: bool = True, drop_loops: bool = True) -> DataFrame:
    out = edges.filter(F.col("src_key").isNotNull() & F.col("dst_key").isNotNull())
    if drop_loops:
        out = out.filter("src_key <> dst_key")
    return out.distinct() if dedup else out


def symmetrize(edges: DataFrame, dedup: bool = True) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("dst_key").alias("src_key"), F.col("src_key").alias("dst_key")))
    return both.distinct() if dedup else both


def _succession(rows: DataFrame, key: str, parts: list, order: list) -> DataFrame:
    nxt = F.lead(key).over(Window.partitionBy(*parts).orderBy(*order))
    return clean_edges(rows.select(F.col(key).alias("src_key"), nxt.alias("dst_key")))


def g_copart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part to the next part of the same order."""
    rows = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_suppkey")
    return _succession(rows, "l_partkey", ["l_orderkey"], ["l_linenumber", "l_partkey", "l_suppkey"])


def g_custday(spark: SparkSession, sf_dir: str, priorities: tuple[str, ...] | None = None) -> DataFrame:
    """Customer to the next customer who orders on the same day."""
    rows = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    if priorities:
        rows = rows.filter(F.col("o_orderpriority").isin(*priorities))
    return _succession(rows, "o_custkey", ["o_orderdate"], ["o_orderkey"])


def g_custhigh(spark: SparkSession, sf_dir: str) -> DataFrame:
    return g_custday(spark, sf_dir, ("1-URGENT", "2-HIGH"))


def g_custurg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return g_custday(spark, sf_dir, ("1-URGENT",))


def g_user(spark: SparkSession, sf_dir: str, event_type: str = "purchase") -> DataFrame:
    """Purchaser to the next purchaser.

    Ordered within days; the last of a day then leads to the first of the next day that has
    any.  So only one row a day meets in the window without a partition.
    """
    rows = read_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type").filter(F.col("event_type") == event_type).withColumn("day", F.to_date("ts"))
    day = Window.partitionBy("day").orderBy("ts", "event_id")
    within = rows.select(F.col("user_id").alias("src_key"), F.lead("user_id").over(day).alias("dst_key"))
    ends = rows.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    across = ends.select(F.col("last").alias("src_key"), F.lead("first").over(Window.orderBy("day")).alias("dst_key"))
    return clean_edges(within.unionByName(across))


def g_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer to the suppliers of what was ordered; supplier keys start at ``OFFSET``."""
    orders, items = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    return clean_edges(orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("src_key"), (F.col("l_suppkey") + OFFSET).alias("dst_key")))


def g_web(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page to the targets of its links, string keys."""
    pages = read_table(spark, sf_dir, "pages", "page_id", "html")
    links = pages.select(F.concat(F.lit("page:"), "page_id").alias("src_key"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("dst_key"))
    return clean_edges(links)


def g_talk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turn of a conversation to the next one."""
    turns = read_table(spark, sf_dir, "conversations", "conv_id", "turn").select((F.col("conv_id") * 100 + F.col("turn")).alias("k"), "conv_id", "turn").distinct()
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("k").alias("dst_key"))
    return clean_edges(turns.withColumnRenamed("k", "src_key").join(after, ["conv_id", "turn"]).select("src_key", "dst_key"))


def g_lattice(spark: SparkSession, sf_dir: str, limit: int | None = None) -> DataFrame:
    """Triangulated square mesh over the part keys, both directions.  ``limit``: use keys below it."""
    parts = read_table(spark, sf_dir, "part", "p_partkey")
    if limit:
        parts = parts.filter(F.col("p_partkey") < limit)
    stats = parts.agg(F.count("*").alias("n"), F.max("p_partkey").alias("top")).first()
    side = math.isqrt(max(0, stats["n"] - 1)) + 1
    key, x = F.col("p_partkey"), F.col("p_partkey") % side
    steps = F.array(F.struct((key + 1).alias("to"), (x < side - 1).alias("ok")), F.struct((key + side).alias("to"), F.lit(True).alias("ok")), F.struct((key + side + 1).alias("to"), (x < side - 1).alias("ok")))
    half = parts.select(key.alias("src_key"), F.explode(steps).alias("s")).filter(F.col("s.ok") & (F.col("s.to") <= F.lit(stats["top"]))).select("src_key", F.col("s.to").alias("dst_key"))
    return clean_edges(symmetrize(half))


def g_knn(spark: SparkSession, sf_dir: str, k: int = 6, block_bytes: int = 16 << 20) -> DataFrame:
    """Each vector's ``k`` nearest by cosine (ties: smaller id), symmetrised.

    Equal vectors are compared once: of each group the ``k + 1`` smallest ids can be
    neighbours, and all its members get the group's list without themselves.  Tasks own
    queries; the vectors they are compared with come in broadcasts of ``block_bytes``, so
    (vectors * k * broadcasts) rows are ranked.  A product in single precision leaves the
    few that may be among the nearest, and those are ranked by cosines in double precision,
    summed in the same order for every pair.
    """
    import numpy as np
    import pandas as pd

    rows = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").filter("vec_id IS NOT NULL AND embedding IS NOT NULL")
    same = Window.partitionBy("embedding").orderBy("vec_id")
    folder = work_dir(spark, "knn")
    ranked = write_table(rows.select("vec_id", "embedding", F.min("vec_id").over(Window.partitionBy("embedding")).alias("rep"), F.row_number().over(same).alias("nth")), f"{folder}/ranked")
    listed = ranked.filter(F.col("nth") <= k + 1).groupBy("rep").agg(F.min_by("embedding", "nth").alias("embedding"), F.array_sort(F.collect_list("vec_id")).alias("ids"))
    listed = write_table(listed, f"{folder}/listed")
    size = listed.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size("embedding")), F.lit(1)).alias("dim")).first()
    blocks = max(1, -(-size["n"] * size["dim"] * 4 // block_bytes))
    block_of = F.pmod(F.xxhash64("rep"), F.lit(blocks))
    queries = listed.select("rep", "embedding").repartition(max(spark.sparkContext.defaultParallelism, -(-size["n"] // 20_000)), "rep")
    found = None
    for b in range(blocks):
        block = listed.filter(block_of == b).select("embedding", "ids").toPandas()  # about block_bytes
        matrix = np.array(block["embedding"].tolist(), np.float32).reshape(len(block), size["dim"])
        shared = spark.sparkContext.broadcast((matrix, np.array([len(i) for i in block["ids"]], np.int64), np.concatenate([np.asarray(i, np.int64) for i in block["ids"]] or [np.zeros(0, np.int64)])))

        def nearest(batches, shared=shared):
            x, counts, ids = shared.value
            first, x_len = np.cumsum(counts) - counts, _lengths(x)
            unit = (x / x_len[:, None]).astype(np.float32)
            margin = np.float32(1e-6 + 4e-7 * x.shape[1])
            for frame in batches:
                for lo in range(0, len(frame), 256):
                    part = frame.iloc[lo : lo + 256]
                    q = np.array(part["embedding"].tolist(), np.float32).reshape(len(part), -1)
                    q_len = _lengths(q)
                    who, other = _candidates((q / q_len[:, None]).astype(np.float32), unit, k + 1, margin)
                    cos = np.empty(len(who))
                    for c in range(0, len(who), 1 << 16):
                        w, o = who[c : c + (1 << 16)], other[c : c + (1 << 16)]
                        cos[c : c + (1 << 16)] = np.add.reduce(q[w].astype(np.float64) * x[o], axis=1) / (q_len[w] * x_len[o])
                    many = counts[other]
                    within = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                    out = pd.DataFrame({"rep": part["rep"].to_numpy()[np.repeat(who, many)], "dst_key": ids[np.repeat(first[other], many) + within], "cos": np.repeat(cos, many)})
                    out = out.sort_values(["rep", "cos", "dst_key"], ascending=[True, False, True])
                    yield out[out.groupby("rep").cumcount() <= k]

        part = queries.mapInPandas(nearest, "rep long, dst_key long, cos double")
        found = part if found is None else found.unionByName(part)
    lists = found.withColumn("r", F.row_number().over(Window.partitionBy("rep").orderBy(F.desc("cos"), "dst_key"))).filter(F.col("r") <= k + 1)
    others = ranked.select(F.col("vec_id").alias("src_key"), "rep").join(lists, "rep").filter("src_key <> dst_key")
    best = others.withColumn("r", F.row_number().over(Window.partitionBy("src_key").orderBy(F.desc("cos"), "dst_key"))).filter(F.col("r") <= k)
    return clean_edges(symmetrize(best.select("src_key", "dst_key")))


def _lengths(x):
    """Length of each row in double precision; never nought."""
    import numpy as np

    wide = x.astype(np.float64)
    return np.maximum(np.sqrt((wide * wide).sum(axis=1)), 1e-300)


def _candidates(q, x, k: int, margin):
    """(row of ``q``, row of ``x``) of every pair that may be among a query's ``k`` nearest.

    The ``k``-th greatest of the maxima of runs of rows is no greater than the ``k``-th
    greatest product, so what lies under it by more than ``margin``, the error of single
    precision, is out.
    """
    import numpy as np

    cos = np.nan_to_num(q @ x.T, nan=-2.0)
    n, run = cos.shape[1], 64
    if n < 2 * k * run:
        run = 1
    whole = n // run * run
    tops = cos[:, :whole].reshape(len(cos), -1, run).max(axis=2) if run > 1 else cos
    if tops.shape[1] <= k:
        return np.nonzero(np.ones(cos.shape, bool))
    least = np.partition(tops, tops.shape[1] - k, axis=1)[:, tops.shape[1] - k]
    return np.nonzero(cos >= (least - margin)[:, None])


def g_userk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User to the k of the event's properties; k starts at ``OFFSET``."""
    rows = read_table(spark, sf_dir, "events", "user_id", "props")
    return clean_edges(rows.select(F.col("user_id").alias("src_key"), (F.from_json("props", "k long")["k"] + OFFSET).alias("dst_key")))


BUILDERS = {f.__name__: f for f in (g_copart, g_custday, g_custhigh, g_custurg, g_user, g_trade, g_web, g_talk, g_lattice, g_knn, g_userk)}
