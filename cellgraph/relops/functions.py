"""Scalar functions and user-defined functions, one query each."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..graph_queries import BANDS, grid_of, with_rows, with_rows_sql
from ..oracle import sqlgen
from ..planner import schedule
from ..registry import query
from ..sources.tables import read_table


@query("op_str_url", "SELECT page_id, lower(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)) AS host, length(url) AS n, split_part(url, '/', 4) AS first_part FROM pages")
def str_url(spark, sf_dir):
    url = F.col("url")
    return read_table(spark, sf_dir, "pages", "page_id", "url").select("page_id", F.lower(F.parse_url(url, F.lit("HOST"))).alias("host"), F.length(url).cast("long").alias("n"), F.split_part(url, F.lit("/"), F.lit(4)).alias("first_part"))


@query("op_str_anchor", "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links, lower(substr(trim(regexp_replace(html, '<[^>]*>', ' ', 'g')), 1, 20)) AS head FROM pages")
def str_anchor(spark, sf_dir):
    html = F.col("html")
    return read_table(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.size(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), 1)).cast("long").alias("links"), F.lower(F.substring(F.trim(F.regexp_replace(html, "<[^>]*>", " ")), 1, 20)).alias("head"))


@query("op_date_trunc", "SELECT date_trunc('month', o_orderdate)::VARCHAR[1:7] AS month, count(*) AS n FROM orders GROUP BY 1".replace("::VARCHAR[1:7]", "::DATE::VARCHAR"))
def date_trunc(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month")).agg(F.count("*").alias("n"))


@query("op_date_diff", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofweek(o_orderdate) + 1 AS dow, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def date_diff(spark, sf_dir):
    d = F.col("o_orderdate")
    return read_table(spark, sf_dir, "orders").select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.dayofweek(d).cast("long").alias("dow"), F.datediff(F.to_date(d), F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("op_math_band", "SELECT p_partkey, (p_partkey) // 7 + 1 AS band, p_partkey % 7 AS place, round(sqrt(p_size), 6) AS root, round(ln(p_retailprice), 6) AS lg, least(p_size, 10) AS low, greatest(p_size, 40) AS high FROM part")
def math_band(spark, sf_dir):
    k, s = F.col("p_partkey"), F.col("p_size")
    return read_table(spark, sf_dir, "part").select("p_partkey", (F.expr("p_partkey div 7") + 1).alias("band"), F.pmod(k, F.lit(7).cast("long")).alias("place"), F.round(F.sqrt(s), 6).alias("root"), F.round(F.log("p_retailprice"), 6).alias("lg"), F.least(s, F.lit(10)).alias("low"), F.greatest(s, F.lit(40)).alias("high"))


@query("op_array_cosine", "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cos FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id = 0) b")
def array_cosine(spark, sf_dir):
    """Cosine to one vector with array functions: a single row is broadcast."""
    rows = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").withColumn("e", F.col("embedding").cast("array<double>"))
    one = rows.filter("vec_id = 0").select(F.col("e").alias("o"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return rows.crossJoin(F.broadcast(one)).select("vec_id", F.round(dot(F.col("e"), F.col("o")) / F.sqrt(dot(F.col("e"), F.col("e")) * dot(F.col("o"), F.col("o"))), 6).alias("cos"))


@query("op_map_bandstats", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, count(*) FILTER (sb = 1) AS from_first, count(DISTINCT sb) AS sources, count(*) AS edges FROM e GROUP BY db")
def map_stats(spark, sf_dir):
    per = grid_of(spark, sf_dir, "custday").cells.groupBy("dst_band", "src_band").agg(F.count("*").alias("c"))
    maps = per.groupBy("dst_band").agg(F.map_from_entries(F.collect_list(F.struct("src_band", "c"))).alias("m"))
    return maps.select("dst_band", F.coalesce(F.element_at("m", F.lit(1)), F.lit(0)).alias("from_first"), F.size(F.map_keys("m")).cast("long").alias("sources"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x).alias("edges"))


@query("op_json_k", "SELECT event_id, CAST(props->>'k' AS BIGINT) AS k FROM events")
def json_k(spark, sf_dir):
    return read_table(spark, sf_dir, "events", "event_id", "props").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("op_decimal_fixed", "SELECT o_custkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS VARCHAR) AS total FROM orders GROUP BY o_custkey")
def decimal_fixed(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("string").alias("total"))


@query("op_bitmap_active", sqlgen.base("custurg", BANDS) + "\nSELECT db AS dst_band, CAST(bit_or(1 << (sb - 1)) AS INTEGER) AS bitmap, CAST(count(DISTINCT sb) AS INTEGER) AS bits FROM e GROUP BY db")
def bitmap_active(spark, sf_dir):
    cells = grid_of(spark, sf_dir, "custurg").cells
    return cells.groupBy("dst_band").agg(F.bit_or(F.expr("shiftleft(1, src_band - 1)")).alias("bitmap")).select("dst_band", "bitmap", F.bit_count("bitmap").cast("int").alias("bits"))


# ------------------------------------------------------------------------------- UDFs


@query("op_udf_scalar", "SELECT c_custkey, round(CASE WHEN c_acctbal > 0 THEN ln(1 + c_acctbal) ELSE 0 END, 6) AS damped FROM customer")
def udf_scalar(spark, sf_dir):
    @F.pandas_udf("double")
    def damped(x: pd.Series) -> pd.Series:
        return np.log1p(x.clip(lower=0))

    return read_table(spark, sf_dir, "customer", "c_custkey", "c_acctbal").select("c_custkey", F.round(damped("c_acctbal"), 6).alias("damped"))


@query("op_udf_grouped_cell", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, count(*) AS edges, max(dst - src) AS reach FROM e GROUP BY ALL")
def udf_grouped(spark, sf_dir):
    """A user's update of whole cells; cells are bounded by the number of bands."""

    def summary(frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"dst_band": frame.dst_band[:1], "src_band": frame.src_band[:1], "edges": [len(frame)], "reach": [int((frame.dst - frame.src).max())]})

    return grid_of(spark, sf_dir, "custday").cells.groupBy("dst_band", "src_band").applyInPandas(summary, "dst_band int, src_band int, edges long, reach long")


@query("op_udaf_fold", sqlgen.base("custurg", BANDS) + "\nSELECT dst, CAST(bit_xor(src) AS BIGINT) AS folded FROM e GROUP BY dst")
def udaf_fold(spark, sf_dir):
    """A user's own commutative and associative fold."""

    @F.pandas_udf("long")
    def xor(x: pd.Series) -> int:
        return int(np.bitwise_xor.reduce(x.to_numpy()))

    return grid_of(spark, sf_dir, "custurg").cells.groupBy("dst").agg(xor("src").alias("folded"))


@query("op_udtf_schedule", with_rows_sql("SELECT CAST(row_number() OVER (ORDER BY phase, a, b) AS INTEGER) AS step, region, src_band, dst_band FROM (SELECT 1 AS phase, 1 AS a, 1 AS b, 'RR' AS region, 1 AS src_band, 1 AS dst_band UNION ALL SELECT 2, 2, CAST(j AS INTEGER), CASE WHEN j <= 1 THEN 'DR' ELSE 'DD' END, 2, CAST(j AS INTEGER) FROM range(1, 3) y(j) UNION ALL SELECT 3, 2, CAST(i AS INTEGER), CASE WHEN i <= 1 THEN 'RD' ELSE 'HUB' END, CAST(i AS INTEGER), 2 FROM range(1, 3) x(i))", 2))
def udtf_schedule(spark, sf_dir):
    """The visiting order as a table function that SQL can call, beside the rows each step reads."""

    @F.udtf(returnType="step int, region string, src_band int, dst_band int")
    class CellPlan:
        def eval(self, bands: int, resident: int):
            yield from schedule("hybrid", bands, resident)

    spark.udtf.register("cell_plan", CellPlan)
    return with_rows(spark.sql("SELECT * FROM cell_plan(2, 1)"), grid_of(spark, sf_dir, "custday", EngineConfig(bands=2, strategy="resident")))


@query("op_map_arrow", sqlgen.base("custday", BANDS) + "\nSELECT dst, src, dst - src AS gap FROM e")
def map_arrow(spark, sf_dir):
    def gaps(batches):
        for b in batches:
            dst, src = b.column(0).to_numpy(), b.column(1).to_numpy()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(dst - src)], names=["dst", "src", "gap"])

    return grid_of(spark, sf_dir, "custday").cells.select("dst", "src").mapInArrow(gaps, "dst long, src long, gap long")
