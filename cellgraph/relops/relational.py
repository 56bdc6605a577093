"""Scans, joins, aggregations, windows, sorts and set operations around the graph methods,
one query each on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph_queries import BANDS, grid_of
from ..oracle import sqlgen
from ..prep.grid import pack_cells, unpack_cells
from ..registry import query
from ..sources.builders import BUILDERS
from ..sources.tables import read_table

# ------------------------------------------------------------------- scans and filters


@query("op_scan_project", "SELECT l_orderkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def scan_project(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").select("l_orderkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("op_filter_range", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_discount < 0.05")
def filter_range(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").where(F.col("l_quantity").between(10, 20) & (F.col("l_discount") < 0.05)).select("l_orderkey", "l_linenumber", "l_quantity")


@query("op_filter_in", "SELECT p_partkey, p_size FROM part WHERE p_size IN (1, 5, 9)")
def filter_in(spark, sf_dir):
    return read_table(spark, sf_dir, "part", "p_partkey", "p_size").where(F.col("p_size").isin(1, 5, 9))


@query("op_filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%1%' AND regexp_matches(p_brand, '[0-9]')")
def filter_like(spark, sf_dir):
    return read_table(spark, sf_dir, "part").where(F.col("p_name").like("%1%") & F.col("p_brand").rlike("[0-9]")).select("p_partkey", "p_name")


@query("op_filter_nullsafe", "SELECT o_orderkey FROM orders WHERE nullif(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL")
def filter_nullsafe(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").where(F.nullif("o_orderstatus", F.lit("F")).eqNullSafe(F.lit(None))).select("o_orderkey")


# --------------------------------------------------------------------------------- joins


@query("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf_dir):
    """Nations and regions are fixed lists, so they may be broadcast."""
    nation, region = read_table(spark, sf_dir, "nation"), read_table(spark, sf_dir, "region")
    return read_table(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


_ORDER_ITEM = "SELECT o_orderkey, count(*) AS items, round(sum(l_quantity), 4) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey"


def _order_item(spark: SparkSession, sf_dir: str, hint: str) -> DataFrame:
    items = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity").hint(hint)
    return read_table(spark, sf_dir, "orders", "o_orderkey").join(items, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("items"), F.round(F.sum("l_quantity"), 4).alias("quantity"))


@query("op_join_sortmerge", _ORDER_ITEM)
def join_sortmerge(spark, sf_dir):
    return _order_item(spark, sf_dir, "merge")


@query("op_join_shufflehash", _ORDER_ITEM)
def join_shufflehash(spark, sf_dir):
    return _order_item(spark, sf_dir, "shuffle_hash")


@query("op_join_cross_bands", sqlgen.base("custday", BANDS) + "\nSELECT x.band AS src_band, y.band AS dst_band, (SELECT count(*) FROM e WHERE sb = x.band AND db = y.band) AS edges FROM (SELECT DISTINCT band FROM v) x, (SELECT DISTINCT band FROM v) y")
def join_cross(spark, sf_dir):
    """The P x P cells, empty ones too: a product of two lists of the P bands that a graph's
    vertices have, never of data."""
    grid = grid_of(spark, sf_dir, "custday")
    bands = grid.vertices.select("band").distinct()
    cells = bands.withColumnRenamed("band", "src_band").crossJoin(bands.withColumnRenamed("band", "dst_band"))
    edges = grid.cells.groupBy("src_band", "dst_band").agg(F.count("*").alias("edges"))
    return cells.join(edges, ["src_band", "dst_band"], "left").select("src_band", "dst_band", F.coalesce("edges", F.lit(0)).alias("edges"))


@query("op_join_theta", "SELECT a.p_partkey AS small, b.p_partkey AS large FROM part a JOIN part b ON a.p_size < b.p_size AND a.p_size <= 2 AND b.p_size >= 49 AND a.p_brand = b.p_brand")
def join_theta(spark, sf_dir):
    part = read_table(spark, sf_dir, "part", "p_partkey", "p_size", "p_brand")
    a, b = part.filter("p_size <= 2").alias("a"), part.filter("p_size >= 49").alias("b")
    return a.join(b, (F.col("a.p_brand") == F.col("b.p_brand")) & (F.col("a.p_size") < F.col("b.p_size"))).select(F.col("a.p_partkey").alias("small"), F.col("b.p_partkey").alias("large"))


@query("op_join_range_band", sqlgen.base("custday", BANDS) + "\nSELECT vid, band FROM v")
def join_range(spark, sf_dir):
    """Ids to bands by band borders; P rows of borders are a bounded broadcast."""
    grid = grid_of(spark, sf_dir, "custday")
    w = grid.spec.width
    borders = spark.createDataFrame([(b, (b - 1) * w + 1, b * w) for b in range(1, BANDS + 1)], "band int, lo long, hi long")
    return grid.vids.table.select("vid").join(F.broadcast(borders), F.col("vid").between(F.col("lo"), F.col("hi"))).select("vid", "band")


@query("op_join_interval", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval(spark, sf_dir):
    """Events of a user within an hour, bucketed by hour so that the join is an equi-join."""
    rows = read_table(spark, sf_dir, "events", "event_id", "user_id", "ts").withColumn("hour", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    a = rows.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(F.col("hour"), F.col("hour") + 1)).alias("hour"))
    b = rows.select(F.col("event_id").alias("second"), "user_id", F.col("ts").alias("t2"), "hour")
    return a.join(b, ["user_id", "hour"]).filter((F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr("INTERVAL 1 HOUR"))).select("first", "second")


@query("op_join_asof", """SELECT v.event_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.event_type = 'purchase' AND p.user_id = v.user_id AND (p.ts, p.event_id) < (v.ts, v.event_id)) AS purchase_id FROM events v WHERE v.event_type = 'view'""".replace("max_by(p.event_id, (p.ts, p.event_id))", "arg_max(p.event_id, p.ts)"))
def join_asof(spark, sf_dir):
    """The last purchase before each view of a user: one window, no join."""
    rows = read_table(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type").filter(F.col("event_type").isin("view", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return rows.withColumn("purchase_id", last).filter("event_type = 'view'").select("event_id", "purchase_id")


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def join_semi(spark, sf_dir):
    return read_table(spark, sf_dir, "customer", "c_custkey").join(read_table(spark, sf_dir, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def join_anti(spark, sf_dir):
    urgent = read_table(spark, sf_dir, "orders", "o_custkey", "o_orderpriority").filter("o_orderpriority = '1-URGENT'")
    return read_table(spark, sf_dir, "customer", "c_custkey").join(urgent, F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def join_left(spark, sf_dir):
    orders = read_table(spark, sf_dir, "orders", "o_custkey", "o_orderkey")
    return read_table(spark, sf_dir, "customer", "c_custkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("op_join_full", sqlgen.base("custurg", BANDS) + "\nSELECT coalesce(o.k, i.k) AS vid, coalesce(o.c, 0) AS out_deg, coalesce(i.c, 0) AS in_deg FROM (SELECT src AS k, count(*) AS c FROM e GROUP BY src) o FULL JOIN (SELECT dst AS k, count(*) AS c FROM e GROUP BY dst) i ON o.k = i.k")
def join_full(spark, sf_dir):
    cells = grid_of(spark, sf_dir, "custurg").cells
    out, into = cells.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("o")), cells.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("i"))
    return out.join(into, "vid", "full").select("vid", F.coalesce("o", F.lit(0)).alias("out_deg"), F.coalesce("i", F.lit(0)).alias("in_deg"))


@query("op_join_self_2hop", sqlgen.base("custurg", BANDS) + "\nSELECT DISTINCT a.src, b.dst FROM e a JOIN e b ON a.dst = b.src WHERE a.src <> b.dst")
def join_self(spark, sf_dir):
    e = grid_of(spark, sf_dir, "custurg").cells.select("src", "dst")
    return e.join(e.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").filter("src <> far").select("src", F.col("far").alias("dst")).distinct()


# -------------------------------------------------------------------------- aggregations


@query("op_agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 8) AS discount FROM lineitem GROUP BY ALL")
def agg_hash(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 8).alias("discount"))


@query("op_agg_partial_final", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey")
def agg_two_level(spark, sf_dir):
    """Salted partial counts, then their sum: what a hot destination needs."""
    salted = read_table(spark, sf_dir, "lineitem", "l_suppkey", "l_orderkey").groupBy("l_suppkey", F.pmod("l_orderkey", F.lit(8)).alias("salt")).agg(F.count("*").alias("part"))
    return salted.groupBy("l_suppkey").agg(F.sum("part").alias("n"))


@query("op_agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderpriority")
def agg_distinct(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("customers"))


@query("op_agg_approx_distinct")
def agg_approx(spark, sf_dir):
    """Sketched distinct count; the tests bound its error."""
    return read_table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("op_agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("op_agg_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, sf_dir):
    joined = read_table(spark, sf_dir, "customer").join(F.broadcast(read_table(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read_table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("op_agg_grouping_sets", "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf_dir):
    read_table(spark, sf_dir, "lineitem").createOrReplaceTempView("cellgraph_lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS g, count(*) AS n FROM cellgraph_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@query("op_agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_orderpriority")
def agg_pivot(spark, sf_dir):
    t = read_table(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count()
    return t.select("o_orderpriority", *[F.coalesce(F.col(c.upper()), F.lit(0)).alias(c) for c in "fop"])


@query("op_agg_stats", "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, round(quantile_cont(l_quantity, 0.5), 6) AS median FROM lineitem GROUP BY l_returnflag")
def agg_stats(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.percentile("l_quantity", 0.5), 6).alias("median"))


@query("op_agg_minmax_by", "SELECT o_custkey, max(o_orderkey) AS last_order, arg_max(o_orderpriority, o_orderkey) AS last_priority, arg_min(o_orderpriority, o_orderkey) AS first_priority FROM orders GROUP BY o_custkey")
def agg_by(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max("o_orderkey").alias("last_order"), F.max_by("o_orderpriority", "o_orderkey").alias("last_priority"), F.min_by("o_orderpriority", "o_orderkey").alias("first_priority"))


@query("op_agg_bool", "SELECT o_custkey, bool_or(o_orderpriority = '1-URGENT') AS any_urgent, bool_and(o_totalprice > 1000) AS all_large, count_if(o_orderstatus = 'F') AS filled FROM orders GROUP BY o_custkey".replace("count_if(o_orderstatus = 'F')", "count(*) FILTER (o_orderstatus = 'F')"))
def agg_bool(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.bool_or(F.col("o_orderpriority") == "1-URGENT").alias("any_urgent"), F.bool_and(F.col("o_totalprice") > 1000).alias("all_large"), F.count_if(F.col("o_orderstatus") == "F").alias("filled"))


@query("op_agg_collect", "SELECT o_custkey, array_to_string(list_sort(list(DISTINCT o_orderpriority)), ',') AS priorities FROM orders GROUP BY o_custkey")
def agg_collect(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.array_join(F.sort_array(F.collect_set("o_orderpriority")), ",").alias("priorities"))


# ------------------------------------------------------------------------------- windows


@query("op_win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey)")
def win_rank(spark, sf_dir):
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderpriority", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return read_table(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"))


@query("op_win_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS quarter FROM customer")
def win_ntile(spark, sf_dir):
    return read_table(spark, sf_dir, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias("quarter"))


@query("op_win_lead_lag", "SELECT event_id, lead(event_id) OVER w AS nxt, lag(event_id) OVER w AS prv FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lead_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read_table(spark, sf_dir, "events").select("event_id", F.lead("event_id").over(w).alias("nxt"), F.lag("event_id").over(w).alias("prv"))


@query("op_win_running", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS total FROM orders")
def win_running(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return read_table(spark, sf_dir, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("total"))


@query("op_win_range7d", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS week FROM orders")
def win_range(spark, sf_dir):
    rows = read_table(spark, sf_dir, "orders").withColumn("day", F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01").cast("date")))
    return rows.select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-6, 0)).alias("week"))


@query("op_win_first_last", "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type, nth_value(event_type, 2) OVER w AS second_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read_table(spark, sf_dir, "events").select("user_id", F.first("event_type").over(w).alias("first_type"), F.last("event_type").over(w).alias("last_type"), F.nth_value("event_type", 2).over(w).alias("second_type")).distinct()


# ------------------------------------------------------------------- sorts, limits, sets


@query("op_sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey")
def sort_global(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("op_topk_per_band", sqlgen.base("custday", BANDS) + "\nSELECT band, vid, in_deg FROM (SELECT *, row_number() OVER (PARTITION BY band ORDER BY in_deg DESC, vid) AS r FROM v) WHERE r <= 5")
def topk_per_band(spark, sf_dir):
    w = Window.partitionBy("band").orderBy(F.desc("in_deg"), "vid")
    return grid_of(spark, sf_dir, "custday").vertices.withColumn("r", F.row_number().over(w)).filter("r <= 5").select("band", "vid", "in_deg")


@query("op_limit", "SELECT count(*) AS n FROM (SELECT * FROM lineitem LIMIT 100)")
def limited(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", "l_orderkey").limit(100).agg(F.count("*").alias("n"))


@query("op_union", "SELECT o_custkey AS k FROM orders UNION SELECT c_custkey FROM customer")
def union(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", "o_custkey").union(read_table(spark, sf_dir, "customer", "c_custkey")).distinct().withColumnRenamed("o_custkey", "k")


@query("op_intersect", f"SELECT * FROM ({sqlgen.GRAPHS['custhigh']}) INTERSECT SELECT * FROM ({sqlgen.GRAPHS['custday']})")
def intersect(spark, sf_dir):
    return BUILDERS["g_custhigh"](spark, sf_dir).intersect(BUILDERS["g_custday"](spark, sf_dir))


@query("op_except", f"SELECT * FROM ({sqlgen.GRAPHS['custhigh']}) EXCEPT SELECT * FROM ({sqlgen.GRAPHS['custday']})")
def exclude(spark, sf_dir):
    return BUILDERS["g_custhigh"](spark, sf_dir).subtract(BUILDERS["g_custday"](spark, sf_dir))


@query("op_reciprocal_edges", sqlgen.base("custday", BANDS) + "\nSELECT a.src, a.dst FROM e a JOIN e b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst")
def reciprocal(spark, sf_dir):
    e = grid_of(spark, sf_dir, "custday").cells.select("src", "dst")
    return e.intersect(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).filter("src < dst")


@query("op_explode_unpack", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, dst, src FROM e")
def explode_unpack(spark, sf_dir):
    return unpack_cells(pack_cells(grid_of(spark, sf_dir, "custday"), chunk=3))


@query("op_posexplode", "SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY event_type) - 1 AS INTEGER) AS pos, event_type FROM (SELECT DISTINCT user_id, event_type FROM events)")
def posexplode(spark, sf_dir):
    sets = read_table(spark, sf_dir, "events").groupBy("user_id").agg(F.sort_array(F.collect_set("event_type")).alias("types"))
    return sets.select("user_id", F.posexplode("types").alias("pos", "event_type"))


@query("op_unpivot", sqlgen.base("custurg", BANDS) + "\nSELECT vid, 'out_deg' AS kind, out_deg AS degree FROM v UNION ALL SELECT vid, 'in_deg', in_deg FROM v")
def unpivot(spark, sf_dir):
    return grid_of(spark, sf_dir, "custurg").vertices.select("vid", "out_deg", "in_deg").unpivot(["vid"], ["out_deg", "in_deg"], "kind", "degree")
