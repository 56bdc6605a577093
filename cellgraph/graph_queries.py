"""Queries of the graph methods: builders, preprocessing, programs under every strategy,
baselines, measures and schedules, each with DuckDB SQL where SQL can say it."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algorithms import scc as scc_module
from .algorithms import traversal
from .algorithms.pagerank import pagerank, pagerank_delta, pagerank_fixed_point
from .config import EngineConfig
from .cost import Sizes, io_model, resident_bands, total_io
from .driver import run
from .oracle import sqlgen
from .planner import choose_strategy, schedule
from .prep.densify import degrees, densify_ids
from .prep.grid import EdgeGrid, avg_d, build_grid, grid_stats, pack_cells
from .registry import query
from .sources.builders import BUILDERS

#: Bands in queries: small enough that every cell of the test graphs has edges.
BANDS = 4
#: Constants of the largest graph the data-transfer figure is drawn for.
WEB_SIZES = Sizes(7.20e8, 6.63e9, 8, 4, 4, 15)


def config_for(strategy: str, **more) -> EngineConfig:
    return EngineConfig(bands=BANDS, strategy=strategy, **more)


def grid_of(spark: SparkSession, sf_dir: str, graph: str, config: EngineConfig | None = None) -> EdgeGrid:
    return build_grid(BUILDERS[f"g_{graph}"](spark, sf_dir), config or config_for("resident"))


# ------------------------------------------------------------------ builders and layout

for _g in sqlgen.GRAPHS:
    query(f"g_{_g}", sqlgen.GRAPHS[_g])(BUILDERS[f"g_{_g}"])

for _g in ("custday", "web"):

    @query(f"vid_map_{_g}", sqlgen.base(_g) + "\nSELECT vid, raw_key, out_deg, in_deg FROM v")
    def _vid_map(spark, sf_dir, g=_g):
        return densify_ids(BUILDERS[f"g_{g}"](spark, sf_dir)).table

    @query(f"degrees_{_g}", sqlgen.base(_g) + "\nSELECT raw_key, out_deg, in_deg FROM v")
    def _degrees(spark, sf_dir, g=_g):
        return degrees(BUILDERS[f"g_{g}"](spark, sf_dir))


_DATASETS = ("copart", "custday", "custhigh", "custurg", "user", "trade", "talk", "lattice", "userk")


@query("dataset_table", "SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{g}' AS graph, (SELECT count(*) FROM (SELECT src_key FROM ({sqlgen.GRAPHS[g]}) UNION SELECT dst_key FROM ({sqlgen.GRAPHS[g]}))) AS n, (SELECT count(*) FROM ({sqlgen.GRAPHS[g]})) AS m" for g in _DATASETS) + ")")
def dataset_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices with an edge, and edges, of each graph."""
    out = None
    for g in _DATASETS:
        d = degrees(BUILDERS[f"g_{g}"](spark, sf_dir)).agg(F.count("*").alias("n"), F.coalesce(F.sum("out_deg"), F.lit(0)).alias("m")).select(F.lit(g).alias("graph"), "n", "m")
        out = d if out is None else out.unionByName(d)
    return out


@query("grid_cells_copart", sqlgen.base("copart", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, dst, src FROM e")
def grid_cells(spark, sf_dir):
    return grid_of(spark, sf_dir, "copart").cells


@query("grid_packed_custday", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, dst, array_to_string(list_sort(list(src)), ',') AS srcs FROM e GROUP BY ALL")
def grid_packed(spark, sf_dir):
    packed = pack_cells(grid_of(spark, sf_dir, "custday"))
    return packed.select("dst_band", "src_band", "dst", F.array_join(F.col("srcs").cast("array<string>"), ",").alias("srcs"))


for _g in ("custday", "trade", "lattice"):

    @query(f"grid_stats_{_g}", sqlgen.base(_g, BANDS) + "\nSELECT db AS dst_band, sb AS src_band, count(*) AS edges, count(DISTINCT dst) AS dsts, round(count(*) / count(DISTINCT dst), 8) AS d FROM e GROUP BY ALL")
    def _stats(spark, sf_dir, g=_g):
        return grid_stats(grid_of(spark, sf_dir, g)).withColumn("d", F.round("d", 8))

    @query(f"avg_d_{_g}", sqlgen.base(_g, BANDS) + "\nSELECT round(count(*) / count(DISTINCT (sb, dst)), 8) AS d FROM e")
    def _avg_d(spark, sf_dir, g=_g):
        return spark.createDataFrame([(avg_d(grid_of(spark, sf_dir, g)),)], "d double").select(F.round("d", 8).alias("d"))


@query("grid_cube", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, count(*) AS edges FROM e GROUP BY CUBE (db, sb)")
def grid_cube(spark, sf_dir):
    return grid_of(spark, sf_dir, "custday").cells.cube("dst_band", "src_band").agg(F.count("*").alias("edges"))


@query("grid_rollup", sqlgen.base("custday", BANDS) + "\nSELECT db AS dst_band, sb AS src_band, count(*) AS edges FROM e GROUP BY ROLLUP (db, sb)")
def grid_rollup(spark, sf_dir):
    return grid_of(spark, sf_dir, "custday").cells.rollup("dst_band", "src_band").agg(F.count("*").alias("edges"))


@query("grid_pivot", sqlgen.base("custday", BANDS) + "\nSELECT sb AS src_band, " + ", ".join(f"count(*) FILTER (db = {b}) AS to_{b}" for b in range(1, BANDS + 1)) + " FROM e GROUP BY sb")
def grid_pivot(spark, sf_dir):
    cells = grid_of(spark, sf_dir, "custday").cells
    return cells.groupBy("src_band").pivot("dst_band", list(range(1, BANDS + 1))).count().select("src_band", *[F.coalesce(F.col(str(b)), F.lit(0)).alias(f"to_{b}") for b in range(1, BANDS + 1)])


# --------------------------------------------------------------------------- PageRank

_PR = {
    "resident": ("resident", {}, None),
    "resident_merge_sync": ("resident", {"sync": "merge"}, None),
    "staged": ("staged", {"materialize_hubs": True}, None),
    "staged_fused": ("staged", {}, None),
    "hybrid_q0": ("hybrid", {}, 0),
    "hybrid_qhalf": ("hybrid", {}, BANDS // 2),
    "hybrid_qP": ("hybrid", {}, BANDS),
    "swap": ("swap", {}, None),
    "psw": ("psw", {"order": "src", "parallel": "coarse"}, None),
    "two_level": ("two_level", {"order": "none"}, None),
    "nbr_view": ("nbr_view", {}, None),
    "nbr_view_lazy": ("nbr_view_lazy", {}, None),
    "scatter": ("scatter", {}, None),
    "flat": ("flat", {}, None),
    "plain": ("plain", {}, None),
    "src_coarse": ("resident", {"order": "src", "parallel": "coarse"}, None),
    "src_fine": ("resident", {"order": "src"}, None),
    "dst_coarse": ("resident", {"parallel": "coarse"}, None),
    "unsorted_fine": ("resident", {"order": "none"}, None),
    "auto": ("auto", {}, None),
    "resident_cached": ("resident", {"cached_bands": BANDS}, None),
    "resident_part_cached": ("resident", {"cached_bands": BANDS // 2}, None),
    "resident_row_order": ("resident", {"cell_order": "row"}, None),
    "resident_col_order": ("resident", {"cell_order": "col"}, None),
    "resident_large_state": ("resident", {"broadcast_limit_bytes": 1}, None),
    "hybrid_heavy": ("hybrid", {"resident_choice": "heavy"}, BANDS // 2),
    "hybrid_hubs": ("hybrid", {"materialize_hubs": True}, BANDS // 2),
    "swap_kept_bands": ("swap", {"cached_bands": BANDS // 2}, None),
}


def ranks(result) -> DataFrame:
    return result.values("rank").select("vid", F.round("rank", 8).alias("rank"))


for _name, (_strategy, _more, _q) in _PR.items():

    @query(f"pagerank_{_name}_custday", sqlgen.pagerank("custday"))
    def _pagerank(spark, sf_dir, strategy=_strategy, more=_more, q=_q):
        config = config_for(strategy, **more)
        return ranks(pagerank(grid_of(spark, sf_dir, "custday", config), 10, config=config, resident=q))


for _g, _rule in (("web", "drop"), ("web", "spread"), ("trade", "drop"), ("custhigh", "drop"), ("custhigh", "spread"), ("lattice", "drop")):

    @query(f"pagerank_{_g}_{_rule}", sqlgen.pagerank(_g, dangling=_rule))
    def _rules(spark, sf_dir, g=_g, rule=_rule):
        config = config_for("hybrid")
        return ranks(pagerank(grid_of(spark, sf_dir, g, config), 10, dangling=rule, config=config))


for _strategy in ("resident", "staged", "hybrid", "nbr_view", "two_level", "scatter", "flat", "plain"):

    @query(f"pagerank1_{_strategy}_copart", sqlgen.pagerank("copart", 1))
    def _one_round(spark, sf_dir, strategy=_strategy):
        """One round on the densest graph: the limited and the best-resources experiments."""
        config = config_for(strategy)
        return ranks(pagerank(grid_of(spark, sf_dir, "copart", config), 1, config=config))


@query("pagerank_topk", sqlgen.pagerank("custday", tail="SELECT raw_key, round(rank, 8) AS rank FROM r{k} JOIN v USING (vid) ORDER BY r{k}.rank DESC, vid LIMIT 20"))
def pagerank_topk(spark, sf_dir):
    """The twenty highest ranks, by raw key."""
    config = config_for("hybrid")
    result = pagerank(grid_of(spark, sf_dir, "custday", config), 10, config=config)
    top = result.values("rank").orderBy(F.desc("rank"), "vid").limit(20)
    return top.join(result.grid.vids.table.select("vid", "raw_key"), "vid").select("raw_key", F.round("rank", 8).alias("rank"))


for _strategy in ("resident", "staged", "hybrid"):

    @query(f"pagerank_fixed_point_{_strategy}", sqlgen.pagerank_units("custday"))
    def _units(spark, sf_dir, strategy=_strategy):
        config = config_for(strategy)
        return pagerank_fixed_point(grid_of(spark, sf_dir, "custday", config), 10, config).values("rank")


@query("pagerank_tolerance_custday", sqlgen.pagerank("custday", 60, tail="SELECT vid, round(rank, 6) AS rank FROM r{k}"))
def pagerank_tolerance(spark, sf_dir):
    """Rounds until the summed change is under 1e-8; compared with sixty rounds."""
    config = config_for("resident")
    return pagerank(grid_of(spark, sf_dir, "custday", config), 60, config=config, tolerance=1e-8).values("rank").select("vid", F.round("rank", 6).alias("rank"))


@query("pagerank_delta_custday", sqlgen.pagerank("custday", 20, start="0.15::DOUBLE"))
def pagerank_residuals(spark, sf_dir):
    """Twenty rounds of the residual form: as many full rounds from the base rank."""
    result = pagerank_delta(grid_of(spark, sf_dir, "custday"), 0.0, config=config_for("resident"), rounds=20)
    return result.state.select("vid", F.round("attr.rank", 8).alias("rank"))


# ------------------------------------------------------------------------- traversals

for _strategy in ("resident", "staged", "hybrid", "swap", "psw"):

    @query(f"bfs_{_strategy}_custhigh", sqlgen.bfs("custhigh"))
    def _bfs(spark, sf_dir, strategy=_strategy):
        config = config_for(strategy)
        return traversal.bfs(grid_of(spark, sf_dir, "custhigh", config), 1, config).values("depth")


for _g in ("custday", "copart", "trade"):

    @query(f"bfs_max_depth_{_g}", sqlgen.bfs(_g, "SELECT max(depth) AS max_depth, count(*) AS reached FROM b", 60))
    def _depth(spark, sf_dir, g=_g):
        return traversal.bfs_max_depth(traversal.bfs(grid_of(spark, sf_dir, g), 1, config_for("resident")))


@query("bfs_noskip_custhigh", sqlgen.bfs("custhigh"))
def bfs_noskip(spark, sf_dir):
    """Without skipping cells of inactive bands: the same depths."""
    return traversal.bfs(grid_of(spark, sf_dir, "custhigh"), 1, config_for("resident", skip_inactive=False)).values("depth")


@query("bfs_parent_custday", sqlgen.bfs("custday", "SELECT y.vid, min(x.vid) AS parent FROM e JOIN b x ON x.vid = e.src JOIN b y ON y.vid = e.dst WHERE y.depth = x.depth + 1 GROUP BY y.vid"))
def bfs_parent(spark, sf_dir):
    grid = grid_of(spark, sf_dir, "custday")
    return traversal.bfs_parents(grid, traversal.bfs(grid, 1, config_for("resident")))


@query("bfs_recursive_sql_custday", sqlgen.bfs("custday", "SELECT vid, depth FROM b"))
def bfs_recursive(spark, sf_dir):
    grid = grid_of(spark, sf_dir, "custday")
    return traversal.bfs_sql(spark, grid.rows().select("src", "dst"), 1)


@query("bfs_hops3_copart", sqlgen.bfs("copart", "SELECT v.vid, CASE WHEN depth <= 2 THEN depth END AS depth FROM v LEFT JOIN b USING (vid)", 3))
def bfs_hops(spark, sf_dir):
    return traversal.hop_limited(grid_of(spark, sf_dir, "copart"), 1, 2, config_for("resident")).values("depth")


@query("active_bands_log_bfs", sqlgen.bfs("custhigh", "SELECT CAST(d.depth + 1 AS INTEGER) AS round, count(DISTINCT v.band) AS active_bands FROM b d JOIN v USING (vid) GROUP BY d.depth"))
def active_log(spark, sf_dir):
    """How many bands each round reads: those with a vertex found in the round before."""
    result = traversal.bfs(grid_of(spark, sf_dir, "custhigh"), 1, config_for("resident"), log=True)
    return spark.createDataFrame([(r["round"], r["active_bands"]) for r in result.log], "round int, active_bands long")


for _g in ("custurg", "web", "talk"):

    @query(f"wcc_{_g}", sqlgen.wcc(_g))
    def _wcc(spark, sf_dir, g=_g):
        return traversal.wcc(grid_of(spark, sf_dir, g), config_for("hybrid")).values()

    @query(f"wcc_hooking_{_g}", sqlgen.wcc(_g))
    def _hooking(spark, sf_dir, g=_g):
        return traversal.wcc_hooking(grid_of(spark, sf_dir, g))


@query("wcc_hooking_lattice", sqlgen.base("lattice") + "\nSELECT vid, CAST(1 AS BIGINT) AS attr FROM v")
def wcc_lattice(spark, sf_dir):
    """A mesh is one component; hooking needs a few rounds where propagation takes its width."""
    return traversal.wcc_hooking(grid_of(spark, sf_dir, "lattice"))


@query("wcc_sizes_custurg", sqlgen.wcc("custurg", "SELECT attr AS component, count(*) AS size FROM c GROUP BY attr"))
def wcc_sizes(spark, sf_dir):
    return traversal.wcc(grid_of(spark, sf_dir, "custurg"), config_for("resident")).state.groupBy(F.col("attr").alias("component")).agg(F.count("*").alias("size"))


for _g in ("custurg", "custhigh", "trade"):

    @query(f"scc_{_g}", sqlgen.scc(_g))
    def _scc(spark, sf_dir, g=_g):
        return scc_module.scc(grid_of(spark, sf_dir, g), config_for("resident"))


@query("scc_sizes_custday", sqlgen.scc("custday", "SELECT attr AS component, count(*) AS size FROM c GROUP BY attr"))
def scc_sizes(spark, sf_dir):
    return scc_module.scc(grid_of(spark, sf_dir, "custday"), config_for("resident")).groupBy(F.col("attr").alias("component")).agg(F.count("*").alias("size"))


@query("program_in_degree_trade", sqlgen.base("trade") + "\nSELECT vid, in_deg AS attr FROM v")
def in_degree(spark, sf_dir):
    return run(grid_of(spark, sf_dir, "trade"), traversal.in_degree_program(), config_for("staged"), rounds=1).values()


@query("program_max_neighbour_custday", sqlgen.base("custday") + "\nSELECT v.vid, greatest(v.vid, coalesce(max(e.src), 0)) AS attr FROM v LEFT JOIN e ON e.dst = v.vid GROUP BY v.vid")
def max_neighbour(spark, sf_dir):
    return run(grid_of(spark, sf_dir, "custday"), traversal.max_neighbour_program(), config_for("hybrid"), rounds=1).values()


_WEIGHT = "1 + (src * 7 + dst * 3) % 5"


@query("sssp_custhigh", f"""{sqlgen.base("custhigh", recursive=True)},
walk(vid, dist) AS (SELECT CAST(1 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT e.dst, dist + {_WEIGHT} FROM walk JOIN e ON e.src = walk.vid WHERE dist + {_WEIGHT} <= 120)
SELECT v.vid, CAST(min(dist) AS DOUBLE) AS dist FROM v LEFT JOIN walk USING (vid) GROUP BY v.vid""")
def sssp_query(spark, sf_dir):
    """Weights from 1 to 5 by the ends of an edge."""
    grid = grid_of(spark, sf_dir, "custhigh")
    return traversal.sssp(grid, grid.cells.select("src", "dst", F.expr(_WEIGHT).cast("double").alias("w")))


# --------------------------------------------------------------------- cost and schedule

_FRACTIONS = (0.05, 0.1, 0.25, 0.5, 0.75, 0.9, 1.0)
_VALUES = ", ".join(f"({f}::DOUBLE)" for f in _FRACTIONS)
#: f(f), the budget's shares, and c(s, e, u), the bytes of state, edges and hubs of a graph.
_MODEL = f"""{sqlgen.base("custday", BANDS)}, f(f) AS (VALUES {_VALUES}),
c AS (SELECT 8::DOUBLE * n AS s, 4::DOUBLE * m AS e, 12::DOUBLE * k AS u FROM nn, (SELECT count(*) AS m, count(DISTINCT (sb, dst)) AS k FROM e))"""


def measured_sizes(spark: SparkSession, sf_dir: str, graph: str, bands: int = BANDS) -> Sizes:
    """A graph's own n, m and d."""
    grid = grid_of(spark, sf_dir, graph, replace(config_for("resident"), bands=bands))
    return Sizes(grid.n, grid.m, d=avg_d(grid))


@query("io_model_table2", f"""{_MODEL}
SELECT f AS share, 'resident' AS strategy, CASE WHEN f >= 1 OR s = 0 THEN round(e, 3) END AS read_bytes, CASE WHEN f >= 1 OR s = 0 THEN 0::DOUBLE END AS write_bytes FROM f, c
UNION ALL SELECT f, 'staged', round(e + u + s, 3), round(u + s, 3) FROM f, c
UNION ALL SELECT f, 'hybrid', round(e + (1 - f) * (1 - f) * u + (1 - f) * s, 3), round((1 - f) * (1 - f) * u + (1 - f) * s, 3) FROM f, c
UNION ALL SELECT f, 'swap', round(e + s / f + s, 3), round(s, 3) FROM f, c""")
def io_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Read and write bytes a round under each strategy, by the share of memory for two copies,
    of the customer-succession graph."""
    rows, s = [], measured_sizes(spark, sf_dir, "custday")
    for f in _FRACTIONS:
        for name in ("resident", "staged", "hybrid", "swap"):
            cost = io_model(name, s, 2 * s.state * f, table_form=name == "swap")
            rows.append((f, name, *((None, None) if cost is None else tuple(float(x) for x in cost))))
    return spark.createDataFrame(rows, "share double, strategy string, read_bytes double, write_bytes double").withColumns({c: F.round(c, 3) for c in ("read_bytes", "write_bytes")})


@query("io_ratio_fig6", f"""{_MODEL}, t AS (
  SELECT f, e + 2 * ((1 - f) * (1 - f) * u + (1 - f) * s) AS h, e + s / f + s AS w FROM f, c)
SELECT f AS share, round(h / 1e9, 12) AS hybrid_gb, round(w / 1e9, 12) AS swap_gb, CASE WHEN w > 0 THEN round(h / w, 4) END AS ratio FROM t""")
def io_ratio_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total bytes of HYBRID against SWAP over the memory budget, on the customer-succession graph."""
    s = measured_sizes(spark, sf_dir, "custday")
    rows = [(f, total_io("hybrid", s, 2 * s.state * f), total_io("swap", s, 2 * s.state * f)) for f in _FRACTIONS]
    return spark.createDataFrame(rows, "share double, h double, w double").select("share", F.round(F.col("h") / 1e9, 12).alias("hybrid_gb"), F.round(F.col("w") / 1e9, 12).alias("swap_gb"), F.round(F.try_divide("h", "w"), 4).alias("ratio"))


_MEASURED = ("custday", "copart", "trade")


def _measured_sql(g: str) -> str:
    return f"SELECT * FROM ({sqlgen.base(g, BANDS)} SELECT '{g}' AS graph, f AS share, round(4 * m + (1 - f) * (1 - f) * 12 * k + (1 - f) * 8 * n, 3) AS hybrid_read, round(4 * m + 8 * n * 8 * n * 2 / (16 * n * f), 3) AS swap_read FROM (SELECT count(*) AS m, count(DISTINCT (sb, dst)) AS k FROM e), nn, (VALUES (0.25::DOUBLE), (0.5::DOUBLE)) x(f))"


@query("io_model_measured", " UNION ALL ".join(_measured_sql(g) for g in _MEASURED))
def io_measured(spark, sf_dir):
    """The model with each graph's own n, m and d."""
    rows = []
    for g in _MEASURED:
        grid = grid_of(spark, sf_dir, g)
        s = Sizes(grid.n, grid.m, d=avg_d(grid))
        for f in (0.25, 0.5):
            budget = 2 * s.state * f
            rows.append((g, f, float(io_model("hybrid", s, budget)[0]), float(io_model("swap", s, budget)[0])))
    return spark.createDataFrame(rows, "graph string, share double, hybrid_read double, swap_read double").withColumns({c: F.round(c, 3) for c in ("hybrid_read", "swap_read")})


_CHOICES = (0.05, 0.25, 0.5, 0.9, 1.0, 4.0)


def _choice_sql(g: str) -> str:
    """The least of HYBRID's and SWAP's bytes; HYBRID never moves more than STAGED."""
    return f"""SELECT * FROM ({sqlgen.base(g, 24)}, c AS (SELECT 8::DOUBLE * n AS s, 4::DOUBLE * m AS e, 12::DOUBLE * k AS u, CASE WHEN k > 0 THEN m / k ELSE 1 END AS d FROM nn, (SELECT count(*) AS m, count(DISTINCT (sb, dst)) AS k FROM e)),
t AS (SELECT f, d, q, e + 2 * ((1 - q / 24) * (1 - q / 24) * u + (1 - q / 24) * s) AS h, s, e + s / f + s AS w FROM c, (SELECT f, least(24, floor(24 * f)) AS q FROM (VALUES {", ".join(f"({f}::DOUBLE)" for f in _CHOICES)}) x(f)))
SELECT '{g}' AS graph, f AS share, round(d, 6) AS d, CASE WHEN f >= 1 OR s = 0 THEN 'resident' WHEN h <= w THEN 'hybrid' ELSE 'swap' END AS strategy, CAST(CASE WHEN f >= 1 OR s = 0 THEN 24 WHEN h <= w THEN q ELSE 0 END AS INTEGER) AS resident_bands FROM t)"""


@query("strategy_choice", " UNION ALL ".join(_choice_sql(g) for g in ("custday", "custurg")))
def strategy_choice(spark, sf_dir):
    """What the planner picks by budget share for graphs with their own n, m and d; SWAP wins
    where cells hardly combine."""
    rows = []
    for g in ("custday", "custurg"):
        s = measured_sizes(spark, sf_dir, g, 24)
        for f in _CHOICES:
            p = choose_strategy(s, 2 * s.state * f, 24)
            rows.append((g, f, float(s.d), p.strategy, p.resident))
    return spark.createDataFrame(rows, "graph string, share double, d double, strategy string, resident_bands int").withColumn("d", F.round("d", 6))


for _g in ("custday", "trade"):
    for _q in (0, BANDS // 2, BANDS):

        @query(f"io_observed_{_g}_q{_q}", sqlgen.base(_g, BANDS) + f"\nSELECT count(*) AS edge_rows, (SELECT count(*) FROM v WHERE band > {_q}) AS state_rows, count(DISTINCT CASE WHEN sb > {_q} AND db > {_q} THEN (sb, dst) END) AS hub_rows FROM e")
        def _observed(spark, sf_dir, g=_g, q=_q):
            return io_observed(grid_of(spark, sf_dir, g), q)


def io_observed(grid: EdgeGrid, resident: int) -> DataFrame:
    """Rows a HYBRID round touches: edges, state of bands that aren't resident, hub rows."""
    outside = (F.col("src_band") > resident) & (F.col("dst_band") > resident)
    rows = grid.cells.groupBy("dst_band", "src_band", "dst").agg(F.count("*").alias("e")).agg(F.sum("e").alias("edge_rows"), F.count(F.when(outside, 1)).alias("hub_rows"))
    state = grid.vertices.agg(F.count(F.when(F.col("band") > resident, 1)).alias("state_rows"))
    return rows.crossJoin(state).select("edge_rows", "state_rows", "hub_rows")


def with_rows_sql(steps: str, bands: int = BANDS) -> str:
    """Steps of ``steps`` with the rows of the customer-succession graph that each one reads."""
    return f"""{sqlgen.base("custday", bands)}
SELECT step, region, src_band, dst_band, coalesce(CASE WHEN region = 'HUB' THEN c.dsts ELSE c.edges END, 0) AS row_count
FROM ({steps}) LEFT JOIN (SELECT sb, db, count(*) AS edges, count(DISTINCT dst) AS dsts FROM e GROUP BY sb, db) c ON c.sb = src_band AND c.db = dst_band"""


def with_rows(steps: DataFrame, grid: EdgeGrid) -> DataFrame:
    """The rows each step reads: a cell's edges, or of a hub one row a destination."""
    cells = grid_stats(grid).select("src_band", "dst_band", "edges", "dsts")
    rows = F.coalesce(F.when(F.col("region") == "HUB", F.col("dsts")).otherwise(F.col("edges")), F.lit(0)).alias("row_count")
    return steps.join(cells, ["src_band", "dst_band"], "left").select("step", "region", "src_band", "dst_band", rows)


def _schedule_frame(spark, *args) -> DataFrame:
    return spark.createDataFrame(schedule(*args), "step int, region string, src_band int, dst_band int")


@query("schedule_p4_q2", with_rows_sql("""SELECT CAST(row_number() OVER (ORDER BY phase, a, b) AS INTEGER) AS step, region, src_band, dst_band FROM (
  SELECT 1 AS phase, i AS a, j AS b, 'RR' AS region, i AS src_band, j AS dst_band FROM range(1, 3) x(i), range(1, 3) y(j)
  UNION ALL SELECT 2, i, j, CASE WHEN j <= 2 THEN 'DR' ELSE 'DD' END, i, j FROM range(3, 5) x(i), range(1, 5) y(j)
  UNION ALL SELECT 3, j, i, CASE WHEN i <= 2 THEN 'RD' ELSE 'HUB' END, i, j FROM range(1, 5) x(i), range(3, 5) y(j))""".replace("i AS src_band", "CAST(i AS INTEGER) AS src_band").replace("j AS dst_band", "CAST(j AS INTEGER) AS dst_band")))
def schedule_hybrid(spark, sf_dir):
    return with_rows(_schedule_frame(spark, "hybrid", 4, 2), grid_of(spark, sf_dir, "custday"))


@query("schedule_resident_p4", with_rows_sql("SELECT CAST((i - 1) * 4 + j AS INTEGER) AS step, 'RR' AS region, CAST(i AS INTEGER) AS src_band, CAST(j AS INTEGER) AS dst_band FROM range(1, 5) x(i), range(1, 5) y(j)"))
def schedule_resident(spark, sf_dir):
    return with_rows(_schedule_frame(spark, "resident", 4), grid_of(spark, sf_dir, "custday"))


@query("schedule_staged_p4", with_rows_sql("SELECT CAST((i - 1) * 4 + j AS INTEGER) AS step, 'DD' AS region, CAST(i AS INTEGER) AS src_band, CAST(j AS INTEGER) AS dst_band FROM range(1, 5) x(i), range(1, 5) y(j) UNION ALL SELECT CAST(16 + (j - 1) * 4 + i AS INTEGER), 'HUB', CAST(i AS INTEGER), CAST(j AS INTEGER) FROM range(1, 5) x(i), range(1, 5) y(j)"))
def schedule_staged(spark, sf_dir):
    return with_rows(_schedule_frame(spark, "staged", 4), grid_of(spark, sf_dir, "custday"))


@query("resident_bands", sqlgen.base("custday", 24) + "\nSELECT CAST(b AS INTEGER) AS pct, CAST(q AS INTEGER) AS q, (SELECT count(*) FROM v WHERE band <= q) AS vertices FROM (SELECT b, CASE WHEN n = 0 THEN 24 ELSE least(24, b * 24 // 100) END AS q FROM range(0, 151, 10) t(b), nn)")
def resident_band_count(spark, sf_dir):
    """How many of 24 bands of the customer-succession graph stay resident, and their vertices,
    by the per cent of memory for two copies of its state."""
    grid = grid_of(spark, sf_dir, "custday", replace(config_for("resident"), bands=24))
    counts = spark.createDataFrame([(p, resident_bands(2 * grid.n * 8 * p / 100, grid.n, 8, 24)) for p in range(0, 151, 10)], "pct int, q int")
    per = grid.vertices.groupBy("band").agg(F.count("*").alias("c"))
    return counts.join(F.broadcast(per), F.col("band") <= F.col("q"), "left").groupBy("pct", "q").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("vertices"))
