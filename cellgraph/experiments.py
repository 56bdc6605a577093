"""The experiments as functions: each gives plain rows, and times only what a round does.

Deterministic parts (bytes, rows, cells skipped, results) are registered as queries below;
times come from ``bench.py``.
"""

from __future__ import annotations

import os
import subprocess
import sys
import time
from collections.abc import Callable, Iterable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algorithms import scc as scc_module
from .algorithms import traversal
from .algorithms.pagerank import pagerank, pagerank_program
from .config import EngineConfig
from .cost import Sizes, io_model, mteps, resident_bands
from .driver import Result, run
from .graph_queries import BANDS, config_for, grid_of
from .oracle import sqlgen
from .prep.grid import EdgeGrid, avg_d, build_grid, induced, pack_state, unpack_state
from .program import started_from
from .registry import query
from .sources.builders import BUILDERS
from .sources.tables import lattice_edges


def timed(work: Callable, times: int = 1) -> tuple[float, object]:
    """(median seconds, last result) of so many runs."""
    secs, out = [], None
    for _ in range(times):
        began = time.time()
        out = work()
        secs.append(time.time() - began)
    return sorted(secs)[len(secs) // 2], out


def _sum(result: Result) -> float:
    return result.state.agg(F.sum("attr")).first()[0]


def order_by_parallelism(raw: DataFrame, bands: int = 12, rounds: int = 10) -> list[dict]:
    """Edge order x parallelism: seconds and the sum of ranks, which must not differ."""
    out = []
    for order in ("src", "dst", "none"):
        for parallel in ("coarse", "fine"):
            config = EngineConfig(bands=bands, strategy="resident", order=order, parallel=parallel)
            grid = build_grid(raw, config)
            secs, total = timed(lambda g=grid, c=config: _sum(pagerank(g, rounds, config=c)))
            out.append({"order": order, "parallel": parallel, "secs": secs, "rank_sum": total})
    return out


def sweep_bands(raw: DataFrame, bands: Iterable[int] = (1, 4, 12, 24, 48, 96), strategy: str = "resident") -> list[dict]:
    """Number of bands against seconds and cells skipped, for a global and a targeted program."""
    out = []
    for p in bands:
        config = EngineConfig(bands=p, strategy=strategy)
        grid = build_grid(raw, config)
        secs, _ = timed(lambda g=grid, c=config: _sum(pagerank(g, 2, config=c)))
        out.append({"bands": p, "program": "pagerank", "secs": secs, "cells_read": None, "cells_skipped": 0})
        secs, found = timed(lambda g=grid, c=config: traversal.bfs(g, 1, c, log=True))
        out.append({"bands": p, "program": "bfs", "secs": secs, "cells_read": sum(x["cells_read"] for x in found.log), "cells_skipped": sum(x["cells_skipped"] for x in found.log)})
    return out


def sweep_budget(grid: EdgeGrid, shares: Iterable[float] = (0.0, 0.05, 0.1, 0.25, 0.5, 0.75, 1.0, 2.0), strategies: Iterable[str] = ("hybrid", "swap", "psw"), rounds: int = 1) -> list[dict]:
    """Memory budget, as a share of both copies of the state, against seconds, modelled bytes
    and the rows that running rounds read and wrote.  Beyond the state, edges are cached."""
    s = Sizes(grid.n, grid.m, d=avg_d(grid))
    out = []
    for f in shares:
        budget = 2 * s.state * f
        q = resident_bands(budget, s.n, s.attr, grid.bands)
        left = max(0.0, budget - 2 * s.state)
        for name in strategies:
            config = EngineConfig(bands=grid.bands, strategy=name, observe=name == "hybrid", materialize_hubs=name == "hybrid", cached_bands=int(min(1.0, left / s.edges) * grid.bands) if name == "hybrid" and s.edges else 0)
            secs, result = timed(lambda n=name, c=config, k=q: run(grid, pagerank_program(grid.n), c, rounds=rounds, resident=k))
            cost = io_model(name, s, budget) if name != "swap" or budget else None
            seen = {k: sum(x.get(k, 0) for x in result.log) for k in ("edge_rows", "state_rows", "hub_rows")} if name == "hybrid" else {}
            out.append({"share": f, "strategy": name, "resident": q, "secs": secs, "read": cost and cost[0], "write": cost and cost[1], **seen})
    return out


def saturation(rows: Iterable[dict], strategy: str = "hybrid", within: float = 0.1) -> float:
    """The least share of memory from which on more of it gains no more than ``within``."""
    own = sorted((r["share"], r["secs"]) for r in rows if r["strategy"] == strategy)
    best = min(secs for _, secs in own)
    return next((f for k, (f, _) in enumerate(own) if all(secs <= best * (1 + within) for _, secs in own[k:])), own[-1][0])


def sweep_threads(sf_dir: str, threads: Iterable[int] = (1, 2, 4, 8), graph: str = "copart", rounds: int = 5) -> list[dict]:
    """Threads against seconds: each number in a session of its own process."""
    code = (
        "import sys, time\n"
        "from pyspark.sql import SparkSession\n"
        "k, sf, g, rounds = int(sys.argv[1]), sys.argv[2], sys.argv[3], int(sys.argv[4])\n"
        "spark = SparkSession.builder.master(f'local[{k}]').config('spark.sql.shuffle.partitions', '8').config('spark.ui.enabled', 'false').getOrCreate()\n"
        "from cellgraph.algorithms.pagerank import pagerank\n"
        "from cellgraph.config import EngineConfig\n"
        "from cellgraph.prep.grid import build_grid\n"
        "from cellgraph.sources.builders import BUILDERS\n"
        "c = EngineConfig(bands=4, strategy='resident')\n"
        "grid = build_grid(BUILDERS['g_' + g](spark, sf), c)\n"
        "pagerank(grid, 1, config=c)\n"
        "began = time.time()\n"
        "pagerank(grid, rounds, config=c)\n"
        "print('SECS', time.time() - began)\n"
    )
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    out = []
    for k in threads:
        done = subprocess.run([sys.executable, "-c", code, str(k), sf_dir, graph, str(rounds)], capture_output=True, text=True, check=True, timeout=600, env=os.environ | {"PYTHONPATH": root + os.pathsep + os.environ.get("PYTHONPATH", "")})
        secs = float(next(line.split()[1] for line in done.stdout.splitlines() if line.startswith("SECS")))
        out.append({"threads": k, "secs": secs, "speedup": out[0]["secs"] / secs if out else 1.0})
    return out


def doubling_meshes(spark: SparkSession, first: int = 64, count: int = 5, rounds: int = 3, strategies: Iterable[str] = ("hybrid", "swap", "psw")) -> list[dict]:
    """Meshes whose vertices double: million edges traversed a second under each strategy."""
    out = []
    for k in range(count):
        side = round(first * 2 ** (k / 2))
        config = EngineConfig(bands=12, strategy="hybrid")
        grid = build_grid(lattice_edges(spark, side), config)
        for name in strategies:
            secs, _ = timed(lambda g=grid, c=replace(config, strategy=name): _sum(pagerank(g, rounds, config=c)))
            out.append({"n": grid.n, "m": grid.m, "strategy": name, "secs": secs, "mteps": mteps(grid.m, rounds, secs)})
    return out


def tasks_by_strategy(spark: SparkSession, sf_dir: str, graphs: Iterable[str] = ("custurg", "custhigh"), strategies: Iterable[str] = ("resident", "staged", "hybrid", "swap", "psw")) -> list[dict]:
    """BFS, WCC and SCC under every strategy: seconds, rounds, and a result that must not differ."""
    out = []
    for g in graphs:
        grid = grid_of(spark, sf_dir, g)
        for name in strategies:
            config = config_for(name)
            secs, found = timed(lambda c=config, x=grid: traversal.bfs(x, 1, c))
            out.append({"graph": g, "task": "bfs", "strategy": name, "secs": secs, "rounds": found.rounds, "answer": found.state.filter("attr IS NOT NULL").count()})
            secs, found = timed(lambda c=config, x=grid: traversal.wcc(x, c))
            out.append({"graph": g, "task": "wcc", "strategy": name, "secs": secs, "rounds": found.rounds, "answer": found.state.select("attr").distinct().count()})
            secs, found = timed(lambda c=config, x=grid: scc_module.scc(x, c).select("attr").distinct().count())
            out.append({"graph": g, "task": "scc", "strategy": name, "secs": secs, "rounds": None, "answer": found})
    return out


def one_round(grid: EdgeGrid, share: float | None, strategies: Iterable[str]) -> list[dict]:
    """One round of PageRank under each strategy: with a share of memory (the limited setting),
    or with all edges cached (``share`` None, the best one)."""
    out = []
    for name in strategies:
        config = EngineConfig(bands=grid.bands, strategy=name, cached_bands=grid.bands if share is None and name == "resident" else 0)
        q = grid.bands if share is None else int(share * grid.bands)
        secs, _ = timed(lambda c=config, k=q: _sum(run(grid, pagerank_program(grid.n), c, rounds=1, resident=k)), 3)
        out.append({"strategy": name, "secs": secs})
    base = out[0]["secs"]
    return [r | {"speedup_of_first": r["secs"] / base} for r in out]


def accuracy(result: DataFrame, exact: DataFrame, value: str = "rank", key: str = "vid") -> DataFrame:
    """(max_abs, l1, rows): how far two answers are apart; rows that only one has count whole."""
    other = exact.select(F.col(key).alias("_k"), F.col(value).alias("_v"))
    gap = F.abs(F.coalesce(F.col(value), F.lit(0)) - F.coalesce(F.col("_v"), F.lit(0)))
    return result.select(key, value).join(other, F.col(key) == F.col("_k"), "full").agg(F.max(gap).alias("max_abs"), F.sum(gap).alias("l1"), F.count("*").alias("rows"))


def physical_metrics(df: DataFrame) -> dict[str, int]:
    """Run ``df`` and add up the metrics of its physical operators by name: bytes read from
    files, shuffled, broadcast and spilled."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    out: dict[str, int] = {}
    todo = [execution.executedPlan()]
    while todo:
        node = todo.pop()
        for inner in ("executedPlan", "plan"):  # adaptive plans and their stages
            if inner in dir(node):
                todo.append(getattr(node, inner)())
        entries = node.metrics().iterator()
        while entries.hasNext():
            entry = entries.next()
            out[entry._1()] = out.get(entry._1(), 0) + max(0, entry._2().value())
        children = node.children().iterator()
        while children.hasNext():
            todo.append(children.next())
    return out


def register_graph(spark: SparkSession, name: str, grid: EdgeGrid, config: EngineConfig | None = None, rounds: int = 10) -> list[str]:
    """Views for SQL: graph_<name>_edges, _vertices, _pagerank, _bfs, _wcc."""
    config = config or EngineConfig(bands=grid.bands, strategy="hybrid")
    views = {
        "edges": grid.cells.select("src", "dst"),
        "vertices": grid.vertices,
        "pagerank": pagerank(grid, rounds, config=config).values("rank"),
        "bfs": traversal.bfs(grid, 1, config).values("depth"),
        "wcc": traversal.wcc(grid, config).values("component"),
    }
    for k, df in views.items():
        df.createOrReplaceTempView(f"graph_{name}_{k}")
    return [f"graph_{name}_{k}" for k in views]


# ------------------------------------------------------------------------------- queries

_SKIPS = " UNION ALL ".join(
    f"""SELECT * FROM ({sqlgen.bfs("custday", f"SELECT CAST({p} AS INTEGER) AS bands, max(b.depth) + 1 AS rounds, (SELECT count(*) FROM (SELECT DISTINCT d.depth, v.band FROM b d JOIN v USING (vid)) a JOIN (SELECT DISTINCT sb, db FROM e) c ON c.sb = a.band) AS cells_read, (max(b.depth) + 1) * (SELECT count(*) FROM (SELECT DISTINCT sb, db FROM e)) - (SELECT count(*) FROM (SELECT DISTINCT d.depth, v.band FROM b d JOIN v USING (vid)) a JOIN (SELECT DISTINCT sb, db FROM e) c ON c.sb = a.band) AS cells_skipped FROM b", bands=p)})"""
    for p in (1, 4, 12)
)


@query("exp_bands_bfs_custday", _SKIPS)
def exp_bands(spark, sf_dir):
    """More bands, more cells skipped: a targeted program at three numbers of bands."""
    rows = []
    for p in (1, 4, 12):
        config = EngineConfig(bands=p, strategy="resident")
        found = traversal.bfs(build_grid(BUILDERS["g_custday"](spark, sf_dir), config), 1, config, log=True)
        rows.append((p, found.rounds, sum(x["cells_read"] for x in found.log), sum(x["cells_skipped"] for x in found.log)))
    return spark.createDataFrame(rows, "bands int, rounds long, cells_read long, cells_skipped long")


def io_running(grid: EdgeGrid, resident: int) -> dict[str, int]:
    """Rows that a running HYBRID round reads of edges and of state on disk, and hubs it writes."""
    config = EngineConfig(bands=grid.bands, strategy="hybrid", observe=True, materialize_hubs=True)
    log = run(grid, pagerank_program(grid.n), config, rounds=1, resident=resident).log[0]
    return {k: log.get(k, 0) for k in ("edge_rows", "state_rows", "hub_rows")}


@query("exp_budget_trade", " UNION ALL ".join(
    f"SELECT * FROM ({sqlgen.base('trade', BANDS)} SELECT CAST({q} AS INTEGER) AS resident, count(*) AS edge_rows, (SELECT count(*) FROM v WHERE band > {q}) AS state_rows, count(DISTINCT CASE WHEN sb > {q} AND db > {q} THEN (sb, dst) END) AS hub_rows FROM e)" for q in range(BANDS + 1)
))
def exp_budget(spark, sf_dir):
    """From no to all bands resident: rows observed in the running rounds."""
    grid = grid_of(spark, sf_dir, "trade")
    rows = [(q, *io_running(grid, q).values()) for q in range(BANDS + 1)]
    return spark.createDataFrame(rows, "resident int, edge_rows long, state_rows long, hub_rows long")


_SIDES = (6, 8, 11, 16, 23)


@query("exp_scale_meshes", "SELECT side, CAST(side * side AS BIGINT) AS n, CAST(2 * (2 * side * (side - 1) + (side - 1) * (side - 1)) AS BIGINT) AS m, CAST(9 AS BIGINT) AS reached FROM (VALUES " + ", ".join(f"({s})" for s in _SIDES) + ") t(side)")
def exp_scale(spark, sf_dir):
    """Five meshes whose vertices double: sizes, and what two steps from a corner reach."""
    rows = []
    for side in _SIDES:
        grid = build_grid(lattice_edges(spark, side), config_for("hybrid"))
        rows.append((side, grid.n, grid.m, traversal.hop_limited(grid, 1, 2, config_for("hybrid")).state.filter("attr IS NOT NULL").count()))
    return spark.createDataFrame(rows, "side int, n long, m long, reached long")


@query("exp_tasks_talk", f"""SELECT * FROM ({sqlgen.bfs("talk", "SELECT 'bfs' AS task, count(*) AS answer FROM b")})
UNION ALL SELECT * FROM ({sqlgen.wcc("talk", "SELECT 'wcc' AS task, count(DISTINCT attr) AS answer FROM c")})
UNION ALL SELECT * FROM ({sqlgen.scc("talk", "SELECT 'scc' AS task, count(DISTINCT attr) AS answer FROM c")})""")
def exp_tasks(spark, sf_dir):
    """Vertices reached, weak and strong components."""
    rows = tasks_by_strategy(spark, sf_dir, ("talk",), ("hybrid",))
    return spark.createDataFrame([(r["task"], r["answer"]) for r in rows], "task string, answer long")


_L1 = ["SELECT CAST({0} AS INTEGER) AS round, round(sum(abs(a.rank - b.rank)), 8) AS l1 FROM r{0} a JOIN r{1} b USING (vid)".format(k, k - 1) for k in range(1, 6)]


@query("pagerank_residual_log_custday", sqlgen.pagerank("custday", 5, tail=" UNION ALL ".join(_L1)))
def residual_log(spark, sf_dir):
    """How much a round still moves: the summed change of each."""
    grid = grid_of(spark, sf_dir, "custday")
    log = pagerank(grid, 5, config=config_for("resident"), tolerance=0.0, log=True).log
    return spark.createDataFrame([(x["round"], x["l1"]) for x in log], "round int, l1 double").select("round", F.round("l1", 8).alias("l1"))


@query("accuracy_strategies_custday", "SELECT CAST(0 AS DOUBLE) AS max_abs, CAST(0 AS DOUBLE) AS l1, CAST((SELECT count(*) FROM (SELECT src_key FROM (" + sqlgen.GRAPHS["custday"] + ") UNION SELECT dst_key FROM (" + sqlgen.GRAPHS["custday"] + "))) AS BIGINT) AS rows")
def accuracy_query(spark, sf_dir):
    """Ten rounds of HYBRID against the textbook join: rounding apart, no difference."""
    grid = grid_of(spark, sf_dir, "custday")
    a, b = (pagerank(grid, 10, config=config_for(s)).values("rank") for s in ("hybrid", "plain"))
    return accuracy(a, b).select(F.round("max_abs", 9).alias("max_abs"), F.round("l1", 9).alias("l1"), "rows")


@query("pagerank_auto_quarter_custday", sqlgen.pagerank("custday"))
def auto_quarter(spark, sf_dir):
    """The planner's choice with memory for a quarter of both copies of the state."""
    grid = grid_of(spark, sf_dir, "custday")
    config = config_for("auto", budget_bytes=2 * grid.n * 8 * 0.25)
    return pagerank(grid, 10, config=config).values("rank").select("vid", F.round("rank", 8).alias("rank"))


@query("bfs_from_outside_custday", f"""{sqlgen.base("custday", recursive=True)},
walk(vid, depth) AS (SELECT vid, CAST(0 AS BIGINT) FROM v WHERE raw_key % 100 = 7 UNION SELECT e.dst, depth + 1 FROM walk JOIN e ON e.src = walk.vid WHERE depth < 60)
SELECT v.vid, min(depth) AS depth FROM v LEFT JOIN walk USING (vid) GROUP BY v.vid""")
def bfs_from_outside(spark, sf_dir):
    """Search from many vertices, whose start values come from a file by raw key."""
    from .sources.tables import read_init
    from .storage import work_dir

    path = work_dir(spark, "init")
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").filter("c_custkey % 100 = 7")
    customers.select(F.col("c_custkey").cast("long").alias("raw_key"), F.lit(0).cast("long").alias("attr"), F.lit(True).alias("active")).write.parquet(path)
    program = started_from(traversal.bfs_program(0), read_init(spark, path, "long"), "raw_key")
    return run(grid_of(spark, sf_dir, "custday"), program, config_for("hybrid")).values("depth")


@query("state_packed_custday", sqlgen.base("custday", BANDS) + "\nSELECT band, min(vid) AS first_vid, count(*) AS n, CAST(sum(out_deg) AS BIGINT) AS total FROM v GROUP BY band")
def state_packed(spark, sf_dir):
    grid = grid_of(spark, sf_dir, "custday")
    packed = pack_state(grid.vertices.select("vid", "band", F.col("out_deg").alias("attr")), grid.spec)
    back = unpack_state(packed).groupBy("band").agg(F.sum("attr").alias("total"))
    return packed.groupBy("band").agg(F.min("first_vid").alias("first_vid"), F.sum(F.size("values")).alias("n")).join(back, "band")


@query("induced_subgraph_custday", sqlgen.base("custday", BANDS) + "\nSELECT src, dst FROM e WHERE src % 3 <> 0 AND dst % 3 <> 0")
def induced_query(spark, sf_dir):
    return induced(grid_of(spark, sf_dir, "custday"), F.col("vid") % 3 != 0)


@query("graph_views_custurg", f"""SELECT w.component, count(*) AS n, round(sum(p.rank), 8) AS rank, count(d.depth) AS reached
FROM ({sqlgen.wcc("custurg", "SELECT vid, attr AS component FROM c")}) w JOIN ({sqlgen.pagerank("custurg", tail="SELECT vid, rank FROM r{k}")}) p USING (vid) JOIN ({sqlgen.bfs("custurg")}) d USING (vid) GROUP BY 1""")
def graph_views(spark, sf_dir):
    """Components, ranks and depths joined in SQL over registered views."""
    register_graph(spark, "custurg", grid_of(spark, sf_dir, "custurg"))
    return spark.sql("SELECT w.component, count(*) AS n, round(sum(p.rank), 8) AS rank, count(d.depth) AS reached FROM graph_custurg_wcc w JOIN graph_custurg_pagerank p USING (vid) JOIN graph_custurg_bfs d USING (vid) GROUP BY w.component")
