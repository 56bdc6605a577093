"""Headline runs: prints one JSON line.  BENCH_SF_DIR and BENCH_CPUS choose data and cores.

Grids are built once (``build_*``, both layouts); the other times are rounds alone, as the
published ones; one round is the median of three.  ``experiments`` holds the sweeps: memory,
bands and meshes, and with BENCH_EXPERIMENTS=all also order x parallelism, tasks and threads.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from cellgraph import experiments
    from cellgraph.algorithms.pagerank import pagerank
    from cellgraph.algorithms.traversal import bfs, wcc_hooking
    from cellgraph.config import EngineConfig
    from cellgraph.cost import mteps
    from cellgraph.prep.grid import avg_d, build_grid
    from cellgraph.sources.builders import BUILDERS

    times: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name, f):
        began = time.time()
        out = f()
        times[name] = round(time.time() - began, 3)
        return out

    bands = 12
    grids = {}
    for g in ("custday", "copart"):
        config = EngineConfig(bands=bands, strategy="resident")
        grids[g] = timed(f"build_{g}", lambda g=g, c=config: build_grid(BUILDERS[f"g_{g}"](spark, sf_dir), c))
        timed(f"build_rows_{g}", grids[g].rows)
        facts[f"d_{g}"] = round(avg_d(grids[g]), 3)

    def ranks(name, g, rounds, strategy, **more):
        config = EngineConfig(bands=bands, strategy=strategy, **more)
        grid = grids[g]
        times[name] = round(experiments.timed(lambda: pagerank(grid, rounds, config=config).state.agg({"attr": "sum"}).collect(), 3 if rounds == 1 else 1)[0], 3)
        facts[f"mteps_{name}"] = round(mteps(grid.m, rounds, times[name]), 3)

    ranks("warm_up", "custday", 1, "resident")
    for strategy in ("resident", "staged", "hybrid"):
        ranks(f"pagerank10_{strategy}_custday", "custday", 10, strategy)
    for strategy in ("resident", "staged", "hybrid", "swap", "two_level", "nbr_view", "scatter", "flat", "plain"):
        ranks(f"pagerank1_{strategy}_copart", "copart", 1, strategy)
    ranks("pagerank1_resident_cached_copart", "copart", 1, "resident", cached_bands=bands)
    ranks("pagerank10_resident_copart", "copart", 10, "resident")
    timed("bfs_resident_copart", lambda: bfs(grids["copart"], 1, EngineConfig(bands=bands, strategy="resident")).state.count())
    timed("wcc_hooking_custday", lambda: wcc_hooking(grids["custday"]).count())
    del times["warm_up"]
    budget = experiments.sweep_budget(grids["copart"], (0.0, 0.25, 0.5, 1.0, 2.0), ("hybrid",))
    found = {"memory": budget, "saturation": experiments.saturation(budget), "bands": experiments.sweep_bands(BUILDERS["g_custday"](spark, sf_dir), (1, 12, 48)), "meshes": experiments.doubling_meshes(spark, 64, 3, 2, ("hybrid", "swap"))}
    if os.environ.get("BENCH_EXPERIMENTS") == "all":
        found["order"] = experiments.order_by_parallelism(BUILDERS["g_custday"](spark, sf_dir), bands)
        found["tasks"] = experiments.tasks_by_strategy(spark, sf_dir, ("talk",))
        found["limited"] = experiments.one_round(grids["copart"], 0.25, ("hybrid", "two_level", "scatter", "nbr_view"))
        found["best"] = experiments.one_round(grids["copart"], None, ("resident", "scatter", "two_level", "flat", "plain"))
        found["threads"] = experiments.sweep_threads(sf_dir)
    total = round(sum(times.values()), 3)
    print(json.dumps({"metric": "graph headline runs, total", "value": total, "unit": "sec", "queries": times, "facts": facts, "experiments": found, "sf": os.path.basename(sf_dir.rstrip("/"))}))
    spark.stop()


if __name__ == "__main__":
    sys.exit(main())
