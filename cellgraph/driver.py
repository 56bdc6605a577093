"""Rounds of a vertex program until they are done."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .config import EngineConfig
from .engine.strategies import BANDED, STRATEGIES, Round
from .planner import Plan, choose_strategy, sizes_of
from .prep.densify import to_raw
from .prep.grid import EdgeGrid, build_grid
from .program import VertexProgram
from .storage import delete, forget, work_dir, write_bucketed, write_table


@dataclass
class Result:
    state: DataFrame  # vid, band, out_deg, attr, changed
    rounds: int
    log: list[dict] = field(default_factory=list)
    plan: Plan | None = None
    grid: EdgeGrid | None = None

    def values(self, name: str = "attr") -> DataFrame:
        return self.state.select("vid", F.col("attr").alias(name))

    def to_raw(self, name: str = "attr") -> DataFrame:
        return to_raw(self.values(name), self.grid.vids)


def step(r: Round, strategy: str) -> DataFrame:
    """The state after one synchronous round; the old state isn't touched."""
    parts = STRATEGIES[strategy](r)
    p = r.program
    if len(parts) > 1 and p.combine(F.lit(None), F.lit(None)) is None:
        every = parts[0]
        for part in parts[1:]:
            every = every.unionByName(part)
        parts = [r.fold(every, "dst", value="inc")]
    met, inc = r.state, None
    for k, part in enumerate(parts):
        part = part.select(F.col("dst").alias(f"_d{k}"), F.col("inc").alias(f"_i{k}"))
        met = met.join(r.near(part), met["vid"] == part[f"_d{k}"], "left")
        inc = F.col(f"_i{k}") if inc is None else p.combine(inc, F.col(f"_i{k}"))
    if p.extra:
        met = met.crossJoin(F.broadcast(p.extra(r.state)))  # one row
    old = F.col("attr")
    met = met.withColumn("inc", inc)
    new = p.apply(old, F.col("inc")) if not p.apply_extra else p.apply_extra(F.col("inc"), F.col("extra"))
    return met.select("vid", "band", "out_deg", old.alias("old"), new.alias("attr")).select("vid", "band", "out_deg", "attr", p.differs(F.col("old"), F.col("attr")).alias("changed"))


def active_bands(state: DataFrame) -> list[int]:
    """Bands with a changed vertex; one row a band reaches the driver at most."""
    return sorted(r["band"] for r in state.filter("changed").select("band").distinct().collect())


def resident_set(grid: EdgeGrid, count: int, choice: str) -> list[int]:
    """``count`` bands to keep in memory: the first, or those that most edges read."""
    if choice == "first" or count >= grid.bands or not count:
        return list(range(1, min(count, grid.bands) + 1))
    heavy = grid.vertices.groupBy("band").agg(F.sum("out_deg").alias("w")).collect()
    return sorted(b for _, b in sorted((-r["w"], r["band"]) for r in heavy)[:count])


def run(grid: EdgeGrid, program: VertexProgram, config: EngineConfig | None = None, rounds: int | None = None, resident: int | None = None, tolerance: float | None = None, log: bool = False) -> Result:
    """Run ``rounds`` rounds, or until no band is active (``rounds`` None), or until the
    summed change of a numeric attribute falls below ``tolerance``.

    Each round's state is written, bucketed by id as the grid is: a round reads it twice or
    more, so uncut plans would grow by that factor each, and the write costs a few hundredths
    of what the edges do.  Only the last states are kept.  A run until quiet that isn't after
    ``max_rounds`` raises an error.
    """
    config = config or EngineConfig()
    spark = grid.cells.sparkSession
    strategy, plan = config.strategy, None
    if strategy == "auto":
        sizes = sizes_of(grid, config)
        plan = choose_strategy(sizes, config.budget_bytes if config.budget_bytes is not None else 2 * sizes.state + sizes.edges, grid.bands)
        strategy, resident = plan.strategy, plan.resident
        if plan.cached_edge_bytes and sizes.edges:
            config = replace(config, cached_bands=int(plan.cached_edge_bytes * grid.bands // sizes.edges))
    if resident is None:
        resident = grid.bands // 2
    kept_bands = resident_set(grid, resident, config.resident_choice)
    folder = work_dir(spark, f"run-{program.name}")
    paths: list[str] = []

    def save(state: DataFrame, number: int) -> DataFrame:
        paths.append(f"{folder}/r{number}")
        return write_bucketed(state, paths[-1], "vid", grid.buckets) if grid.buckets else write_table(state, paths[-1])

    state = save(program.init(grid.vertices), 0)
    skip = (program.monotone and program.kind != "global" if config.skip_inactive is None else config.skip_inactive) and strategy in BANDED
    if skip and not program.monotone:
        raise ValueError(f"{program.name} restarts its sums, so no band can be skipped")
    kept: dict = {}
    steps, entries = 0, []
    by_source = {r["src_band"]: r["c"] for r in grid.cells.select("dst_band", "src_band").distinct().groupBy("src_band").agg(F.count("*").alias("c")).collect()} if log else {}
    targeted = rounds is None and tolerance is None
    active = active_bands(state) if targeted or skip else None
    while rounds is None or steps < rounds:
        if targeted and not active:
            break
        if rounds is None and steps >= config.max_rounds:
            raise RuntimeError(f"{program.name} is not settled after {steps} rounds")
        began = time.time()
        last = state
        r = Round(grid, program, config, state, active if skip else None, kept_bands, kept, f"{folder}/t{steps}")
        state = save(step(r, strategy), steps + 1)
        steps += 1
        delete(spark, f"{folder}/t{steps - 1}")
        if log or config.observe:
            entries.append({"round": steps, "active_bands": len(active) if active is not None else grid.bands, "cells_read": sum(by_source.get(b, 0) for b in active) if skip else sum(by_source.values()), "cells_skipped": sum(c for b, c in by_source.items() if skip and b not in active), "secs": time.time() - began, **r.counts()})
            entries[-1]["changed"] = state.filter("changed").count() if log else None
        if targeted or skip:
            active = active_bands(state)
        moved = None
        if tolerance is not None:
            moved = state.join(last.select("vid", F.col("attr").alias("was")), "vid").agg(F.sum(F.abs(F.col("attr") - F.col("was"))).alias("l1")).first()["l1"]
            if log:
                entries[-1]["l1"] = moved
        forget(spark, paths.pop(0))
        if tolerance is not None and (moved is None or moved < tolerance):
            break
    for table in kept.values():
        if isinstance(table, DataFrame) and table.is_cached:
            table.unpersist()
    return Result(state, steps, entries, plan, grid)


class GraphEngine:
    """Facade: raw edges in, results keyed by raw key out."""

    def __init__(self, grid: EdgeGrid, config: EngineConfig):
        self.grid, self.config = grid, config

    @classmethod
    def from_edges(cls, edges: DataFrame, config: EngineConfig | None = None) -> GraphEngine:
        config = config or EngineConfig()
        return cls(build_grid(edges, config), config)

    def with_budget(self, budget_bytes: float) -> GraphEngine:
        """Another memory budget on the same grid: nothing is partitioned anew."""
        return GraphEngine(self.grid, replace(self.config, budget_bytes=budget_bytes))

    def run(self, program: VertexProgram, **options) -> Result:
        return run(self.grid, program, self.config, **options)
