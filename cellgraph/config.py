"""Engine parameters in one place."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class EngineConfig:
    """``bands`` are logical units of activity and residency; ``buckets`` share the work, so a
    few hundred bands do for any graph size."""

    bands: int = 24
    strategy: str = "auto"
    budget_bytes: float | None = None  # memory for vertex state and, beyond both its copies, for edges
    buckets: int | None = None  # files a table is dealt into by id; None: as many as shuffle partitions
    attr_bytes: int = 8
    id_bytes: int = 4
    edge_bytes: int = 4
    order: str = "dst"  # dst, src, none: order of edges inside a cell
    parallel: str = "fine"  # fine: tasks own runs of destinations; coarse: one task a column of cells
    sync: str = "owner"  # owner: one task folds a destination; merge: partial folds meet in an exchange
    cell_order: str = "any"  # row, col, any: order in which a task visits its cells
    resident_choice: str = "first"  # first: bands 1..Q; heavy: the Q bands that edges read most
    cached_bands: int = 0  # destination bands whose edges stay in memory (RESIDENT), or source bands that SWAP keeps
    block: int = 2  # fine bands a coarse block of TWO-LEVEL has in each direction
    materialize_hubs: bool = False
    skip_inactive: bool | None = None  # None: where the program allows it
    broadcast_limit_bytes: int = 200 << 20
    max_rounds: int = 10_000  # of a run until quiet, which raises an error if it isn't by then
    observe: bool = False  # count the rows that each round reads and folds
