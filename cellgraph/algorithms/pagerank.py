"""PageRank: fixed rounds, to a tolerance, by residuals, and in whole numbers."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..config import EngineConfig
from ..driver import Result, run
from ..prep.grid import EdgeGrid
from ..program import VertexProgram, with_attr

DAMPING = 0.85
#: Units of the whole-number form: ranks are counts of 1e-12.
UNITS = 10**12


def pagerank_program(n: int, damping: float = DAMPING, dangling: str = "drop") -> VertexProgram:
    """rank = (1 - damping) / n + damping * sum(rank / out_deg); what vertices without
    out-edges hold is dropped or spread evenly."""
    base = (1 - damping) / max(1, n)
    common = dict(
        name="pagerank", init=lambda v: with_attr(v, F.lit(1.0 / max(1, n))), message=lambda a, d: a / d, fold=F.sum,
        apply=lambda a, inc: F.lit(base) + damping * F.coalesce(inc, F.lit(0.0)), monotone=False, sends=lambda a: F.col("out_deg") > 0, kind="global",
    )
    if dangling == "spread":
        common |= dict(
            extra=lambda state: state.agg(F.coalesce(F.sum(F.when(F.col("out_deg") == 0, F.col("attr"))), F.lit(0.0)).alias("extra")),
            apply_extra=lambda inc, lost: F.lit(base) + damping * (F.coalesce(inc, F.lit(0.0)) + lost / n),
        )
    return VertexProgram(**common)


def pagerank(grid: EdgeGrid, rounds: int = 10, damping: float = DAMPING, dangling: str = "drop", config: EngineConfig | None = None, resident: int | None = None, tolerance: float | None = None, log: bool = False) -> Result:
    return run(grid, pagerank_program(grid.n, damping, dangling), config, rounds=rounds, resident=resident, tolerance=tolerance, log=log)


def pagerank_fixed_point(grid: EdgeGrid, rounds: int = 10, config: EngineConfig | None = None, resident: int | None = None) -> Result:
    """Ranks as whole numbers of 1e-12: sums don't depend on their order."""
    n = max(1, grid.n)
    program = VertexProgram(
        "pagerank_units", lambda v: with_attr(v, F.lit(UNITS // n).cast("long")), lambda a, d: F.expr("attr div out_deg"), F.sum,
        lambda a, inc: F.lit(15 * UNITS // 100 // n).cast("long") + F.expr("(85 * coalesce(inc, 0L)) div 100"), False, sends=lambda a: F.col("out_deg") > 0, kind="global",
    )
    return run(grid, program, config, rounds=rounds, resident=resident)


def pagerank_delta(grid: EdgeGrid, epsilon: float = 1e-12, damping: float = DAMPING, config: EngineConfig | None = None, rounds: int | None = None) -> Result:
    """Residual form: a vertex sends on only what it has got since it last sent, so bands whose
    residuals are all under ``epsilon / n`` are skipped.  A residual that isn't sent is kept
    and adds up, so no mass is lost: ranks are within ``epsilon / (1 - damping)`` in
    sum of those of endless rounds.  ``attr`` is a struct (rank, res); without ``rounds`` it
    runs until no residual is large enough, which takes ``epsilon`` above 0."""
    n = max(1, grid.n)
    start = F.struct(F.lit((1 - damping) / n).alias("rank"), F.lit((1 - damping) / n).alias("res"))
    ready = lambda a: a["res"] > epsilon / n
    got = lambda inc: F.coalesce(inc, F.lit(0.0))
    program = VertexProgram(
        "pagerank_delta", lambda v: with_attr(v, start), lambda a, d: damping * a["res"] / d, F.sum,
        lambda a, inc: F.struct((a["rank"] + got(inc)).alias("rank"), (F.when(ready(a), 0.0).otherwise(a["res"]) + got(inc)).alias("res")),
        True, sends=lambda a: (F.col("out_deg") > 0) & ready(a), changed=lambda old, new: ready(new),
    )
    if rounds is None and epsilon <= 0:
        raise ValueError("an endless run: give epsilon above 0 or a number of rounds")
    return run(grid, program, config or EngineConfig(strategy="resident"), rounds=rounds)
