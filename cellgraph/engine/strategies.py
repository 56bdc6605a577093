"""Update strategies and baselines: each turns a state and a grid into (dst, inc) rows.

All give the same answer; they differ in what is joined where and in what is moved.

==============  ==========================================================================
resident        broadcast state met by edges in the column layout: folds need no exchange;
                state beyond the limit meets edges in the row layout, bucket by bucket
staged          row layout: co-bucketed state and edges make hubs, and only hubs move
hybrid          resident for edges from the resident bands, staged for the rest
swap            the state copied once for each destination band
psw             values on the edges: out-edge windows are rewritten, in-edges are gathered
two_level       an unsorted fine grid merged into coarse blocks, then as swap
nbr_view        each destination band has a view of its in-neighbours' state
scatter         one update row for each edge, shuffled before any combining
flat            an unpartitioned scan of cached edges
plain           the textbook join and aggregation on hash partitions
==============  ==========================================================================

A strategy returns a list of frames, each with a destination once; the update joins them to
the state one by one and combines their increments, so a part that needs no exchange never
has to move for one that does.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..config import EngineConfig
from ..prep.grid import EdgeGrid
from ..program import VertexProgram
from ..storage import work_dir, write_table

_VIEWS = {"row": ("src_band", "dst_band"), "col": ("dst_band", "src_band")}


def attr_size(kind: T.DataType) -> int:
    """Bytes of one attribute, by its type."""
    if isinstance(kind, T.StructType):
        return sum(attr_size(f.dataType) for f in kind.fields)
    return {T.BooleanType: 1, T.ByteType: 1, T.ShortType: 2, T.IntegerType: 4, T.FloatType: 4, T.LongType: 8, T.DoubleType: 8, T.DateType: 4, T.TimestampType: 8}.get(type(kind), 24)


@dataclass
class Round:
    """What a strategy gets: the grid, the program, old state, and bands that may be skipped."""

    grid: EdgeGrid
    program: VertexProgram
    config: EngineConfig
    state: DataFrame
    active: list[int] | None  # source bands to read, None for all
    resident: list[int] = field(default_factory=list)  # bands whose state stays in memory
    kept: dict = field(default_factory=dict)  # what a strategy keeps between rounds
    folder: str | None = None  # for what lives no longer than the round
    seen: dict[str, list[Observation]] = field(default_factory=dict)

    def watch(self, what: str, rows: DataFrame, when: Column | None = None) -> DataFrame:
        """Count ``rows`` (``when`` something holds) as they pass, if the configuration wants that."""
        if not self.config.observe:
            return rows
        self.seen.setdefault(what, []).append(Observation())
        return rows.observe(self.seen[what][-1], F.count(F.lit(1) if when is None else F.when(when, 1)).alias("rows"))

    def counts(self) -> dict[str, int]:
        return {k: sum(o.get["rows"] for o in v) for k, v in self.seen.items()}

    def temp(self, label: str) -> str:
        return f"{self.folder}/{label}" if self.folder else work_dir(self.state.sparkSession, label)

    def cells(self, layout: str = "column", bands: list[int] | None = None, others: bool = False, above: int = 0) -> DataFrame:
        """Edges from active bands, and from ``bands`` only (``others``: from all but these), into
        bands ``above`` one.  Source bands are literals on a partition column, so no other folder is opened."""
        cells = {"column": lambda: self.grid.cells, "row": self.grid.rows, "flat": self.grid.flat}[layout]()
        if self.active is not None:
            cells = cells.filter(F.col("src_band").isin(self.active))
        if bands is not None:
            inside = F.col("src_band").isin(bands)
            cells = cells.filter(~inside if others else inside)
        if above:
            cells = cells.filter(F.col("dst_band") > above)
        return self.watch("edge_rows", cells)

    def sources(self, bands: list[int] | None = None, others: bool = False, count: str | None = None) -> DataFrame:
        """(s_band, s_vid, msg): what each source sends; sources that send nothing are left out."""
        state = self.state
        if self.active is not None:
            state = state.filter(F.col("band").isin(self.active))
        if bands is not None:
            inside = F.col("band").isin(bands)
            state = state.filter(~inside if others else inside)
        if count:
            state = self.watch(count, state)
        if self.program.sends:
            state = state.filter(self.program.sends(F.col("attr")))
        return state.select(F.col("band").alias("s_band"), F.col("vid").alias("s_vid"), self.program.message(F.col("attr"), F.col("out_deg")).alias("msg"))

    def fold(self, rows: DataFrame, *keys: str, value: str = "msg") -> DataFrame:
        return rows.groupBy(*keys).agg(self.program.fold(F.col(value)).alias("inc"))

    def by_destination(self, rows: DataFrame, value: str = "msg") -> DataFrame:
        """(dst, inc).  Whole columns of cells as tasks fold by band and destination, which
        their distribution by band allows without an exchange."""
        if self.grid.parallel == "coarse" and "dst_band" in rows.columns:
            return self.fold(rows, "dst_band", "dst", value=value).select("dst", "inc")
        return self.fold(rows, "dst", value=value)

    def fits(self, rows: float) -> bool:
        """Whether so many state rows may be broadcast: a bound checked by their type's size."""
        return rows * (attr_size(self.state.schema["attr"].dataType) + 16) <= self.config.broadcast_limit_bytes


    def near(self, rows: DataFrame) -> DataFrame:
        """``rows``, one a vertex, as the side of a bucketed join that is held or sorted: a
        bucket of it is held while its bound allows."""
        return rows.hint("shuffle_hash" if self.fits(self.grid.n / max(1, self.grid.buckets)) else "merge")


def _met(r: Round, cells: DataFrame, sources: DataFrame) -> DataFrame:
    """Edges of the row layout with their sources' messages: both are bucketed by id."""
    return cells.join(r.near(sources), cells["src"] == sources["s_vid"])


def _from_memory(r: Round, bands: list[int] | None = None) -> list[DataFrame]:
    """Increments that sources held in memory send (of ``bands``, or all)."""
    share = r.grid.n if bands is None else r.grid.n * len(bands) / r.grid.bands
    sources = r.sources(bands)
    if not r.fits(share):
        return [r.fold(_met(r, r.cells("row", bands), sources), "dst")]
    layout = "flat" if r.config.sync == "merge" else "column"
    held = min(r.config.cached_bands, r.grid.bands) if layout == "column" else 0
    if not held:
        cells = r.cells(layout, bands)
        if r.config.cell_order in _VIEWS:
            cells = cells.sortWithinPartitions(*_VIEWS[r.config.cell_order])
        return [r.by_destination(cells.join(F.broadcast(sources), cells["src"] == sources["s_vid"]))]
    if "edges" not in r.kept:
        r.kept["edges"] = r.grid.cells.filter(F.col("dst_band") <= held).persist()
    cached = r.kept["edges"]
    if r.active is not None:
        cached = cached.filter(F.col("src_band").isin(r.active))
    if bands is not None:
        cached = cached.filter(F.col("src_band").isin(bands))
    parts = [cached] + ([r.cells(layout, bands, above=held)] if held < r.grid.bands else [])
    return [r.by_destination(part.join(F.broadcast(sources), part["src"] == sources["s_vid"])) for part in parts]


def resident(r: Round) -> list[DataFrame]:
    return _from_memory(r)


def _through_hubs(r: Round, met: DataFrame, between: Column | None = None) -> DataFrame:
    """Column pass over hubs.  Written hubs hold each destination of a cell once; otherwise
    the map side of the exchange combines, and shuffle files are the hubs.  What leads into
    resident bands (not ``between`` others) is folded there straight, and counts as no hub."""
    if not r.config.materialize_hubs:
        return r.fold(met, "dst")
    hubs = r.watch("hub_rows", r.fold(met, "dst_band", "src_band", "dst"), between)
    return r.fold(write_table(hubs, r.temp("hubs"), "dst_band"), "dst", value="inc")


def staged(r: Round) -> list[DataFrame]:
    return [_through_hubs(r, _met(r, r.cells("row"), r.sources(count="state_rows")))]


def hybrid(r: Round) -> list[DataFrame]:
    if len(r.resident) >= r.grid.bands:
        return resident(r)
    if not r.resident:
        return staged(r)
    met = _met(r, r.cells("row", r.resident, others=True), r.sources(r.resident, others=True, count="state_rows"))
    return [*_from_memory(r, r.resident), _through_hubs(r, met, ~F.col("dst_band").isin(r.resident))]


def _copied(r: Round, sources: DataFrame, blocks: int, cells: DataFrame, to: str, own: str) -> DataFrame:
    copies = sources.withColumn("to_block", F.explode(F.sequence(F.lit(1), F.lit(blocks))))
    return cells.join(copies.hint("merge"), (cells[to] == copies["to_block"]) & (cells[own] == copies["s_block"]) & (cells["src"] == copies["s_vid"]))


def swap(r: Round) -> list[DataFrame]:
    """Every cell rereads its source band: P copies of the state are made and moved.  Bands
    that stay in memory between cells (``cached_bands``) are read once."""
    kept = list(range(1, min(r.config.cached_bands, r.grid.bands) + 1))
    out = []
    if kept:
        sources, cells = r.sources(kept), r.cells("flat", kept)
        out.append(r.fold(cells.join(F.broadcast(sources) if r.fits(r.grid.n * len(kept) / r.grid.bands) else sources, cells["src"] == sources["s_vid"]), "dst"))
    if len(kept) < r.grid.bands:
        sources = r.sources(kept, others=True).withColumnRenamed("s_band", "s_block")
        out.append(r.fold(_copied(r, sources, r.grid.bands, r.cells("flat", kept, others=True), "dst_band", "src_band"), "dst"))
    return out


def psw(r: Round) -> list[DataFrame]:
    """Both sides of every band are loaded: its out-edges, the sliding windows of all columns,
    get its values written on them; then its in-edges are gathered from its own column."""
    windows = _met(r, r.cells("row"), r.sources()).select("dst_band", "src_band", "src", "dst", "msg")
    valued = write_table(windows.sortWithinPartitions("dst_band", "src", "dst"), r.temp("valued"), "dst_band")
    return [r.fold(valued.repartition("dst_band"), "dst_band", "dst").select("dst", "inc")]


def two_level(r: Round) -> list[DataFrame]:
    """As SWAP between coarse blocks, into which the fine cells are merged as they are read."""
    ratio = max(1, r.config.block)
    block = lambda c: (F.floor((F.col(c) - 1) / ratio) + 1).cast("int")
    sources = r.sources().withColumn("s_block", block("s_band"))
    cells = r.cells("flat").withColumns({"d_block": block("dst_band"), "r_block": block("src_band")})
    return [r.fold(_copied(r, sources, -(-r.grid.bands // ratio), cells, "d_block", "r_block"), "dst")]


def nbr_view(r: Round, written: bool = True) -> list[DataFrame]:
    """The view's keys are found once; its values are refreshed in each round, as a table
    (``written``) or inside the plan."""
    if "keys" not in r.kept:
        r.kept["keys"] = r.grid.flat().select(F.col("dst_band").alias("v_band"), F.col("src").alias("v_vid")).distinct().persist()
    keys, sources = r.kept["keys"], r.sources()
    view = keys.join(sources, keys["v_vid"] == sources["s_vid"]).select("v_band", "v_vid", "msg")
    if written:
        view = write_table(view, r.temp("view"))
    cells = r.cells("flat")
    return [r.fold(cells.join(view, (cells["dst_band"] == view["v_band"]) & (cells["src"] == view["v_vid"])), "dst")]


def nbr_view_lazy(r: Round) -> list[DataFrame]:
    return nbr_view(r, written=False)


def scatter(r: Round) -> list[DataFrame]:
    """The exchange comes before the fold, so nothing is combined on the way."""
    cells = r.cells("flat")
    updates = cells.join(r.sources(), cells["src"] == F.col("s_vid")).select("dst", "msg").repartition("dst")
    return [r.fold(updates, "dst")]


def flat(r: Round) -> list[DataFrame]:
    if "edges" not in r.kept:
        r.kept["edges"] = r.grid.flat().select("src", "dst").persist()
    edges = r.kept["edges"]
    return [r.fold(edges.join(F.broadcast(r.sources()) if r.fits(r.grid.n) else r.sources(), edges["src"] == F.col("s_vid")), "dst")]


def plain(r: Round) -> list[DataFrame]:
    edges = r.grid.flat().select("src", "dst")
    return [r.fold(edges.join(r.sources().hint("merge"), edges["src"] == F.col("s_vid")), "dst")]


STRATEGIES = {f.__name__: f for f in (resident, staged, hybrid, swap, psw, two_level, nbr_view, nbr_view_lazy, scatter, flat, plain)}
#: Strategies that read cells by band and may therefore leave inactive ones out.
BANDED = {"resident", "staged", "hybrid", "swap", "psw", "two_level", "nbr_view", "nbr_view_lazy"}
