"""Strongly connected components by forward colours and backward marks."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..driver import run
from ..prep.grid import EdgeGrid, regrid, transpose
from ..program import VertexProgram, with_attr
from ..storage import delete, forget, work_dir, write_table


def trim(edges: DataFrame, m: int, folder: str, tag: str, max_rounds: int = 10_000) -> tuple[DataFrame, DataFrame, int]:
    """(edges left, vertices left, number of edges) after removing, again and again, vertices
    without an in-edge or without an out-edge: each is a component of its own."""
    spark = edges.sparkSession
    for k in range(max_rounds):
        live = edges.select(F.col("src").alias("vid")).distinct().join(edges.select(F.col("dst").alias("vid")).distinct(), "vid", "left_semi")
        live = write_table(live, f"{folder}/live{tag}-{k}")
        left = edges.join(live.withColumnRenamed("vid", "src"), "src", "left_semi").join(live.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        left = write_table(left.select("src", "dst"), f"{folder}/left{tag}-{k}")
        before, m = m, left.count()
        delete(spark, f"{folder}/live{tag}-{k}")
        if k:
            delete(spark, f"{folder}/left{tag}-{k - 1}")
        edges = left
        if before == m or not m:
            return edges, edges.select(F.col("src").alias("vid")).distinct(), m
    raise RuntimeError(f"trimming is not done after {max_rounds} rounds")


def scc(grid: EdgeGrid, config: EngineConfig | None = None, max_rounds: int = 10_000) -> DataFrame:
    """(vid, attr): the least id of each vertex's strongly connected component.

    A round trims, spreads the greatest id forward as a colour, and from each colour's root
    walks backward inside the colour over the transposed grid; what it reaches is the root's
    component and leaves the graph, so the grid shrinks from round to round.
    """
    config = config or EngineConfig(strategy="resident")
    spark = grid.cells.sparkSession
    folder = work_dir(spark, "scc")
    edges, m = grid.cells.select("src", "dst"), grid.m
    found: list[DataFrame] = []
    colour = VertexProgram("colour", lambda v: with_attr(v, F.col("vid")), lambda a, d: a, F.max, lambda a, inc: F.greatest(a, inc), True)
    mark = VertexProgram("mark", lambda v: v.select("vid", "band", "out_deg", (F.col("vid") == F.col("colour")).alias("attr"), (F.col("vid") == F.col("colour")).alias("changed")), lambda a, d: a, F.bool_or, lambda a, inc: a | F.coalesce(inc, F.lit(False)), True, sends=lambda a: a)
    for k in range(max_rounds):
        edges, live, m = trim(edges, m, folder, str(k))
        if not m:
            break
        forward = regrid(grid, edges, "scc-forward", vertices=write_table(grid.vertices.join(live, "vid", "left_semi"), f"{folder}/vertices{k}"))
        colours = run(forward, colour, config).values("colour")
        c_src, c_dst = colours.withColumnsRenamed({"vid": "src", "colour": "cs"}), colours.withColumnsRenamed({"vid": "dst", "colour": "cd"})
        inside = forward.with_cells(edges.join(c_src, "src").join(c_dst, "dst").filter("cs = cd").select("src", "dst"))
        backward = transpose(replace(inside, vertices=write_table(forward.vertices.join(colours, "vid"), f"{folder}/coloured{k}")))
        marks = run(backward, mark, config).state.filter("attr").select("vid")
        done = write_table(colours.join(marks, "vid", "left_semi"), f"{folder}/done{k}")
        found.append(done)
        gone = done.select("vid")
        edges = write_table(edges.join(gone.withColumnRenamed("vid", "src"), "src", "left_anti").join(gone.withColumnRenamed("vid", "dst"), "dst", "left_anti"), f"{folder}/edges{k}")
        m = edges.count()
        for path in (f"{forward.folder}/cells", f"{forward.folder}/rows", f"{backward.folder}/cells", f"{backward.folder}/rows", f"{folder}/coloured{k}", f"{folder}/vertices{k}"):
            forget(spark, path)
    else:
        raise RuntimeError(f"components are not all found after {max_rounds} rounds")
    grouped = None
    for d in found:
        grouped = d if grouped is None else grouped.unionByName(d)
    if grouped is None:
        return grid.vertices.select("vid", F.col("vid").alias("attr"))
    least = grouped.groupBy("colour").agg(F.min("vid").alias("attr"))
    return grid.vertices.select("vid").join(grouped.join(least, "colour").select("vid", "attr"), "vid", "left").select("vid", F.coalesce("attr", "vid").alias("attr"))
