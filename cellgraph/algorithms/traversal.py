"""Breadth-first search, hop-limited reach, weakly connected components, user examples."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..driver import Result, run
from ..prep.grid import EdgeGrid, symmetric
from ..program import VertexProgram, with_attr
from ..storage import delete, work_dir, write_table


def bfs_program(root: int) -> VertexProgram:
    """Depth from ``root``; null where it isn't reached."""
    return VertexProgram(
        "bfs", lambda v: with_attr(v, F.when(F.col("vid") == root, F.lit(0).cast("long")), F.col("vid") == root), lambda a, d: a + 1, F.min, lambda a, inc: F.least(a, inc), True, sends=lambda a: a.isNotNull()
    )


def bfs(grid: EdgeGrid, root: int = 1, config: EngineConfig | None = None, **options) -> Result:
    """``root`` is an id; the first vertex unless told otherwise."""
    return run(grid, bfs_program(root), config or EngineConfig(strategy="resident"), **options)


def bfs_max_depth(result: Result) -> DataFrame:
    return result.state.agg(F.max("attr").alias("max_depth"), F.count("attr").alias("reached"))


def bfs_parents(grid: EdgeGrid, result: Result) -> DataFrame:
    """(vid, parent): the least in-neighbour one step nearer to the root."""
    depth = result.values("depth").filter("depth IS NOT NULL")
    source, target = depth.withColumnsRenamed({"vid": "src", "depth": "ds"}), depth.withColumnsRenamed({"vid": "dst", "depth": "dd"})
    return grid.cells.select("src", "dst").join(source, "src").join(target, "dst").filter("dd = ds + 1").groupBy(F.col("dst").alias("vid")).agg(F.min("src").alias("parent"))


def bfs_sql(spark: SparkSession, edges: DataFrame, root: int, limit: int | None = None, block: int = 4) -> DataFrame:
    """The same depths by recursive SQL, as an independent check.  A recursion can't see what
    earlier steps found, so it walks ``block`` steps at a time and leaves out what the blocks
    before it have reached: their rows stay in the number of vertices, whatever the depth.
    ``LIMIT ALL`` lifts the bound that Spark sets on the rows of a recursion.  With ``limit``,
    a path that is walked so many steps without meeting its end raises an error."""
    folder, tag = work_dir(spark, "bfs-sql"), uuid.uuid4().hex[:12]
    names = {part: f"cellgraph_bfs_{part}_{tag}" for part in ("edges", "front", "seen")}
    edges.createOrReplaceTempView(names["edges"])
    try:
        paths, depth = [f"{folder}/d0"], 0
        front = write_table(spark.range(1).select(F.lit(root).cast("long").alias("vid"), F.lit(0).cast("long").alias("depth")), paths[0])
        while True:
            seen = spark.read.schema(front.schema).parquet(*paths)
            if not front.limit(1).count():
                return seen
            if limit is not None and depth >= limit:
                raise RuntimeError(f"the graph is deeper than {limit} steps")
            to = depth + block if limit is None else min(depth + block, limit)
            front.createOrReplaceTempView(names["front"])
            seen.createOrReplaceTempView(names["seen"])
            found = spark.sql(
                f"""WITH RECURSIVE walk(vid, depth) MAX RECURSION LEVEL {to - depth + 2} AS (
                      SELECT vid, depth FROM {names["front"]}
                      UNION ALL
                      SELECT DISTINCT e.dst, w.depth + 1 FROM walk w JOIN {names["edges"]} e ON e.src = w.vid
                      LEFT ANTI JOIN (SELECT vid AS known FROM {names["seen"]}) ON known = e.dst WHERE w.depth < {to})
                    SELECT vid, min(depth) AS depth FROM (SELECT * FROM walk LIMIT ALL) WHERE depth > {depth} GROUP BY vid"""
            )
            paths.append(f"{folder}/d{to}")
            front, depth = write_table(found, paths[-1]).filter(F.col("depth") == to), to
    finally:
        for name in names.values():
            spark.catalog.dropTempView(name)


def hop_limited(grid: EdgeGrid, root: int, hops: int, config: EngineConfig | None = None) -> Result:
    """Vertices within ``hops`` steps: a search of so many rounds."""
    return run(grid, bfs_program(root), config or EngineConfig(strategy="resident"), rounds=hops)


def wcc(grid: EdgeGrid, config: EngineConfig | None = None, is_symmetric: bool = False, **options) -> Result:
    """Least id of the weakly connected component, by propagation over both directions."""
    both = grid if is_symmetric else symmetric(grid)
    program = VertexProgram("wcc", lambda v: with_attr(v, F.col("vid")), lambda a, d: a, F.min, lambda a, inc: F.least(a, inc), True)
    return run(both, program, config or EngineConfig(strategy="resident"), **options)


def wcc_hooking(grid: EdgeGrid, max_rounds: int = 50) -> DataFrame:
    """(vid, attr): the same labels in O(log n) rounds: roots hook onto smaller neighbouring
    labels, then pointers are jumped.  For deep graphs, where propagation takes as many
    rounds as the graph is wide."""
    spark = grid.cells.sparkSession
    folder = work_dir(spark, "hooking")
    edges = grid.cells.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    label = write_table(grid.vertices.select("vid", F.col("vid").alias("p")), f"{folder}/r0")
    for k in range(1, max_rounds + 1):
        pu, pv = label.withColumnsRenamed({"vid": "u", "p": "pu"}), label.withColumnsRenamed({"vid": "v", "p": "pv"})
        across = edges.join(pu, "u").join(pv, "v").filter("pu <> pv").select(F.greatest("pu", "pv").alias("vid"), F.least("pu", "pv").alias("h"))
        hooks = across.groupBy("vid").agg(F.min("h").alias("h"))
        hooked = label.join(hooks, "vid", "left").select("vid", F.least("p", F.coalesce("h", "p")).alias("p"))
        hooked = write_table(hooked, f"{folder}/h{k}")
        up = hooked.select(F.col("vid").alias("p"), F.col("p").alias("g"))
        nxt = write_table(hooked.join(up, "p").select("vid", F.col("g").alias("p")), f"{folder}/r{k}")
        moved = nxt.join(label.withColumnRenamed("p", "was"), "vid").filter("p <> was").limit(1).count()
        for path in (f"{folder}/r{k - 1}", f"{folder}/h{k}"):
            delete(spark, path)
        label = nxt
        if not moved:
            return label.select("vid", F.col("p").alias("attr"))
    raise RuntimeError(f"labels not settled after {max_rounds} rounds")


def in_degree_program() -> VertexProgram:
    return VertexProgram("in_degree", lambda v: with_attr(v, F.lit(0).cast("long")), lambda a, d: F.lit(1).cast("long"), F.sum, lambda a, inc: F.coalesce(inc, F.lit(0).cast("long")), False, kind="global")


def max_neighbour_program() -> VertexProgram:
    """Greatest id among the in-neighbours and the vertex itself, one round."""
    return VertexProgram("max_neighbour", lambda v: with_attr(v, F.col("vid")), lambda a, d: a, F.max, lambda a, inc: F.greatest(a, inc), False, kind="global")


def sssp(grid: EdgeGrid, weights: DataFrame, root: int = 1, max_rounds: int = 10_000) -> DataFrame:
    """(vid, dist): least sum of edge weights from ``root``; ``weights``: src, dst, w >= 0."""
    spark = grid.cells.sparkSession
    folder = work_dir(spark, "sssp")
    state = write_table(grid.vertices.select("vid", F.when(F.col("vid") == root, F.lit(0.0)).alias("dist"), (F.col("vid") == root).alias("changed")), f"{folder}/r0")
    for k in range(1, max_rounds + 1):
        front = state.filter("changed").select(F.col("vid").alias("src"), "dist")
        better = weights.join(front, "src").groupBy(F.col("dst").alias("vid")).agg(F.min(F.col("dist") + F.col("w")).alias("inc"))
        nxt = state.join(better, "vid", "left").select("vid", F.least("dist", "inc").alias("dist"), F.coalesce(F.col("inc") < F.col("dist"), F.col("inc").isNotNull()).alias("changed"))
        state = write_table(nxt, f"{folder}/r{k}")
        if k > 1:
            delete(spark, f"{folder}/r{k - 2}")
        if state.filter("changed").limit(1).count() == 0:
            return state.select("vid", "dist")
    raise RuntimeError(f"distances not settled after {max_rounds} rounds")
