"""Exact Jaccard self-join of word-shingle sets in the metric space of d = 1 - J.

1. Scan.  A document becomes the set of 64-bit hashes of its word n-grams; equal sets are
   folded to one representative.
2. Where links can be.  Two sets with J >= t share an element among the first
   n - ceil(t n) + 1 elements of each, in any fixed order of all elements.  The order takes a
   fixed share of the hash space first, by how many sets hold the element (rarest first), and
   then the rest by hash.  The share is a third more than the prefix takes (a fifth at 85 %),
   so the commonest elements can be left out; a scan ships about that share and no text.
   Elements of one set alone can't link anything and are dropped at once.
3. Pivots and regions.  For each shared element the least set that has it is the pivot; a
   pivot's region is every set that shares such an element with it.  A set near the border
   of several pivots is copied to all of their regions, so two linked sets always meet.
4. Joining a region.  Distances to the pivot are computed; what is within tau = 1 - t, its
   ball, is linked to it.  By the triangle inequality a set y outside can link with a set x of
   the ball only if d(y, p) <= d(x, p) + tau; such pairs are compared, and the ball is finished.
   The sets outside are joined recursively with a pivot of their own.  A region too large for
   a task does the same in distributed steps.
5. The links found (a spanning forest of each region) give the components.

Nothing is sampled or capped.  What is joined are the *different sets*, numbered by the row
that stands for each, never the documents' ids: rows of one id, or without id, keep their own
texts and links.  A component's number is the least id of its rows, so rows without id are in
the component of what they link with and return null only where no row of it has an id.  Null
texts are empty; sets without elements link with nothing.  A very long text is a block of its
own; empty tables give none; columns other than the two named are never read.
"""

from __future__ import annotations

import gc
import hashlib
import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import scan
from .components import connected_components
from .storage import fresh_names, materialise, remove, shared_dir

#: Near copies, unless a caller says otherwise, share 80 % of their five-word shingles.
WORDS = 5
PERCENT = 80
#: Share of the hash space whose elements are ordered by frequency, by the prefix's share.
POOL = 4 / 3
#: Sets of a region that one task joins.
REGION_SETS = 2000
#: A set held by more than this share of all rows is hot; there are fewer than its inverse.
HOT_SHARE = 0.001

_STEP = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def shingle_sets(data: np.ndarray, starts: np.ndarray, width: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct 63-bit shingle hashes of each document of a block."""
    begin, end, doc = scan.words(data, starts, scan.NOT_SPACE)
    h = scan.word_hashes(data, begin, end)
    n = len(starts) - 1
    bounds = scan.by_document(np.bincount(doc, minlength=n))
    total = np.zeros(max(0, len(h) - width + 1), np.uint64)
    for k in range(width):
        total += scan.mix(h[k : k + len(total)] + _STEP[k % 5]) * _STEP[(k + 1) % 5] if k else h[: len(total)] * _STEP[1]
    rolled = scan.mix(total) >> np.uint64(1)
    out = []
    for k in range(n):
        lo, hi = int(bounds[k]), int(bounds[k + 1])
        if hi - lo >= width:
            out.append(np.unique(rolled[lo : hi - width + 1]))
        elif hi > lo:
            seed = hashlib.blake2b(h[lo:hi].tobytes(), digest_size=8, key=b"short").digest()
            out.append(np.frombuffer(seed, np.uint64) >> np.uint64(1))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def prefix_length(n: int, percent: int = PERCENT) -> int:
    """Elements of a set of ``n`` of which a linked set must have one."""
    return n - -(-percent * n // 100) + 1 if n else 0


def pool_limit(percent: int = PERCENT) -> np.uint64:
    """Hashes below are in the pool.  A pool no larger than the prefix would leave it no choice."""
    return np.uint64(int(min(1.0, POOL * (1 - percent / 100)) * ((1 << 63) - 1)))


def _signatures(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """(doc_id, t1, t2, n, set_key, sketch) of rows (id, text, t1, t2): the elements of the pool,
    and as many more as a prefix needs."""

    limit = pool_limit(percent)

    def scan_batches(batches):
        for batch in batches:
            for lo, hi, data, starts in scan.blocks(batch.column(1)):
                sets = shingle_sets(data, starts, width)
                sketches = [s[: max(int(np.searchsorted(s, limit)), prefix_length(len(s), percent))] for s in sets]
                offsets = scan.by_document(np.array([len(s) for s in sketches], np.int64)).astype(np.int32)
                values = np.concatenate(sketches) if sketches else np.zeros(0, np.uint64)
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(k).slice(lo, hi - lo) for k in (0, 2, 3)), pa.array([len(s) for s in sets], pa.int32()), pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values.astype(np.int64)))],
                    names=["doc_id", "t1", "t2", "n", "set_key", "sketch"],
                )

    return docs.mapInArrow(scan_batches, "doc_id long, t1 long, t2 long, n int, set_key binary, sketch array<long>")


def _prefixes(reps: DataFrame, percent: int) -> DataFrame:
    """(id, v): the elements of each set's prefix that other sets have as well."""
    need = F.col("n") - F.expr(f"({percent} * n + 99) div 100") + 1
    spread = reps.select("id", need.alias("need"), F.size("sketch").alias("size"), F.explode("sketch").alias("v"))
    shared = spread.groupBy("v").agg(F.count("*").alias("df")).filter("df > 1")
    met = spread.join(shared, "v")
    order = Window.partitionBy("id").orderBy("df", "v")
    every = Window.partitionBy("id")
    ranked = met.withColumns({"rank": F.row_number().over(order), "common": F.count("*").over(every)})
    # elements of this set alone come first and use up places of the prefix
    return ranked.filter((F.col("size") == F.col("need")) | (F.col("size") - F.col("common") + F.col("rank") <= F.col("need"))).select("id", "v")


def _regions(prefixes: DataFrame) -> DataFrame:
    """(pivot, id): sets by the pivots whose region they belong to, pivots included."""
    pivots = prefixes.groupBy("v").agg(F.min("id").alias("pivot"), F.count("*").alias("sets")).filter("sets > 1").select("v", "pivot")
    return prefixes.join(pivots, "v").select("pivot", "id").distinct()


def intersections(pivot: np.ndarray, values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Size of the intersection of ``pivot`` with each of the sets laid end to end."""
    if not len(values):
        return np.zeros(len(bounds) - 1, np.int64)
    at = np.searchsorted(pivot, values)
    at[at == len(pivot)] = 0
    hit = np.concatenate([[0], np.cumsum(pivot[at] == values)])
    return hit[bounds[1:]] - hit[bounds[:-1]]


def join_region(sets: list[np.ndarray], percent: int = PERCENT, home: np.ndarray | None = None, group: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that connect exactly what all links between a set of ``home`` (None: every set) and
    any other connect.  Sets of one ``group`` (below 0: of none) count as connected already.

    Recursion written as a loop: a pivot is linked with the sets of its ball, d <= tau.  These
    are connected through it, and of the others only those with d <= 2 tau can link with them;
    once compared, the whole ball is finished and leaves.
    """
    n, tau = len(sets), 1 - percent / 100
    home = np.ones(n, bool) if home is None else home
    group = np.full(n, -1) if group is None else group
    part_of = np.arange(n)  # components so far
    for g in np.unique(group[group >= 0]):
        part_of[group == g] = np.flatnonzero(group == g)[0]
    alive, links = np.arange(n), []

    def link(x: int, y: int) -> None:
        links.append((x, y))
        part_of[part_of == part_of[y]] = part_of[x]

    def measure(p: int, to: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        bounds = scan.by_document(np.array([len(sets[k]) for k in to]))
        inter = intersections(sets[p], np.concatenate([sets[k] for k in to]), bounds)
        union = len(sets[p]) + np.diff(bounds) - inter
        return (100 * inter >= percent * union) & (inter > 0), 1 - inter / union

    while True:
        open_ = alive[home[alive]]
        if not len(open_) or (part_of[alive] == part_of[alive[0]]).all():
            return links
        p = int(open_[0])
        alive = alive[alive != p]
        met = alive if group[p] < 0 else alive[part_of[alive] != part_of[p]]
        if not len(met):
            continue
        near, d = measure(p, met)
        for k in met[near]:
            if part_of[k] != part_of[p]:
                link(p, int(k))
        inside = near & home[met]
        ball, reach = met[inside], d[inside]
        if not len(ball):
            continue
        shell = ~near & (d <= 2 * tau + 1e-9)
        for y, far in zip(met[shell], d[shell], strict=True):
            window = ball[reach >= far - tau - 1e-9]
            if part_of[y] != part_of[p] and len(window):
                found = window[measure(int(y), window)[0]]
                if len(found):
                    link(int(found[0]), int(y))
        alive = np.setdiff1d(alive, ball, assume_unique=True)


def _join_groups(rows: DataFrame, width: int, percent: int) -> DataFrame:
    """Links of rows (part, id, home, grp, text), each part joined by itself."""

    def join(batches):
        key, ids, homes, groups, sets = None, [], [], [], []

        def close():
            links = join_region(sets, percent, np.array(homes, bool), np.array(groups, np.int64)) if len(sets) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([ids[a] for a, _ in links], pa.int64()), pa.array([ids[b] for _, b in links], pa.int64())], names=["a", "b"])

        for batch in batches:
            parts, own, marks, grps = (batch.column(k).to_pylist() for k in range(4))
            for lo, _, data, starts in scan.blocks(batch.column(4)):
                for k, found in enumerate(shingle_sets(data, starts, width), lo):
                    if parts[k] != key:
                        if ids:
                            yield close()
                        key, ids, homes, groups, sets = parts[k], [], [], [], []
                    ids.append(own[k])
                    homes.append(marks[k])
                    groups.append(grps[k])
                    sets.append(found)
        if ids:
            yield close()

    laid = rows.select("part", "id", "home", "grp", "text").repartition("part").sortWithinPartitions("part", "id")
    return laid.mapInArrow(join, "a long, b long")


def _distances(rows: DataFrame, width: int) -> DataFrame:
    """(region, pivot, id, n, inter, total) of rows (region, pivot, id, text, pivot_text)."""

    def measure(batches):
        for batch in batches:
            known: dict = {}
            first, texts = batch.column(1).to_pylist(), batch.column(4)
            for k, p in enumerate(first):
                if p not in known:
                    raw = np.frombuffer(texts[k].as_py().encode(), np.uint8)
                    known[p] = shingle_sets(raw, np.array([0, len(raw)]), width)[0]
            sizes, inter, total = [], [], []
            for lo, _, data, starts in scan.blocks(batch.column(3)):
                for k, s in enumerate(shingle_sets(data, starts, width), lo):
                    same = int(intersections(known[first[k]], s, np.array([0, len(s)]))[0])
                    sizes.append(len(s))
                    inter.append(same)
                    total.append(len(s) + len(known[first[k]]) - same)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(3)), *(pa.array(x, pa.int64()) for x in (sizes, inter, total))], names=["region", "pivot", "id", "n", "inter", "total"])

    return rows.select("region", "pivot", "id", "text", "pivot_text").mapInArrow(measure, "region long, pivot long, id long, n long, inter long, total long")


def _plain(part: Column, home: Column | bool = True) -> list[Column]:
    return [part.alias("part"), F.col("id"), (F.lit(home) if isinstance(home, bool) else home).alias("home"), F.lit(-1).cast("long").alias("grp")]


def _settle_large(large: DataFrame, texts: DataFrame, folder: str, width: int, percent: int, limit: int, max_levels: int) -> tuple[list[DataFrame], list[DataFrame]]:
    """(links, parts to join) of regions (pivot, id) with more than ``limit`` sets.

    :func:`join_region` in distributed steps: each level links every large region's least set
    with its ball, compares the ball with the shell around it in blocks, and goes on with what
    is outside the ball, in one part once that is small.  After ``max_levels`` the rest is cut
    by size (linked sets differ by no more than the threshold's factor, so a set meets its own
    band of sizes and the next) and the bands are joined by pairs of blocks, which is exact
    whatever their shape.
    """
    tau = 1 - percent / 100
    links, parts = [], []
    now = large.select(F.col("pivot").alias("region"), "id")
    for level in range(max(1, max_levels)):
        least = now.groupBy("region").agg(F.min("id").alias("pivot"))
        centre = least.join(texts.withColumnRenamed("id", "pivot"), "pivot").withColumnRenamed("text", "pivot_text")
        measured = _distances(now.join(texts, "id").join(centre, "region").filter("id <> pivot"), width)
        measured = measured.withColumns({"near": F.expr(f"inter > 0 AND 100 * inter >= {percent} * total"), "d": 1 - F.col("inter") / F.col("total")})
        done = materialise(measured.withColumn("shell", ~F.col("near") & (F.col("d") <= 2 * tau + 1e-9)), f"{folder}/level{level}")
        links.append(done.filter("near").select(F.col("pivot").alias("a"), F.col("id").alias("b")))

        blocks_of = lambda c: F.ceil(F.sum(F.when(F.col(c), 1)) / limit).cast("int")
        met = done.groupBy("region").agg(F.min(F.when(F.col("shell"), F.col("d"))).alias("lo"), blocks_of("near").alias("balls"), blocks_of("shell").alias("shells")).filter("balls > 0 AND shells > 0")
        sides = []
        for inside, mine, others in ((True, "balls", "shells"), (False, "shells", "balls")):
            side = done.filter(F.col("near") if inside else F.col("shell")).join(met, "region").filter((F.col("d") >= F.col("lo") - tau - 1e-9) | F.lit(not inside))
            side = side.withColumn("own", F.pmod(F.xxhash64("id"), F.col(mine)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col(others) - 1)))
            place = ("own", "other") if inside else ("other", "own")
            sides.append(side.select(F.concat_ws(":", "region", F.lit(level), *place).alias("part"), "id", F.lit(inside).alias("home"), (F.col("pivot") if inside else F.lit(-1).cast("long")).alias("grp")))
        parts.append(sides[0].unionByName(sides[1]))

        rest = done.filter("NOT near").select("region", "id", "n")
        sizes = rest.groupBy("region").agg((F.count("*") > limit).alias("large"))
        rest = materialise(rest.join(sizes, "region"), f"{folder}/rest{level}")
        parts.append(rest.filter("NOT large").select(*_plain(F.concat_ws(":", "region", F.lit(level)))))
        now = rest.filter("large").select("region", "id", "n")
        if now.isEmpty():
            return links, parts
    step = math.log(100 / percent) + 1e-9
    band = F.floor(F.log(F.col("n").cast("double")) / step)
    banded = now.select("region", "id", F.explode(F.array(F.struct(band.alias("band"), F.lit(True).alias("home")), F.struct((band + 1).alias("band"), F.lit(False).alias("home")))).alias("b")).select("region", "id", "b.*")
    sizes = banded.groupBy("region", "band").agg(F.ceil(F.count("*") * 2 / limit).cast("int").alias("blocks"), F.bool_or("home").alias("any")).filter("any")
    cut = banded.join(sizes, ["region", "band"]).withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    pairs = cut.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    parts.append(pairs.select(*_plain(F.concat_ws(":", "region", F.lit("pair"), "band", F.least("own", "other"), F.greatest("own", "other")), F.col("home"))))
    return links, parts


def _free(spark: SparkSession) -> None:
    """Let Spark drop shuffle files of plans that nothing refers to any more."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def _attach(rows: DataFrame, keys: DataFrame, hot: DataFrame, on: str) -> DataFrame:
    """``rows`` left-joined with ``keys`` on ``on``.  ``hot``, the keys of more than ``HOT_SHARE``
    of all rows, are fewer than its inverse at any size: they are broadcast, so no task gets
    all rows of one."""
    often = keys.join(F.broadcast(hot), on, "left_semi")
    seldom = rows.join(F.broadcast(hot), on, "left_anti")
    return seldom.join(keys.hint("merge"), on, "left").unionByName(rows.join(F.broadcast(often), on))


def _numbered(docs: DataFrame, id_col: str, text_col: str, width: int, percent: int, region_sets: int, max_levels: int) -> DataFrame:
    """(t1, t2, doc_id, n, component_id, keeper) of each row of ``docs``; ``keeper``: the number
    of the set whose row stays of the component, and ``own``: that of the row's set."""
    spark = docs.sparkSession
    folder = shared_dir(spark, "jaccard")
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), text.alias("text"), F.xxhash64(text).alias("t1"), F.xxhash64(F.lit(1), text).alias("t2"))
    # the number is written with the row: it can't change when a lost task is run again
    sketched = materialise(_signatures(rows, width, percent).withColumn("rid", F.monotonically_increasing_id()), f"{folder}/sketches")
    reps = sketched.filter("n > 0").groupBy("set_key").agg(F.min(F.struct("rid", "n", "sketch")).alias("r")).select(F.col("r.rid").alias("id"), "r.n", "r.sketch")
    regions = materialise(_regions(_prefixes(reps, percent)), f"{folder}/regions")
    marks = materialise(sketched.drop("sketch"), f"{folder}/marks")
    remove(spark, f"{folder}/sketches")
    _free(spark)

    sizes = regions.groupBy("pivot").agg(F.count("*").alias("sets"))
    over = materialise(sizes.filter(F.col("sets") > region_sets).select("pivot"), f"{folder}/over")
    has_large = not over.isEmpty()
    few = regions.join(over, "pivot", "left_anti") if has_large else regions
    # a few wanted texts could be broadcast, many can't; the merge joins are the same at every size
    wanted = marks.join(regions.select(F.col("id").alias("rid")).distinct().hint("merge"), "rid", "left_semi").select(F.col("rid").alias("node"), F.col("doc_id").alias("w_id"), F.col("t1").alias("w1"), F.col("t2").alias("w2"))
    same = F.col("id").eqNullSafe(F.col("w_id")) & (F.col("t1") == F.col("w1")) & (F.col("t2") == F.col("w2"))
    texts = materialise(rows.join(wanted.hint("merge"), same).dropDuplicates(["node"]).select(F.col("node").alias("id"), "text"), f"{folder}/texts")
    _free(spark)
    parts = [few.select(*_plain(F.col("pivot").cast("string")))]
    links = []
    if has_large:
        more_links, more_parts = _settle_large(regions.join(over, "pivot", "left_semi"), texts, folder, width, percent, region_sets, max_levels)
        links, parts = more_links, parts + more_parts
    together = parts[0]
    for p in parts[1:]:
        together = together.unionByName(p)
    found = _join_groups(together.hint("merge").join(texts, "id"), width, percent)
    for more in links:
        found = found.unionByName(more)
    edges = materialise(found, f"{folder}/links")
    remove(spark, f"{folder}/texts")
    _free(spark)
    component = connected_components(edges)

    # of a component the row with the least id stays; of equal ids the first row, nulls last
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "rid")
    keys = materialise(marks.filter("n > 0").groupBy("set_key").agg(F.min("rid").alias("node"), F.min(first).alias("first"), F.count("*").alias("held")), f"{folder}/keys")
    labelled = keys.join(component.hint("merge"), "node", "left").select("set_key", "held", "first", F.coalesce("component", "node").alias("c"))
    # only sets that hold several rows or are linked need an answer from others
    several = labelled.groupBy("c").agg(F.min("first").alias("least"), F.sum("held").alias("rows")).filter("rows > 1")
    answers = materialise(labelled.join(several.hint("merge"), "c").select("set_key", "held", F.col("least.doc_id").alias("component_id"), F.col("least.rid").alias("keeper")), f"{folder}/answers")
    total = marks.count()
    hot = answers.filter(F.col("held") > HOT_SHARE * total).select("set_key")
    met = _attach(marks.filter("n > 0"), answers.drop("held"), hot, "set_key")
    alone = marks.filter("n = 0").withColumns({"component_id": F.lit(None).cast("long"), "keeper": F.lit(None).cast("long")})
    shown = [F.when(F.col("keeper").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), F.coalesce("keeper", "rid").alias("keeper")]
    return met.unionByName(alone).select("doc_id", "t1", "t2", "n", "rid", *shown)


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WORDS, percent: int = PERCENT, region_sets: int = REGION_SETS, max_levels: int = 4) -> DataFrame:
    """(doc_id, n_shingles, component_id) of each row of ``docs``."""
    found = _numbered(docs, id_col, text_col, width, percent, region_sets, max_levels)
    return found.select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id")


def keep_one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WORDS, percent: int = PERCENT, region_sets: int = REGION_SETS, max_levels: int = 4) -> DataFrame:
    """The rows of ``docs`` that stay, one of each component, with all their columns.

    Rows go by (id, text), so a repeated id takes no other text along; rows that agree in
    both are one row.
    """
    spark = docs.sparkSession
    found = materialise(_numbered(docs, id_col, text_col, width, percent, region_sets, max_levels), shared_dir(spark, "near"))
    names = fresh_names(docs, "id", "t1", "t2", "gone_id", "gone1", "gone2")
    own_id, own1, own2, gone_id, gone1, gone2 = names
    mine = F.col("keeper") == F.col("rid")
    by_row = found.groupBy(F.col("doc_id").alias(gone_id), F.col("t1").alias(gone1), F.col("t2").alias(gone2)).agg(F.bool_or(mine).alias("stay"), F.bool_or(~mine).alias("go"))
    gone = by_row.filter("go").drop("stay", "go")
    # a row that stays may have twins among these: one of them comes back
    twins = by_row.filter("go AND stay").drop("stay", "go")
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    rows = docs.withColumns({own_id: F.col(f"`{id_col}`").cast("long"), own1: F.xxhash64(text), own2: F.xxhash64(F.lit(1), text)})
    same = F.col(own_id).eqNullSafe(F.col(gone_id)) & (F.col(own1) == F.col(gone1)) & (F.col(own2) == F.col(gone2))
    out = rows.join(gone.hint("merge"), same, "left_anti")
    if not twins.isEmpty():
        out = out.unionByName(rows.join(twins, same, "left_semi").dropDuplicates([own_id, own1, own2]))
    return out.drop(*names)


def op7_metric_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet"), width=4, percent=85)


ORACLE_SQL = r"""
WITH RECURSIVE w AS MATERIALIZED (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), s AS MATERIALIZED (
  SELECT DISTINCT doc_id, array_to_string(ws[i + 1:i + least(len(ws), 4)], ' ') AS g
  FROM (SELECT doc_id, ws, unnest(range(0, greatest(len(ws) - 3, 1))) AS i FROM w WHERE len(ws) > 0)
), n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), p AS MATERIALIZED (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2
), e AS MATERIALIZED (
  SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 85 * (x.n + y.n - k)
), u AS MATERIALIZED (SELECT a, b FROM e UNION ALL SELECT b, a FROM e
), r(node, root) AS (
  SELECT doc_id, doc_id FROM documents UNION SELECT u.b, r.root FROM r JOIN u ON u.a = r.node
)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT node, min(root) AS component_id FROM r GROUP BY node) c ON c.node = d.doc_id
"""
