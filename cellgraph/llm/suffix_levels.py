"""Removal of repeated byte strings with a logarithmic family of suffix arrays.

A byte is removed when some ``LENGTH``-byte string that covers it also starts earlier (at a
smaller document id, or in the same document at a smaller position).

1. Texts that are equal as a whole fold to their first document; the others, if they are
   long enough, are removed as a whole.
2. Every window of ``LENGTH`` bytes is named by the least hash of the ``GRAM``-byte strings in
   it.  Neighbouring windows mostly share that name, so a document becomes runs of windows,
   and equal windows have equal names wherever they are.  Only names of two runs, or of a
   run in which the naming string occurs twice, can hold a repeated window; they are found by
   one aggregation and one join of narrow rows.
3. The bytes of these runs go to shards by name.  A map task first folds runs with the same
   bytes to the earliest, so a passage of any number of documents reaches a shard once a task.
4. In a shard the runs of all tasks fold alike and arrive in batches.  A batch gets a suffix array: its windows in byte
   order.  It is merge-scanned against each existing level, and of equal windows the later
   one is marked.  Windows not met before enter the family as level 0, and equal-sized levels
   merge into the next, so n batches make at most log2(n) levels.
5. Marked windows become byte ranges of documents, which are cut out of the texts.

:func:`remove_repeats` does so within one table, with the family of a shard in its task's
memory.  :class:`LevelIndex` keeps the families in a shared folder: every later batch meets the
levels of the former ones there.

Hashes only name and group; windows count as equal when their bytes are.  Null texts are
empty; texts under ``LENGTH`` bytes lose nothing.  Rows that repeat id and text are one
document and get the same result; of different texts under one id the order is that of their
hashes.  A null id sorts last.  An empty table gives an empty one.  Other columns are ignored,
whatever their names.  A text of any length Spark can hold is one block of work in its task,
which holds several arrays of eight bytes for each of its bytes.
"""

from __future__ import annotations

import gc
import hashlib
import json
import time
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import scan
from .storage import materialise, remove, shared_dir

LENGTH = 100
GRAM = 20
#: Bytes of runs of a shard, about, and batches a shard's runs arrive in.
SHARD_BYTES = 8 << 20
BATCHES = 4
#: Bytes of different runs that a map task holds before it ships them.
HELD_BYTES = 48 << 20
_NULL_ID = (1 << 63) - 1


# ------------------------------------------------------------------- suffix array levels


def big_endian_words(text: np.ndarray) -> np.ndarray:
    """The eight bytes at every offset as one number, so that numbers order like bytes."""
    padded = np.concatenate([text, np.zeros(8, np.uint8)])
    out = np.zeros(len(text), np.uint64)
    for k in range(8):
        out |= padded[k : k + len(text)].astype(np.uint64) << np.uint64(56 - 8 * k)
    return out


def _offsets(length: int) -> list[int]:
    """Offsets of eight-byte words that cover ``length`` bytes (8 at least)."""
    return [*range(0, length - 8, 8), length - 8]


def suffix_order(words: np.ndarray, at: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """Indices into ``at`` in the byte order of the ``length`` bytes there; stable."""
    order = np.argsort(words[at], kind="stable")
    key = words[at][order]
    group = np.cumsum(np.concatenate([[0], (key[1:] != key[:-1]).astype(np.int64)])) if len(at) else np.zeros(0, np.int64)
    open_ = np.arange(len(at))
    for off in _offsets(length)[1:]:
        g = group[open_]
        same = g[1:] == g[:-1]
        several = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(g) else np.zeros(0, bool)
        open_ = open_[several]
        if not len(open_):
            break
        g = group[open_]
        word = words[at[order[open_]] + off]
        turn = np.lexsort((word, g))
        order[open_] = order[open_][turn]
        word = word[turn]
        fresh = np.concatenate([[0], ((word[1:] != word[:-1]) | (g[1:] != g[:-1])).astype(np.int64)])
        # new numbers rise within the old group and stay below the next one's
        group[open_] = np.cumsum(fresh)
    return order


class Level:
    """Different windows in byte order: ``at`` in the text, and where each first occurs."""

    def __init__(self, words: np.ndarray, at: np.ndarray, rank: np.ndarray, size: int):
        self.words, self.at, self.rank, self.size = words, at, rank, size

    def compare(self, other_words: np.ndarray, other_at: np.ndarray, mine: np.ndarray, length: int) -> np.ndarray:
        """-1, 0, 1: window ``mine`` of this level against the other windows, element by element."""
        out = np.zeros(len(mine), np.int8)
        open_ = np.arange(len(mine))
        for off in _offsets(length):
            a, b = self.words[self.at[mine[open_]] + off], other_words[other_at[open_] + off]
            differs = a != b
            out[open_[differs]] = np.where(a[differs] < b[differs], -1, 1)
            open_ = open_[~differs]
            if not len(open_):
                break
        return out

    def lower_bound(self, words: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
        """For each window, how many of this level's are smaller."""
        first = self.words[self.at]
        key = words[at]
        lo = np.searchsorted(first, key, side="left")
        hi = np.searchsorted(first, key, side="right")
        open_ = np.flatnonzero(lo < hi)
        while len(open_):
            mid = (lo[open_] + hi[open_]) >> 1
            less = self.compare(words, at[open_], mid, length) < 0
            lo[open_[less]] = mid[less] + 1
            hi[open_[~less]] = mid[~less]
            open_ = open_[lo[open_] < hi[open_]]
        return lo

    def merged(self, other: Level, length: int) -> Level:
        """Both levels' windows (they share none) in one byte order."""
        place = self.lower_bound(other.words, other.at, length)
        return Level(np.concatenate([self.words, other.words]), np.insert(self.at, place, other.at + len(self.words)), np.insert(self.rank, place, other.rank), self.size + other.size)


class LevelFamily:
    """Suffix array levels of 1, 2, 4, ... batches.  ``rank`` numbers every window by its
    place in the order of (document, position); the later of two equal ones is marked."""

    def __init__(self, length: int = LENGTH):
        self.length = length
        self.levels: list[Level | None] = []

    def add(self, text: np.ndarray, at: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """Add the windows of ``text`` that start at ``at``; the ranks that are now known to
        be repeats of earlier windows (of this batch or of former ones)."""
        words = big_endian_words(text)
        first = np.argsort(rank, kind="stable")
        order = first[suffix_order(words, at[first], self.length)]
        at, rank = at[order], rank[order]
        # equal windows are neighbours in the suffix array, earliest first
        twin = np.arange(1, len(at))
        for off in _offsets(self.length):
            twin = twin[words[at[twin] + off] == words[at[twin - 1] + off]]
        marked = [rank[twin]]
        at, rank = np.delete(at, twin), np.delete(rank, twin)
        fresh = np.ones(len(at), bool)
        for level in self.levels:
            if level is None or not len(level.at):
                continue
            left = np.flatnonzero(fresh)
            place = level.lower_bound(words, at[left], self.length)
            inside = np.flatnonzero(place < len(level.at))
            hit = inside[level.compare(words, at[left[inside]], place[inside], self.length) == 0]
            new, old = left[hit], place[hit]
            marked.append(np.maximum(rank[new], level.rank[old]))
            level.rank[old] = np.minimum(rank[new], level.rank[old])
            fresh[new] = False
        at, rank = at[fresh], rank[fresh]
        # only bytes of new windows enter the family
        cover = np.zeros(len(words) + 1, np.int64)
        cover[at] += 1
        np.subtract.at(cover, at + self.length, 1)
        inside = np.cumsum(cover[:-1]) > 0
        carry, k = Level(words[inside], (np.cumsum(inside) - 1)[at], rank, 1), 0
        while k < len(self.levels) and self.levels[k] is not None:
            carry, self.levels[k], k = self.levels[k].merged(carry, self.length), None, k + 1
        if k == len(self.levels):
            self.levels.append(None)
        self.levels[k] = carry
        return np.concatenate(marked)


# ------------------------------------------------------------------------------ the scan


def sliding_min(a: np.ndarray, width: int) -> np.ndarray:
    """Least of each ``width`` neighbours, by doubling."""
    have, span = a, 1
    while span * 2 <= width:
        have = np.minimum(have[:-span], have[span:]) if len(have) > span else have[:0]
        span *= 2
    rest = width - span
    return np.minimum(have[:-rest], have[rest:]) if rest and len(have) > rest else have if not rest else have[:0]


#: Bits of a position in a block of texts (a string of Spark has fewer than 2^31 bytes); the
#: rest of 64 orders the strings.
_PLACE = np.uint64(31)


def window_runs(data: np.ndarray, starts: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(document, first window, windows, name, several) of each run of windows with one name.

    ``several``: the string that names the windows has more than one place in the run, as in
    periodic text, so windows of this run can equal each other.  Otherwise they can't: equal
    windows have their first least string at the same distance from their begin.
    """
    none = np.zeros(0, np.int64)
    if len(data) < length:
        return none, none, none, none, none.astype(bool)
    if len(data) >> int(_PLACE):
        raise ValueError("a block of texts of two gigabytes or more")
    h = scan.window_hashes(data, gram)
    least = sliding_min((h >> _PLACE << _PLACE) | np.arange(len(h), dtype=np.uint64), length - gram + 1)
    place = (least & np.uint64((1 << int(_PLACE)) - 1)).astype(np.int64)
    names = (h[place] >> np.uint64(1)).astype(np.int64)
    n = len(names)
    # windows that reach over the end of their document don't count
    valid = np.zeros(n + 1, np.int64)
    whole = np.flatnonzero(np.diff(starts) >= length)
    valid[starts[whole]] += 1
    valid[starts[whole + 1] - length + 1] -= 1
    inside = np.cumsum(valid[:n]) > 0
    first = inside.copy()
    first[1:] &= (names[1:] != names[:-1]) | ~inside[:-1]
    first[starts[whole]] = True
    begin = np.flatnonzero(first)
    last = inside.copy()
    last[:-1] &= first[1:] | ~inside[1:]
    end = np.flatnonzero(last) + 1
    doc = np.searchsorted(starts[:-1], begin, side="right") - 1
    # of empty documents with the same start the last one is found; it is the whole one
    return doc, begin - starts[doc], end - begin, names[begin], place[begin] != place[end - 1]


def _runs(rows: DataFrame, length: int, gram: int) -> DataFrame:
    """(id, dg, n_bytes, digest, names, loops) of rows (id, dg, text): the names of a document,
    once each, and those that occur in it more than once; ``digest`` is of the whole text."""

    def find(batches):
        for batch in batches:
            for lo, hi, data, starts in scan.blocks(batch.column(2)):
                doc, _, _, name, several = window_runs(data, starts, length, gram)
                edges = scan.by_document(np.bincount(doc, minlength=hi - lo))
                digests, names, loops = [], [], []
                for k in range(hi - lo):
                    digests.append(hashlib.blake2b(data[starts[k] : starts[k + 1]].tobytes(), digest_size=16).digest())
                    own = name[edges[k] : edges[k + 1]]
                    once, count = np.unique(own, return_counts=True)
                    again = count > 1
                    if several[edges[k] : edges[k + 1]].any():
                        again |= np.isin(once, own[several[edges[k] : edges[k + 1]]])
                    names.append(once)
                    loops.append(once[again])
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(np.diff(starts), pa.int64()), pa.array(digests, pa.binary()), *(_lists(x) for x in (names, loops))],
                    names=["id", "dg", "n_bytes", "digest", "names", "loops"],
                )

    return rows.select("id", "dg", "text").mapInArrow(find, "id long, dg long, n_bytes long, digest binary, names array<long>, loops array<long>")


def _lists(parts: list[np.ndarray]) -> pa.Array:
    offsets = scan.by_document(np.array([len(x) for x in parts], np.int64)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64), pa.int64()))


# ---------------------------------------------------------------------------- the shards

_SHIP = "shard int, ids binary, dgs binary, begins binary, sizes binary, bytes binary, cut_ids binary, cut_dgs binary, cut_begins binary, cut_ends binary"


def _ship_runs(rows: DataFrame, shards: int, length: int, gram: int) -> DataFrame:
    """Bytes of candidate runs of rows (id, dg, text, names), one row for each shard and task;
    runs with equal bytes are folded to the earliest, and the others travel as ready-made cuts.
    Without names (null in every row) all runs are candidates."""

    def ship(batches):
        held: dict[bytes, tuple] = {}
        names: dict[bytes, int] = {}
        cuts: list[tuple] = []
        size = 0

        def flush():
            by: dict[int, list] = {}
            for raw, where in held.items():
                by.setdefault(names[raw], []).append((where, raw))
            if cuts and not by:
                by[0] = []
            for k, (shard, items) in enumerate(by.items()):
                ids, dgs, begins = (np.array([w[j] for w, _ in items], np.int64) for j in range(3))
                gone = cuts if k == 0 else []
                yield pa.RecordBatch.from_arrays(
                    [pa.array([shard], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in (ids, dgs, begins, np.array([len(r) for _, r in items], np.int64))), pa.array([b"".join(r for _, r in items)], pa.binary()), *(pa.array([np.array([c[j] for c in gone], np.int64).tobytes()], pa.binary()) for j in range(4))],
                    names=[c.split()[0] for c in _SHIP.split(", ")],
                )

        for batch in batches:
            ids, dgs = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            whole = batch.column(3).null_count == batch.num_rows
            wanted, edges = (None, None) if whole else (batch.column(3).flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(batch.column(3).value_lengths().to_numpy(zero_copy_only=False))]))
            for lo, hi, data, starts in scan.blocks(batch.column(2)):
                doc, begin, count, name, _ = window_runs(data, starts, length, gram)
                bounds = scan.by_document(np.bincount(doc, minlength=hi - lo))
                shard = (scan.mix(name.view(np.uint64)) % np.uint64(shards)).astype(np.int64)
                text = data.tobytes()
                for k in range(lo, hi):
                    mine = slice(bounds[k - lo], bounds[k - lo + 1])
                    chosen = np.ones(len(name[mine]), bool) if whole else np.isin(name[mine], wanted[edges[k] : edges[k + 1]])
                    base = int(starts[k - lo])
                    for b, c, own in zip(begin[mine][chosen].tolist(), count[mine][chosen].tolist(), shard[mine][chosen].tolist(), strict=True):
                        part = text[base + b : base + b + c + length - 1]
                        here = ids[k], dgs[k], b
                        there = held.get(part)
                        if there is None:
                            held[part] = here
                            names[part] = own
                            size += len(part)
                            continue
                        if here < there:
                            held[part] = here
                            here = there
                        cuts.append((here[0], here[1], here[2], here[2] + len(part)))
                if size > HELD_BYTES:
                    yield from flush()
                    held.clear()
                    names.clear()
                    cuts.clear()
                    size = 0
        if held or cuts:
            yield from flush()

    return rows.select("id", "dg", "text", "names").mapInArrow(ship, _SHIP)


def _cut_shard(frame: pd.DataFrame, length: int, batches: int, family: LevelFamily | None = None) -> tuple[np.ndarray, ...]:
    """(ids, dgs, begins, ends) of what a shard's runs repeat, of each other and of what
    ``family`` holds already; its new windows enter the family."""
    read = lambda c: np.concatenate([np.frombuffer(x, np.int64) for x in frame[c]]) if len(frame) else np.zeros(0, np.int64)
    ids, dgs, begins, sizes = (read(c) for c in ("ids", "dgs", "begins", "sizes"))
    # in the order of (document, position) a window's rank says which is earlier; tasks fold
    # their own runs only, so runs with equal bytes of several tasks fold to the first here
    order = np.lexsort((begins, dgs, ids))
    raw, place = b"".join(frame["bytes"]), scan.by_document(sizes)
    known: dict[bytes, int] = {}
    is_first = np.zeros(len(order), bool)
    for k, (run, lo, hi) in enumerate(zip(order.tolist(), place[order].tolist(), place[order + 1].tolist(), strict=True)):
        is_first[k] = known.setdefault(raw[lo:hi], run) == run
    text = np.frombuffer(b"".join(known), np.uint8)
    del raw, known
    again, order = order[~is_first], order[is_first]
    folded = ids[again], dgs[again], begins[again], begins[again] + sizes[again]
    ids, dgs, begins, sizes = (x[order] for x in (ids, dgs, begins, sizes))
    place, windows = scan.by_document(sizes), sizes - length + 1
    rank0 = scan.by_document(windows)
    family = family or LevelFamily(length)
    marked = []
    run_batch = np.minimum(rank0[:-1] * batches // max(1, int(rank0[-1])), batches - 1)
    for turn in range(batches):
        mine = np.flatnonzero(run_batch == turn)
        if not len(mine):
            continue
        # a batch's runs are neighbours, so its bytes are a slice
        lo, hi = mine[0], mine[-1] + 1
        count = windows[lo:hi]
        step = np.arange(count.sum()) - np.repeat(scan.by_document(count)[:-1], count)
        marked.append(family.add(text[place[lo] : place[hi]], np.repeat(place[lo:hi] - place[lo], count) + step, np.arange(rank0[lo], rank0[hi])))
    flags = np.zeros(int(rank0[-1]) + 1, np.int8)
    if marked:
        flags[np.concatenate(marked)] = 1
    # neighbouring marked windows of one run make one range
    border = np.zeros(len(flags), bool)
    border[rank0[:-1]] = True
    on = flags[:-1] > 0
    prev = np.concatenate([[False], on[:-1]]) & ~border[:-1]
    nxt = np.concatenate([on[1:], [False]]) & ~border[1:]
    first, last = np.flatnonzero(on & ~prev), np.flatnonzero(on & ~nxt)
    run = np.searchsorted(rank0, first, side="right") - 1
    begin = begins[run] + first - rank0[run]
    found = ids[run], dgs[run], begin, begin + (last - first) + length
    return tuple(np.concatenate([x, y]) for x, y in zip(found, folded, strict=True))


def _free(spark: SparkSession) -> None:
    """Let Spark drop shuffle files of plans that nothing refers to any more."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def _shared_names(runs: DataFrame) -> DataFrame:
    """(id, dg, names): of each different text, the names that can hold repeated windows."""
    firsts = runs.groupBy("digest").agg(F.min(F.struct("id", "dg", "seq", "names", "loops")).alias("r")).select("r.*")
    flat = firsts.select("seq", F.explode("names").alias("name"))
    shared = flat.groupBy("name").agg(F.count("*").alias("n")).filter("n > 1").select("name")
    met = flat.join(shared, "name").groupBy("seq").agg(F.collect_list("name").alias("met"))
    looped = runs.select("id", "dg", "seq", "digest", "loops")
    least = looped.groupBy("digest").agg(F.min(F.struct("id", "dg", "seq", "loops")).alias("r")).select("r.*")
    none = F.array().cast("array<long>")
    return least.join(met, "seq", "left").select("id", "dg", F.array_union(F.coalesce("met", none), F.coalesce("loops", none)).alias("names")).filter(F.size("names") > 0)


def repeated_ranges(rows: DataFrame, folder: str, length: int = LENGTH, gram: int = GRAM, shard_bytes: int = SHARD_BYTES, batches: int = BATCHES) -> tuple[DataFrame, DataFrame]:
    """From rows (id, dg, text): (id, dg, ranges) of documents that lose some bytes, and
    (id, dg, copy) of every text, ``copy`` for those an earlier document has whole."""
    spark = rows.sparkSession
    runs = materialise(_runs(rows, length, gram).withColumn("seq", F.monotonically_increasing_id()), f"{folder}/runs")
    wanted = materialise(_shared_names(runs), f"{folder}/wanted")
    least = runs.groupBy("digest").agg(F.min(F.struct("id", "dg")).alias("least"))
    copies = runs.filter(F.col("n_bytes") >= length).select("id", "dg", "digest").distinct().join(least, "digest").filter((F.col("id") != F.col("least.id")) | (F.col("dg") != F.col("least.dg")))
    copies = materialise(copies.select("id", "dg"), f"{folder}/copies")
    remove(spark, f"{folder}/runs")
    _free(spark)
    size = wanted.agg(F.coalesce(F.sum(F.size("names")), F.lit(0)).alias("n")).first()["n"] * (length + (length - gram) // 2)
    shards = max(1, -(-int(size) // shard_bytes))

    def cut(key, frame):
        ids, dgs, begins, ends = _cut_shard(frame, length, batches)
        more = [np.concatenate([np.frombuffer(x, np.int64) for x in frame[c]]) for c in ("cut_ids", "cut_dgs", "cut_begins", "cut_ends")]
        return pd.DataFrame({k: np.concatenate([a, b]) for k, a, b in zip(("id", "dg", "begin", "end"), (ids, dgs, begins, ends), more, strict=True)})

    # rows that repeat id and text count once; the join has already laid them side by side
    texts = rows.join(wanted, ["id", "dg"]).dropDuplicates(["id", "dg"])
    cuts = _ship_runs(texts, shards, length, gram).groupBy("shard").applyInPandas(cut, "id long, dg long, begin long, end long")
    ranges = materialise(cuts.groupBy("id", "dg").agg(F.sort_array(F.collect_list(F.struct("begin", "end"))).alias("ranges")), f"{folder}/ranges")
    _free(spark)
    return ranges, copies


_PIECE = "shard int, id long, dg long, begin long, end long, level int, text binary, at binary"


class LevelIndex:
    """Suffix array levels in a shared folder, which meet the batches of later runs.

    A batch's windows go to ``shards`` by name.  In a shard they get a suffix array, are
    merge-scanned against the 100-byte windows of every level there, and what wasn't met
    before becomes a level, merged with equal-sized ones: n batches leave at most log2(n) + 1
    levels.  A level is a table bucketed by shard, so old levels aren't shuffled while bucket
    numbers agree; a row holds a shard's bytes and the places of its windows in byte order.

    All that earlier batches brought counts as earlier, whatever its ids.  A level needs about
    seven times the bytes of its texts (places and overlaps); ``shards`` is fixed with the first
    batch, and a level's row must stay under a gigabyte, or ``add`` raises before anything
    changes: take shards for the corpus to come, about one for each 64 MB of text.

    ``manifest-N.json`` names the tables of a state.  It is put in place by a rename, last of
    all, so a batch that fails leaves the former state; of two writers at once one raises.
    """

    def __init__(self, spark: SparkSession, folder: str, shards: int = 256, length: int = LENGTH, gram: int = GRAM):
        self.spark, self.folder = spark, folder.rstrip("/")
        self.state = {"shards": shards, "length": length, "gram": gram, "batches": 0, "levels": []}
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(self.folder))
        numbers = [int(f.getPath().getName()[9:-5]) for f in self._fs.listStatus(self._path(self.folder)) if f.getPath().getName().startswith("manifest-")]
        if numbers:
            found = json.loads(spark.read.text(f"{self.folder}/manifest-{max(numbers)}.json", wholetext=True).first()[0])
            if (found["length"], found["gram"]) != (length, gram):
                raise ValueError(f"the index is of {found['length']} bytes by {found['gram']}")
            self.state = found

    def _open(self, name: str) -> DataFrame:
        """A written table, bucketed also in a session that didn't write it."""
        table = f"suffix_{uuid.uuid4().hex}"
        n, place = self.state["shards"], f"{self.folder}/{name}".replace("'", "\\'")
        self.spark.sql(f"CREATE TABLE {table} ({_PIECE}) USING parquet CLUSTERED BY (shard) INTO {n} BUCKETS LOCATION '{place}'")
        self._tables.append(table)
        return self.spark.table(table)

    def levels(self) -> DataFrame:
        """(shard, level, text, at) of every level."""
        out = self.spark.createDataFrame([], _PIECE)
        for k, name in enumerate(self.state["levels"]):
            if name:
                own = self._open(name).filter("text IS NOT NULL").withColumn("level", F.lit(k))
                out = own if not any(self.state["levels"][:k]) else out.unionByName(own)
        return out.select("shard", "level", "text", "at")

    def add(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """What :func:`remove_repeats` says of a batch, with all earlier batches before it; the
        batch is in the index when this returns.  Rows and odd cases as there."""
        length, gram, shards = (self.state[k] for k in ("length", "gram", "shards"))
        filled = [bool(x) for x in self.state["levels"]]
        top = filled.index(False) if False in filled else len(filled)
        self._tables: list[str] = []
        rows = _keyed(docs, id_col, text_col)
        shipped = _ship_runs(rows.dropDuplicates(["id", "dg"]).withColumn("names", F.lit(None).cast("array<long>")), shards, length, gram)

        def meet(key, batch, old):
            family = LevelFamily(length)
            none = np.zeros(0, np.int64)
            family.levels = [Level(np.zeros(0, np.uint64), none, none, 1 << k) if f else None for k, f in enumerate(filled)]
            for level, text, at in zip(old["level"], old["text"], old["at"], strict=True):
                place = np.frombuffer(at, np.int32).astype(np.int64)
                family.levels[level] = Level(big_endian_words(np.frombuffer(text, np.uint8)), place, np.full(len(place), -1), 1 << level)
            cuts = _cut_shard(batch, length, 1, family)
            if len(batch) == 0:
                family.add(np.zeros(0, np.uint8), none, none)
            made = family.levels[top]
            if len(made.words) >> 30:
                raise ValueError("a level's shard of a gigabyte or more: the index needs more shards")
            more = [np.concatenate([none, *(np.frombuffer(x, np.int64) for x in batch[c])]) for c in ("cut_ids", "cut_dgs", "cut_begins", "cut_ends")]
            out = pd.DataFrame({k: np.concatenate([a, b]) for k, a, b in zip(("id", "dg", "begin", "end"), cuts, more, strict=True)}).astype("Int64")
            tail = pd.DataFrame({"level": [top], "text": [(made.words >> np.uint64(56)).astype(np.uint8).tobytes()], "at": [made.at.astype(np.int32).tobytes()]})
            both = pd.concat([out, tail], ignore_index=True)
            both["shard"] = key[0]
            return both[[c.split()[0] for c in _PIECE.split(", ")]]

        name = f"batch-{self.state['batches']}-{uuid.uuid4().hex[:8]}"
        table = f"suffix_{uuid.uuid4().hex}"
        try:
            met = shipped.groupBy("shard").cogroup(self.levels().groupBy("shard")).applyInPandas(meet, _PIECE)
            met.write.format("parquet").option("path", f"{self.folder}/{name}").bucketBy(shards, "shard").saveAsTable(table)
            self._tables.append(table)
            ranges = self.spark.table(table).filter("id IS NOT NULL").groupBy("id", "dg").agg(F.sort_array(F.collect_list(F.struct("begin", "end"))).alias("ranges"))
            out = rows.join(materialise(ranges, f"{self.folder}/cuts-{name}"), ["id", "dg"], "left")
            self._commit(top, name)
        finally:
            for made in self._tables:
                self.spark.sql(f"DROP TABLE IF EXISTS {made}")
        return _cut_texts(out.select(F.when(F.col("id") != _NULL_ID, F.col("id")).alias("doc_id"), "text", F.lit(False).alias("copy"), "ranges"))

    def _commit(self, top: int, name: str) -> None:
        gone = [x for x in self.state["levels"][:top] if x]
        state = dict(self.state, batches=self.state["batches"] + 1, levels=[None] * top + [name] + self.state["levels"][top + 1 :])
        draft, place = self._path(f"{self.folder}/draft-{name}"), self._path(f"{self.folder}/manifest-{state['batches']}.json")
        out = self._fs.create(draft)
        out.write(bytearray(json.dumps(state).encode()))
        out.close()
        if self._fs.exists(place) or not self._fs.rename(draft, place):
            raise RuntimeError("another batch was added at the same time")
        self.state = state
        for old in gone:
            remove(self.spark, f"{self.folder}/{old}")


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, dg, text) of ``docs``: null texts are empty, null ids sort last."""
    rows = docs.select(F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(_NULL_ID)).alias("id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    return rows.withColumn("dg", F.xxhash64("text"))


def _cut_texts(rows: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans) of rows (doc_id, text, copy, ranges)."""
    kind = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))

    def cut(batches):
        for batch in batches:
            data, edges = scan.string_parts(batch.column(1))
            copies, ranges = batch.column(2).to_pylist(), batch.column(3)
            out = []
            for k in range(batch.num_rows):
                raw = data[edges[k] : edges[k + 1]].tobytes()
                spans = []
                if copies[k]:
                    spans = [(0, len(raw))]
                elif ranges[k].is_valid:
                    for x in ranges[k].as_py():
                        if spans and x["begin"] <= spans[-1][1]:
                            spans[-1] = spans[-1][0], max(spans[-1][1], x["end"])
                        else:
                            spans.append((x["begin"], x["end"]))
                kept, at = hashlib.sha256(), 0
                for a, b in spans:
                    kept.update(raw[at:a])
                    at = b
                kept.update(raw[at:])
                out.append((len(raw), sum(b - a for a, b in spans), len(spans), kept.hexdigest(), [{"begin": a, "end": b} for a, b in spans]))
            columns = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int64(), pa.string(), kind), strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"])

    return rows.select("doc_id", "text", "copy", "ranges").mapInArrow(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<begin:long,end:long>>")


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row for each row of ``docs``: what was removed, and the digest of what is left."""
    folder = shared_dir(docs.sparkSession, "suffix")
    rows = _keyed(docs, id_col, text_col)
    ranges, copies = repeated_ranges(rows, folder, **options)
    facts = materialise(ranges.join(copies.withColumn("copy", F.lit(True)), ["id", "dg"], "full").select("id", "dg", F.coalesce("copy", F.lit(False)).alias("copy"), "ranges"), f"{folder}/facts")
    joined = rows.join(facts, ["id", "dg"], "left").select(F.when(F.col("id") != _NULL_ID, F.col("id")).alias("doc_id"), "text", F.coalesce("copy", F.lit(False)).alias("copy"), "ranges")
    return _cut_texts(joined)


def op2_suffix_level_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("spans")
