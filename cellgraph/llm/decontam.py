"""Benchmark decontamination with an Aho-Corasick automaton.

Texts are normalised to lower-case words (A-Z folded; a word is a run of digits, letters and
non-ASCII characters).  Every window of ``width`` consecutive words of a benchmark item, or
the whole item when it is shorter, is a pattern; patterns and documents are framed by single
spaces, so a pattern only matches whole words.  Each document is scanned once, and matches
are mapped back to word numbers and to byte ranges of the original text.

A task holds one automaton of at most ``max_automaton_bytes`` (``NODE_BYTES`` a pattern byte
bound it).  Patterns beyond that make further slices, which are written to the shared folder;
a task reads texts in chunks of bounded size and passes each chunk through the slices in
turn, so method and results are the same at any size of the benchmark.

Null and empty texts have no words and no hits; empty items match nothing; items with equal
windows are all reported, repeated items once.  A very long text is a chunk of its own.
Documents are passed through row by row, so repeated rows give repeated results and empty
tables give none; only the columns named are read, so other columns may have any name.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterable, Iterator

import ahocorasick
import numpy as np
import pandas as pd
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import shared_dir

WIDTH = 10
RESULT = "doc_id long, n_words long, n_hit long, item_ids array<long>, spans array<struct<begin:long,end:long>>"
#: Bytes of automaton a byte of pattern costs at most: a node and its link (as the library reports).
NODE_BYTES = 40
MAX_AUTOMATON_BYTES = 256 << 20
#: Bytes of text that meet all slices together, when there are several.
CHUNK_BYTES = 32 << 20

#: Bytes that separate words become spaces, A-Z are folded, everything else stays.
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def normal_words(raw: bytes) -> list[bytes]:
    return raw.translate(_TABLE).split()


def item_windows(text: bytes, width: int = WIDTH) -> list[bytes]:
    """The item's patterns without frames, in order."""
    found = normal_words(text)
    if not found:
        return []
    return [b" ".join(found[k : k + width]) for k in range(max(1, len(found) - width + 1))]


def slices_of(items: Iterable[tuple[int, str | None]], width: int = WIDTH, max_automaton_bytes: int = MAX_AUTOMATON_BYTES) -> Iterator[dict[bytes, set[int]]]:
    """Patterns with the ids of the items that hold them, in slices whose automaton is bounded.
    A slice is given away before the next is begun, so one is held at a time."""
    found, size = {}, 0
    for item_id, text in items:
        for window in item_windows((text or "").encode(), width):
            if window not in found:
                size += (len(window) + 2) * NODE_BYTES
                if found and size > max_automaton_bytes:
                    yield found
                    found, size = {}, (len(window) + 2) * NODE_BYTES
            found.setdefault(window, set()).add(item_id)
    yield found


def build_automaton(patterns: dict[bytes, set[int]]):
    """Automaton over byte strings held as Latin-1 text; a hit gives (number of words, item ids)."""
    machine = ahocorasick.Automaton()
    for window, items in patterns.items():
        machine.add_word(f" {window.decode('latin-1')} ", (window.count(b" ") + 1, tuple(items)))
    if patterns:
        machine.make_automaton()
    return machine


def store_slices(benchmark: DataFrame, width: int, max_automaton_bytes: int) -> tuple[str, list[str]]:
    """Write the benchmark's slices to the shared folder: (folder, file names)."""
    folder = shared_dir(benchmark.sparkSession, "decontam")
    store, root = fs.FileSystem.from_uri(folder)
    store.create_dir(root, recursive=True)
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).toLocalIterator()
    names = []
    for k, patterns in enumerate(slices_of(((r["item_id"], r["text"]) for r in rows), width, max_automaton_bytes)):
        names.append(f"slice-{k:06d}")
        with store.open_output_stream(f"{root}/{names[-1]}") as sink:
            sink.write(pickle.dumps(patterns))
    return folder, names


class Hits:
    """The words of a text and what the slices found in it so far."""

    def __init__(self, raw: bytes):
        self.folded = raw.translate(_TABLE)
        found = self.folded.split()
        self.n_words = len(found)
        self.framed = (b" " + b" ".join(found) + b" ").decode("latin-1") if found else ""
        self.ends: list[tuple[int, int]] = []  # (offset of the closing space, words)
        self.items: set[int] = set()

    def meet(self, machine) -> None:
        for end, (n, ids) in machine.iter(self.framed) if self.n_words and len(machine) else ():
            self.ends.append((end, n))
            self.items.update(ids)

    def result(self) -> tuple[int, int, list[int], list[tuple[int, int]]]:
        """(words, words hit, items found, byte ranges of the original)."""
        if not self.ends:
            return self.n_words, 0, [], []
        spaces = np.flatnonzero(np.frombuffer(self.framed.encode("latin-1"), np.uint8) == 32)
        last = np.searchsorted(spaces, [end for end, _ in self.ends])  # the space that ends word number last
        edges = np.zeros(self.n_words + 1, np.int64)
        for stop, (_, n) in zip(last.tolist(), self.ends, strict=True):
            edges[stop - n] += 1
            edges[stop] -= 1
        covered = np.cumsum(edges[:-1]) > 0
        change = np.diff(np.concatenate([[0], covered.astype(np.int8), [0]]))
        inside = np.frombuffer(self.folded, np.uint8) != 32
        turn = np.diff(np.concatenate([[0], inside.astype(np.int8), [0]]))
        begins, ends = np.flatnonzero(turn == 1), np.flatnonzero(turn == -1)
        spans = [(int(begins[a]), int(ends[b - 1])) for a, b in zip(np.flatnonzero(change == 1), np.flatnonzero(change == -1), strict=True)]
        return self.n_words, int(covered.sum()), sorted(self.items, key=lambda x: (x is None, x)), spans


class Scanner:
    """Passes texts through the slices; the automaton last used stays in memory."""

    def __init__(self, folder: str, names: list[str]):
        self.folder, self.names = folder, names
        self.loaded: str | None = None
        self.machine = None

    def _load(self, name: str):
        if name != self.loaded:
            self.machine = None  # one automaton at a time
            store, root = fs.FileSystem.from_uri(self.folder)
            with store.open_input_stream(f"{root}/{name}") as source:
                self.machine = build_automaton(pickle.loads(source.read()))
            self.loaded = name
        return self.machine

    def scan(self, texts: Iterable[bytes]) -> Iterator[tuple]:
        if len(self.names) == 1:  # text by text: nothing has to wait
            machine = self._load(self.names[0])
            for text in texts:
                found = Hits(text)
                found.meet(machine)
                yield found.result()
            return
        held = [Hits(t) for t in texts]
        # begin with the slice that is loaded
        for name in sorted(self.names, key=lambda x: x != self.loaded):
            machine = self._load(name)
            for found in held:
                found.meet(machine)
        for found in held:
            yield found.result()

    def chunks(self, batches: Iterable, size_of) -> Iterator[list]:
        """Batches together until their texts reach ``CHUNK_BYTES``; one by one for one slice."""
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += size_of(batch)
            if len(self.names) == 1 or size >= CHUNK_BYTES:
                yield held
                held, size = [], 0
        if held:
            yield held


_scanners: dict[str, Scanner] = {}


def scanner_of(folder: str, names: list[str]) -> Scanner:
    """The worker's scanner of a benchmark; another benchmark replaces it."""
    if folder not in _scanners:
        _scanners.clear()
        _scanners[folder] = Scanner(folder, names)
    return _scanners[folder]


def scan_documents(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, max_automaton_bytes: int = MAX_AUTOMATON_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each document row: ``RESULT``.  ``spans`` are byte ranges of the original text."""
    folder, names = store_slices(benchmark, width, max_automaton_bytes)

    def scan(batches):
        scanner = scanner_of(folder, names)
        for held in scanner.chunks(batches, lambda b: b.column(1).nbytes):
            rows = scanner.scan(text.as_py().encode() for batch in held for text in batch.column(1))
            for batch in held:
                own = [next(rows) for _ in range(batch.num_rows)]
                columns = list(zip(*own, strict=True)) if own else [[]] * 4
                span = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.list_(pa.int64())), pa.array([[{"begin": a, "end": b} for a, b in x] for x in columns[3]], span)],
                    names=["doc_id", "n_words", "n_hit", "item_ids", "spans"],
                )

    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    return rows.mapInArrow(scan, RESULT)


def clean_documents(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, max_automaton_bytes: int = MAX_AUTOMATON_BYTES) -> DataFrame:
    """The rows of ``docs`` (text) without any hit, with all their columns."""
    folder, names = store_slices(benchmark, width, max_automaton_bytes)

    @F.pandas_udf("boolean")
    def clean(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scanner = scanner_of(folder, names)
        for held in scanner.chunks(batches, lambda s: int(s.str.len().sum())):
            rows = scanner.scan(t.encode() for texts in held for t in texts)
            for texts in held:
                yield pd.Series([next(rows)[1] == 0 for _ in range(len(texts))], dtype=bool)

    return docs.filter(clean(F.coalesce(F.col("text").cast("string"), F.lit(""))))


def op3_aho_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    names = F.array_join(F.array_sort(F.col("item_ids").cast("array<string>")), ",")
    return found.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(names.cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


ORACLE_SQL = r"""
WITH dw AS MATERIALIZED (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), bw AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), bs AS (
  SELECT item_id, w, least(len(w), 10) AS k FROM bw WHERE len(w) > 0
), win AS (
  SELECT DISTINCT item_id, k, array_to_string(w[i + 1:i + k], ' ') AS s
  FROM (SELECT item_id, w, k, unnest(range(0, len(w) - k + 1)) AS i FROM bs)
), ks AS (SELECT DISTINCT k FROM win
), dwin AS (
  SELECT doc_id, i, k, array_to_string(w[i + 1:i + k], ' ') AS s
  FROM (SELECT doc_id, w, k, unnest(range(0, len(w) - k + 1)) AS i FROM dw, ks WHERE len(w) >= k)
), met AS MATERIALIZED (
  SELECT doc_id, i, dwin.k, item_id FROM dwin JOIN win ON dwin.k = win.k AND dwin.s = win.s
), hit AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM met) GROUP BY doc_id
), its AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM met) GROUP BY doc_id
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id)
"""
