"""Best-fit packing of documents into fixed-size token sequences, under conflicts.

A bin of ``capacity`` tokens holds at most one piece of a source and at most one piece of a
duplicate cluster.  Open bins are ordered by their residual room; each carries one bitmap of
its sources and one of its clusters.  A piece looks for the successor of its length among
the residuals and goes on to larger ones until it meets a compatible bin, which so is the
tightest; without one it opens a bin.

Pieces are packed in order of falling length, then id.  A text longer than a bin gives full
bins of its own and one remainder that is packed, so every token is placed exactly once.
Work is dealt out by a hash of the id into shards of about ``shard_tokens`` tokens, whatever
the sources and clusters; only lengths and keys move, never texts.

Null texts are empty: just the end token.  A null source or cluster conflicts with nothing.
Repeated rows are pieces of their own.  An empty table gives no rows.  A very long text is
one row of a shard until it is cut there.  Only the columns named are read, so others may
have any name.  Shard, order and so bin ids depend on the rows alone.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .exact_stream import normalised
from .storage import materialise, shared_dir

CAPACITY = 2048
SHARD_TOKENS = 4_000_000
RESULT = "doc_id long, piece int, token_begin long, n_tokens int, bin_id long, bin_offset int"


class BestFit:
    """Open bins by residual.  ``sources`` and ``clusters`` of a piece are bit numbers or -1."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.used: list[int] = []  # of each bin
        self.source_bits: list[int] = []
        self.cluster_bits: list[int] = []
        self.occupied = 0  # bit r: a bin has residual r
        self.levels: dict[int, dict[int, list[int]]] = {}  # residual -> source bitmap -> bins
        self.count: dict[int, int] = defaultdict(int)  # bins of a residual
        self.with_source: dict[tuple[int, int], int] = defaultdict(int)  # (residual, source) -> bins
        self.blocked: dict[int, int] = defaultdict(int)  # source -> bit r: all bins of residual r have it
        self.blocks: dict[int, set[int]] = defaultdict(set)  # residual -> sources it is blocked for

    @staticmethod
    def _bits(bitmap: int):
        while bitmap:
            low = bitmap & -bitmap
            yield low.bit_length() - 1
            bitmap ^= low

    def _insert(self, b: int) -> None:
        r, bits = self.capacity - self.used[b], self.source_bits[b]
        if not r:
            return
        self.levels.setdefault(r, {}).setdefault(bits, []).append(b)
        fresh = not self.count[r]
        self.count[r] += 1
        self.occupied |= 1 << r
        for s in [s for s in self.blocks[r] if not bits >> s & 1]:
            self.blocks[r].discard(s)
            self.blocked[s] &= ~(1 << r)
        for s in self._bits(bits):
            self.with_source[r, s] += 1
            if fresh:
                self.blocks[r].add(s)
                self.blocked[s] |= 1 << r

    def _remove(self, r: int, bits: int, b: int) -> None:
        level = self.levels[r]
        level[bits].remove(b)
        if not level[bits]:
            del level[bits]
        self.count[r] -= 1
        for s in self._bits(bits):
            self.with_source[r, s] -= 1
        if not self.count[r]:
            self.occupied &= ~(1 << r)
            del self.levels[r]
            for s in self.blocks.pop(r, ()):
                self.blocked[s] &= ~(1 << r)
        else:
            for s in self._bits(next(iter(level))):
                if self.with_source[r, s] == self.count[r] and s not in self.blocks[r]:
                    self.blocks[r].add(s)
                    self.blocked[s] |= 1 << r

    def _find(self, n: int, source: int, cluster: int) -> tuple[int, int, int] | None:
        room = self.occupied & ~(self.blocked[source] if source >= 0 else 0)
        room = room >> n << n
        while room:
            r = (room & -room).bit_length() - 1
            best = None
            for bits, members in self.levels[r].items():
                if source >= 0 and bits >> source & 1:
                    continue
                for b in members:
                    if (best is None or b < best[2]) and not (cluster >= 0 and self.cluster_bits[b] >> cluster & 1):
                        best = r, bits, b
                        break
            if best:
                return best
            room &= room - 1
        return None

    def place(self, n: int, source: int = -1, cluster: int = -1) -> tuple[int, int]:
        """(bin, offset) of a piece of ``n`` tokens, at most ``capacity``."""
        found = self._find(n, source, cluster)
        if found:
            r, bits, b = found
            self._remove(r, bits, b)
        else:
            b = len(self.used)
            self.used.append(0)
            self.source_bits.append(0)
            self.cluster_bits.append(0)
        at = self.used[b]
        self.used[b] += n
        if source >= 0:
            self.source_bits[b] |= 1 << source
        if cluster >= 0:
            self.cluster_bits[b] |= 1 << cluster
        self._insert(b)
        return b, at


def pack_shard(pieces: pd.DataFrame, capacity: int) -> pd.DataFrame:
    """Pack one shard: columns doc_id, piece, token_begin, n_tokens, source, cluster."""
    pieces = pieces.sort_values(["n_tokens", "doc_id", "piece"], ascending=[False, True, True], kind="stable", na_position="last")
    numbered = pd.factorize(pieces["source"])[0]  # nulls are -1
    twins = pieces["cluster"].where(pieces["cluster"].duplicated(keep=False))  # others can't conflict
    bins = BestFit(capacity)
    placed = [bins.place(int(n), int(s), int(c)) for n, s, c in zip(pieces["n_tokens"], numbered, pd.factorize(twins)[0], strict=True)]
    return pieces[["doc_id", "piece", "token_begin", "n_tokens"]].assign(bin=[b for b, _ in placed], bin_offset=[a for _, a in placed])


def token_count(text):
    """Words plus the end token; null as empty."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long") + 1


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """``RESULT`` rows from (doc_id long, n_tokens long, source string, cluster string)."""
    rows = docs.select("doc_id", "n_tokens", "source", "cluster")
    total = rows.agg(F.coalesce(F.sum("n_tokens"), F.lit(0)).alias("t")).first()["t"]
    shards = max(1, -(-int(total) // shard_tokens))
    rows = rows.withColumn("shard", F.pmod(F.xxhash64("doc_id", "cluster"), F.lit(shards)))
    names = [c.split()[0] for c in RESULT.split(", ")]

    def pack(key, frame):
        whole, rest = frame["n_tokens"] // capacity, frame["n_tokens"] % capacity
        begun = frame.assign(piece=whole, token_begin=whole * capacity, n_tokens=rest)
        out = pack_shard(begun[rest > 0], capacity)
        # full pieces come after the shared bins, in order of id and piece: the same in every run
        long = frame[whole > 0].sort_values(["doc_id", "n_tokens"], kind="stable", na_position="last")
        turns = (long["n_tokens"] // capacity).to_numpy()
        full = long.loc[long.index.repeat(turns), ["doc_id"]]
        piece = np.concatenate([np.arange(n) for n in turns]) if len(turns) else np.zeros(0, np.int64)
        bins = int(out["bin"].max()) + 1 if len(out) else 0
        full = full.assign(piece=piece, token_begin=piece * capacity, n_tokens=capacity, bin=bins + np.arange(len(piece)), bin_offset=0)
        every = pd.concat([out, full], ignore_index=True)
        return every.assign(bin_id=(int(key[0]) << 32) + every["bin"])[names]

    return rows.groupBy("shard").applyInPandas(pack, RESULT)


def fill_rate(placed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """(bins, tokens, fill): how full the bins of ``pack_documents`` are, from 0 to 1."""
    each = placed.groupBy("bin_id").agg(F.sum("n_tokens").alias("t"))
    return each.agg(F.count("*").alias("bins"), F.coalesce(F.sum("t"), F.lit(0)).alias("tokens")).withColumn("fill", F.when(F.col("bins") > 0, F.col("tokens") / (F.col("bins") * capacity)))


def pack_texts(docs: DataFrame, capacity: int = CAPACITY, shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """Pack a documents table (doc_id, text, source); clusters are texts equal but for white space."""
    text = F.col("text").cast("string")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), token_count(text).alias("n_tokens"), F.col("source").cast("string").alias("source"), F.sha2(normalised(text).cast("binary"), 256).alias("cluster"))
    return pack_documents(materialise(keyed, shared_dir(docs.sparkSession, "pack")), capacity, shard_tokens)


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_texts(spark.read.parquet(f"{sf_dir}/documents.parquet"))
