"""N-gram language model in an Elias-Fano trie, memory-mapped by the tasks that score.

Level 1 holds the words: their 64-bit hashes as an Elias-Fano sequence, counts in one byte
(larger ones in an exception list) and the back-off mass of the word as a context.  Levels 2
to ``order`` are a trie: an entry is the 32-bit code of a word that followed the entry above
it, pointers into the next level are an Elias-Fano sequence, and so are the codes, made
monotone by the number of the entry above, so a query is a successor search between two
pointers, relative to its context.  Probabilities are quantised to one byte each, uniformly
in their logarithm; entries that are contexts carry their back-off mass.

Smoothing: p(w) = (c + 0.1) / (N + 0.1 (V + 1)) for one word, and for a context h, h' being h
without its first word, p(w | h) = kept(h, w) + backoff(h) p(w | h'), where kept = (c(h, w) - D)
/ c(h) for everything seen (``min_count`` prunes words after words on request only), and
backoff(h) = 1 - sum of kept, taken from the *quantised* values, so that each context's
probabilities sum to one.  D is below 1, so what was seen once keeps a share of its own.

All counting is distributed and covers every training row.  A map task sorts and adds up
its own n-grams, and ships, for each shard, one compact block of keys and counts; a reduce
task merges the blocks of a shard and writes its part of the trie as one file in the shared
folder.  An n-gram's shard comes from its first word; words counted more often than a share
of a shard are spread by the second word too, over as many shards as their counts ask for,
so no task holds more than a bounded part.  The driver sees one manifest row a shard and the
frequent words, of which there are a few a shard.  Scoring maps the shard files into memory;
pages that aren't used aren't read.

Words are runs of bytes other than ASCII white space, with A-Z folded; every text has one
end token more.  Null texts are empty; repeated rows count and are scored each; an empty
table gives an empty model or no rows.  A very long text is a block of its own.  Only the
columns named are read, so others may have any name.  Words are told apart by 64-bit hashes
(a collision among ten million words has a chance of 3 in a million), continuations of one
context by 32 bits.
"""

from __future__ import annotations

import json
import os
import tempfile
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import scan
from .langid import held_out
from .storage import materialise, shared_dir

#: Hashes of the end token and of the context before the first word; no word has a blank.
END = np.uint64(scan.hash_bytes(b" end"))
START = np.uint64(scan.hash_bytes(b" start"))
MIN_COUNT = 1
DISCOUNT = 0.75
ORDER = 3
SHARD_BYTES = 16 << 20
FLUSH_TOKENS = 1_500_000
#: Bytes of text that are scored together: each distinct n-gram of them is looked up once.
SCORE_BLOCK = 4 << 20
#: A word counted more often than this share of a shard's tokens is spread over several.
HOT_SHARE = 0.25

_SELECT8 = np.zeros((256, 8), np.uint8)
for _b in range(256):
    _at = [k for k in range(8) if _b >> k & 1]
    _SELECT8[_b, : len(_at)] = _at


def _select_in_word(word: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Position of set bit number ``r`` of each 64-bit word."""
    word, r = word.copy(), r.astype(np.int64)
    pos = np.zeros(len(word), np.int64)
    for width in (32, 16, 8):
        low = word & np.uint64((1 << width) - 1)
        ones = np.bitwise_count(low).astype(np.int64)
        up = r >= ones
        r = np.where(up, r - ones, r)
        word = np.where(up, word >> np.uint64(width), low)
        pos += np.where(up, width, 0)
    return pos + _SELECT8[(word & np.uint64(255)).astype(np.int64), r]


class EliasFano:
    """A non-decreasing sequence of 64-bit numbers: low bytes as they are, upper parts in
    unary with rank directories.  All queries take and give arrays."""

    FIELDS = ("low", "high", "ones", "zeros")

    def __init__(self, n: int, low_bytes: int, low, high, ones, zeros):
        self.n, self.low_bytes = n, low_bytes
        self.low, self.high, self.ones, self.zeros = low, high, ones, zeros

    @classmethod
    def build(cls, values: np.ndarray, low_bytes: int | None = None) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        top = int(values[-1]) + 1 if n else 1
        bits = max(0, (top // max(1, n)).bit_length() - 1)
        size = min(7, -(-bits // 8)) if low_bytes is None else low_bytes
        low = values.astype("<u8").view(np.uint8).reshape(n, 8)[:, :size].copy() if n else np.zeros((0, size), np.uint8)
        upper = (values >> np.uint64(8 * size)).astype(np.int64)
        at = upper + np.arange(n)
        length = (int(upper[-1]) if n else 0) + n + 1
        marks = np.zeros(-(-(length + 1) // 64) * 64, np.uint8)
        marks[at] = 1
        high = np.packbits(marks, bitorder="little").view("<u8").astype(np.uint64)
        per = np.bitwise_count(high).astype(np.int64)
        ones = np.concatenate([[0], np.cumsum(per)])
        return cls(n, size, low, high, ones, np.arange(len(ones)) * 64 - ones)

    def parts(self) -> dict[str, np.ndarray]:
        return {k: getattr(self, k) for k in self.FIELDS}

    def _low(self, i: np.ndarray) -> np.ndarray:
        out = np.zeros(len(i), np.uint64)
        rows = self.low[i]
        for k in range(self.low_bytes):
            out |= rows[:, k].astype(np.uint64) << np.uint64(8 * k)
        return out

    def access(self, i: np.ndarray) -> np.ndarray:
        """The values at positions ``i``."""
        i = np.asarray(i, np.int64)
        w = np.searchsorted(self.ones, i, side="right") - 1
        pos = w * 64 + _select_in_word(self.high[w], i - self.ones[w])
        return ((pos - i).astype(np.uint64) << np.uint64(8 * self.low_bytes)) | self._low(i)

    def _before(self, upper: np.ndarray) -> np.ndarray:
        """How many values have an upper part below ``upper``."""
        total = int(self.zeros[-1])
        out = np.where(upper > total, self.n, 0)
        some = np.flatnonzero((upper > 0) & (upper <= total))
        j = upper[some] - 1  # the zero that closes the bucket before
        w = np.searchsorted(self.zeros, j, side="right") - 1
        pos = w * 64 + _select_in_word(~self.high[w], j - self.zeros[w])
        out[some] = np.minimum(pos - j, self.n)
        return out

    def successor(self, x: np.ndarray, lo=None, hi=None) -> np.ndarray:
        """Position of the first value >= ``x`` among positions lo..hi (hi if there is none)."""
        x = np.asarray(x, np.uint64)
        upper = (x >> np.uint64(8 * self.low_bytes)).astype(np.int64)
        a, b = self._before(upper), self._before(upper + 1)
        if lo is not None:
            a, b = np.clip(a, lo, hi), np.clip(b, lo, hi)
        want = x & np.uint64((1 << (8 * self.low_bytes)) - 1)
        open_ = np.flatnonzero(a < b)
        while len(open_):
            mid = (a[open_] + b[open_]) >> 1
            less = self._low(mid) < want[open_]
            a[open_[less]] = mid[less] + 1
            b[open_[~less]] = mid[~less]
            open_ = open_[a[open_] < b[open_]]
        return a

    def find(self, x: np.ndarray, lo=None, hi=None) -> np.ndarray:
        """Position of each ``x``, or -1."""
        x = np.asarray(x, np.uint64)
        out = np.full(len(x), -1, np.int64)
        if not self.n or not len(x):
            return out
        at = self.successor(x, lo, hi)
        limit = self.n if hi is None else hi
        inside = np.flatnonzero(at < limit)
        hit = self.access(at[inside]) == x[inside]
        out[inside[hit]] = at[inside[hit]]
        return out


def find_code(ef: EliasFano, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Position of each 32-bit code among the entries lo..hi of its context, or -1.  Within a
    context the values' upper parts are one and the same, so the successor search compares
    the four low bytes alone."""
    low = ef.low.reshape(-1).view("<u4") if ef.n else np.zeros(0, np.uint32)
    a, b = lo.copy(), hi.copy()
    open_ = np.flatnonzero(a < b)
    while len(open_):
        mid = (a[open_] + b[open_]) >> 1
        less = low[mid] < codes[open_]
        a[open_[less]] = mid[less] + 1
        b[open_[~less]] = mid[~less]
        open_ = open_[a[open_] < b[open_]]
    out = np.full(len(codes), -1, np.int64)
    inside = np.flatnonzero(a < hi)
    hit = inside[low[a[inside]] == codes[inside]]
    out[hit] = a[hit]
    return out


# ---------------------------------------------------------------------------- level files


def write_arrays(folder: str, name: str, meta: dict, arrays: dict[str, np.ndarray]) -> str:
    """One file: a JSON head, then the arrays at multiples of 64 bytes.  Renamed when whole."""
    store, root = fs.FileSystem.from_uri(folder)
    store.create_dir(root, recursive=True)
    layout, at = {}, 0
    for key, a in arrays.items():
        layout[key] = (a.dtype.str, a.shape, at)
        at += -(-a.nbytes // 64) * 64
    head = json.dumps({"meta": meta, "layout": layout}).encode()
    head += b" " * (-(len(head) + 8) % 64)
    final = f"{name}-{uuid.uuid4().hex[:8]}.ef"
    with store.open_output_stream(f"{root}/{final}.part") as sink:
        sink.write(len(head).to_bytes(8, "little") + head)
        for a in arrays.values():
            sink.write(np.ascontiguousarray(a).tobytes() + b"\0" * (-a.nbytes % 64))
    store.move(f"{root}/{final}.part", f"{root}/{final}")
    return final


def map_arrays(folder: str, name: str) -> tuple[dict, dict[str, np.ndarray]]:
    """Map a file into memory.  From a store that can't be mapped it is copied to a local
    file first, which has no name any more once it is mapped."""
    store, root = fs.FileSystem.from_uri(folder)
    path = f"{root}/{name}"
    if isinstance(store, fs.LocalFileSystem):
        raw = np.memmap(path, np.uint8, "r")
    else:
        with tempfile.NamedTemporaryFile(delete=False) as copy, store.open_input_stream(path) as source:
            while part := source.read(8 << 20):
                copy.write(part)
        raw = np.memmap(copy.name, np.uint8, "r")
        os.unlink(copy.name)
    size = int.from_bytes(raw[:8].tobytes(), "little")
    head = json.loads(raw[8 : 8 + size].tobytes())
    out = {}
    for key, (kind, shape, at) in head["layout"].items():
        n = int(np.prod(shape)) * np.dtype(kind).itemsize
        out[key] = raw[8 + size + at : 8 + size + at + n].view(kind).reshape(shape) if n else np.zeros(shape, kind)
    return head["meta"], out


def _pack_ef(prefix: str, ef: EliasFano, meta: dict, arrays: dict) -> None:
    meta[prefix] = (ef.n, ef.low_bytes)
    arrays |= {f"{prefix}.{k}": v for k, v in ef.parts().items()}


def _open_ef(prefix: str, meta: dict, arrays: dict) -> EliasFano:
    return EliasFano(*meta[prefix], *(arrays[f"{prefix}.{k}"] for k in EliasFano.FIELDS))


# ------------------------------------------------------------------------------- counting


def text_tokens(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(token hashes with each document's end token, offsets of the documents)."""
    begin, end, doc = scan.words(data, starts, scan.NOT_SPACE)
    n = len(starts) - 1
    own = np.bincount(doc, minlength=n)
    offsets = scan.by_document(own + 1)
    out = np.empty(offsets[-1], np.uint64)
    out[np.arange(len(begin)) + doc] = scan.word_hashes(data, begin, end)
    out[offsets[1:] - 1] = END
    return out, offsets


def with_starts(tokens: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(tokens with a start mark before each document, offsets of the documents in them)."""
    n = len(offsets) - 1
    wide = offsets + np.arange(n + 1)
    out = np.empty(len(tokens) + n, np.uint64)
    out[wide[:-1]] = START
    out[np.arange(len(tokens)) + np.repeat(np.arange(n), np.diff(offsets)) + 1] = tokens
    return out, wide


def code_of(token: np.ndarray) -> np.ndarray:
    """32-bit code of a continuation; 0 is kept for none."""
    return np.maximum((token >> np.uint64(32)).astype(np.uint32), np.uint32(1))


class Dealer:
    """Which shard an n-gram belongs to: by its first word, and for frequent first words by
    the second one's code too.  ``often`` are those words, sorted, ``ways`` over how many."""

    def __init__(self, shards: int, often: np.ndarray, ways: np.ndarray):
        self.shards, self.often, self.ways = shards, often, ways

    def shard(self, context: np.ndarray, code: np.ndarray | None = None) -> np.ndarray:
        key = context
        if code is not None and len(self.often):
            at = np.minimum(np.searchsorted(self.often, context), len(self.often) - 1)
            ways = np.where(self.often[at] == context, self.ways[at], 1)
            key = context + (code.astype(np.uint64) % ways.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        return (scan.mix(key) % np.uint64(self.shards)).astype(np.int64)


def even_keys(spark: SparkSession, n: int) -> np.ndarray:
    """A number for each of ``n`` shards, such that Spark's hash deals them to different ones of
    ``n`` partitions: with their own numbers some partitions would get several shards."""
    tries = n * (20 + 2 * n.bit_length())
    found = spark.range(tries).select(F.col("id").cast("int").alias("k"), F.pmod(F.hash(F.col("id").cast("int")), F.lit(n)).alias("p")).groupBy("p").agg(F.min("k").alias("k")).collect()
    out = np.arange(n, dtype=np.int64) + tries  # a partition that no try met gets some number of its own
    for r in found:
        out[r["p"]] = r["k"]
    return out


def _small(counts: np.ndarray) -> bytes:
    """Counts in the narrowest unsigned type, marked by its size."""
    top = int(counts.max()) if len(counts) else 0
    kind = np.uint8 if top < 1 << 8 else np.uint32 if top < 1 << 32 else np.uint64
    return bytes([np.dtype(kind).itemsize]) + counts.astype(kind).tobytes()


def _from_small(raw: bytes) -> np.ndarray:
    return np.frombuffer(raw, {1: np.uint8, 4: np.uint32, 8: np.uint64}[raw[0]], offset=1).astype(np.int64)


BLOCK_SCHEMA = "place int, shard int, a binary, b binary, c binary, d binary"


def _block_batch(rows: list[tuple], places: np.ndarray) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(places[list(cols[0])], pa.int32()), pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["place", "shard", "a", "b", "c", "d"])


def _by_owner(own: np.ndarray, shards: int):
    order = np.argsort(own, kind="stable")
    edges = np.searchsorted(own[order], np.arange(shards + 1))
    for s in range(shards):
        part = order[edges[s] : edges[s + 1]]
        if len(part):
            yield s, part


def _word_blocks(tokens: np.ndarray, dealer: Dealer):
    key, count = np.unique(tokens, return_counts=True)
    for s, part in _by_owner(dealer.shard(key), dealer.shards):
        yield s, key[part].tobytes(), _small(count[part]), b"", b""


def _distinct(columns: list[np.ndarray], bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions of the first of each distinct row, how many there are), in order of the rows."""
    if bits * len(columns) <= 64:
        key = columns[0].astype(np.uint64)
        for c in columns[1:]:
            key = (key << np.uint64(bits)) | c.astype(np.uint64)
        order = np.argsort(key, kind="stable")
        key = key[order]
        fresh = key[1:] != key[:-1]
    else:
        order = np.lexsort(columns[::-1])
        fresh = np.zeros(max(0, len(order) - 1), bool)
        for c in columns:
            c = c[order]
            fresh |= c[1:] != c[:-1]
    first = np.flatnonzero(np.concatenate([[True], fresh])) if len(order) else np.zeros(0, np.int64)
    return order[first], np.diff(np.append(first, len(order)))


def _gram_blocks(wide: np.ndarray, offsets: np.ndarray, order: int, dealer: Dealer):
    """Blocks of the n-grams that begin at each place of a document, cut off at its end."""
    vocabulary, rank = np.unique(wide, return_inverse=True)
    rank = rank.astype(np.int64) + 1  # 0: beyond the end
    left = np.repeat(offsets[1:], np.diff(offsets)) - np.arange(len(wide))
    columns = [rank]
    for k in range(1, order):
        nxt = np.zeros(len(wide), np.int64)
        nxt[: max(0, len(wide) - k)] = rank[k:]
        nxt[left <= k] = 0
        columns.append(nxt)
    first, count = _distinct(columns, int(len(vocabulary)).bit_length())
    codes = np.concatenate([[0], code_of(vocabulary)]).astype(np.uint32)
    context = vocabulary[columns[0][first] - 1]
    parts = [codes[c[first]] for c in columns[1:]]
    for s, part in _by_owner(dealer.shard(context, parts[0]), dealer.shards):
        own = context[part]
        turn = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        yield s, own[turn].tobytes(), _small(np.diff(np.append(turn, len(own)))), b"".join(c[part].tobytes() for c in parts), _small(count[part])


def _count_blocks(texts: DataFrame, order: int, dealer: Dealer, places: np.ndarray) -> DataFrame:
    def count(batches):
        held, n = [], 0

        def flush():
            if order == 1:
                rows = list(_word_blocks(np.concatenate([t for t, _ in held]), dealer))
            else:
                wide = [with_starts(t, o) for t, o in held]
                shift = np.cumsum([0] + [len(t) for t, _ in wide])
                offsets = np.concatenate([[0], *(o[1:] + k for (_, o), k in zip(wide, shift))])
                rows = list(_gram_blocks(np.concatenate([t for t, _ in wide]), offsets, order, dealer))
            yield _block_batch(rows, places)
            scan.release()

        for batch in batches:
            for _, _, data, starts in scan.blocks(batch.column(0)):
                held.append(text_tokens(data, starts))
                n += len(held[-1][0])
                if n >= FLUSH_TOKENS:
                    yield from flush()
                    held, n = [], 0
        if n:
            yield from flush()

    return texts.mapInArrow(count, BLOCK_SCHEMA).repartition(dealer.shards, "place")


def _add_up(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


# ----------------------------------------------------------------------------- quantising

#: Probabilities from 1e-12 to 1 in 255 steps of their logarithm; code 0 is the smallest.  A
#: pair seen once after a word seen 10**11 times is above it: rounding such pairs up would
#: give frequent contexts more mass than one.
LOWEST = -12.0


def quantise(p: np.ndarray) -> np.ndarray:
    return np.clip(np.floor((np.log10(np.maximum(p, 1e-30)) - LOWEST) / -LOWEST * 255), 0, 255).astype(np.uint8)


CODEBOOK = 10.0 ** (LOWEST - LOWEST * np.arange(256) / 255)
CODEBOOK[0] = 10.0**LOWEST


# -------------------------------------------------------------------------------- building


class Level1:
    def __init__(self, folder: str, names: list[str]):
        self.parts = []
        for name in names:
            meta, arrays = map_arrays(folder, name)
            self.parts.append((_open_ef("words", meta, arrays), arrays) if name else None)

    def lookup(self, words: np.ndarray, dealer: Dealer) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(count, shard, position) of each word; count 0 and position -1 if unknown."""
        own = dealer.shard(words)
        count, at = np.zeros(len(words), np.int64), np.full(len(words), -1, np.int64)
        for s in np.unique(own):
            mine = np.flatnonzero(own == s)
            ef, arrays = self.parts[s]
            pos = ef.find(words[mine])
            at[mine] = pos
            there = mine[pos >= 0]
            pos = pos[pos >= 0]
            c = arrays["count8"][pos].astype(np.int64)
            big = np.flatnonzero(c == 255)
            c[big] = arrays["count_big"][np.searchsorted(arrays["count_at"], pos[big])]
            count[there] = c
        return count, own, at


def _write_level1(folder: str, shard: int, keys: np.ndarray, counts: np.ndarray) -> str:
    meta, arrays = {}, {}
    _pack_ef("words", EliasFano.build(keys), meta, arrays)
    big = np.flatnonzero(counts >= 255)
    arrays |= {"count8": np.minimum(counts, 255).astype(np.uint8), "count_at": big.astype(np.int64), "count_big": counts[big].astype(np.int64)}
    return write_arrays(folder, f"l1-{shard:06d}", meta, arrays)


_level1: dict[str, Level1] = {}


def level1_of(folder: str, names: list[str]) -> Level1:
    """The worker's mapped level 1 of a model."""
    if folder not in _level1:
        _level1.clear()
        _level1[folder] = Level1(folder, names)
    return _level1[folder]


class TriePart:
    """A shard's trie, built from counted n-grams or opened from its file."""

    def __init__(self, order: int, contexts: EliasFano, levels: list[tuple[EliasFano, EliasFano, np.ndarray]], left: list[np.ndarray]):
        self.order, self.contexts, self.levels, self.left = order, contexts, levels, left

    @staticmethod
    def write(folder: str, shard: int, order: int, contexts: np.ndarray, levels: list[tuple[np.ndarray, np.ndarray, np.ndarray]], left: list[np.ndarray]) -> str:
        """``levels``: (entry above, code, quantised probability) of each entry of levels 2 and
        up, in order; ``left``: back-off mass of the entries that are contexts."""
        meta, arrays, above = {"order": order}, {}, len(contexts)
        _pack_ef("contexts", EliasFano.build(contexts), meta, arrays)
        for k, (parent, code, prob) in enumerate(levels, 2):
            sizes = np.bincount(parent, minlength=above)
            _pack_ef(f"pointers{k}", EliasFano.build(np.concatenate([[0], np.cumsum(sizes)]).astype(np.uint64)), meta, arrays)
            _pack_ef(f"codes{k}", EliasFano.build((parent.astype(np.uint64) << np.uint64(32)) | code.astype(np.uint64), 4), meta, arrays)
            arrays[f"prob{k}"] = prob
            if k < order:
                arrays[f"left{k}"] = left[k - 2]
            above = len(code)
        return write_arrays(folder, f"trie-{shard:06d}", meta, arrays)

    @classmethod
    def open(cls, folder: str, name: str) -> TriePart:
        meta, arrays = map_arrays(folder, name)
        n = meta["order"]
        return cls(n, _open_ef("contexts", meta, arrays), [(_open_ef(f"pointers{k}", meta, arrays), _open_ef(f"codes{k}", meta, arrays), arrays[f"prob{k}"]) for k in range(2, n + 1)], [arrays[f"left{k}"] for k in range(2, n)])

    def children(self, level: int, above: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(entry of ``level``, its probability) of each code after the entry above; -1 and 0 if unseen."""
        pointers, ef, prob = self.levels[level - 2]
        at, p = np.full(len(codes), -1, np.int64), np.zeros(len(codes))
        known = np.flatnonzero(above >= 0)
        if len(known):
            own, back = np.unique(above[known], return_inverse=True)
            lo, hi = pointers.access(own).astype(np.int64), pointers.access(own + 1).astype(np.int64)
            at[known] = find_code(ef, codes[known], lo[back], hi[back])
            hit = at >= 0
            p[hit] = CODEBOOK[prob[at[hit]]]
        return at, p


LEFT_STEPS = 65535


def _left(mass: np.ndarray) -> np.ndarray:
    return np.clip(np.floor((1 - mass) * LEFT_STEPS), 1, LEFT_STEPS).astype(np.uint16)


def _trie_levels(rank: np.ndarray, codes: list[np.ndarray], count: np.ndarray, total: np.ndarray, order: int, min_count: int, discount: float):
    """(levels, back-off masses, kept mass of each context) of sorted distinct n-grams: ``rank``
    of the first word, ``codes`` of the others (0 for none), ``total`` of each first word."""
    levels, left = [], []
    above, above_total = rank.astype(np.int64), total
    alive, context_mass = np.ones(len(rank), bool), None
    for k in range(2, order + 1):
        code = codes[k - 2]
        alive = alive & (code > 0)
        rows = np.flatnonzero(alive)
        fresh = np.concatenate([[True], (above[rows][1:] != above[rows][:-1]) | (code[rows][1:] != code[rows][:-1])]) if len(rows) else np.zeros(0, bool)
        first = np.flatnonzero(fresh)
        c = np.add.reduceat(count[rows], first) if len(first) else np.zeros(0, np.int64)
        number = np.cumsum(fresh) - 1
        if min_count > 1:
            keep = c >= min_count
            renumber = np.cumsum(keep) - 1
            rows, number, first, c = rows[keep[number]], renumber[number[keep[number]]], first[keep], c[keep]
            heads = np.flatnonzero(alive)[first]
            alive = np.zeros(len(rank), bool)
            alive[rows] = True
        else:
            heads = rows[first]
        parent = above[heads]
        prob = quantise((c - discount) / np.maximum(above_total[parent], 1))
        mass = np.bincount(parent, weights=CODEBOOK[prob], minlength=len(above_total)) if len(above_total) else np.zeros(0)
        if k == 2:
            context_mass = mass
        else:
            left.append(_left(mass))
        levels.append((parent, code[heads], prob))
        above = np.full(len(rank), -1, np.int64)
        above[rows] = number
        above_total = c
    return levels, left, context_mass


def _by_shard(names: dict[int, str], shards: int, folder: str, empty) -> list[str]:
    return [names.get(s) or empty(folder, s) for s in range(shards)]


def build_model(train: DataFrame, folder: str | None = None, order: int = ORDER, min_count: int = MIN_COUNT, discount: float = DISCOUNT, shard_bytes: int = SHARD_BYTES, hot_tokens: int | None = None) -> dict:
    """Count ``text`` of all rows and write the levels; the manifest (names of files, totals)."""
    if order < 2:
        raise ValueError("a trie has two levels at least")
    spark = train.sparkSession
    folder = folder or shared_dir(spark, "ngram")
    texts = train.select(F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    size = texts.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()
    shards, n_texts = max(2, -(-int(size["b"]) // shard_bytes)), int(size["n"])
    places = even_keys(spark, shards)
    hot_tokens = hot_tokens or max(1, int(HOT_SHARE * shard_bytes / 6))  # a word takes about six bytes
    plain = Dealer(shards, np.zeros(0, np.uint64), np.zeros(0, np.int64))

    def words(key, frame):
        shard = int(frame["shard"].iloc[0])
        out = []
        for shard, part in frame.groupby("shard"):
            keys, counts = _add_up(np.concatenate([np.frombuffer(x, np.uint64) for x in part["a"]]), np.concatenate([_from_small(x) for x in part["b"]]))
            often = counts > hot_tokens
            out.append((int(shard), _write_level1(folder, int(shard), keys, counts), len(keys), int(counts.sum()), keys[often].tobytes(), counts[often].tobytes()))
        return pd.DataFrame(out, columns=["shard", "name", "distinct", "total", "often", "counts"])

    rows = materialise(_count_blocks(texts, 1, plain, places).groupBy("place").applyInPandas(words, "shard int, name string, distinct long, total long, often binary, counts binary"), f"{folder}/manifest1").collect()
    level1 = _by_shard({r["shard"]: r["name"] for r in rows}, shards, folder, lambda f, s: _write_level1(f, s, np.zeros(0, np.uint64), np.zeros(0, np.int64)))
    often = np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(r["often"], np.uint64) for r in rows), np.array([START] if n_texts > hot_tokens else [], np.uint64)])
    counts = np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(r["counts"], np.int64) for r in rows), np.array([n_texts] if n_texts > hot_tokens else [], np.int64)])
    by_word = np.argsort(often)
    dealer = Dealer(shards, often[by_word], np.minimum(-(-counts[by_word] // hot_tokens), shards))

    def grams(key, frame):
        out = []
        for shard, part in frame.groupby("shard"):
            out += _merge_grams(int(shard), part)
        return pd.DataFrame(out, columns=["shard", "owner", "owner_place", "name", "contexts", "mass"])

    def _merge_grams(shard, part):
        sizes = [_from_small(x) for x in part["b"]]
        context = np.concatenate([np.repeat(np.frombuffer(a, np.uint64), b) for a, b in zip(part["a"], sizes, strict=True)])
        split = [np.frombuffer(x, np.uint32).reshape(order - 1, -1) for x in part["c"]]
        codes = [np.concatenate([x[k] for x in split]) for k in range(order - 1)]
        count = np.concatenate([_from_small(x) for x in part["d"]])
        vocabulary, rank = np.unique(context, return_inverse=True)
        del context, split
        pair = (rank.astype(np.uint64) << np.uint64(32)) | codes[0]
        by = np.lexsort([*codes[:0:-1], pair]) if order > 2 else np.argsort(pair, kind="stable")
        rank, count, codes, pair = rank[by], count[by], [c[by] for c in codes], pair[by]
        fresh = np.concatenate([[True], pair[1:] != pair[:-1]])
        for c in codes[1:]:
            fresh[1:] |= c[1:] != c[:-1]
        first = np.flatnonzero(fresh)
        rank, codes, count = rank[first], [c[first] for c in codes], np.add.reduceat(count, first)
        del pair, by, fresh
        total = level1_of(folder, level1).lookup(vocabulary, plain)[0]
        total[vocabulary == START] = n_texts
        levels, left, mass = _trie_levels(rank, codes, count, total, order, min_count, discount)
        name = TriePart.write(folder, shard, order, vocabulary, levels, left)
        own = plain.shard(vocabulary)
        scan.release()
        return [(shard, s, int(places[s]), name, vocabulary[own == s].tobytes(), mass[own == s].tobytes()) for s in np.unique(own).tolist()]

    second = materialise(_count_blocks(texts, order, dealer, places).groupBy("place").applyInPandas(grams, "shard int, owner int, owner_place int, name string, contexts binary, mass binary"), f"{folder}/manifest2")
    none = np.zeros(0, np.int64)
    empty = [(none, np.zeros(0, np.uint32), np.zeros(0, np.uint8))] * (order - 1)
    trie = _by_shard({r["shard"]: r["name"] for r in second.select("shard", "name").distinct().collect()}, shards, folder, lambda f, s: TriePart.write(f, s, order, np.zeros(0, np.uint64), empty, [np.zeros(0, np.uint16)] * (order - 2)))

    def masses(key, frame):
        """Back-off of each first word, in the order of the level-1 shard that has the word."""
        out = []
        for shard, part in frame.groupby("owner"):
            keys = np.concatenate([np.frombuffer(x, np.uint64) for x in part["contexts"]])
            mass = np.concatenate([np.frombuffer(x, np.float64) for x in part["mass"]])
            keys, mass = _add_up(keys, mass)
            ef = level1_of(folder, level1).parts[int(shard)][0]
            at = ef.find(keys)
            known = at >= 0
            left = np.full(ef.n, LEFT_STEPS, np.uint16)
            left[at[known]] = _left(mass[known])
            start = float(1 - mass[keys == START].sum()) if (keys == START).any() else None
            out.append((int(shard), write_arrays(folder, f"bow-{int(shard):06d}", {}, {"left": left}), start))
        return pd.DataFrame(out, columns=["shard", "name", "start"])

    third = materialise(second.select("owner", "owner_place", "contexts", "mass").repartition(shards, "owner_place").groupBy("owner_place").applyInPandas(masses, "shard int, name string, start double"), f"{folder}/manifest3").collect()
    return {
        "folder": folder, "shards": shards, "order": order, "often": dealer.often, "ways": dealer.ways, "level1": level1, "trie": trie, "backoff": {r["shard"]: r["name"] for r in third},
        "tokens": sum(r["total"] for r in rows), "distinct": sum(r["distinct"] for r in rows), "texts": n_texts, "start_left": next((r["start"] for r in third if r["start"] is not None and r["start"] == r["start"]), 1.0),
    }


class Model:
    """The mapped levels of a manifest; queries are arrays."""

    def __init__(self, manifest: dict):
        self.m, self.order = manifest, manifest["order"]
        self.dealer = Dealer(manifest["shards"], manifest["often"], manifest["ways"])
        self.first = Level1(manifest["folder"], manifest["level1"])
        self.left = {s: map_arrays(manifest["folder"], name)[1]["left"] for s, name in manifest["backoff"].items()}
        self.parts = [TriePart.open(manifest["folder"], name) for name in manifest["trie"]]
        self.scale = manifest["tokens"] + 0.1 * (manifest["distinct"] + 1)

    def _words(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(count, back-off mass) of each distinct word."""
        count, own, at = self.first.lookup(words, self.dealer)
        left = np.ones(len(words))
        for s in np.unique(own):
            if s in self.left:
                mine = np.flatnonzero((own == s) & (at >= 0))
                left[mine] = self.left[s][at[mine]] / LEFT_STEPS
        return count, np.where(words == START, self.m["start_left"], left)

    def score(self, tokens: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(known tokens, base score, score) of each document."""
        wide, bounds = with_starts(tokens, offsets)
        words, inverse = np.unique(wide, return_inverse=True)
        count, left = self._words(words)
        single, codes = (count + 0.1) / self.scale, code_of(words)
        place = np.arange(len(wide)) - np.repeat(bounds[:-1], np.diff(bounds))  # 0: the start mark
        real = np.flatnonzero(place > 0)
        p = single[inverse[real]]
        base = np.log10(p)
        # n-grams by their end: number of the distinct one of the level below that ends one word
        # earlier, and the last word; each distinct one is looked up once
        ends, ids, back, shard, entry = real, inverse, left, None, None
        for level in range(2, self.order + 1):
            if level > 2:
                ends = ends[place[ends] >= level - 1]
            key, of = np.unique(ids[ends - 1] * len(words) + inverse[ends], return_inverse=True)
            above, last = np.divmod(key, len(words))
            code = codes[last]
            own = self.dealer.shard(words[above], code) if level == 2 else shard[above]
            at, kept, mass = np.full(len(key), -1, np.int64), np.zeros(len(key)), np.ones(len(key))
            for s, mine in _by_owner(own, self.dealer.shards):
                part = self.parts[s]
                if level == 2:
                    heads, again = np.unique(above[mine], return_inverse=True)
                    parent = part.contexts.find(words[heads])[again]
                else:
                    parent = entry[above[mine]]
                at[mine], kept[mine] = part.children(level, parent, code[mine])
                if level < self.order:
                    seen = mine[at[mine] >= 0]
                    mass[seen] = part.left[level - 2][at[seen]] / LEFT_STEPS
            # p so far is that of the context without its first word
            rows = slice(None) if level == 2 else np.searchsorted(real, ends)
            p[rows] = kept[of] + back[above][of] * p[rows]
            ids = np.zeros(len(wide), np.int64)
            ids[ends] = of
            shard, entry, back = own, at, mass
        first = offsets[:-1]
        return np.add.reduceat((count > 0)[inverse[real]].astype(np.int64), first), np.add.reduceat(base, first), np.add.reduceat(np.log10(p), first)


_models: dict[str, Model] = {}


def score_texts(docs: DataFrame, manifest: dict) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of each row of
    (doc_id, held_out, text)."""
    shared = docs.sparkSession.sparkContext.broadcast(manifest)

    def score(batches):
        m = shared.value
        if m["folder"] not in _models:
            _models.clear()
            _models[m["folder"]] = Model(m)
        model = _models[m["folder"]]
        for batch in batches:
            for lo, hi, data, starts in scan.blocks(batch.column(2), SCORE_BLOCK):
                tokens, offsets = text_tokens(data, starts)
                known, base, value = model.score(tokens, offsets)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(np.diff(offsets), pa.int64()), pa.array(known, pa.int64()), pa.array(np.full(hi - lo, m["tokens"]), pa.int64()), pa.array(base, pa.float64()), pa.array(value, pa.float64())],
                    names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "held_out", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.mapInArrow(score, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op6_elias_fano_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", held_out(10, 0).alias("held_out"))
    return score_texts(docs, build_model(docs.filter(~F.col("held_out"))))
