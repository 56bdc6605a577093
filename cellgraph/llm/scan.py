"""Vectorised scanning of Arrow string columns: word borders, folding and 64-bit hashes.

Nothing here loops over characters or words in Python.  Texts are taken straight from the
Arrow buffers in blocks of about ``BLOCK`` bytes (a longer text is a block of its own).
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

BLOCK = 1 << 20

_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1

#: A-Z to a-z, every other byte as it is.
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32

#: Bytes of words delimited by ASCII white space (0x20, 0x09-0x0D).
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[32, 9, 10, 11, 12, 13]] = False

#: Bytes of words made of letters only: a-z after folding, and all bytes of non-ASCII characters.
LETTERS = np.zeros(256, dtype=bool)
LETTERS[65:91] = LETTERS[97:123] = LETTERS[128:] = True

_powers: dict[str, np.ndarray] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _powers.get("up")
    if have is None or len(have) < n:
        size = max(n, BLOCK + BLOCK // 4)
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            table = np.full(size, base, dtype=np.uint64)
            table[0] = 1
            _powers[name] = np.multiply.accumulate(table)
    return _powers["up"], _powers["down"]


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the 64 output bits."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def hash_bytes(word: bytes) -> int:
    """The hash :func:`words` gives a word, for constants and tests."""
    total = sum((b + 1) * pow(_BASE, i, 1 << 64) for i, b in enumerate(word)) & _MASK
    total = (total + len(word) * 0xD6E8FEB86659FD93) & _MASK
    return int(mix(np.array([total], dtype=np.uint64))[0])


def string_parts(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts and the n+1 offsets into them; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    kind = np.int64 if wide else np.int32
    ends = np.frombuffer(offsets, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64) if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, ends


def blocks(column: pa.Array, limit: int = BLOCK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, past last row, bytes, starts): whole texts, about ``limit`` bytes a block."""
    raw, ends = string_parts(column)
    n, lo = len(ends) - 1, 0
    while lo < n:
        hi = int(np.searchsorted(ends, ends[lo] + limit, side="right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi, raw[ends[lo] : ends[hi]], ends[lo : hi + 1] - ends[lo]
        lo = hi


def words(data: np.ndarray, starts: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(begin, end, document) of each word: maximal runs of bytes marked in the table ``inside``.

    Words never cross documents; ``starts`` has one more entry than there are documents.
    """
    n = len(data)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, none
    member = inside[data]
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = member[:-1]
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = member[1:]
    first = starts[:-1]
    first = first[first < n]
    before[first] = False
    after[first[first > 0] - 1] = False
    begin = np.flatnonzero(member & ~before)
    end = np.flatnonzero(member & ~after) + 1
    return begin, end, np.searchsorted(starts[:-1], begin, side="right") - 1


def word_hashes(data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """One 64-bit hash for each byte range, after folding A-Z."""
    n = len(data)
    up, down = _power_tables(n + 1)
    sums = np.empty(n + 1, dtype=np.uint64)
    sums[0] = 0
    weighted = FOLD[data].astype(np.uint64)
    weighted += np.uint64(1)
    weighted *= up[:n]
    np.cumsum(weighted, out=sums[1:])
    h = (sums[end] - sums[begin]) * down[begin]
    return mix(h + (end - begin).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def window_hashes(data: np.ndarray, width: int, fold: bool = False) -> np.ndarray:
    """Hash of the ``width`` bytes that start at each position (n - width + 1 of them)."""
    n = len(data)
    if n < width:
        return np.zeros(0, np.uint64)
    up, down = _power_tables(n + 1)
    sums = np.empty(n + 1, dtype=np.uint64)
    sums[0] = 0
    weighted = (FOLD[data] if fold else data).astype(np.uint64)
    weighted += np.uint64(1)
    weighted *= up[:n]
    np.cumsum(weighted, out=sums[1:])
    return mix((sums[width:] - sums[:-width]) * down[: n - width + 1])


def by_document(counts: np.ndarray) -> np.ndarray:
    """Offsets (one more than there are documents) from the number of items of each."""
    out = np.zeros(len(counts) + 1, dtype=np.int64)
    np.cumsum(counts, out=out[1:])
    return out


def release() -> None:
    """Give freed memory back to the system, where the C library can: workers live on."""
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:
        pass
