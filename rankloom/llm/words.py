"""Vectorised word hashing of Arrow text columns.

A chunk of documents is looked at as one byte array: word borders come from a
byte class table and every word gets a 64-bit hash by differences of one running
polynomial sum, so that no Python loop runs over words or documents.
"""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 20

#: ASCII space and the five control characters TAB to CR part words.
SPACE_SEPARATORS = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)

_MIX = np.random.default_rng(20240229)
_BYTE_CODE = _MIX.integers(1, 2**63, 256, dtype=np.uint64)
_RADIX = int(_MIX.integers(1, 2**62, dtype=np.uint64)) * 2 + 1
_RADIX_INVERSE = pow(_RADIX, -1, 2**64)
_POWERS: dict[str, np.ndarray] = {}


def give_back() -> None:
    """Returns freed memory to the system: a worker that waits for its next task should be small."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def tidy(run: Callable) -> Callable:
    """A mapInArrow function that gives memory back when its task ends."""

    @functools.wraps(run)
    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def tidy_table(run: Callable) -> Callable:
    """The same for an applyInArrow function."""

    def wrapped(table: pa.Table) -> pa.Table:
        try:
            return run(table)
        finally:
            give_back()

    return wrapped


def tidy_pair(run: Callable) -> Callable:
    """The same for a function of two cogrouped tables."""

    def wrapped(left: pa.Table, right: pa.Table) -> pa.Table:
        try:
            return run(left, right)
        finally:
            give_back()

    return wrapped


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """radix**i and radix**-i mod 2**64 for i < n, kept for the next chunk."""
    if not _POWERS or len(_POWERS["up"]) < n:
        size = max(n, CHUNK_BYTES + (1 << 16))
        for name, base in (("up", _RADIX), ("down", _RADIX_INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


def forget_powers() -> None:
    """Drops the kept powers, which would travel with functions made on the driver."""
    _POWERS.clear()


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def class_tables(alnum: bool) -> tuple[np.ndarray, np.ndarray]:
    """(byte -> is part of a word, byte -> code after lower-casing A-Z).

    alnum: words are runs of ASCII letters, digits and all non-ASCII bytes;
    else runs of anything but white space.
    """
    member = np.ones(256, bool)
    if alnum:
        member[:128] = [chr(i).isalnum() for i in range(128)]
    else:
        member[list(SPACE_SEPARATORS)] = False
    lower = np.arange(256)
    lower[65:91] += 32
    return member, _BYTE_CODE[lower]


class WordChunk:
    """Words of some documents: hashes in order and each document's slice.

    hashes  uint64, one for each word
    first   int64, document d owns words first[d] to first[d + 1]
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, alnum: bool = False):
        member, code = class_tables(alnum)
        n = len(data)
        self.docs = len(offsets) - 1
        inside = member[data]
        border = np.zeros(n + 1, bool)
        border[offsets] = True
        begins = inside.copy()
        begins[1:] &= ~inside[:-1] | border[1:n]
        starts = np.flatnonzero(begins)
        ends_here = inside
        ends_here[:-1] &= ~inside[1:] | border[1:n]
        ends = np.flatnonzero(ends_here) + 1
        up, down = _powers(n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum(code[data] * up[:n], out=total[1:])
        self.hashes = mix64((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))
        self.first = np.searchsorted(starts, offsets)
        self.starts, self.ends = starts, ends

    def doc_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(self.docs), np.diff(self.first))


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null texts are empty."""
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data, offsets


def row_chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most limit bytes each, or of one row that is longer."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi
        lo = hi


def word_chunks(column: pa.Array, alnum: bool = False) -> Iterator[tuple[int, int, WordChunk]]:
    """(first row, end row, words) for chunk after chunk of a string column."""
    data, offsets = text_buffers(column)
    for lo, hi in row_chunks(offsets):
        part = offsets[lo : hi + 1]
        yield lo, hi, WordChunk(data[part[0] : part[-1]], part - part[0], alnum)


def shingles(words: WordChunk, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of the distinct shingles, sorted by both.

    A document with fewer words than width has its whole sequence as one
    shingle; one without words has none.
    """
    h, first = words.hashes, words.first
    count = np.diff(first)
    short = np.flatnonzero((count > 0) & (count < width))
    if len(h) >= width:
        code = h[: len(h) - width + 1].copy()
        for k in range(1, width):
            code = mix64(code * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - width + 1 + k])
        doc = words.doc_of_word()
        whole = doc[: len(code)] == doc[width - 1 :]
        code, doc = code[whole], doc[: len(whole)][whole]
    else:
        code, doc = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    extra = []
    for d in short:
        x = np.uint64(int(count[d]))
        for w in h[first[d] : first[d + 1]]:
            x = mix64(np.array([(int(x) * 0x9E3779B97F4A7C15 + int(w) + 1) % 2**64], np.uint64))[0]
        extra.append(x)
    code = np.concatenate([code, np.array(extra, np.uint64)])
    doc = np.concatenate([doc, short])
    order = np.lexsort((code, doc))
    code, doc = code[order], doc[order]
    keep = np.ones(len(code), bool)
    keep[1:] = (code[1:] != code[:-1]) | (doc[1:] != doc[:-1])
    return doc[keep], code[keep]
