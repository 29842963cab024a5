"""Vectorised text kernels over Arrow string buffers.

A word is a longest run of bytes outside ``[\\x20\\x09-\\x0D]``.  All of these
are ASCII, so byte positions never fall inside a UTF-8 character.  Every
function works on whole texts of a batch at once and never copies a text into
a Python string.
"""

from __future__ import annotations

import ctypes
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLANKS = np.array([0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D], np.uint8)
STEP = np.uint64(0x9E3779B97F4A7C15)
MASK = (1 << 64) - 1
CHUNK_BYTES = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """Finalising 64-bit mixer (a bijection on uint64)."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _byte_values(fold: bool) -> np.ndarray:
    table = mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * STEP)
    if fold:
        table[65:91] = table[97:123]
    table[BLANKS] = 0
    return table


FOLDED, EXACT = _byte_values(True), _byte_values(False)
IS_WORD = np.ones(256, bool)
IS_WORD[BLANKS] = False
BASE = 0x9E3779B97F4A7C15 | 1
BASE_INVERSE = pow(BASE, -1, 1 << 64)


SEGMENT = 1 << 18  # bytes that are hashed at once, unless one word is longer; a worker keeps tables of 32 times as many
_TABLES: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    """base ** 0, 1, ... for n at least; one table a base grows by doubling, up to about a segment."""
    out = _TABLES.get(base, np.ones(1, np.uint64))
    while len(out) < n:
        out = np.concatenate([out, out * np.uint64(pow(base, len(out), 1 << 64))])
        if len(out) <= 2 * SEGMENT:
            _TABLES[base] = out
    return out


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    return _powers(BASE, n + 1), _powers(BASE_INVERSE, n + 1)


LETTERS, DIGITS = 1, 2  # bits of a code point's kind


@lru_cache(maxsize=1)
def _kinds() -> np.ndarray:
    """LETTERS for letters and marks, DIGITS for numbers, by code point."""
    bit = {"L": LETTERS, "M": LETTERS, "N": DIGITS}
    return np.array([bit.get(unicodedata.category(chr(c))[0], 0) for c in range(0x110000)], np.uint8)


def _wide(data: np.ndarray, kinds: int) -> np.ndarray:
    """True for every byte of the characters beyond ASCII that are of the given kinds."""
    out = np.zeros(len(data), bool)
    heads = np.flatnonzero(data >= 0xC0)
    lead = data[heads]
    for low, high, size in ((0xC0, 0xE0, 2), (0xE0, 0xF0, 3), (0xF0, 0x100, 4)):
        at = heads[(lead >= low) & (lead < high)]
        code = data[at].astype(np.int64) & (0x7F >> size)
        for j in range(1, size):
            code = code << 6 | (data[at + j] & 0x3F)
        at = at[(_kinds()[code] & kinds) > 0]
        for j in range(size):
            out[at + j] = True
    return out


class Texts:
    """The texts of a batch as one byte array with offsets; null is empty.  ``lower`` folds case in all of Unicode."""

    def __init__(self, column: pa.Array, lower: bool = False):
        column = column.cast(pa.large_string())
        if column.null_count:
            column = column.fill_null("")
        if lower:
            column = pc.utf8_lower(column)
        _, where, data = column.buffers()
        ends = np.frombuffer(where, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
        first, last = int(ends[0]), int(ends[-1])
        self.data = np.frombuffer(data, np.uint8)[first:last] if data is not None and last > first else np.zeros(0, np.uint8)
        self.offs = ends - first


class Words:
    """Word starts, ends and hashes of a batch; ``first[i]:first[i+1]`` are text i's.

    ``inside`` marks the bytes of words; with ``kinds`` it does so for ASCII
    only, and characters beyond it belong to words by their kind.  ``joins`` is
    a byte that belongs to a word only between two of its bytes.
    """

    def __init__(self, texts: Texts, fold: bool = True, inside: np.ndarray = IS_WORD, kinds: int = 0, joins: int | None = None):
        data, offs = texts.data, texts.offs
        word = inside[data]
        self.mask = None
        if kinds and len(data) and data.max() >= 0x80:
            self.mask = word = (word & (data < 0x80)) | _wide(data, kinds)
        if joins is not None and len(data) > 2:
            at = np.flatnonzero(data[1:-1] == joins) + 1
            at = at[word[at - 1] & word[at + 1] & ~np.isin(at, offs) & ~np.isin(at + 1, offs)]
            if len(at):
                self.mask = word = word.copy()
                word[at] = True
        begin, end = word.copy(), word.copy()
        if len(data):
            begin[1:] &= ~word[:-1]
            end[:-1] &= ~word[1:]
            full = offs[:-1] < offs[1:]
            heads, tails = offs[:-1][full], offs[1:][full] - 1
            begin[heads], end[tails] = word[heads], word[tails]
        self.starts = np.flatnonzero(begin)
        self.ends = np.flatnonzero(end) + 1
        self.first = np.searchsorted(self.starts, offs)
        table = FOLDED if fold else EXACT
        self.values = table if self.mask is not None else np.where(inside, table, np.uint64(0))
        self.data = data

    def hashes(self) -> np.ndarray:
        """A hash for each word, from its bytes alone; whole words are worked on segment by segment."""
        out = np.zeros(len(self.starts), np.uint64)
        at = 0
        while at < len(out):
            stop = max(at + 1, int(np.searchsorted(self.ends, self.starts[at] + SEGMENT, side="right")))
            low, high = int(self.starts[at]), int(self.ends[stop - 1])
            up, down = powers(high - low)
            terms = self.values[self.data[low:high]] * up[: high - low]
            if self.mask is not None:
                terms *= self.mask[low:high]
            heads = self.starts[at:stop] - low
            size = (self.ends[at:stop] - self.starts[at:stop]).astype(np.uint64)
            out[at:stop] = mix(np.add.reduceat(terms, heads) * down[heads] + size * STEP)
            at = stop
        return out

    def prefix_hashes(self, which: np.ndarray, size: int) -> np.ndarray:
        """Hashes of the first ``size`` bytes of some words, each longer than that."""
        up, _ = powers(size)
        at = self.starts[which]
        total = np.zeros(len(at), np.uint64)
        for j in range(size):
            total += self.values[self.data[at + j]] * up[j]
        return mix(total + np.uint64(size * int(STEP) & MASK))

    def longer(self, size: int) -> np.ndarray:
        return np.flatnonzero(self.ends - self.starts > size)


def chained(hashes: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of ``n`` consecutive word hashes (``len - n + 1`` of them)."""
    count = max(0, len(hashes) - n + 1)
    total = np.full(count, n, np.uint64) * STEP
    for j in range(n):
        total = total + mix(hashes[j : j + count] + np.uint64((j + 1) * BASE & MASK))
    return mix(total)


def word_hash(word: str, fold: bool = True, inside: np.ndarray = IS_WORD) -> int:
    """The hash that :class:`Words` gives to one word."""
    return int(Words(Texts(pa.array([word])), fold, inside).hashes()[0])


class HashLookup:
    """Values of a few hashes, found fast among many."""

    def __init__(self, table: dict[int, int]):
        self.keys = np.array(sorted(table), np.uint64)
        self.values = np.array([table[int(k)] for k in self.keys], np.int64)
        self.low = np.zeros(1 << 16, bool)
        self.low[(self.keys & np.uint64(0xFFFF)).astype(np.int64)] = True

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions, values) of the hashes that the table holds."""
        if not len(self.keys) or not len(hashes):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        some = np.flatnonzero(self.low[(hashes & np.uint64(0xFFFF)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.keys, hashes[some]), len(self.keys) - 1)
        right = self.keys[at] == hashes[some]
        return some[right], self.values[at[right]]


@lru_cache(maxsize=1)
def _trim():
    """In a Spark worker, memory that is freed goes back to the system, as workers live on after their task; returns what trims it."""
    from pyspark import TaskContext

    if TaskContext.get() is None:
        return lambda: None
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 1 << 18)  # larger arrays are mapped, and unmapped when freed
        return lambda: libc.malloc_trim(0)
    except (OSError, AttributeError):  # another C library than the GNU one
        return lambda: None


def chunks(batches, text: str, most: int = CHUNK_BYTES):
    """Cut Arrow batches so that each piece holds few text bytes (one text at least)."""
    trim = _trim()
    for batch in batches:
        if not batch.num_rows:
            continue
        column = batch.column(batch.schema.get_field_index(text))
        sizes = np.cumsum(_sizes(column))
        start, n = 0, batch.num_rows
        while start < n:
            base = sizes[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(sizes, base + most, side="right")))
            yield batch.slice(start, stop - start)
            start = stop
    trim()


def trimming(run):
    """``run``, a function of Arrow batches, which at its end gives what it has freed back to the system."""

    def whole(batches):
        trim = _trim()
        yield from run(batches)
        trim()

    return whole


def _sizes(column: pa.Array) -> np.ndarray:
    return np.asarray(pc.binary_length(column).fill_null(0), np.int64)


def packed(values: np.ndarray, width: int) -> bytes:
    """The low ``width`` bytes of each uint64, little end first."""
    return values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def unpacked(blob: bytes, width: int) -> np.ndarray:
    raw = np.frombuffer(blob, np.uint8).reshape(-1, width)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :width] = raw
    return out.view("<u8").ravel()


def long_array(values: np.ndarray) -> pa.Array:
    """uint64 values as a signed 64-bit Arrow column with the same bits."""
    return pa.array(np.ascontiguousarray(values).view(np.int64), pa.int64())
