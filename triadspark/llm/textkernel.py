"""Vectorised byte kernels shared by the corpus operators.

Everything here works on one Arrow batch: texts become one padded byte array plus offsets, words become
(start, length) arrays, and hashes are computed for all words at once.  Nothing loops over words in Python.
"""

from __future__ import annotations

import ctypes
import gc
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
PAD = 96
LONG = 64  # bytes from which a word is hashed in one go
GOLD = U(0x9E3779B97F4A7C15)
_M1, _M2 = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)
_KEEP = np.array([(1 << (8 * i)) - 1 if i < 8 else (1 << 64) - 1 for i in range(9)], dtype=U)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: bytes of a word: all but space and \t..\r
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[0x20, *range(0x09, 0x0E)]] = False
#: bytes of a word once lower-cased: digits, a-z, everything beyond ASCII
ALNUM = np.zeros(256, dtype=bool)
ALNUM[0x30:0x3A] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit generator; overwrites and returns x."""
    x ^= x >> U(30)
    x *= _M1
    x ^= x >> U(27)
    x *= _M2
    x ^= x >> U(31)
    return x


def release_encoders() -> None:
    """Lets go what encoders kept in this worker, which has gone over to another operator."""
    held = sys.modules.get("_chunk_cache_of_worker")
    names = [k for k in vars(held) if ":" in k] if held is not None else []
    for name in names:
        delattr(held, name)
    if names:
        gc.collect()  # an encoder and its cache name each other
    release_memory()


def release_memory() -> None:
    """Gives back what this worker has freed: the C library and Arrow keep freed pages of a task's largest step, for every worker of an executor."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes with PAD zeros behind, offsets) of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    wide = pa.large_string() if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else pa.large_binary()
    column = column.cast(wide)
    if column.null_count:
        column = column.fill_null("" if wide == pa.large_string() else b"")
    off = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    out = np.zeros(int(off[-1] - off[0]) + PAD, dtype=np.uint8)
    if len(out) > PAD:
        out[:-PAD] = np.frombuffer(column.buffers()[2], dtype=np.uint8)[off[0] : off[-1]]
    return out, off - off[0]


def pieces(batch: pa.RecordBatch | pa.Table, column: str, limit: int = 2 << 20) -> Iterator[pa.Table]:
    """Runs of rows with at most `limit` text bytes together (a longer text stands alone)."""
    table = pa.Table.from_batches([batch]) if isinstance(batch, pa.RecordBatch) else batch
    n = table.num_rows
    if not n:
        return
    col = table[column].combine_chunks()
    if isinstance(col, pa.ChunkedArray):
        col = pa.concat_arrays(col.chunks)
    import pyarrow.compute as pc

    ends = np.cumsum(pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    start, base = 0, 0
    while start < n:
        stop = max(start + 1, int(np.searchsorted(ends, base + limit, "right")))
        yield table.slice(start, stop - start)
        base, start = int(ends[stop - 1]), stop


def loads(padded: np.ndarray) -> np.ndarray:
    """Unaligned little-endian 8-byte word at every position."""
    return np.ndarray((len(padded) - 8,), dtype="<u8", buffer=padded, strides=(1,))


def words(padded: np.ndarray, off: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and lengths of maximal runs of bytes of `kind` inside each text, and words per text."""
    n = int(off[-1])
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off) - 1, np.int64)
    inside = kind[padded[:n]]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    cuts = off[:-1][np.diff(off) > 0]
    first[cuts] = inside[cuts]
    ends = off[1:][np.diff(off) > 0] - 1
    last[ends] = inside[ends]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1 - starts, np.diff(np.searchsorted(starts, off))


def word_hash(padded: np.ndarray, starts: np.ndarray, lens: np.ndarray, seed: int = 0) -> np.ndarray:
    """64-bit hash of each word's bytes."""
    w8 = loads(padded)
    h = w8[starts] & _KEEP[np.minimum(lens, 8)]
    h += lens.astype(U) * GOLD + U(seed)
    h = mix(h)
    at, sel = 8, np.flatnonzero((lens > 8) & (lens <= LONG))
    while len(sel):
        x = w8[starts[sel] + at] & _KEEP[np.minimum(lens[sel] - at, 8)]
        h[sel] = mix((h[sel] * _M1 + U(at)) ^ x)
        at += 8
        sel = sel[lens[sel] > at]
    # the pieces of longer words are hashed all at once with their numbers, and added
    sel = np.flatnonzero(lens > LONG)
    upto = np.cumsum(lens[sel])
    i = 0
    while i < len(sel):
        j = max(i + 1, int(np.searchsorted(upto, (upto[i - 1] if i else 0) + (1 << 23), "right")))
        of = sel[i:j]
        n = -(-lens[of] // 8)
        ends = np.cumsum(n)
        word = np.repeat(np.arange(len(of)), n)
        no = np.arange(int(ends[-1])) - (ends - n)[word]
        x = w8[starts[of][word] + 8 * no] & _KEEP[np.minimum(lens[of][word] - 8 * no, 8)]
        x = mix(x + (no.astype(U) + U(1)) * GOLD)
        h[of] = mix((h[of] * _M1) ^ np.add.reduceat(mix(x ^ _M2), ends - n))
        i = j
    return h


def span_hash(h: np.ndarray, width: int) -> np.ndarray:
    """Order-sensitive hash of each run of `width` consecutive word hashes (len(h)-width+1 values)."""
    n = max(0, len(h) - width + 1)
    out = h[:n].copy()
    for j in range(1, width):
        out *= GOLD
        out += h[j : j + n]
        out ^= out >> U(29)
    return mix(out)


def inside_text(counts: np.ndarray, width: int) -> np.ndarray:
    """Mask over runs of `width` words: those that stay in one text."""
    total = int(counts.sum())
    n = max(0, total - width + 1)
    left = np.repeat(np.cumsum(counts), counts)[:n] - np.arange(n)
    return left >= width
