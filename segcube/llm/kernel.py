"""Vectorised text kernels over Arrow buffers.

Spark hands a Python worker whole Arrow batches; the functions here look at the UTF-8 bytes of a batch as
one numpy array and find, lower-case and hash all its words with array operations, so that no Python object
is made per word.  They hold no state and no data of other batches.

Edge cases: a null text counts as empty; empty texts have no words; a text of any length is handled whole
(memory grows with the longest single text, not with the table).
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

#: Bytes of text looked at in one step; bounds a worker's memory to some 25 times as much.
STEP_BYTES = 4 << 20

_u64 = np.uint64
_M1, _M2, _M3 = _u64(0x9E3779B97F4A7C15), _u64(0xBF58476D1CE4E5B9), _u64(0x94D049BB133111EB)
_TAIL = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [2**64 - 1], dtype=np.uint64)
#: Words longer than this are hashed one by one; the choice depends on the word alone.
_LONG = 256

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Bytes of words: digits, letters and everything beyond ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[65:91] = ALNUM[97:123] = ALNUM[128:] = True

#: Bytes of words: everything but white space.
NONSPACE = np.ones(256, dtype=bool)
NONSPACE[[9, 10, 11, 12, 13, 32]] = False


try:
    _trim = ctypes.CDLL(None).malloc_trim
except (OSError, AttributeError):  # another C library
    _trim = None


def release() -> None:
    """Give freed memory back to the system, as Spark keeps its workers for later tasks."""
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


def steps(batch: pa.RecordBatch, column: str, limit: int = STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of ``batch`` whose texts hold about ``limit`` bytes at most, or a single longer text; frees memory behind the last."""
    if not batch.num_rows:
        return
    _, offsets = text_bytes(batch.column(column))
    at = 0
    while at < batch.num_rows:
        end = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        end = min(max(end, at + 1), batch.num_rows)
        yield batch.slice(at, end - at)
        at = end
    release()


def text_bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string array, one text after the other, and each text's offset (one more at the end)."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    texts = texts.cast(pa.large_binary())
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    if not len(texts) or texts.buffers()[2] is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(texts) + 1, dtype=np.int64)
    data = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]]
    return data, offsets - offsets[0]


def find_words(data: np.ndarray, offsets: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of each maximal run of word bytes, and the index of each text's first word (one more at the end)."""
    if not len(data):
        none = np.zeros(0, dtype=np.int64)
        return none, none, np.zeros(len(offsets), dtype=np.int64)
    inside = kind[data]
    change = np.empty(len(data) + 1, dtype=bool)
    change[0], change[-1] = True, True
    np.not_equal(inside[1:], inside[:-1], out=change[1:-1])
    change[offsets] = True
    bounds = np.flatnonzero(change)
    keep = inside[bounds[:-1]]
    starts, ends = bounds[:-1][keep], bounds[1:][keep]
    return starts, ends, np.searchsorted(starts, offsets)


def mix(h: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit values, in place."""
    h ^= h >> _u64(30)
    h *= _M2
    h ^= h >> _u64(27)
    h *= _M3
    h ^= h >> _u64(31)
    return h


def hash_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span's bytes."""
    padded = np.empty(len(data) + 8, dtype=np.uint8)
    padded[: len(data)], padded[len(data) :] = data, 0
    view = np.ndarray((len(padded) - 7,), dtype="<u8", buffer=padded.data, strides=(1,))
    size = ends - starts
    h = size.astype(np.uint64) * _M1
    h ^= view[starts] & _TAIL[np.minimum(size, 8)]
    mix(h)
    rest, done = np.flatnonzero((size > 8) & (size <= _LONG)), 8
    while len(rest):
        left = size[rest] - done
        h[rest] = mix((h[rest] + _M1) ^ (view[starts[rest] + done] & _TAIL[np.minimum(left, 8)]))
        done += 8
        rest = rest[left > 8]
    for i in np.flatnonzero(size > _LONG):
        h[i] = xxhash.xxh3_64_intdigest(data[starts[i] : ends[i]].tobytes())
    return h


def roll(words: np.ndarray, k: int) -> np.ndarray:
    """The hash of each ``k`` consecutive word hashes; borders of texts are the caller's."""
    n = max(0, len(words) - k + 1)
    h = np.full(n, k, dtype=np.uint64)
    for j in range(k):
        h *= _M1
        h += words[j : j + n]
    return mix(h)


def hash_text(words: list[str]) -> np.ndarray:
    """Hashes of single words given as strings, equal to those of :func:`hash_spans`."""
    data, offsets = text_bytes(pa.array(words, type=pa.string()))
    return hash_spans(data, offsets[:-1], offsets[1:])


def ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Concatenated ``starts[i] .. starts[i] + sizes[i] - 1``."""
    sizes = np.asarray(sizes, dtype=np.int64)
    total = int(sizes.sum())
    first = np.cumsum(sizes) - sizes
    return np.arange(total, dtype=np.int64) + np.repeat(np.asarray(starts, dtype=np.int64) - first, sizes)
