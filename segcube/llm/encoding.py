"""Whole texts to token ids with a public tokenizer, each distinct piece encoded once.

A byte-pair tokenizer first cuts a text by a pattern and then merges inside each cut.  This module places
borders only where that pattern must cut whatever stands around (white space that the tokenizer drops, a space
that starts a new match, a change between letters, digits and punctuation), so the ids of a text are the ids
of its pieces, one after the other.  Pieces are found and hashed with array operations, only pieces that the
worker has not met are given to the tokenizers library, and ids are put together by indexing.

Two layouts of tokenizer are known: ``words`` (lower-cases, drops white space, digits alone) and ``bytes``
(keeps white space, a leading space belongs to the next word).  Special tokens' strings in a text are ordinary text.
"""

from __future__ import annotations

import os
import zlib

import numpy as np
import pyarrow as pa

from segcube.llm import kernel as K

#: Pieces that a worker keeps; beyond them it starts anew, which costs time and changes no result.
CACHE_PIECES = 1_000_000
_TABLE_BITS = 22

_W, _L, _D, _P, _O = range(5)
_CLASS = np.full(256, _O, dtype=np.uint8)
_CLASS[[9, 10, 13, 32]] = _W
_CLASS[33:127] = _P
_CLASS[48:58] = _D
_CLASS[65:91] = _CLASS[97:123] = _L


def vocabulary(name: str) -> str:
    """Where a public tokenizer's file lies on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def _classes(data: np.ndarray) -> np.ndarray:
    kinds = _CLASS[data]
    lead = np.flatnonzero(data[:-1] == 0xC3)  # U+00C0..U+00FF: letters but for two signs
    second = data[lead + 1]
    lead = lead[(second >= 0x80) & (second <= 0xBF) & (second != 0x97) & (second != 0xB7)]
    kinds[lead] = kinds[lead + 1] = _L
    return kinds


def pieces(data: np.ndarray, offsets: np.ndarray, layout: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end of each piece, and each text's first piece."""
    if not len(data):
        none = np.zeros(0, dtype=np.int64)
        return none, none, np.zeros(len(offsets), dtype=np.int64)
    kinds = _classes(data)
    left, right = kinds[:-1], kinds[1:]
    cut = np.zeros(len(data) + 1, dtype=bool)
    known = (left != _W) & (left != _O) & (right != _W) & (right != _O)
    cut[1:-1] = known & (left != right) & (data[:-1] != 39)
    if layout == "words":
        cut[1:-1] |= (left == _W) != (right == _W)
    else:
        space = data == 32
        plain = (data > 32) & (data < 127)
        cut[1:-1] |= space[1:] & plain[:-1]
        cut[1:-2] |= space[1:-1] & plain[2:]
    cut[offsets] = True
    bounds = np.flatnonzero(cut)
    starts, ends = bounds[:-1], bounds[1:]
    if layout == "words":
        keep = kinds[starts] != _W
        starts, ends = starts[keep], ends[keep]
    return starts, ends, np.searchsorted(starts, offsets)


class Encoder:
    """Ids of texts by a tokenizer's file; one per worker and file, see :func:`encoder`."""

    def __init__(self, path: str, layout: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.layout = layout
        self._reset()

    def _reset(self):
        self.used = 0
        self.table = np.full(1 << _TABLE_BITS, -1, dtype=np.int32)  # the slot of a key by its first bits
        self.keys = np.zeros(1 << 16, dtype=np.uint64)  # by slot, as the next two
        self.sizes = np.zeros(1 << 16, dtype=np.int32)
        self.firsts = np.zeros(1 << 16, dtype=np.int64)
        self.n_ids = 0
        self.ids = np.zeros(1 << 18, dtype=np.uint32)
        self.crowded = np.zeros(0, dtype=np.uint64)  # keys whose place in the table another has, sorted
        self.crowded_slots = np.zeros(0, dtype=np.int32)

    @staticmethod
    def _grown(values: np.ndarray, need: int) -> np.ndarray:
        if need <= len(values):
            return values
        out = np.zeros(max(need, len(values) * 3 // 2), dtype=values.dtype)
        out[: len(values)] = values
        return out

    def _learn(self, keys: np.ndarray, texts: list[str]) -> np.ndarray:
        made = self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)
        sizes = np.fromiter((len(x) for x in made), dtype=np.int32, count=len(made))
        ids = np.fromiter((i for x in made for i in x.ids), dtype=np.uint32, count=int(sizes.sum()))
        slots = np.arange(self.used, self.used + len(keys), dtype=np.int32)
        self.used += len(keys)
        self.keys, self.sizes, self.firsts = (self._grown(x, self.used) for x in (self.keys, self.sizes, self.firsts))
        self.keys[slots], self.sizes[slots] = keys, sizes
        self.firsts[slots] = self.n_ids + np.cumsum(sizes, dtype=np.int64) - sizes
        self.ids = self._grown(self.ids, self.n_ids + len(ids))
        self.ids[self.n_ids : self.n_ids + len(ids)] = ids
        self.n_ids += len(ids)
        place = keys >> np.uint64(64 - _TABLE_BITS)
        free = self.table[place] < 0
        self.table[place[free]] = slots[free]
        late = self.keys[self.table[place]] != keys
        at = np.searchsorted(self.crowded, keys[late])
        self.crowded, self.crowded_slots = np.insert(self.crowded, at, keys[late]), np.insert(self.crowded_slots, at, slots[late])
        return slots

    def _slots(self, keys: np.ndarray, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        slots = self.table[keys >> np.uint64(64 - _TABLE_BITS)]
        miss = np.flatnonzero((slots < 0) | (self.keys[slots] != keys))
        if len(miss) and len(self.crowded):
            at = np.minimum(np.searchsorted(self.crowded, keys[miss]), len(self.crowded) - 1)
            hit = self.crowded[at] == keys[miss]
            slots[miss[hit]] = self.crowded_slots[at[hit]]
            miss = miss[~hit]
        if len(miss):
            new, sample, back = np.unique(keys[miss], return_index=True, return_inverse=True)
            if self.used and self.used + len(new) > CACHE_PIECES:
                self._reset()
                return self._slots(keys, data, starts, ends)
            raw, at = data.tobytes(), miss[sample]
            slots[miss] = self._learn(new, [raw[a:b].decode() for a, b in zip(starts[at], ends[at], strict=True)])[back]
        return slots

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, one after the other, and each text's offset in them (one more at the end)."""
        data, offsets = K.text_bytes(texts)
        if self.layout == "words":
            data = K.LOWER[data]
        starts, ends, first = pieces(data, offsets, self.layout)
        if not len(starts):
            return np.zeros(0, dtype=np.uint32), np.zeros(len(offsets), dtype=np.int64)
        slots = self._slots(K.hash_spans(data, starts, ends), data, starts, ends)
        sizes = self.sizes[slots]
        ids = self.ids[K.ranges(self.firsts[slots], sizes)]
        return ids, np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])[first]


_ENCODERS: dict[tuple[str, str], Encoder] = {}


def encoder(path: str, layout: str) -> Encoder:
    if (path, layout) not in _ENCODERS:
        _ENCODERS[path, layout] = Encoder(path, layout)
    return _ENCODERS[path, layout]


def append_end(ids: np.ndarray, offsets: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """The same texts with ``end_id`` after each."""
    n = len(offsets) - 1
    out_offsets = offsets + np.arange(n + 1)
    out = np.empty(len(ids) + n, dtype=np.uint32)
    out[out_offsets[1:] - 1] = end_id
    out[K.ranges(out_offsets[:-1], np.diff(offsets))] = ids
    return out, out_offsets


def crc32(ids: np.ndarray) -> int:
    """Unsigned CRC-32 of ids as little-endian unsigned 32-bit integers."""
    return zlib.crc32(np.ascontiguousarray(ids, dtype="<u4").tobytes())
