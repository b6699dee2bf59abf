"""Benchmark decontamination with a distributed positional inverted index.

The index is a table of *segments*, each made by one task from a few megabytes of text: its documents, its distinct
terms (64-bit hashes, sorted), and for every term the list of word positions at which it stands, as compressed gaps.
All words of all documents are stored, so one index answers any later set of test items.  A search takes the windows of the
test items in blocks of bounded size; in each segment it starts from the posting list of a window's rarest term there,
shifts it by the term's place in the window, and intersects the shifted lists of the other terms, rarest first.
Segments answer independently: a search shuffles nothing, and no term's list is ever gathered from the whole corpus.

Words are maximal runs of ASCII letters and digits and all other non-ASCII characters, A-Z lower-cased.  A null or empty text has no
words and no hits; repeated documents are indexed and reported one by one; an item without words matches nothing; a null item id is
the empty string, items of equal id count once; empty tables give no rows or no hits.  Two words are taken as equal if their
64-bit hashes are.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.llm import kernel as K
from segcube.llm import shared

#: Words of a window.
WINDOW = 10
#: Windows broadcast at once (some 20 MB); more are searched block by block.
BLOCK_WINDOWS = 200_000
#: Candidate places looked at in one step.
_CANDIDATES = 1 << 20

_SEGMENTS = "segment bigint, doc_ids array<bigint>, text_hashes array<bigint>, first_words binary, terms binary, term_starts binary, gaps binary"


def _packed(values: np.ndarray) -> bytes:
    """Unsigned 32-bit numbers byte plane by byte plane, compressed."""
    planes = np.ascontiguousarray(values.astype("<u4").view(np.uint8).reshape(-1, 4).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), dtype=np.uint8)
    return np.ascontiguousarray(planes.reshape(4, -1).T).view("<u4").ravel().astype(np.int64)


def _words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    data, offsets = K.text_bytes(texts)
    data = K.LOWER[data]
    starts, ends, first = K.find_words(data, offsets, K.ALNUM)
    return K.hash_spans(data, starts, ends), first


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The segments of all documents, stored in the shared folder."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        segment = TaskContext.get().partitionId() << 32
        for batch in batches:
            for part in K.steps(batch, "text"):
                hashes, first = _words(part.column("text"))
                order = np.argsort(hashes, kind="stable")
                terms, term_starts = np.unique(hashes[order], return_index=True)
                gaps = np.diff(order, prepend=0)
                gaps[term_starts] = order[term_starts]
                ids = pa.array([part.column("doc_id").to_pylist()], pa.list_(pa.int64()))
                marks = pa.array([part.column("text_hash").to_pylist()], pa.list_(pa.int64()))
                blobs = [_packed(first), terms.tobytes(), _packed(term_starts), _packed(gaps)]
                yield pa.RecordBatch.from_arrays([pa.array([segment], pa.int64()), ids, marks, *(pa.array([b], pa.binary()) for b in blobs)], names=["segment", "doc_ids", "text_hashes", "first_words", "terms", "term_starts", "gaps"])
                segment += 1

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_hash"))
    return shared.materialised(rows.mapInArrow(build, _SEGMENTS), "postings")


class Segment:
    """A segment in memory: posting lists as one array of ``term number * words + position``, ascending."""

    def __init__(self, row: dict):
        self.first = _unpacked(row["first_words"])
        self.n_words = int(self.first[-1])
        self.terms = np.frombuffer(row["terms"], dtype=np.uint64)
        self.starts = np.append(_unpacked(row["term_starts"]), self.n_words)
        sums = np.cumsum(_unpacked(row["gaps"]))
        before = np.concatenate([[0], sums])[self.starts[:-1]]
        number = np.repeat(np.arange(len(self.terms)), np.diff(self.starts))
        self.positions = sums - before[number]
        self.keys = number * np.int64(self.n_words + 1) + self.positions

    def term_numbers(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.terms):
            return np.full(hashes.shape, -1)
        at = np.minimum(np.searchsorted(self.terms, hashes), len(self.terms) - 1)
        return np.where(self.terms[at] == hashes, at, -1)

    def holds(self, numbers: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Whether each term stands at one of the positions ``low..high``."""
        base = numbers * np.int64(self.n_words + 1)
        at = np.searchsorted(self.keys, base + np.maximum(low, 0))
        found = self.keys[np.minimum(at, len(self.keys) - 1)]
        return (at < len(self.keys)) & (found <= base + np.minimum(high, self.n_words))

    def _anchors(self, windows: np.ndarray, sizes: np.ndarray, vocabulary: np.ndarray):
        """Windows all whose terms occur here, in steps: window, term numbers, rarest-first order, places of the rarest."""
        numbers = self.term_numbers(vocabulary)[windows]
        used = np.arange(windows.shape[1]) < sizes[:, None]
        count = np.where(used, np.where(numbers >= 0, np.diff(self.starts, append=0)[numbers], 0), np.iinfo(np.int64).max)
        alive = np.flatnonzero(count.min(axis=1, initial=np.iinfo(np.int64).max) > 0)
        rarity = np.argsort(count[alive], axis=1, kind="stable")
        work = np.cumsum(count[alive, rarity[:, 0]]) if len(alive) else np.zeros(0)
        at = 0
        while at < len(alive):
            end = max(at + 1, int(np.searchsorted(work, (work[at - 1] if at else 0) + _CANDIDATES, side="right")))
            w, order = alive[at:end], rarity[at:end]
            rarest = numbers[w, order[:, 0]]
            n = self.starts[rarest + 1] - self.starts[rarest]
            row = np.repeat(np.arange(len(w)), n)
            yield w, numbers[w], order, row, self.positions[K.ranges(self.starts[rarest], n)]
            at = end

    def phrases(self, windows: np.ndarray, sizes: np.ndarray, vocabulary: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Window and first word of each exact occurrence inside a document."""
        found_w, found_at = [], []
        for w, numbers, order, row, place in self._anchors(windows, sizes, vocabulary):
            start = place - order[row, 0]
            for k in range(1, windows.shape[1]):
                slot = order[row, k]
                need = slot < sizes[w[row]]
                ok = ~need
                ok[need] = self.holds(numbers[row[need], slot[need]], start[need] + slot[need], start[need] + slot[need])
                row, start = row[ok], start[ok]
            doc = np.searchsorted(self.first, start, side="right") - 1
            inside = (start >= 0) & (start + sizes[w[row]] <= self.first[np.minimum(doc + 1, len(self.first) - 1)])
            found_w.append(w[row[inside]])
            found_at.append(start[inside])
        none = np.zeros(0, dtype=np.int64)
        return np.concatenate([none, *found_w]), np.concatenate([none, *found_at])

    def near(self, windows: np.ndarray, sizes: np.ndarray, vocabulary: np.ndarray, slop: int) -> tuple[np.ndarray, np.ndarray]:
        """Window and place of its rarest word where all its words stand within ``slop`` words of that place, in any order."""
        found_w, found_at = [], []
        for w, numbers, order, row, place in self._anchors(windows, sizes, vocabulary):
            for k in range(1, windows.shape[1]):
                doc = np.searchsorted(self.first, place, side="right") - 1
                slot = order[row, k]
                need = slot < sizes[w[row]]
                ok = ~need
                low, high = np.maximum(place - slop, self.first[doc]), np.minimum(place + slop, self.first[doc + 1] - 1)
                ok[need] = self.holds(numbers[row[need], slot[need]], low[need], high[need])
                row, place = row[ok], place[ok]
            found_w.append(w[row])
            found_at.append(place)
        none = np.zeros(0, dtype=np.int64)
        return np.concatenate([none, *found_w]), np.concatenate([none, *found_at])


class Block:
    """A bounded set of windows: term numbers in ``vocabulary``, sizes, and the items each belongs to."""

    def __init__(self, items: list[tuple[str, np.ndarray]], window: int):
        rows: dict[bytes, int] = {}
        owners: list[tuple[int, str]] = []
        for item, hashes in items:
            for k in range(max(1, len(hashes) - window + 1) if len(hashes) else 0):
                owners.append((rows.setdefault(hashes[k : k + window].tobytes(), len(rows)), item))
        whole = [np.frombuffer(x, dtype=np.uint64) for x in rows]
        self.sizes = np.array([len(x) for x in whole], dtype=np.int64)
        self.vocabulary, numbers = np.unique(np.concatenate([np.zeros(0, dtype=np.uint64), *whole]), return_inverse=True)
        self.windows = np.zeros((len(whole), window), dtype=np.int64)
        self.windows[np.arange(window) < self.sizes[:, None]] = numbers
        self.items = sorted({item for _, item in owners})
        number = {item: n for n, item in enumerate(self.items)}
        pairs = sorted({(w, number[item]) for w, item in owners})
        self.owner_items = np.array([i for _, i in pairs], dtype=np.int64)
        self.owner_first = np.searchsorted(np.array([w for w, _ in pairs], dtype=np.int64), np.arange(len(whole) + 1))


def blocks(items: DataFrame, window: int = WINDOW, limit: int = BLOCK_WINDOWS, id_col: str = "item_id", text_col: str = "text") -> Iterator[Block]:
    """The windows of the test items, in blocks of about ``limit`` windows."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in K.steps(batch, "text"):
                hashes, first = _words(part.column("text"))
                words = [hashes[a:b].astype(np.uint64).tobytes() for a, b in zip(first[:-1], first[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("item_id"), pa.array(words, pa.binary()), pa.array(np.diff(first), pa.int64())], names=["item_id", "words", "n"])

    rows = items.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("item_id"), F.col(text_col).alias("text"))
    rows = shared.materialised(rows.mapInArrow(hashed, "item_id string, words binary, n bigint").filter("n > 0"), "items")
    total = rows.agg(F.sum("n")).first()[0] or 0
    n = max(1, -(-total // limit))
    for k in range(n):
        part = rows.filter(F.pmod(F.xxhash64("item_id", "words"), F.lit(n)) == k) if n > 1 else rows
        yield Block([(r.item_id, np.frombuffer(r.words, dtype=np.uint64)) for r in part.select("item_id", "words").collect()], window)


def _search(index: DataFrame, block: Block) -> DataFrame:
    """Per document: its number of words, its hit words as disjoint ranges, and the items found."""
    schema = "segment bigint, doc int, doc_id bigint, text_hash bigint, n_words bigint, ranges array<struct<low:bigint,high:bigint>>, items array<string>"
    sent = index.sparkSession.sparkContext.broadcast(block)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = sent.value
        for batch in batches:
            for row in batch.to_pylist():
                yield found(Segment(row), row, block)

    def found(segment: Segment, row: dict, block: Block) -> pa.RecordBatch:
        n_docs = len(row["doc_ids"])
        w, at = segment.phrases(block.windows, block.sizes, block.vocabulary)
        edge = np.bincount(at, minlength=segment.n_words + 1) - np.bincount(at + block.sizes[w], minlength=segment.n_words + 1)
        hit = np.concatenate([[False], np.cumsum(edge[: segment.n_words]) > 0, [False]])
        border = np.zeros(segment.n_words + 1, dtype=bool)
        border[segment.first] = True
        low = np.flatnonzero(hit[1:] & (~hit[:-1] | border))
        low = low[low < segment.n_words]
        high = np.flatnonzero(hit[1:-1] & (~hit[2:] | border[1:])) + 1
        doc = np.searchsorted(segment.first, low, side="right") - 1
        n_items = block.owner_first[w + 1] - block.owner_first[w]
        pairs = np.unique(np.stack([np.repeat(np.searchsorted(segment.first, at, side="right") - 1, n_items), block.owner_items[K.ranges(block.owner_first[w], n_items)]]), axis=1)
        place = lambda doc: np.searchsorted(doc, np.arange(n_docs + 1)).astype(np.int32)
        pair_type = pa.struct([("low", pa.int64()), ("high", pa.int64())])
        spans = pa.StructArray.from_arrays([pa.array(low - segment.first[doc]), pa.array(high - segment.first[doc])], fields=list(pair_type))
        items = pa.array([block.items[i] for i in pairs[1]], pa.string())
        columns = [
            pa.array(np.full(n_docs, row["segment"]), pa.int64()), pa.array(np.arange(n_docs), pa.int32()), pa.array(row["doc_ids"], pa.int64()), pa.array(row["text_hashes"], pa.int64()), pa.array(np.diff(segment.first), pa.int64()),
            pa.ListArray.from_arrays(pa.array(place(doc)), spans), pa.ListArray.from_arrays(pa.array(place(pairs[0])), items),
        ]
        return pa.RecordBatch.from_arrays(columns, names=["segment", "doc", "doc_id", "text_hash", "n_words", "ranges", "items"])

    return index.mapInArrow(search, schema)


def contamination(index: DataFrame, items: DataFrame, window: int = WINDOW, limit: int = BLOCK_WINDOWS, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """One row per indexed document: ``doc_id, n_words, n_hit``, the hit ``ranges`` and the ``items`` whose windows occur."""
    parts = [_search(index, block) for block in blocks(items, window, limit, id_col, text_col)]
    out = parts[0]
    if len(parts) > 1:
        for part in parts[1:]:
            out = out.unionByName(part)
        # at most one row per document and block meets here
        out = out.groupBy("segment", "doc").agg(
            F.first("doc_id").alias("doc_id"), F.first("text_hash").alias("text_hash"), F.first("n_words").alias("n_words"), F.array_sort(F.flatten(F.collect_list("ranges"))).alias("ranges"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"),
        )
    n_hit = "aggregate(ranges, named_struct('seen', 0L, 'n', 0L), (a, r) -> named_struct('seen', greatest(a.seen, r.high), 'n', a.n + greatest(0L, r.high - greatest(a.seen, r.low))), a -> a.n)"
    return out.select("segment", "doc", "doc_id", "text_hash", "n_words", F.expr(n_hit).alias("n_hit"), "ranges", "items")


def without_contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that hold a window of any test item."""
    hit = contamination(build_index(docs, id_col, text_col), items).filter("n_hit > 0").select(F.col("doc_id").alias("_hit_id"), F.col("text_hash").alias("_hit_hash")).distinct()
    text_hash = F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))
    return docs.join(hit, F.col(id_col).cast("bigint").eqNullSafe(F.col("_hit_id")) & (text_hash == F.col("_hit_hash")), "left_anti")


def proximity(index: DataFrame, items: DataFrame, slop: int, window: int = WINDOW, limit: int = BLOCK_WINDOWS, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """Places where all words of a window stand within ``slop`` words of its locally rarest word, in any order: ``doc_id, item_id, word``."""

    def searcher(block):
        sent = index.sparkSession.sparkContext.broadcast(block)

        def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            block = sent.value
            for batch in batches:
                for row in batch.to_pylist():
                    segment = Segment(row)
                    w, at = segment.near(block.windows, block.sizes, block.vocabulary, slop)
                    n = block.owner_first[w + 1] - block.owner_first[w]
                    item, at = block.owner_items[K.ranges(block.owner_first[w], n)], np.repeat(at, n)
                    doc = np.searchsorted(segment.first, at, side="right") - 1
                    yield pa.RecordBatch.from_arrays([pa.array([row["doc_ids"][d] for d in doc], pa.int64()), pa.array([block.items[i] for i in item], pa.string()), pa.array(at - segment.first[doc])], names=["doc_id", "item_id", "word"])

        return search

    out = None
    for block in blocks(items, window, limit, id_col, text_col):
        part = index.mapInArrow(searcher(block), "doc_id bigint, item_id string, word bigint")
        out = part if out is None else out.unionByName(part)
    return out.distinct()


def items_digest(items: str = "items") -> F.Column:
    """Lower-case hex SHA-256 of the item ids, sorted as strings and joined by commas."""
    return F.sha2(F.array_join(F.array_sort(F.col(items)), ","), 256)


def digest_of(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
