"""Best-fit packing of token sequences by length patterns.

Only the histogram of piece lengths (at most ``capacity`` numbers, whatever the corpus) reaches the driver.  There
patterns of two to four lengths that fill a sequence exactly are enumerated, their repeat counts fitted to the
histogram by non-negative least squares and rounded down, and what remains is packed best-fit, longest first, again
as patterns with repeat counts.  A plan has a few thousand rows at most.  Each piece then finds its place from its
length and its rank among all pieces of that length; ranks come from counts per task, so a length that
a third of all rows share is no hot key.  Token ids stay with their piece, as little-endian unsigned 32-bit integers (compressed byte
planes until the piece has its place); :func:`sequences` puts the pieces of each sequence together.

Null texts and empty texts are a single end id; repeated ids and rows are packed like any others; a null id is kept;
an empty table gives no rows; columns other than id and text are not read.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segcube.llm import encoding, shared
from segcube.llm import kernel as K

_PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids binary, part int, rank bigint"
_PLACED = "doc_id bigint, piece int, start bigint, length bigint, ids binary, sequence_id bigint, offset bigint"
#: Pieces that go to Spark at once; bounds their ids.
_BATCH = 500


def _compressed(compressor: zstandard.ZstdCompressor, ids: np.ndarray) -> bytes:
    return compressor.compress(np.ascontiguousarray(ids.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes())


def _plain(decompressor: zstandard.ZstdDecompressor, data: bytes) -> bytes:
    return np.ascontiguousarray(np.frombuffer(decompressor.decompress(data), dtype=np.uint8).reshape(4, -1).T).tobytes()


def exact_patterns(lengths: np.ndarray, capacity: int, per_anchor: int = 6) -> list[tuple[int, ...]]:
    """Patterns of two to four present lengths that sum to ``capacity``; per longest length a few, evenly spread."""
    present = np.zeros(capacity + 1, dtype=bool)
    present[lengths] = True
    out: dict[tuple[int, ...], None] = {}
    for a in lengths[::-1]:
        rest = capacity - int(a)
        if 0 < rest <= a and present[rest]:
            out[int(a), rest] = None
        seconds = lengths[(lengths <= a) & (lengths < rest)]
        thirds = seconds[(rest - seconds <= seconds) & present[np.clip(rest - seconds, 0, capacity)]]
        for b in thirds[np.linspace(0, len(thirds) - 1, min(per_anchor, len(thirds))).astype(int)]:
            out[int(a), int(b), rest - int(b)] = None
        for b in seconds[np.linspace(0, len(seconds) - 1, min(per_anchor, len(seconds))).astype(int)]:
            left = rest - int(b)
            c = lengths[(lengths <= b) & (lengths < left)]
            c = c[(left - c <= c) & present[np.clip(left - c, 0, capacity)]]
            if len(c):
                out[int(a), int(b), int(c[len(c) // 2]), left - int(c[len(c) // 2])] = None
    return list(out)


def non_negative_fit(patterns: list[tuple[int, ...]], target: np.ndarray, sweeps: int = 25) -> np.ndarray:
    """Least squares ``min |A x - target|`` over ``x >= 0`` by coordinate descent; a column of A counts a pattern's lengths."""
    x = np.zeros(len(patterns))
    left = target.astype(float).tolist()
    columns = [(dict((v, p.count(v)) for v in p), sum(p.count(v) ** 2 for v in set(p))) for p in patterns]
    for _ in range(sweeps):
        moved = 0.0
        for j, (column, norm) in enumerate(columns):
            step = max(-x[j], sum(left[v] * n for v, n in column.items()) / norm)
            if step:
                x[j] += step
                moved += abs(step)
                for v, n in column.items():
                    left[v] -= step * n
        if moved < 0.5:
            break
    return x


def best_fit(counts: np.ndarray, capacity: int) -> Iterator[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing over a histogram: patterns with repeat counts; uses up ``counts``."""
    present = sorted(int(v) for v in np.flatnonzero(counts))
    while present:
        used: dict[int, int] = {}
        left, pattern = capacity, []
        while True:
            i = bisect.bisect_right(present, left) - 1
            while i >= 0 and counts[present[i]] <= used.get(present[i], 0):
                i -= 1
            if i < 0:
                break
            v = present[i]
            times = min(left // v, int(counts[v]) - used.get(v, 0))
            used[v] = used.get(v, 0) + times
            pattern += [v] * times
            left -= v * times
        repeat = min(int(counts[v]) // n for v, n in used.items())
        for v, n in used.items():
            counts[v] -= repeat * n
            if not counts[v]:
                present.remove(v)
        yield tuple(pattern), repeat


def plan(histogram: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns of lengths and how often each is used; together they use every counted piece once.

    The fitted repeat counts are rounded down at several shares of their size, and the plan with the fewest sequences is taken:
    where lengths have few pieces, too many exact patterns can use up the short ones that long ones need.
    """
    counts = histogram.astype(np.int64).copy()
    whole = [((capacity,), int(counts[capacity]))] if counts[capacity] else []
    counts[capacity] = 0
    patterns = exact_patterns(np.flatnonzero(counts), capacity)
    wishes = non_negative_fit(patterns, counts)
    return whole + min((_rounded(counts, capacity, patterns, wishes * share) for share in (1, 0.9, 0.7, 0.4, 0)), key=lambda p: sum(n for _, n in p))


def _rounded(counts: np.ndarray, capacity: int, patterns: list[tuple[int, ...]], wishes: np.ndarray) -> list[tuple[tuple[int, ...], int]]:
    left, out = counts.copy(), []
    for pattern, wish in zip(patterns, wishes, strict=True):
        repeat = min([int(wish), *(int(left[v]) // pattern.count(v) for v in set(pattern))])
        if repeat > 0:
            out.append((pattern, repeat))
            for v in pattern:
                left[v] -= repeat
    return out + list(best_fit(left, capacity))


def encoded_pieces(docs: DataFrame, tokenizer: str, layout: str, end_id: int, capacity: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: only documents longer than ``capacity`` are cut, their first piece being the short one."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, encoder = TaskContext.get().partitionId(), encoding.encoder(tokenizer, layout)
        seen, compressor = np.zeros(capacity + 1, dtype=np.int64), zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for part in K.steps(batch, "text"):
                ids, offsets = encoding.append_end(*encoder.encode(part.column("text")), end_id)
                size = np.diff(offsets)
                n = -(-size // capacity)
                doc = np.repeat(np.arange(len(size)), n)
                piece = K.ranges(np.zeros(len(n), dtype=np.int64), n)
                short = size - (n - 1) * capacity
                start = np.where(piece == 0, 0, short[doc] + (piece - 1) * capacity)
                length = np.where(piece == 0, short[doc], capacity)
                at = offsets[:-1][doc] + start
                order = np.argsort(length, kind="stable")
                run = length[order]
                rank = np.empty(len(run), dtype=np.int64)
                rank[order] = seen[run] + np.arange(len(run)) - np.searchsorted(run, run)
                seen += np.bincount(length, minlength=capacity + 1)
                for a in range(0, len(doc), _BATCH):
                    these = slice(a, a + _BATCH)
                    blobs = [_compressed(compressor, ids[i:j]) for i, j in zip(at[these], at[these] + length[these], strict=True)]
                    columns = [part.column("doc_id").take(pa.array(doc[these])), pa.array(piece[these], pa.int32()), pa.array(start[these], pa.int64()), pa.array(length[these], pa.int64()), pa.array(blobs, pa.binary()), pa.array(np.full(len(blobs), task), pa.int32()), pa.array(rank[these])]
                    yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "piece", "start", "length", "ids", "part", "rank"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(cut, _PIECES)


def pack(docs: DataFrame, tokenizer: str, layout: str = "bytes", end_id: int = 0, capacity: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every piece with its ids and their checksum, its sequence and its place there."""
    pieces = shared.materialised(encoded_pieces(docs, tokenizer, layout, end_id, capacity, id_col, text_col), "pieces")
    counts = pieces.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shift = counts.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shift"))
    shift = shared.materialised(shift, "shifts")  # as a table of known size it need not move the ids while it is small
    histogram = np.zeros(capacity + 1, dtype=np.int64)
    for row in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most ``capacity`` rows
        histogram[row.length] = row.n
    base = np.cumsum(histogram) - histogram
    taken, sequence = base.copy(), 0
    keys, sequences, offsets = [], [], []
    for pattern, repeat in plan(histogram, capacity):
        at = 0
        for v in pattern:
            keys.append(int(taken[v]))
            sequences.append(sequence)
            offsets.append(at)
            taken[v] += repeat
            at += v
        sequence += repeat
    order = np.argsort(np.array(keys, dtype=np.int64), kind="stable")
    slots = [np.array(x, dtype=np.int64)[order] for x in (keys, sequences, offsets)]
    shared_plan = docs.sparkSession.sparkContext.broadcast((base, *slots))  # bounded by the capacity

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, keys, sequences, offsets = shared_plan.value
        decompressor = zstandard.ZstdDecompressor()
        for every in batches:
            for a in range(0, every.num_rows, _BATCH):
                batch = every.slice(a, _BATCH)
                key = base[batch.column("length").to_numpy()] + batch.column("rank").to_numpy() + batch.column("shift").to_numpy()
                at = np.searchsorted(keys, key, side="right") - 1
                columns = [batch.column(c) for c in ("doc_id", "piece", "start", "length")]
                columns += [pa.array([_plain(decompressor, x) for x in batch.column("ids").to_pylist()], pa.binary()), pa.array(sequences[at] + key - keys[at]), pa.array(offsets[at])]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "piece", "start", "length", "ids", "sequence_id", "offset"])

    return pieces.join(shift, ["length", "part"]).mapInArrow(place, _PLACED).withColumn("ids_crc32", F.crc32("ids"))


def sequences(packed: DataFrame) -> DataFrame:
    """``sequence_id, length, ids, pieces``: the rows of :func:`pack` as whole training sequences, with what each holds from where."""
    pieces = F.array_sort(F.collect_list(F.struct("offset", "length", "doc_id", "piece", "start", "ids")))
    whole = packed.groupBy("sequence_id").agg(F.sum("length").alias("length"), pieces.alias("pieces"))
    ids = F.unhex(F.array_join(F.transform("pieces", lambda p: F.hex(p["ids"])), ""))
    return whole.select("sequence_id", "length", ids.alias("ids"), F.transform("pieces", lambda p: p.dropFields("ids")).alias("pieces"))
