"""Exact Jaccard join of documents' word shingles as a blocked sparse matrix product.

The documents are rows and the shingles columns of a 0/1 matrix A; two documents link when their entry of A.A^T (the
number of shared shingles) reaches the threshold.  Steps:

1. One pass gives each document's number of shingles and a fingerprint of its set; equal sets are one *class* from
   here on.  The pass also counts shingles in a fixed number of buckets, which order all shingles from rare to frequent.
2. A second pass keeps, per class, the columns that sizes alone prove sufficient: two sets with ``J >= t`` share at least
   ``t * max(sizes)`` shingles, so they share at least ``e`` of their rarest ``n - ceil(t n) + e``.  Here
   ``e = ceil(n / 10)`` of the smaller set.  Overlaps are accumulated over these columns only, and pairs that stay below ``e`` or
   whose sizes differ too much are discarded.  Columns of more than ``LIGHT`` classes are not expanded into pairs: their classes are
   tied to one of them.
3. What is left forms groups.  A last pass builds the whole sets of grouped classes (a Bloom filter of fixed size
   picks their documents), lays each group out in blocks of about a million entries ordered by set size, and multiplies
   block by block; block pairs whose sizes exclude a link are skipped.  Each product returns a spanning forest of its links, never all pairs.

Components of the links give the result.  Shingles and classes are told apart by 64-bit hashes.

Null and empty texts, and texts without words, have an empty set and link with nothing; fewer words than a shingle has are one
shingle; repeated rows are copies of each other; rows with a null id take part, but are no component's name unless
all its ids are null; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segcube.llm import kernel as K
from segcube.llm import shared
from segcube.llm.components import components

#: Words of a shingle.
SHINGLE = 5
#: Buckets (as a power of two) that order shingles by frequency; more buckets discard more pairs early, results stay equal.
SKETCH_BITS = 22
#: Columns of at most so many classes are expanded into pairs.
LIGHT = 64
#: Entries of a block, and the fewest that a row of it counts for, so that a block has 1,024 rows at most.
BLOCK_ENTRIES, ROW_ENTRIES = 1 << 20, 1 << 10
#: Bits of the filter that picks the documents of grouped classes.
FILTER_BITS = 1 << 26
_CHUNK = 4096


def shingle_sets(texts: pa.Array, k: int = SHINGLE) -> list[np.ndarray]:
    """Each text's sorted distinct shingle hashes."""
    data, offsets = K.text_bytes(texts)
    data = K.LOWER[data]
    starts, ends, first = K.find_words(data, offsets, K.NONSPACE)
    words = K.hash_spans(data, starts, ends)
    rolled, out = K.roll(words, k), []
    for a, b in zip(first[:-1], first[1:], strict=True):
        if b - a >= k:
            out.append(np.unique(rolled[a : b - k + 1]))
        else:
            out.append(K.roll(words[a:b], int(b - a)) if b > a else words[:0])
    return out


def class_of(hashes: np.ndarray) -> int:
    """A signed 64-bit fingerprint of a set."""
    return xxhash.xxh3_64_intdigest(hashes.tobytes(), seed=len(hashes)) - (1 << 63)


def needed(n, percent: int):
    """The fewest shingles that a set of ``n`` shares with any set it links to."""
    return (n * percent + 99) // 100


def _first_pass(docs: DataFrame, k: int, bits: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << bits, dtype=np.uint32)
        for batch in batches:
            for part in K.steps(batch, "text"):
                sets = shingle_sets(part.column("text"), k)
                every = np.concatenate([np.zeros(0, dtype=np.uint64), *sets])
                counts += np.bincount((every >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits).astype(np.uint32)
                n = part.num_rows
                nodes = pa.array([class_of(s) if len(s) else None for s in sets], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_hash"), pa.array([len(s) for s in sets], pa.int64()), nodes, pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())], names=names)
        pack = zstandard.ZstdCompressor(level=1)
        rows = [(i, pack.compress(c.view(np.uint8).reshape(-1, 4).T.tobytes())) for i, c in enumerate(counts.reshape(-1, _CHUNK)) if c.any()]
        if rows:
            none = pa.nulls(len(rows), pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, none, none, pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=names)

    names = ["doc_id", "text_hash", "n", "node", "chunk", "counts"]
    return shared.materialised(docs.mapInArrow(run, "doc_id bigint, text_hash bigint, n bigint, node bigint, chunk int, counts binary"), "sets")


def _frequencies(first: DataFrame, bits: int) -> np.ndarray:
    """Bucket counts over all documents on a logarithmic scale, a byte each."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for chunk, data in zip(batch.column("chunk").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                planes = np.frombuffer(unpack.decompress(data), dtype=np.uint8).reshape(4, -1)
                total.setdefault(chunk, np.zeros(_CHUNK, dtype=np.int64))
                total[chunk] += np.ascontiguousarray(planes.T).view("<u4").ravel()
        if total:
            scaled = [np.minimum(255, np.round(6 * np.log2(1 + c))).astype(np.uint8).tobytes() for c in total.values()]
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array(scaled, pa.binary())], names=["chunk", "counts"])

    out = np.zeros((1 << bits) // _CHUNK * _CHUNK, dtype=np.uint8)
    rows = first.filter("chunk is not null").select("chunk", "counts").repartition(first.sparkSession.sparkContext.defaultParallelism * 2, "chunk")
    for row in rows.mapInArrow(add, "chunk int, counts binary").collect():  # a fixed number of bytes
        out[row.chunk * _CHUNK : (row.chunk + 1) * _CHUNK] = np.frombuffer(row.counts, dtype=np.uint8)
    return out


def _columns(docs: DataFrame, frequencies: np.ndarray, k: int, percent: int, bits: int) -> DataFrame:
    """Per class (at most once a task): its size and the columns that suffice to find its links."""
    sent = docs.sparkSession.sparkContext.broadcast(frequencies)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for part in K.steps(batch, "text"):
                rows = []
                for s in shingle_sets(part.column("text"), k):
                    node = class_of(s) if len(s) else None
                    if node is None or node in seen:
                        continue
                    seen.add(node)
                    n = len(s)
                    keep = n - needed(n, percent) + -(-n // 10)
                    rank = sent.value[(s >> np.uint64(64 - bits)).astype(np.int64)]
                    rows.append((node, n, s[np.argsort(rank, kind="stable")[:keep]].tobytes()))
                if len(seen) > 500_000:
                    seen.clear()
                if rows:
                    a, b, c = zip(*rows, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.binary())], names=["node", "n", "columns"])

    return shared.materialised(docs.select("text").mapInArrow(run, "node bigint, n bigint, columns binary"), "columns")


def _entries(columns: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            step = 256
            for a in range(0, batch.num_rows, step):
                part = batch.slice(a, step)
                blobs = part.column("columns").to_pylist()
                at = np.repeat(np.arange(len(blobs)), [len(x) // 8 for x in blobs])
                g = np.frombuffer(b"".join(blobs), dtype=np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(g), part.column("node").take(pa.array(at)), part.column("n").take(pa.array(at)).cast(pa.int32())], names=["g", "node", "n"])

    return columns.mapInArrow(run, "g bigint, node bigint, n int")


def _groups(columns: DataFrame, percent: int, light: int) -> DataFrame | None:
    """``node, n, grp``: classes that may link, by group; None if there are none."""
    entries = _entries(columns)
    shared_columns = entries.groupBy("g").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("g")
    held = shared.materialised(entries.join(shared_columns.hint("shuffle_merge"), "g").distinct(), "held")
    size = held.groupBy("g").agg(F.count(F.lit(1)).alias("c"), F.min("node").alias("hub")).filter("c > 1")
    sized = held.join(size, "g")
    few = sized.filter(F.col("c") <= light).select("g", "node", "n")
    one, two = few.alias("one"), few.alias("two")
    pairs = one.join(two, "g").filter("one.node < two.node and 100 * least(one.n, two.n) >= %d * greatest(one.n, two.n)" % percent)
    pairs = pairs.select(F.col("one.node").alias("a"), F.col("two.node").alias("b"), F.least("one.n", "two.n").alias("n"))
    pairs = pairs.groupBy("a", "b").agg(F.first("n").alias("n"), F.count(F.lit(1)).alias("shared")).filter("shared >= ceil(n / 10)")
    ties = sized.filter((F.col("c") > light) & (F.col("node") != F.col("hub"))).select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    edges = shared.materialised(pairs.select("a", "b").unionByName(ties), "candidates")
    return None if edges.isEmpty() else components(edges).select("node", F.col("component").alias("grp"))


def _filter_places(values: np.ndarray) -> np.ndarray:
    h = K.mix(values.astype(np.int64).view(np.uint64).copy())
    return np.concatenate([h % np.uint64(FILTER_BITS), (h >> np.uint64(32)) % np.uint64(FILTER_BITS)]).astype(np.int64)


def _document_filter(ids: DataFrame) -> np.ndarray:
    """A Bloom filter over document ids, built in pieces by the executors; its size does not depend on theirs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                places = np.unique(_filter_places(batch.column("id").fill_null(0).to_numpy()))
                yield pa.RecordBatch.from_arrays([pa.array(places >> 6), pa.array(np.int64(1) << (places & 63))], names=["word", "bit"])

    out = np.zeros(FILTER_BITS // 64, dtype=np.int64)
    for batch in ids.mapInArrow(run, "word bigint, bit bigint").groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow().to_batches():
        out[batch.column("word").to_numpy()] = batch.column("bits").to_numpy()
    return out


def _sets_of(docs: DataFrame, wanted: DataFrame, members: DataFrame, k: int) -> DataFrame:
    """``node, n, grp, hashes``: whole sets of the grouped classes."""
    one_doc = members.groupBy("node").agg(F.min("doc_id").alias("id"))
    ids = one_doc.join(wanted, "node").select("id")
    sent = docs.sparkSession.sparkContext.broadcast(_document_filter(ids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, seen = sent.value, set()
        for batch in batches:
            if not batch.num_rows:
                continue
            places = _filter_places(batch.column("doc_id").fill_null(0).to_numpy()).reshape(2, -1)
            picked = batch.filter(pa.array(((bits[places >> 6] >> (places & 63)) & 1).all(axis=0)))
            for part in K.steps(picked, "text"):
                rows = []
                for s in shingle_sets(part.column("text"), k):
                    node = class_of(s) if len(s) else None
                    if node is not None and node not in seen:
                        seen.add(node)
                        rows.append((node, len(s), s.tobytes()))
                if len(seen) > 500_000:
                    seen.clear()
                if rows:
                    a, b, c = zip(*rows, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.binary())], names=["node", "n", "hashes"])

    sets = docs.select("doc_id", "text").mapInArrow(run, "node bigint, n bigint, hashes binary")
    return shared.materialised(sets.join(wanted, "node").dropDuplicates(["node"]), "whole-sets")


def overlaps(rows: list[np.ndarray], others: list[np.ndarray]) -> np.ndarray:
    """The product block: how many elements each of ``rows`` shares with each of ``others``."""
    m, n = len(rows), len(others)
    every = np.concatenate([*rows, *others])
    owner = np.repeat(np.arange(m + n), [len(x) for x in (*rows, *others)])
    order = np.argsort(every, kind="stable")
    every, owner = every[order], owner[order]
    first = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]])) if len(every) else np.zeros(0, dtype=np.int64)
    size = np.diff(np.append(first, len(every)))
    left = np.add.reduceat(owner < m, first) if len(first) else size  # owners ascend: those of ``rows`` come first
    right = size - left
    out = np.zeros((m, n), dtype=np.float32)
    sparse = np.flatnonzero((left > 0) & (right > 0) & (left * right <= 64))
    if len(sparse):
        many = left[sparse] * right[sparse]
        column, k = np.repeat(sparse, many), K.ranges(np.zeros(len(many), dtype=np.int64), many)
        i, j = owner[first[column] + k // right[column]], owner[first[column] + left[column] + k % right[column]] - m
        out += np.bincount(i * n + j, minlength=m * n).reshape(m, n).astype(np.float32)
    dense = np.flatnonzero(left * right > 64)
    for a in range(0, len(dense), 1024):
        columns = dense[a : a + 1024]
        at = K.ranges(first[columns], size[columns])
        block = np.zeros((m + n, len(columns)), dtype=np.float32)
        block[owner[at], np.repeat(np.arange(len(columns)), size[columns])] = 1
        out += block[:m] @ block[m:].T
    return out


def _forest(linked: np.ndarray) -> list[tuple[int, int]]:
    """Edges (row, column) of a spanning forest of a bipartite 0/1 matrix."""
    m, n = linked.shape
    new_rows, new_columns, edges = np.ones(m, dtype=bool), np.ones(n, dtype=bool), []
    for start in np.flatnonzero(linked.any(axis=1)):
        if not new_rows[start]:
            continue
        new_rows[start], rows = False, [start]
        while rows:
            row = rows.pop()
            for column in np.flatnonzero(linked[row] & new_columns):
                new_columns[column] = False
                edges.append((row, column))
                for other in np.flatnonzero(linked[:, column] & new_rows):
                    new_rows[other] = False
                    edges.append((other, column))
                    rows.append(other)
    return edges


def units_in(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Consecutive rows with equal keys, across batches; one unit is held at a time."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        values = [tuple(x) for x in zip(*(batch.column(k).to_pylist() for k in keys), strict=True)]
        at = 0
        for i in range(1, len(values) + 1):
            if i == len(values) or values[i] != values[at]:
                if held and values[at] != last:
                    yield pa.Table.from_batches(held)
                    held = []
                held.append(batch.slice(at, i - at))
                last = values[at]
                at = i
    if held:
        yield pa.Table.from_batches(held)


def _blocks(sets: DataFrame) -> DataFrame:
    """``grp, node, n, block``: each group in blocks of about ``BLOCK_ENTRIES`` entries by set size.

    Sums run inside range partitions and are shifted by those of the partitions before, so a large group is not one task.
    """
    dealt = sets.select("grp", "node", "n", F.greatest("n", F.lit(ROW_ENTRIES)).alias("weight")).repartitionByRange("grp", "n", "node")
    dealt = shared.materialised(dealt.withColumn("task", F.spark_partition_id()), "sized")
    earlier = Window.partitionBy("grp").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    shifts = dealt.groupBy("grp", "task").agg(F.sum("weight").alias("sum")).select("grp", "task", F.coalesce(F.sum("sum").over(earlier), F.lit(0)).alias("before"))
    here = Window.partitionBy("grp", "task").orderBy("n", "node").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    summed = dealt.withColumn("upto", F.sum("weight").over(here)).join(shifts, ["grp", "task"])
    return summed.select("grp", "node", "n", F.floor((F.col("upto") + F.col("before") - 1) / BLOCK_ENTRIES).alias("block"))


def _products(sets: DataFrame, percent: int) -> DataFrame:
    """Links inside the groups: a spanning forest from each pair of blocks."""
    laid = shared.materialised(_blocks(sets), "blocks")
    spans = laid.groupBy("grp", "block").agg(F.min("n").alias("low"), F.max("n").alias("high"))
    one, two = spans.alias("one"), spans.alias("two")
    pairs = one.join(two, "grp").filter("one.block <= two.block and 100 * one.high >= %d * two.low" % percent)
    pairs = pairs.select("grp", F.col("one.block").alias("left"), F.col("two.block").alias("right"))
    sides = pairs.select("grp", "left", "right", F.explode(F.array_distinct(F.array("left", "right"))).alias("block"))
    rows = sets.join(laid.select("node", "block"), "node").join(sides, ["grp", "block"])
    rows = rows.repartition("grp", "left", "right").sortWithinPartitions("grp", "left", "right", "block", "n", "node")

    def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for unit in units_in(batches, ["grp", "left", "right"]):
            nodes, blocks = unit.column("node").to_numpy(), unit.column("block").to_numpy()
            sets = [np.frombuffer(x, dtype=np.uint64) for x in unit.column("hashes").to_pylist()]
            size = np.array([len(s) for s in sets], dtype=np.int64)
            left = np.flatnonzero(blocks == unit.column("left")[0].as_py())
            right = np.flatnonzero(blocks == unit.column("right")[0].as_py())
            same = overlaps([sets[i] for i in left], [sets[i] for i in right]).astype(np.int64)
            linked = 100 * same >= percent * (size[left][:, None] + size[right][None, :] - same)
            linked &= nodes[left][:, None] != nodes[right][None, :]
            edges = _forest(linked)
            if edges:
                yield pa.RecordBatch.from_arrays([pa.array([nodes[left[i]] for i, _ in edges], pa.int64()), pa.array([nodes[right[j]] for _, j in edges], pa.int64())], names=["a", "b"])

    return rows.select("grp", "left", "right", "block", "n", "node", "hashes").mapInArrow(multiply, "a bigint, b bigint")


def find(docs: DataFrame, percent: int = 80, k: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text", bits: int = SKETCH_BITS, light: int = LIGHT) -> DataFrame:
    """Per document: ``doc_id, text_hash, n_shingles, node`` (its class) and ``component_id`` (the smallest id it reaches by links)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("text_hash"))
    first = _first_pass(rows, k, bits)
    members = first.filter("chunk is null").select("doc_id", "text_hash", "n", "node")
    groups = _groups(_columns(rows, _frequencies(first, bits), k, percent, bits), percent, light)
    out = members.select("doc_id", "text_hash", F.col("n").alias("n_shingles"), "node")
    classes = members.filter("node is not null").groupBy("node").agg(F.min("doc_id").alias("least")).withColumn("component", F.col("node"))
    if groups is not None:
        groups = shared.materialised(groups, "groups")
        ties = components(_products(_sets_of(rows, groups, members, k), percent))
        joined = classes.drop("component").join(ties, "node")
        least = joined.groupBy("component").agg(F.min("least").alias("root"))
        roots = joined.join(least, "component").select("node", "root", F.col("component").alias("tied"))
        classes = classes.join(roots, "node", "left").select("node", F.coalesce("root", "least").alias("least"), F.coalesce("tied", "component").alias("component"))
    classes = shared.materialised(classes, "named")  # a plain table, so that a class with many copies can be split in the join
    named = F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("least")).alias("component_id")
    return out.join(classes, "node", "left").select("doc_id", "text_hash", "n_shingles", "node", "component", named)


def one_of_each(docs: DataFrame, percent: int = 80, k: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text", bits: int = SKETCH_BITS) -> DataFrame:
    """``docs`` with one row of each component: the one with the smallest id, then text hash; documents without words all stay."""
    found = shared.materialised(find(docs, percent, k, id_col, text_col, bits), "components")
    inside = found.filter("component is not null")
    kept = inside.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "text_hash")).alias("kept"))
    same = F.col("doc_id").eqNullSafe(F.col("kept.doc_id")) & (F.col("text_hash") == F.col("kept.text_hash"))
    kept = shared.materialised(kept, "kept")  # a plain table, so that a large component can be split in the join
    gone = inside.join(kept, "component").filter(~same).select(F.col("doc_id").alias("_gone_id"), F.col("text_hash").alias("_gone_hash")).distinct()
    text_hash = F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))
    left = docs.withColumn("_text_hash", text_hash)
    left = left.join(gone, F.col(id_col).cast("bigint").eqNullSafe(F.col("_gone_id")) & (F.col("_text_hash") == F.col("_gone_hash")), "left_anti")
    repeated = inside.groupBy("doc_id", "text_hash").count().filter("count > 1").limit(1)
    if not repeated.isEmpty():  # rows that repeat an id and its text
        empty = left.filter(~F.coalesce(F.col(text_col), F.lit("")).rlike(r"[^\x20\x09-\x0D]"))
        full = left.filter(F.coalesce(F.col(text_col), F.lit("")).rlike(r"[^\x20\x09-\x0D]"))
        left = full.dropDuplicates([id_col, "_text_hash"]).unionByName(empty)
    return left.drop("_text_hash")
