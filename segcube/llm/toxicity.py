"""Toxicity by a convolutional text classifier, trained in numpy.

A word's embedding is the sum of three from hashed tables of fixed size: of the word, of its first and of its last four bytes (words
of a kind often share a stem or an ending); filters of several widths slide over them; each filter's largest response
in the whole text goes through a logistic output.  As everything before the maximum is linear, scoring adds rows of precomputed tables (embedding times
filter) instead of multiplying.

*Training* uses every labelled text outside the held-out fold, whole, one row for each id.  Texts travel as word buckets, packed by a hash of the id into shards of
about ``TRAIN_WORDS`` words that are stored once; none comes to the driver.  The first embedding coordinate starts from how far a bucket's number of toxic texts exceeds what chance
would give (counts over all shards), the rest random from a fixed seed.  In each of ``EPOCHS`` rounds every shard starts from the common weights, goes over all its
texts by Adam and gives out its changes, which are averaged: a bucket's by how many of a shard's batches moved it, all others by texts.  Changes are added up by blocks of buckets in the
cluster, so the driver receives one model per round, whatever the number of shards.  ``thresholds`` holds, by language, the score (on a grid of logits) that separates all these texts best,
by the finished model; a language is used there only, never for a score.  All sums are made in the order of shards, so a table gives the same model however it is partitioned.

Null and empty texts are scored as empty; repeated rows get equal scores; without labelled rows of both kinds every score is
the share of toxic rows (0 if there are none); an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.llm import kernel as K
from segcube.llm import shared

#: Words of a shard of labelled texts, about, and texts at least, both in the mean; neither leaves out a text.
TRAIN_WORDS, SHARD_TEXTS = 2_000_000, 256
#: Buckets of a block of summed changes; shards summed in one task; logits on the grid of thresholds are multiples of 1 / ``GRID``.
BLOCK, FAN_IN, GRID = 1024, 256, 64
WORD_BITS, PART_BITS = 16, 15
BUCKETS, DIM, FILTERS, WIDTHS = (1 << WORD_BITS) + 2 * (1 << PART_BITS), 12, 12, (1, 2, 3)
#: Places whose responses are held at once.
POOLED = 1 << 14
EPOCHS, BATCH, RATE, DECAY = 6, 64, 0.01, 1e-5


def fold(doc_id, n: int):
    """``crc32(id as text) mod n``; a null id counts as an empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % n


def word_ids(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Three buckets of each word, with empty places (bucket ``BUCKETS``) after each text, and each text's bounds."""
    data, offsets = K.text_bytes(texts)
    data = K.LOWER[data]
    starts, ends, first = K.find_words(data, offsets, K.ALNUM)
    n, pad = np.diff(first), max(WIDTHS) - 1
    bounds = first + pad * np.arange(len(first))
    out = np.full((int(bounds[-1]), 3), BUCKETS, dtype=np.int32)
    at = K.ranges(bounds[:-1], n)
    word, part = np.uint64(64 - WORD_BITS), np.uint64(64 - PART_BITS)
    out[at, 0] = K.hash_spans(data, starts, ends) >> word
    out[at, 1] = (K.hash_spans(data, starts, np.minimum(ends, starts + 4)) >> part).astype(np.int32) + (1 << WORD_BITS)
    out[at, 2] = (K.hash_spans(data, np.maximum(starts, ends - 4), ends) >> part).astype(np.int32) + (1 << WORD_BITS) + (1 << PART_BITS)
    return out, bounds


@dataclass
class Model:
    embedding: np.ndarray
    filters: list[np.ndarray]  # by width: (width, DIM, FILTERS)
    bias: np.ndarray
    output: np.ndarray
    intercept: float
    thresholds: dict[str, float] = field(default_factory=dict)

    def tables(self) -> np.ndarray:
        """By bucket the responses of all places of all filters, one row for each (the last for empty places)."""
        rows = np.vstack([self.embedding, np.zeros((1, DIM), dtype=np.float32)])
        places = [f[j] for f in self.filters for j in range(len(f))]
        out = np.empty((len(rows), FILTERS * len(places)), dtype=np.float32)
        for k, f in enumerate(places):
            out[:, k * FILTERS : (k + 1) * FILTERS] = rows @ f
        return out

    def pooled(self, ids: np.ndarray, bounds: np.ndarray, tables: np.ndarray) -> np.ndarray:
        """The largest response of each filter in each text, at least 0."""
        pad = max(WIDTHS) - 1
        out = np.zeros((len(bounds) - 1, len(self.bias)), dtype=np.float32)
        full = np.flatnonzero(np.diff(bounds) > pad)
        # texts one after the other, at most ``POOLED`` places at a time or a single longer text
        at = 0
        while at < len(full):
            end = max(at + 1, int(np.searchsorted(bounds[full + 1], bounds[full[at]] + POOLED, side="right")))
            here = full[at:end]
            first = bounds[here[0]]
            part = ids[first : bounds[here[-1] + 1]]
            places = tables[part[:, 0]]
            for k in (1, 2):
                places += tables[part[:, k]]
            # from each text's first word to behind its last; what lies between texts is left out
            cuts = np.stack([bounds[here], bounds[here + 1] - pad], axis=1).ravel() - first
            column = 0
            for w, f in enumerate(self.filters):
                response = places[:, column : column + FILTERS].copy()
                for j in range(1, len(f)):
                    response[:-j] += places[j:, column + j * FILTERS : column + (j + 1) * FILTERS]
                column += len(f) * FILTERS
                out[here, w * FILTERS : (w + 1) * FILTERS] = np.maximum.reduceat(response, cuts, axis=0)[::2]
            at = end
        return np.where(np.diff(bounds)[:, None] > pad, np.maximum(out + self.bias, 0), 0)

    def logits(self, ids: np.ndarray, bounds: np.ndarray, tables: np.ndarray) -> np.ndarray:
        return np.clip(self.pooled(ids, bounds, tables).astype(np.float64) @ self.output + self.intercept, -50, 50)

    def scores(self, texts: pa.Array, tables: np.ndarray) -> np.ndarray:
        return _logistic(self.logits(*word_ids(texts), tables))


def _logistic(z):
    return 1 / (1 + np.exp(-z))


def _start(texts: list[np.ndarray], labels: np.ndarray, rng: np.random.Generator) -> Model:
    return _started(*_counted(texts, labels), rng)


def _counted(texts, labels) -> tuple[np.ndarray, np.ndarray]:
    """How many texts without and with the label hold each bucket, and how many there are."""
    counts = np.zeros((2, BUCKETS + 1))
    for ids, label in zip(texts, labels, strict=True):
        counts[int(label), np.unique(ids)] += 1
    return counts[:, :-1], np.bincount(np.asarray(labels, dtype=np.int64), minlength=2)


def _started(counts: np.ndarray, n: np.ndarray, rng: np.random.Generator) -> Model:
    chance = counts.sum(axis=0) * n[1] / n.sum()
    excess = (counts[1] - chance) / np.sqrt(chance + 1)
    embedding = rng.normal(0, 0.05, (BUCKETS, DIM)).astype(np.float32)
    embedding[:, 0] = np.sign(excess) * np.log1p(np.abs(excess)) / 2
    filters = [rng.normal(0, 0.2, (w, DIM, FILTERS)).astype(np.float32) for w in WIDTHS]
    for f in filters:
        f[:, 0, : FILTERS // 2] = np.abs(f[:, 0, : FILTERS // 2]) + 0.5 / len(f)
    bias, output, share = np.zeros((len(WIDTHS), FILTERS), dtype=np.float32), rng.normal(0, 0.1, (len(WIDTHS), FILTERS)), n[1] / n.sum()
    bias[:, : FILTERS // 2], output[:, : FILTERS // 2] = -0.7, 0.1
    return Model(embedding, filters, bias.ravel(), output.ravel(), float(np.log(share / (1 - share))))


def _constant(share: float) -> Model:
    filters = [np.zeros((w, DIM, FILTERS), dtype=np.float32) for w in WIDTHS]
    none = np.zeros(FILTERS * len(WIDTHS), dtype=np.float32)
    return Model(np.zeros((BUCKETS, DIM), dtype=np.float32), filters, none, none, float(np.log((share + 1e-9) / (1 - share + 1e-9))))


def _dense(model: Model) -> np.ndarray:
    """All weights but the embedding in rows as long as its own, the last filled up with zeros."""
    flat = np.concatenate([*(f.ravel() for f in model.filters), model.bias, model.output, [model.intercept]])
    return np.append(flat, np.zeros(-len(flat) % DIM)).reshape(-1, DIM)


def _with_dense(model: Model, dense: np.ndarray) -> Model:
    flat, at, parts = dense.ravel(), 0, []
    for w in [*model.filters, model.bias, model.output]:
        parts.append(flat[at : at + w.size].reshape(w.shape).astype(w.dtype))
        at += w.size
    return Model(model.embedding, parts[:-2], parts[-2], parts[-1], float(flat[at]), model.thresholds)


def _pass(start: Model, texts, labels: np.ndarray, epoch: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """One round of Adam over all texts of a shard: buckets moved (rows of :func:`_dense` after the last one), and for each its weight in the average and its weighted change."""
    model = _with_dense(start, _dense(start))
    model.embedding = start.embedding.copy()
    pad, width, rate = max(WIDTHS) - 1, FILTERS * len(WIDTHS), RATE * (1 - epoch / EPOCHS)
    weights = [model.embedding, *model.filters, model.bias, model.output]
    first, second = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
    step, intercept_rate, moved = 0, 0.02, np.zeros(BUCKETS)
    shuffled = rng.permutation(len(labels))
    for a in range(0, len(labels), BATCH):
        batch = shuffled[a : a + BATCH]
        grad = [np.zeros_like(w) for w in weights[1:]]
        touched, moves = [], []
        for i in batch:
            ids = texts[i]
            n = len(ids) - pad
            if n <= 0:
                model.intercept -= intercept_rate / len(batch) * (_logistic(model.intercept) - labels[i])
                continue
            rows = _rows(model.embedding, ids)
            places, pooled = [], np.empty(width, dtype=np.float32)
            for w, f in enumerate(model.filters):
                response = rows[:n] @ f[0]
                for j in range(1, len(f)):
                    response += rows[j : n + j] @ f[j]
                best = response.argmax(axis=0)
                places.append(best)
                pooled[w * FILTERS : (w + 1) * FILTERS] = response[best, np.arange(FILTERS)]
            active = pooled + model.bias > 0
            value = np.where(active, pooled + model.bias, 0)
            miss = (_logistic(np.clip(value @ model.output + model.intercept, -50, 50)) - labels[i]) / len(batch)
            grad[-1] += miss * value
            back = np.where(active, miss * model.output, 0).astype(np.float32)
            grad[-2] += back
            model.intercept -= intercept_rate * miss
            for w, f in enumerate(model.filters):
                part = back[w * FILTERS : (w + 1) * FILTERS]
                for j in range(len(f)):
                    at = places[w] + j
                    grad[w][j] += rows[at].T * part
                    touched.append(ids[at].ravel())
                    moves.append(np.repeat(f[j].T * part[:, None], 3, axis=0))
        step += 1
        if touched:
            ids, back = np.concatenate(touched), np.concatenate(moves)
            real = ids < BUCKETS
            keys, where = np.unique(ids[real], return_inverse=True)
            total = np.zeros((len(keys), DIM), dtype=np.float32)
            np.add.at(total, where, back[real])
            _adam(weights[0], first[0], second[0], total, step, rate, keys)
            moved[keys] += 1
        for w, f, s, g in zip(weights[1:], first[1:], second[1:], grad, strict=True):
            _adam(w, f, s, g + DECAY * w, step, rate, ...)
    keys = np.flatnonzero(moved)
    dense = _dense(model) - _dense(start)
    weight = np.concatenate([moved[keys], np.full(len(dense), len(labels))])[:, None]
    change = np.concatenate([model.embedding[keys] - start.embedding[keys], dense])
    return np.concatenate([keys, BUCKETS + np.arange(len(dense))]), np.hstack([weight, weight * change])


def _rows(embedding: np.ndarray, ids: np.ndarray) -> np.ndarray:
    rows = embedding[np.minimum(ids, BUCKETS - 1)].sum(axis=1)
    rows[ids[:, 0] == BUCKETS] = 0
    return rows


def _adam(weight, first, second, grad, step, rate, at) -> None:
    first[at] = 0.9 * first[at] + 0.1 * grad
    second[at] = 0.999 * second[at] + 0.001 * grad * grad
    weight[at] -= (rate * (first[at] / (1 - 0.9**step)) / (np.sqrt(second[at] / (1 - 0.999**step)) + 1e-8)).astype(weight.dtype)


_FIRST_BUCKETS = np.array([0, 1 << WORD_BITS, (1 << WORD_BITS) + (1 << PART_BITS)], dtype=np.int32)


class _Texts:
    """A shard's texts, unpacked one at a time to word buckets with the empty places behind them."""

    def __init__(self, blobs: list[bytes], sizes: list[int]):
        self.blobs, self.sizes = blobs, sizes

    def __len__(self) -> int:
        return len(self.blobs)

    def __getitem__(self, i: int) -> np.ndarray:
        out = np.full((self.sizes[i] + max(WIDTHS) - 1, 3), BUCKETS, dtype=np.int32)
        if self.sizes[i]:
            raw = pa.decompress(self.blobs[i], 6 * self.sizes[i], codec="zstd", asbytes=True)
            out[: self.sizes[i]] = np.frombuffer(raw, dtype="<u2").reshape(-1, 3) + _FIRST_BUCKETS
        return out


def _packed_text(ids: np.ndarray) -> bytes:
    return pa.compress((ids - _FIRST_BUCKETS).astype("<u2").tobytes(), codec="zstd", asbytes=True) if len(ids) else b""


def _labelled(docs: DataFrame, labels: DataFrame, held_out, id_col: str, text_col: str, lang_col: str) -> tuple[DataFrame, int]:
    """All labelled texts outside the held-out fold, a row for each shard, stored; and the number of shards."""
    spark = docs.sparkSession
    marks = labels.select(F.col("doc_id").alias("_id"), F.col("toxic").cast("int").alias("_toxic")).filter("_toxic in (0, 1) and _id is not null")
    marks = marks.filter(fold(F.col("_id"), 5) != 0 if held_out is None else ~held_out(F.col("_id")))
    marks = marks.groupBy(F.col("_id").cast("string").alias("id")).agg(F.max("_toxic").alias("toxic"))  # one label for each id
    n = marks.count()
    language = F.col(lang_col).cast("string") if lang_col in docs.columns else F.lit(None).cast("string")
    texts = docs.select(F.col(id_col).cast("string").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), F.coalesce(language, F.lit("")).alias("lang"))
    texts = texts.filter("id is not null")
    texts = texts.filter(fold(F.col("id"), 5) != 0) if held_out is None else texts
    size = texts.select("id", F.octet_length("text").alias("b")).join(marks, "id").groupBy("id").agg(F.max("b").alias("b")).agg(F.count("b"), F.sum("b")).first()
    shards = int(max(1, min(size[0] // SHARD_TEXTS, (size[1] or 0) // (6 * TRAIN_WORDS))))  # a word takes six bytes or so
    # texts without label are left where they are: a bit map of hashes (of bounded size) lets few of them pass, the join by id none
    bits = 1 << int(min(26, max(16, np.ceil(np.log2(16 * n + 1)))))
    place = F.pmod(F.xxhash64("id"), F.lit(bits))
    words = marks.select(place.alias("p")).groupBy(F.shiftright("p", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, int(p & 63)))").alias("bits")).toArrow()
    known = np.zeros(bits // 64, dtype=np.int64)
    known[words.column("word").to_numpy()] = words.column("bits").to_numpy()
    sent = spark.sparkContext.broadcast(known)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        for batch in batches:
            at = batch.column("p").to_numpy()
            kept = batch.take(pa.array(np.flatnonzero((known[at >> 6] >> (at & 63)) & 1)))
            best: dict[str, tuple] = {}
            for part in K.steps(kept, "text", 1 << 20):
                ids, bounds = word_ids(part.column("text"))
                for i, (name, lang) in enumerate(zip(part.column("id").to_pylist(), part.column("lang").to_pylist(), strict=True)):
                    real = ids[bounds[i] : bounds[i + 1] - max(WIDTHS) + 1]
                    row = (len(real), _packed_text(real), lang)
                    best[name] = min(best.get(name, row), row)  # one row of those that share an id
            if best:
                columns = [list(c) for c in zip(*best.values(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(list(best)), *(pa.array(c, k) for c, k in zip(columns, (pa.int64(), pa.binary(), pa.string()), strict=True))], names=["id", "n", "ids", "lang"])

    def together(left: pa.Table, right: pa.Table) -> pa.Table:
        toxic = dict(zip(right.column("id").to_pylist(), right.column("toxic").to_pylist(), strict=True))
        shard = [*left.column("shard").unique().to_pylist(), *right.column("shard").unique().to_pylist()][0]
        best: dict[str, tuple] = {}
        for name, *row in zip(*(left.column(c).to_pylist() for c in ("id", "n", "ids", "lang")), strict=True):
            if name in toxic:
                best[name] = min(best.get(name, tuple(row)), tuple(row))
        names = sorted(best)
        rows = [[[best[name][k] for name in names]] for k in range(3)]
        columns = [pa.array([shard], pa.int32()), pa.array(rows[0], pa.list_(pa.int64())), pa.array(rows[1], pa.list_(pa.binary())), pa.array(rows[2], pa.list_(pa.string())), pa.array([[toxic[name] for name in names]], pa.list_(pa.int32()))]
        made = pa.table(columns, names=["shard", "n", "ids", "lang", "toxic"])
        del best, rows, columns
        K.release()
        return made if names else made.slice(0, 0)

    shard = F.pmod(F.xxhash64("id", F.lit("shard")), F.lit(shards)).cast("int").alias("shard")
    left = texts.select("id", "text", "lang", place.alias("p")).mapInArrow(hashed, "id string, n bigint, ids binary, lang string").select("*", shard)
    pairs = left.groupBy("shard").cogroup(marks.select("*", shard).groupBy("shard"))
    stored = shared.materialised(pairs.applyInArrow(together, "shard int, n array<bigint>, ids array<binary>, lang array<string>, toxic array<int>"), "labelled")
    sent.destroy()
    return stored, shards


def _shards(batches: Iterator[pa.RecordBatch]):
    """Number, texts, labels and languages of each shard."""
    for batch in batches:
        for i in range(batch.num_rows):
            shard, n, ids, lang, toxic = (batch.column(c)[i].as_py() for c in ("shard", "n", "ids", "lang", "toxic"))
            yield shard, _Texts(ids, n), np.array(toxic, dtype=np.int64), lang
            K.release()


def _summed(packed: DataFrame, shards: int, made, columns: int, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """Keys and sums of the values that ``made(shard, texts, labels)`` gives for keys; added up by blocks of keys, ``FAN_IN`` shards in a task."""
    size = np.dtype(kind).itemsize

    def pieces(keys: np.ndarray, values: np.ndarray):
        for block in np.unique(keys // BLOCK):
            a, b = np.searchsorted(keys, [block * BLOCK, (block + 1) * BLOCK])
            yield int(block), keys[a:b].astype("<i4").tobytes() + values[a:b].astype(kind).tobytes()

    def unpacked(data: bytes):
        n = len(data) // (4 + size * columns)
        return np.frombuffer(data, "<i4", n), np.frombuffer(data, kind, n * columns, 4 * n).reshape(n, columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard, texts, labels, _ in _shards(batches):
            rows = list(pieces(*made(shard, texts, labels)))
            yield pa.RecordBatch.from_arrays([pa.array([shard] * len(rows), pa.int32()), pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["part", "block", "data"])

    def merged(table: pa.Table) -> pa.Table:
        block, rows = table.column("block")[0].as_py(), sorted(zip(table.column("part").to_pylist(), table.column("data").to_pylist(), strict=True))
        total, seen = np.zeros((BLOCK, columns)), np.zeros(BLOCK, dtype=bool)
        for _, data in rows:
            keys, values = unpacked(data)
            total[keys - block * BLOCK] += values
            seen[keys - block * BLOCK] = True
        keys = np.flatnonzero(seen)
        return pa.table([pa.array([rows[0][0] // FAN_IN], pa.int32()), pa.array([block], pa.int32()), pa.array([next(pieces(keys + block * BLOCK, total[keys]))[1]], pa.binary())], names=["part", "block", "data"])

    schema = "part int, block int, data binary"
    found = packed.mapInArrow(run, schema)
    while True:
        found = found.groupBy("block", F.floor(F.col("part") / FAN_IN)).applyInArrow(merged, schema)
        shards = -(-shards // FAN_IN)
        if shards <= 1:
            break
    rows = sorted((r["block"], r["data"]) for r in found.toArrow().to_pylist())  # one model
    keys, values = zip(*(unpacked(data) for _, data in rows), strict=True) if rows else ([np.zeros(0, "<i4")], [np.zeros((0, columns), kind)])
    return np.concatenate(keys), np.concatenate(values)


def _bucket_counts(shard: int, texts, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    counts, n = _counted(texts, labels)
    counts = np.hstack([counts, n[:, None]])
    keys = np.flatnonzero(counts.sum(axis=0))
    return keys, counts[:, keys].T


def _train(packed: DataFrame, shards: int, seed: int = 5) -> Model:
    spark = packed.sparkSession
    keys, found = _summed(packed, shards, _bucket_counts, 2, "<f8")
    counts = np.zeros((2, BUCKETS + 1))
    counts[:, keys] = found.T
    n = counts[:, -1]
    if not n.all():
        return _constant(n[1] / n.sum() if n.sum() else 0.0)
    model = _started(counts[:, :-1], n, np.random.default_rng(seed))
    for epoch in range(EPOCHS):
        sent = spark.sparkContext.broadcast(model)  # of fixed size
        made = lambda shard, texts, labels, sent=sent, epoch=epoch: _pass(sent.value, texts, labels, epoch, np.random.default_rng([seed, epoch, shard]))
        keys, found = _summed(packed, shards, made, 1 + DIM, "<f4")
        sent.destroy()
        change = found[:, 1:] / found[:, :1]
        own = keys < BUCKETS
        model.embedding[keys[own]] += change[own]
        model = _with_dense(model, _dense(model) + change[~own])
    model.thresholds = _thresholds(packed, model)
    return model


def _thresholds(packed: DataFrame, model: Model) -> dict[str, float]:
    """By language the score that gives the best F1 on all rows, where they hold at least 5 toxic ones and it is not 0.5."""
    sent = packed.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        tables = model.tables()
        for _, texts, labels, languages in _shards(batches):
            bins = np.empty(len(labels), dtype=np.int32)
            held, size, first = [], 0, 0
            for i in range(len(labels)):
                held.append(texts[i])
                size += len(held[-1])
                if size >= POOLED or i == len(labels) - 1:  # some texts together
                    bounds = np.cumsum([0, *map(len, held)])
                    bins[first : i + 1] = np.floor(model.logits(np.concatenate(held), bounds, tables) * GRID)
                    held, size, first = [], 0, i + 1
            yield pa.RecordBatch.from_arrays([pa.array(languages, pa.string()), pa.array(bins), pa.array(labels)], names=["lang", "bin", "toxic"])
        del tables
        K.release()

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cuts = [_best_cut(np.array([(r["bin"], r["n"], r["toxic"]) for r in rows])) for rows in batch.column("rows").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("lang"), pa.array(cuts, pa.float64())], names=["lang", "cut"])

    bins = packed.mapInArrow(run, "lang string, bin int, toxic bigint").groupBy("lang", "bin").agg(F.count(F.lit(1)).alias("n"), F.sum("toxic").alias("toxic"))
    rows = bins.groupBy("lang").agg(F.sum("toxic").alias("all"), F.sort_array(F.collect_list(F.struct("bin", "n", "toxic"))).alias("rows")).filter("all >= 5")  # of a language at most 100 * GRID + 1
    cuts = rows.select("lang", "rows").mapInArrow(best, "lang string, cut double").filter("cut != 0.5").collect()
    sent.destroy()
    return {r.lang: r.cut for r in cuts}


def _best_cut(rows: np.ndarray) -> float:
    """The best F1 of ``bin, texts, toxic texts`` in ascending order, among the bins with a toxic text and 0.5; of equal ones that nearest to 0.5."""
    grid = np.unique(np.append(rows[rows[:, 2] > 0, 0], 0))
    after = np.vstack([np.cumsum(rows[::-1, 1:], axis=0)[::-1], [[0, 0]]])[np.searchsorted(rows[:, 0], grid)]
    f1 = 2 * after[:, 1] / (after[:, 0] + rows[:, 2].sum())
    cuts = _logistic(grid / GRID)
    best = np.flatnonzero(f1 >= f1.max() - 1e-12)
    return float(cuts[best[np.argmin(np.abs(cuts[best] - 0.5))]])


def fit(docs: DataFrame, labels: DataFrame, held_out=None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Train on all labelled rows outside the held-out fold (by default ``crc32(id) mod 5 = 0``)."""
    return _train(*_labelled(docs, labels, held_out, id_col, text_col, lang_col))


def score(docs: DataFrame, model: Model, text_col: str = "text", out: str = "score", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (all, if not given) of ``docs`` with the score of each whole text as a last column."""
    keep = docs.columns if keep is None else keep
    sent = docs.sparkSession.sparkContext.broadcast(model)  # of fixed size
    scored = text_col if text_col in keep else "_scored_text"
    rows = docs.select(*keep) if text_col in keep else docs.select(*keep, F.col(text_col).alias(scored))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        tables = model.tables()
        for batch in batches:
            for part in K.steps(batch, scored, 1 << 20):
                scores = model.scores(part.column(scored), tables)
                yield pa.RecordBatch.from_arrays([*part.columns[: len(keep)], pa.array(scores)], names=[*keep, out])
        del tables
        K.release()

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[: len(keep)]), f"{out} double"])
    return rows.mapInArrow(run, schema)
