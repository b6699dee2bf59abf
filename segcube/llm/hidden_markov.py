"""Hidden Markov language model with additive-smoothed unigram base, over all documents.

1. *Counts.*  Every training token is counted exactly (per task, then by a shuffle).  The frequent tokens, ``KNOWN`` at most, are sent to
   all workers, the rest are looked up by joins, so no worker holds the vocabulary.
2. *Sequences.*  Each document becomes numbers of its tokens: ranks of the frequent ones, places in the document's own list for the others.
3. *Training.*  Expected counts are gathered from all training documents and summed over the partitions.  The first rounds tie
   each ``SEGMENT`` tokens to one state (a mixture, which finds topics and languages quickly), the others are Baum-Welch rounds with the
   scaled forward-backward recursion over whole documents.  All but the last take the tokens beyond rank ``TIED`` as one symbol;
   the last one gathers counts by state for *every* training token, as a table that grows with the vocabulary, and the emissions
   are made from it.  Only the starting point comes from a few documents.
4. *Scoring.*  The scaled forward recursion over each whole document, in double precision, with each token's own emissions.

A state emits a token with ``1 - BACKGROUND`` times its share of the state's counts and ``BACKGROUND`` times the smoothed unigram share, which is all that
tokens unseen in training have.

Lower-case A-Z; tokens are maximal runs of anything but white space, then one end.  Null and empty texts are a single end; repeated rows are counted and scored
one by one; a null id is held out; without training rows all tokens are unknown and the model equals the base; an empty table gives no rows.
Tokens are told apart by 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.llm import kernel as K
from segcube.llm import shared
from segcube.llm.toxicity import fold

STATES, TIED, KNOWN = 8, 32_767, 524_288
#: Rounds of the mixture, of Baum-Welch with rare tokens tied, and (always one) with every token by itself.
SEGMENT, MIXTURE_ROUNDS, ROUNDS = 128, 3, 2
#: Documents that the starting point is chosen from.
SEEDS = 256
#: Share of the unigram distribution in each state's emissions.
BACKGROUND = 0.02
#: Expected counts are summed as multiples of one over this, so that sums do not depend on their order.
UNIT = 1 << 16
_STEP_TOKENS = 300_000
_RARE_ROWS = 500_000
_CHUNK = 1024
#: The end of a text as a token.
END = int(K.mix(np.array([0x0E2D], dtype=np.uint64))[0])


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all tokens, an end after each text, and each text's bounds."""
    data, offsets = K.text_bytes(texts)
    data = K.LOWER[data]
    starts, ends, first = K.find_words(data, offsets, K.NONSPACE)
    bounds = first + np.arange(len(first))
    out = np.full(int(bounds[-1]), END, dtype=np.uint64)
    out[K.ranges(bounds[:-1], np.diff(first))] = K.hash_spans(data, starts, ends)
    return out, bounds


def token_counts(docs: DataFrame) -> DataFrame:
    """``token, c`` over all rows of ``docs`` (column ``text``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, counts = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
        for batch in batches:
            for part in K.steps(batch, "text"):
                more, n = np.unique(tokens(part.column("text"))[0], return_counts=True)
                every, back = np.unique(np.concatenate([keys, more]), return_inverse=True)
                counts = np.bincount(back, weights=np.concatenate([counts, n]), minlength=len(every)).astype(np.int64)
                keys = every
                if len(keys) > 1_000_000:
                    yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts)], names=["token", "c"])
                    keys, counts = keys[:0], counts[:0]
        yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts)], names=["token", "c"])

    return docs.select("text").mapInArrow(run, "token bigint, c bigint").groupBy("token").agg(F.sum("c").alias("c"))


@dataclass
class Counts:
    """The frequent tokens, sorted by hash, with counts and ranks, and totals over all tokens."""

    tokens: np.ndarray
    counts: np.ndarray
    ranks: np.ndarray
    least: int  # tokens of at least so many occurrences are frequent
    total: int
    distinct: int
    tied: int

    @property
    def base_log(self) -> float:
        return float(np.log10(self.total + 0.1 * (self.distinct + 1)))

    def numbers(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.tokens):
            return np.full(len(hashes), -1)
        at = np.minimum(np.searchsorted(self.tokens, hashes), len(self.tokens) - 1)
        return np.where(self.tokens[at] == hashes, at, -1)

    def share(self, c: np.ndarray) -> np.ndarray:
        """Smoothed unigram shares of tokens that occur ``c`` times."""
        return (c + 0.1) / (self.total + 0.1 * (self.distinct + 1))

    def unigram(self) -> np.ndarray:
        """Smoothed shares of the tokens of the first ranks, then of the symbol for all others."""
        out = np.full(self.tied + 1, 0.5)
        inside = self.ranks < self.tied
        out[self.ranks[inside]] += self.counts[inside]
        out[-1] += self.total - self.counts[inside].sum()
        return out / out.sum()


def gathered_counts(all_counts: DataFrame, known: int, tied: int) -> Counts:
    """Frequent are all tokens above a number of occurrences that ``known`` tokens at most reach; no sort, and nothing meets in one task."""
    steps = all_counts.groupBy(F.floor(64 * F.log2("c")).alias("step")).agg(F.min("c").alias("least"), F.sum("c").alias("n"), F.count(F.lit(1)).alias("v")).collect()  # 64 a doubling
    least, held = 1 << 62, 0
    for r in sorted(steps, key=lambda r: -r.step):
        held += r.v
        if held > known:
            break
        least = r.least
    top = all_counts.filter(F.col("c") >= least).toArrow()  # at most ``known`` rows
    hashes, counts = top.column("token").to_numpy().view(np.uint64), top.column("c").to_numpy()
    order = np.argsort(hashes)
    hashes, counts = hashes[order], counts[order]
    ranks = np.empty(len(order), dtype=np.int64)
    ranks[np.argsort(-counts, kind="stable")] = np.arange(len(order))
    return Counts(hashes, counts, ranks, least, sum(r.n for r in steps), sum(r.v for r in steps), min(tied, len(hashes)))


def _packed(values: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(values.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), dtype=np.uint8).reshape(4, -1)
    return np.ascontiguousarray(planes.T).view("<u4").ravel().astype(np.int64)


_SEQUENCES = "row_id bigint, doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, base_part double, sequence binary, rare array<bigint>"


def sequences(docs: DataFrame, counts: Counts) -> DataFrame:
    """Per document its sequence, what the frequent tokens add to its base score, and its distinct rare tokens."""
    sent = docs.sparkSession.sparkContext.broadcast(counts)  # at most ``KNOWN`` tokens

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        row, known = TaskContext.get().partitionId() << 33, sent.value
        share = np.append(np.log10(known.counts + 0.1) - known.base_log, 0.0)
        rank = np.append(known.ranks, 0)
        for batch in batches:
            for part in K.steps(batch, "text"):
                hashes, bounds = tokens(part.column("text"))
                n, number = np.diff(bounds), known.numbers(hashes)
                met = number >= 0
                sums = lambda x: np.add.reduceat(x, bounds[:-1])  # noqa: E731  no text is without tokens
                rare = np.flatnonzero(~met)
                doc = np.searchsorted(bounds, rare, side="right") - 1
                order = np.lexsort((hashes[rare], doc))
                doc, token = doc[order], hashes[rare][order]
                new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (token[1:] != token[:-1])])[: len(doc)]
                first = np.searchsorted(doc[new], np.arange(len(n) + 1))
                symbols = rank[number]
                symbols[rare[order]] = len(known.tokens) + np.cumsum(new) - 1 - first[doc]
                blobs = [_packed(symbols[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
                columns = [
                    pa.array(np.arange(row, row + len(n))), part.column("doc_id"), part.column("held_out"), pa.array(n), pa.array(sums(met.astype(np.int64))), pa.array(sums(share[number])), pa.array(blobs, pa.binary()),
                    pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(token[new].view(np.int64))),
                ]
                yield pa.RecordBatch.from_arrays(columns, names=names)
                row += len(n)

    names = [x.split()[0] for x in _SEQUENCES.split(", ")]
    return shared.materialised(docs.select("doc_id", "text", "held_out").mapInArrow(run, _SEQUENCES), "sequences")


@dataclass
class Model:
    start: np.ndarray  # states
    moves: np.ndarray  # states x states
    emissions: np.ndarray  # symbols x states


def steps_of(batch: pa.RecordBatch) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Documents of like length, longest first, some ``_STEP_TOKENS`` at a time (or a single longer one), with their symbols and bounds."""
    size = batch.column("n_tokens").to_numpy()
    order = np.argsort(-size, kind="stable")
    at = 0
    while at < len(order):
        end = at + max(1, int(np.searchsorted(np.cumsum(size[order[at:]]), _STEP_TOKENS, side="right")))
        part = batch.take(pa.array(order[at:end]))
        yield part, np.concatenate([_unpacked(x) for x in part.column("sequence").to_pylist()]), np.concatenate([[0], np.cumsum(size[order[at:end]])])
        at = end
    K.release()


def segments(bounds: np.ndarray) -> np.ndarray:
    """The bounds of all documents' segments of ``SEGMENT`` tokens."""
    pieces = -(-np.diff(bounds) // SEGMENT)
    return np.append(np.repeat(bounds[:-1], pieces) + SEGMENT * K.ranges(np.zeros(len(pieces), dtype=np.int64), pieces), bounds[-1])


def expected_mixture(model: Model, symbols: np.ndarray, bounds: np.ndarray, emitted: np.ndarray, starts: np.ndarray) -> None:
    """Add the expected counts with a single state per segment."""
    logs = np.log(model.emissions).astype(np.float32)
    like = np.add.reduceat(logs[symbols], bounds[:-1], axis=0) + np.log(model.start)
    like = np.exp(like - like.max(axis=1, keepdims=True))
    like /= like.sum(axis=1, keepdims=True)
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    for s in range(like.shape[1]):
        emitted[:, s] += np.bincount(symbols, weights=like[owner, s], minlength=len(emitted))
    starts += like.sum(axis=0)


def _side_by_side(bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All sequences abreast: which token stands where (by position, then by sequence, longest first), where positions begin, and the order of the sequences."""
    size = np.diff(bounds)
    order = np.argsort(-size, kind="stable")
    first, size = bounds[:-1][order], size[order]
    active = np.searchsorted(-size, -np.arange(int(size[0])), side="left")  # sequences longer than t
    where = first[K.ranges(np.zeros(len(active), dtype=np.int64), active)] + np.repeat(np.arange(len(active)), active)
    return where, np.concatenate([[0], np.cumsum(active)]), order


def forward_backward(model: Model, likely: np.ndarray, begin: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """Each token's posterior of the states by the scaled recursion; adds the expected moves to ``moves``.

    ``likely`` has the emissions of all tokens in the order of :func:`_side_by_side`, and is used up.
    """
    active, total = np.diff(begin), len(likely)
    forward, scale, ones = np.empty_like(likely), np.empty(total), np.ones(likely.shape[1])
    for t, (a, b) in enumerate(zip(begin[:-1], begin[1:], strict=True)):
        now = forward[a:b]
        if t:
            np.dot(forward[begin[t - 1] : begin[t - 1] + active[t]], model.moves, out=now)
            now *= likely[a:b]
        else:
            now[:] = model.start * likely[a:b]
        np.dot(now, ones, out=scale[a:b])
        now /= scale[a:b, None]
    likely /= scale[:, None]
    back, back_moves = np.ones_like(likely), np.ascontiguousarray(model.moves.T)
    for t in range(len(active) - 2, -1, -1):
        a, b, n = begin[t], begin[t + 1], active[t + 1]
        np.dot(likely[b : b + n] * back[b : b + n], back_moves, out=back[a : a + n])
    if len(active) > 1:
        before = K.ranges(begin[: len(active) - 1], active[1:])
        likely *= back
        moves += model.moves * (forward[before].T @ likely[begin[1] :])
    forward *= back
    return forward


def expected_markov(model: Model, symbols: np.ndarray, bounds: np.ndarray, emitted: np.ndarray, starts: np.ndarray, moves: np.ndarray) -> None:
    """Add the expected counts of whole sequences."""
    where, begin, _ = _side_by_side(bounds)
    seen = symbols[where]
    posterior = forward_backward(model, model.emissions[seen], begin, moves)
    starts += posterior[: begin[1]].sum(axis=0)
    for s in range(len(starts)):
        emitted[:, s] += np.bincount(seen, weights=posterior[:, s], minlength=len(emitted))


def _round(training: DataFrame, model: Model, markov: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Expected counts over all partitions; what comes back has the model's size."""
    spark, (n_symbols, n_states) = training.sparkSession, model.emissions.shape
    sent = spark.sparkContext.broadcast(model)
    schema = "chunk int, counts binary"

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        emitted, starts, moves = np.zeros((n_symbols, n_states)), np.zeros(n_states), np.zeros((n_states, n_states))
        for batch in batches:
            for _, symbols, bounds in steps_of(batch):
                symbols = np.minimum(symbols, n_symbols - 1)
                if markov:
                    expected_markov(model, symbols, bounds, emitted, starts, moves)
                else:
                    expected_mixture(model, symbols, segments(bounds), emitted, starts)
        if starts.any():
            flat = np.rint(np.concatenate([starts, moves.ravel(), emitted.ravel()]) * UNIT) / UNIT
            parts = [flat[a : a + _CHUNK * n_states] for a in range(0, len(flat), _CHUNK * n_states)]
            yield pa.RecordBatch.from_arrays([pa.array(range(len(parts)), pa.int32()), pa.array([p.astype("<f8").tobytes() for p in parts], pa.binary())], names=["chunk", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for chunk, data in zip(batch.column("chunk").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                part = np.frombuffer(data, dtype="<f8")
                sums[chunk] = sums[chunk] + part if chunk in sums else part
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.astype("<f8").tobytes() for x in sums.values()], pa.binary())], names=["chunk", "counts"])

    parts = training.select("n_tokens", "sequence").mapInArrow(gather, schema).repartition(2 * spark.sparkContext.defaultParallelism, "chunk")
    rows = sorted(parts.mapInArrow(add, schema).collect(), key=lambda r: r.chunk)
    flat = np.concatenate([np.frombuffer(r.counts, dtype="<f8") for r in rows]) if rows else np.zeros(n_states + n_states**2 + n_symbols * n_states)
    return flat[n_states + n_states**2 :].reshape(n_symbols, n_states), flat[:n_states], flat[n_states : n_states + n_states**2].reshape(n_states, n_states)


def _updated(emitted: np.ndarray, starts: np.ndarray, moves: np.ndarray, unigram: np.ndarray) -> Model:
    share = emitted / np.maximum(emitted.sum(axis=0, keepdims=True), 1e-300)
    share[:, emitted.sum(axis=0) <= 0] = unigram[:, None]
    moves = moves + 0.1
    starts = starts + 0.1
    return Model(starts / starts.sum(), moves / moves.sum(axis=1, keepdims=True), (1 - BACKGROUND) * share + BACKGROUND * unigram[:, None])


def _start(training: DataFrame, unigram: np.ndarray, n_states: int) -> Model:
    """States start at documents far from each other among the ``SEEDS`` with the smallest hashes."""
    rows = training.orderBy(F.xxhash64("doc_id", "n_tokens"), "row_id").limit(SEEDS).select("sequence").collect()
    counts = np.array([np.bincount(np.minimum(_unpacked(r.sequence), len(unigram) - 1), minlength=len(unigram)) for r in rows], dtype=np.float32).reshape(-1, len(unigram))
    counts = counts[counts.sum(axis=1) >= min(50, counts.sum(axis=1).max(initial=0))]
    even = Model(np.full(n_states, 1 / n_states), np.full((n_states, n_states), 1 / n_states), np.repeat(unigram[:, None], n_states, axis=1))
    if not len(counts):
        return even
    shape = np.sqrt(counts / counts.sum(axis=1, keepdims=True))
    chosen = [int(counts.sum(axis=1).argmax())]
    while len(chosen) < min(n_states, len(shape)):
        chosen.append(int((shape @ shape[chosen].T).max(axis=1).argmin()))
    near = (shape @ shape[chosen].T).argmax(axis=1)
    for s in np.unique(near):  # a state that no document is nearest to keeps the unigram
        mine = counts[near == s].sum(axis=0)
        even.emissions[:, s] = 0.7 * mine / mine.sum() + 0.3 * unigram
    return even


def train(training: DataFrame, counts: Counts, n_states: int = STATES, mixture_rounds: int = MIXTURE_ROUNDS, rounds: int = ROUNDS) -> Model:
    unigram = counts.unigram()
    model = _start(training, unigram, n_states)
    for k in range(mixture_rounds + rounds):
        emitted, starts, moves = _round(training, model, markov=k >= mixture_rounds)
        if k < mixture_rounds:  # a segment's state stays with it; some 1 in 50 tokens may change it
            moves = np.eye(n_states) * 50 + 1.0 / n_states
        model = _updated(emitted, starts, moves, unigram)
    return model


def token_emissions(training: DataFrame, model: Model, counts: Counts) -> DataFrame:
    """``token, c, e0, e1, ...``: each training token's number and expected counts by state (in ``1 / UNIT``), of one Baum-Welch round."""
    sent = training.sparkSession.sparkContext.broadcast((model, counts))
    n_states, names = len(model.start), ["token", "c", *(f"e{s}" for s in range(len(model.start)))]

    def rows(token: np.ndarray, c: np.ndarray, e: np.ndarray) -> pa.RecordBatch:
        e = np.rint(e * UNIT).astype(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(token.view(np.int64)), pa.array(c.astype(np.int64)), *(pa.array(x) for x in e.T)], names=names)

    def summed(token: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Counts (the last column) and expected counts of equal tokens together."""
        every, back = np.unique(token, return_inverse=True)
        return every, np.stack([np.bincount(back, weights=x, minlength=len(every)) for x in e.T], axis=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, known = sent.value
        n_known, moves = len(known.tokens), np.zeros_like(model.moves)
        frequent = np.zeros((n_known, n_states + 1))
        rare = np.zeros(0, dtype=np.uint64), np.zeros((0, n_states + 1))
        for batch in batches:
            for part, symbols, bounds in steps_of(batch):
                where, begin, _ = _side_by_side(bounds)
                posterior = forward_backward(model, model.emissions[np.minimum(symbols, known.tied)[where]], begin, moves)
                posterior = np.hstack([posterior, np.ones((len(posterior), 1))])
                seen = symbols[where]
                for s, x in enumerate(posterior.T):
                    frequent[:, s] += np.bincount(np.minimum(seen, n_known), weights=x, minlength=n_known + 1)[:n_known]
                other = np.flatnonzero(seen >= n_known)
                if len(other):
                    lists = part.column("rare")
                    doc = np.searchsorted(bounds, where[other], side="right") - 1
                    at = lists.value_lengths().to_numpy().cumsum() - lists.value_lengths().to_numpy()
                    token = lists.flatten().to_numpy().view(np.uint64)[at[doc] + seen[other] - n_known]
                    rare = summed(np.concatenate([rare[0], token]), np.vstack([rare[1], posterior[other]]))
                    if len(rare[0]) > _RARE_ROWS:
                        yield rows(rare[0], rare[1][:, -1], rare[1][:, :-1])
                        rare = rare[0][:0], rare[1][:0]
        by_rank = np.argsort(known.ranks)
        met = np.flatnonzero(frequent[:, -1])
        yield rows(known.tokens[by_rank[met]], frequent[met, -1], frequent[met, :-1])
        yield rows(rare[0], rare[1][:, -1], rare[1][:, :-1])

    gathered = training.select("n_tokens", "sequence", "rare").mapInArrow(run, ", ".join(f"{n} bigint" for n in names))
    return shared.materialised(gathered.groupBy("token").agg(*(F.sum(n).alias(n) for n in names[1:])), "emissions")


@dataclass
class Emissions:
    """Emissions of the frequent tokens by rank, and what makes those of the others from their counts."""

    frequent: np.ndarray  # tokens x states
    states: np.ndarray  # expected counts of the states

    @staticmethod
    def of(e: np.ndarray, c: np.ndarray, states: np.ndarray, counts: Counts) -> np.ndarray:
        unigram = counts.share(c)[:, None]
        share = np.where(states > 0, e / np.maximum(states, 1e-300), unigram)
        return (1 - BACKGROUND) * share + BACKGROUND * unigram


def gathered_emissions(table: DataFrame, counts: Counts, n_states: int) -> Emissions:
    names = [f"e{s}" for s in range(n_states)]
    states = np.array([x or 0 for x in table.agg(*(F.sum(n) for n in names)).first()], dtype=np.float64)
    top = table.filter(F.col("c") >= counts.least).toArrow()  # the frequent tokens
    at = np.empty(top.num_rows, dtype=np.int64)
    at[counts.ranks[counts.numbers(top.column("token").to_numpy().view(np.uint64))]] = np.arange(top.num_rows)
    e = np.stack([top.column(n).to_numpy()[at] for n in names], axis=1)
    return Emissions(Emissions.of(e, top.column("c").to_numpy()[at], states, counts).astype(np.float32), states)


def forward_log10(model: Model, sequences: list[np.ndarray]) -> np.ndarray:
    """Log10 likelihood of each whole sequence of symbols."""
    bounds = np.concatenate([[0], np.cumsum([len(s) for s in sequences])])
    return chain_log10(model.start, model.moves, model.emissions[np.concatenate(sequences)], bounds)


def chain_log10(start: np.ndarray, moves: np.ndarray, likely: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Log10 likelihood of whole sequences with the given emissions of their tokens, by the scaled forward recursion."""
    where, begin, order = _side_by_side(bounds)
    likely, scale, ones = likely[where], np.empty(len(where)), np.ones(len(start))
    state = start
    for t, (a, b) in enumerate(zip(begin[:-1], begin[1:], strict=True)):
        state = likely[a:b] * (np.dot(state[: b - a], moves) if t else start)
        np.dot(state, ones, out=scale[a:b])
        state /= scale[a:b, None]
    logs = np.empty(len(where))
    logs[where] = np.log10(scale)
    return np.add.reduceat(logs, bounds[:-1])


_OUT = "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double"


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n_states: int = STATES, tied: int = TIED, known: int = KNOWN) -> DataFrame:
    """Per document: ``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score``."""
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    rows = rows.withColumn("held_out", fold(F.col("doc_id"), 10) == 0)
    all_counts = shared.materialised(token_counts(rows.filter(~F.col("held_out"))), "token-counts")
    counts = gathered_counts(all_counts, known, tied)
    stored = sequences(rows, counts)
    training = stored.filter(~F.col("held_out"))
    model = train(training, counts, n_states)
    table = token_emissions(training, model, counts)
    emissions = gathered_emissions(table, counts, n_states)
    sent = docs.sparkSession.sparkContext.broadcast((model.start, model.moves, emissions, counts))
    names = [f"e{s}" for s in range(n_states)]
    rare = stored.select("row_id", F.posexplode("rare").alias("place", "token")).join(table.filter(F.col("c") < counts.least), "token")
    found = rare.groupBy("row_id").agg(F.collect_list(F.struct("place", "c", *names)).alias("found"))  # of one document

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start, moves, emissions, counts = sent.value
        n_known = len(counts.tokens)
        for batch in batches:
            for part, symbols, bounds in steps_of(batch):
                lists, n = part.column("rare"), part.column("rare").value_lengths().fill_null(0).to_numpy()
                first = np.cumsum(n) - n  # places of all documents' rare tokens, one after the other
                c, e = np.zeros(int(n.sum())), np.zeros((int(n.sum()), len(start)))
                hits = part.column("found")
                met = hits.flatten()
                at = np.repeat(first, hits.value_lengths().fill_null(0).to_numpy()) + met.field("place").to_numpy()
                c[at] = met.field("c").to_numpy()
                e[at] = np.stack([met.field(x).to_numpy() for x in names], axis=1)
                other = np.flatnonzero(symbols >= n_known)
                doc = np.searchsorted(bounds, other, side="right") - 1
                mine = first[doc] + symbols[other] - n_known
                likely = np.empty((len(symbols), len(start)))
                inside = symbols < n_known
                likely[inside] = emissions.frequent[symbols[inside]]
                likely[other] = Emissions.of(e, c, emissions.states, counts)[mine]
                sums = lambda x: np.bincount(doc, weights=x, minlength=len(n))
                base = part.column("base_part").to_numpy() + sums(np.log10(c + 0.1)[mine] - counts.base_log)
                n_met = part.column("n_known").to_numpy() + sums((c > 0)[mine]).astype(np.int64)
                score = chain_log10(start, moves, likely, bounds)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), part.column("n_tokens"), pa.array(n_met), pa.array(np.full(len(n), counts.total)), pa.array(base), pa.array(score)], names=out_names)

    out_names = [x.split()[0] for x in _OUT.split(", ")]
    return stored.join(found, "row_id", "left").select("doc_id", "held_out", "n_tokens", "n_known", "base_part", "sequence", "rare", "found").mapInArrow(run, _OUT)
