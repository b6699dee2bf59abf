import math
import random
import re
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from segcube.llm import hidden_markov as hm
from segcube.llm import neighbours, queries, toxicity
from tests.llm import fixtures as X

LOWER = {c: c + 32 for c in range(65, 91)}


def fold(doc_id, n):
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % n


# toxicity


def test_pooling_equals_a_plain_convolution():
    rng = np.random.default_rng(0)
    model = toxicity._start([rng.integers(0, toxicity.BUCKETS, (9, 3)) for _ in range(6)], np.array([0, 1, 0, 1, 0, 1]), rng)
    texts = ["", "one", "one two", "one two three four", "a b c d e f g"]
    ids, bounds = toxicity.word_ids(pa.array(texts))
    got = model.pooled(ids, bounds, model.tables())
    rows = np.vstack([model.embedding, np.zeros((1, toxicity.DIM))])
    for i, text in enumerate(texts):
        x = rows[ids[bounds[i] : bounds[i + 1]]].sum(axis=1)
        n = len(text.split())
        want = []
        for f in model.filters:
            responses = [sum(x[p + j] @ f[j] for j in range(len(f))) for p in range(n)]
            want.append(np.max(responses, axis=0) if n else np.zeros(toxicity.FILTERS))
        want = np.maximum(np.concatenate(want) + model.bias, 0) if n else np.zeros(len(model.bias))
        assert np.allclose(got[i], want, atol=1e-4)


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    rows = {r.doc_id: r for r in queries.op6_toxicity_cnn(spark, sf).collect()}
    marks = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert len(rows) == 1000 and all(r.held_out == (fold(i, 5) == 0) and r.predicted == (r.score >= 0.5) for i, r in rows.items())
    held = [(rows[i].predicted, y) for i, y in marks.items() if rows[i].held_out]
    assert np.mean([p == y for p, y in held]) >= 0.95 and sum(p and y for p, y in held) >= 0.6 * sum(y for _, y in held)


def test_awkward_labels_and_texts(spark):
    docs = X.awkward_documents(spark)[0]
    labels = spark.createDataFrame([(i, i % 2, None if i == 3 else i % 2) for i in range(20)] + [(None, 1, 1), (999, 1, 1)], "doc_id bigint, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    scores = {(r.doc_id, r.text): r.score for r in toxicity.score(docs, model).collect()}
    assert all(0 <= s <= 1 for s in scores.values()) and scores[0, None] == scores[1, ""] == scores[None, None]
    flat = toxicity.fit(docs, labels.filter("toxic = 0"))
    assert toxicity.score(docs, flat).agg({"score": "max"}).first()[0] < 1e-6
    assert toxicity.score(X.empty_documents(spark), flat).count() == 0


def test_scores_equal_a_plain_implementation(spark):
    """A table's scores from the trained weights, one filter and place after the other."""
    docs = spark.createDataFrame([(i, ("vile scum " if i % 2 else "kind words ") * (1 + i % 3) + f"w{i % 7}", "en") for i in range(60)] + [(99, None, "en")], "doc_id bigint, text string, lang string")
    labels = spark.createDataFrame([(i, 0, i % 2) for i in range(60)], "doc_id bigint, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    rows = np.vstack([model.embedding, np.zeros((1, toxicity.DIM))])
    for r in toxicity.score(docs, model).collect():
        words = (r.text or "").split()
        ids, bounds = toxicity.word_ids(pa.array([r.text or ""]))
        x, z = rows[ids].sum(axis=1), model.intercept
        for w, f in enumerate(model.filters):
            for k in range(toxicity.FILTERS):
                responses = [sum(float(x[p + j] @ f[j][:, k]) for j in range(len(f))) for p in range(len(words))]
                at = w * toxicity.FILTERS + k
                z += max(0.0, max(responses) + model.bias[at]) * model.output[at] if words else 0.0
        assert r.score == pytest.approx(1 / (1 + math.exp(-z)), abs=1e-4)
        assert r.doc_id == 99 or (r.score > 0.5) == (r.doc_id % 2 == 1)


def test_repeated_ids_train_once(spark):
    texts = [(i, "vile scum" if i % 2 else "kind words") for i in range(60)]
    labels = spark.createDataFrame([(i, 0, i % 2) for i in range(60)], "doc_id bigint, quality int, toxic int")
    one, many = (toxicity.fit(spark.createDataFrame(x, "doc_id bigint, text string"), labels) for x in (texts, texts + [(7, "vile scum")] * 500))
    assert np.array_equal(one.embedding, many.embedding) and one.intercept == many.intercept


def test_a_text_beyond_the_budget_is_skipped(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "TRAIN_WORDS", 400)
    texts = [(i, "vile scum" if i % 2 else "kind words") for i in range(60)] + [(i, "long " * 1000) for i in range(60, 90)]
    docs = spark.createDataFrame(texts, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, 0, i % 2) for i in range(90)], "doc_id bigint, quality int, toxic int")
    rows = {r.text: r.score for r in toxicity.score(docs, toxicity.fit(docs, labels)).collect()}
    assert rows["vile scum"] > 0.5 > rows["kind words"]


def toxic_texts(n):
    """Every toxic text holds one of 25 bad words, each in a few texts only; ids in no order."""
    rng = random.Random(8)
    texts = [(i * 7919 % 10_007, " ".join([*(f"w{rng.randrange(60)}" for _ in range(rng.randrange(20))), f"bad{i % 25}" if i % 3 == 0 else f"good{i % 40}"]), int(i % 3 == 0)) for i in range(n)]
    return texts, [(i, text, "en" if i % 2 else None) for i, text, _ in texts], [(i, 0, y) for i, _, y in texts]


def test_every_labelled_text_is_learned(spark, monkeypatch):
    """A limit of words smaller than the labelled texts makes more shards, it leaves out no text."""
    monkeypatch.setattr(toxicity, "TRAIN_WORDS", 1000)
    monkeypatch.setattr(toxicity, "SHARD_TEXTS", 40, raising=False)
    texts, rows, marks = toxic_texts(900)
    docs, labels = spark.createDataFrame(rows, "doc_id bigint, text string, lang string"), spark.createDataFrame(marks, "doc_id bigint, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    scores = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    right = [(scores[i] >= 0.5) == (y == 1) for i, _, y in texts]
    assert np.mean(right) >= 0.99
    moved = toxicity.fit(docs.repartition(7), labels.repartition(3))
    assert np.array_equal(model.embedding, moved.embedding) and model.intercept == moved.intercept and model.thresholds == moved.thresholds


def test_shards_hold_each_labelled_text_once(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "TRAIN_WORDS", 300)
    monkeypatch.setattr(toxicity, "SHARD_TEXTS", 40)
    monkeypatch.setattr(toxicity, "FAN_IN", 3)
    texts, rows, marks = toxic_texts(600)
    rows += [rows[5]] * 9 + [(20_000 + i, "not labelled", "en") for i in range(300)] + [(None, "no id", "en")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string").repartition(6)
    labels = spark.createDataFrame([*marks, (99_999, 0, 1), (None, 0, 1), (20_001, 0, None)], "doc_id bigint, quality int, toxic int")
    packed, shards = toxicity._labelled(docs, labels, None, "doc_id", "text", "lang")
    assert shards > 3
    got = Counter((toxic, lang, toxicity._Texts(r.ids, r.n)[k].tobytes()) for r in packed.collect() for k, (toxic, lang) in enumerate(zip(r.toxic, r.lang, strict=True)))
    train = [(y, "en" if i % 2 else "", text) for i, text, y in texts if fold(i, 5)]
    ids = [toxicity.word_ids(pa.array([text]))[0] for *_, text in train]
    assert got == Counter((y, lang, x.tobytes()) for (y, lang, _), x in zip(train, ids, strict=True))
    keys, found = toxicity._summed(packed, shards, toxicity._bucket_counts, 2, "<f8")
    counts, n = toxicity._counted(ids, [y for y, *_ in train])
    want = np.hstack([counts, n[:, None]])
    assert np.array_equal(keys, np.flatnonzero(want.sum(axis=0))) and np.array_equal(found.T, want[:, keys])


def test_the_average_of_shards(spark):
    """Two shards' changes: a bucket's average is over the batches that moved it, that of all others over texts."""
    packed = spark.createDataFrame([(s, [0], [bytearray()], [""], [s]) for s in (0, 1)], "shard int, n array<bigint>, ids array<binary>, lang array<string>, toxic array<int>")
    values = {0: ([1, 5, 4000], [[2, 2.0], [1, 3.0], [8, 8.0]]), 1: ([5, 4000], [[3, 1.0], [4, -2.0]])}
    keys, found = toxicity._summed(packed, 2, lambda shard, texts, labels: (np.array(values[shard][0]), np.array(values[shard][1])), 2, "<f4")
    assert keys.tolist() == [1, 5, 4000] and found.tolist() == [[2, 2], [4, 4], [12, 6]]


def test_the_cut_of_best_f1():
    rng = np.random.default_rng(6)
    for _ in range(30):
        bins, labels = rng.integers(-40, 40, 60), rng.integers(0, 2, 60)
        bins += 15 * labels
        rows = np.array([(b, (bins == b).sum(), labels[bins == b].sum()) for b in np.unique(bins)])
        f1 = lambda b: 2 * (labels[bins >= b]).sum() / ((bins >= b).sum() + labels.sum())
        got = toxicity._best_cut(rows)
        edge = round(math.log(got / (1 - got)) * toxicity.GRID)
        assert f1(edge) == pytest.approx(max(map(f1, [0, *bins[labels == 1]])))


# language model


def plain_tokens(text):
    return [*re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER)), None]


def plain_base(rows):
    counts = Counter(t for d, text in rows if fold(d, 10) for t in plain_tokens(text))
    total, size = sum(counts.values()), len(counts)
    log = math.log10(total + 0.1 * (size + 1))
    out = []
    for d, text in rows:
        tokens = plain_tokens(text)
        out.append((d, fold(d, 10) == 0, len(tokens), sum(counts[t] > 0 for t in tokens), total, sum(math.log10(counts[t] + 0.1) - log for t in tokens)))
    return out


@pytest.mark.parametrize("which", ["awkward", "sf"])
def test_base_scores_equal_brute_force(spark, which):
    docs = X.awkward_documents(spark)[0] if which == "awkward" else X.documents(spark)
    got = X.multiset((*tuple(r)[:5], r.base_score) for r in hm.score_documents(docs, tied=300, known=900).collect())
    want = X.multiset(plain_base(X.rows_of(docs)))
    assert len(got) == len(want)
    for a, b in zip(sorted(got, key=lambda r: (repr(r[:5]), r[5])), sorted(want, key=lambda r: (repr(r[:5]), r[5])), strict=True):
        assert a[:5] == b[:5] and math.isclose(a[5], b[5], rel_tol=1e-9)


def paths(model, seq):
    """The likelihood as a sum over all state paths, without scaling."""
    state = model.start * model.emissions[seq[0]]
    for s in seq[1:]:
        state = (state @ model.moves) * model.emissions[s]
    return state.sum()


def random_model(rng, states=3, symbols=7):
    norm = lambda x, axis: x / x.sum(axis=axis, keepdims=True)
    return hm.Model(norm(rng.random(states), 0), norm(rng.random((states, states)), 1), norm(rng.random((symbols, states)), 0))


def test_forward_is_the_sum_over_paths():
    rng = np.random.default_rng(1)
    model = random_model(rng)
    sequences = [rng.integers(0, 7, n) for n in (1, 5, 2, 9, 5)]
    assert np.allclose(hm.forward_log10(model, sequences), [math.log10(paths(model, s)) for s in sequences])
    total = sum(10 ** hm.forward_log10(model, [np.array([a, b])])[0] for a in range(7) for b in range(7))
    assert math.isclose(total, 1, rel_tol=1e-12)


def test_expected_counts_equal_enumeration():
    rng = np.random.default_rng(2)
    model = random_model(rng, 2, 4)
    sequences = [rng.integers(0, 4, n) for n in (4, 1, 3)]
    emitted, starts, moves = np.zeros((4, 2)), np.zeros(2), np.zeros((2, 2))
    hm.expected_markov(model, np.concatenate(sequences), np.array([0, 4, 5, 8]), emitted, starts, moves)
    want_e, want_s, want_m = np.zeros((4, 2)), np.zeros(2), np.zeros((2, 2))
    for seq in sequences:
        every = []
        for code in range(2 ** len(seq)):
            z = [(code >> k) & 1 for k in range(len(seq))]
            p = model.start[z[0]] * model.emissions[seq[0], z[0]]
            for k in range(1, len(seq)):
                p *= model.moves[z[k - 1], z[k]] * model.emissions[seq[k], z[k]]
            every.append((z, p))
        whole = sum(p for _, p in every)
        for z, p in every:
            want_s[z[0]] += p / whole
            for k, s in enumerate(z):
                want_e[seq[k], s] += p / whole
                if k:
                    want_m[z[k - 1], s] += p / whole
    assert np.allclose(emitted, want_e) and np.allclose(starts, want_s) and np.allclose(moves, want_m)


def plain_forward_backward(model, likely):
    """Log10 likelihood and posteriors of one document, one token and state after the other."""
    n, k = len(likely), len(model.start)
    forward, log = [], 0.0
    for t in range(n):
        now = [(model.start[s] if t == 0 else sum(forward[-1][r] * model.moves[r, s] for r in range(k))) * likely[t][s] for s in range(k)]
        log += math.log10(sum(now))
        forward.append([x / sum(now) for x in now])
    back = [1.0] * k
    posterior = [None] * n
    for t in range(n - 1, -1, -1):
        both = [f * b for f, b in zip(forward[t], back, strict=True)]
        posterior[t] = [x / sum(both) for x in both]
        back = [sum(model.moves[r, s] * likely[t][s] * back[s] for s in range(k)) for r in range(k)]
        back = [x / sum(back) for x in back]
    return log, posterior


@pytest.mark.parametrize("known", [40, 0])
def test_every_token_has_emissions_of_its_own(spark, monkeypatch, known):
    """The last round's counts and the scores, from documents of several segments, against plain Python."""
    monkeypatch.setattr(hm, "_RARE_ROWS", 20)
    rng = random.Random(3)
    texts = [(i, " ".join(rng.choice("abc") * rng.randrange(1, 9) + str(rng.randrange(20)) for _ in range(rng.choice([0, 3, 40, 300])))) for i in range(60)]
    docs = spark.createDataFrame(texts, "doc_id bigint, text string").repartition(3).withColumn("held_out", hm.fold(hm.F.col("doc_id"), 10) == 0)
    all_counts = hm.token_counts(docs.filter("not held_out"))
    counts = hm.gathered_counts(all_counts, known, 15)
    training = hm.sequences(docs, counts).filter("not held_out")
    model = hm.train(training, counts, 3)
    got = {r.token: (r.c, [r[f"e{s}"] / hm.UNIT for s in range(3)]) for r in hm.token_emissions(training, model, counts).collect()}
    seen = Counter(t for i, text in texts if fold(i, 10) for t in plain_tokens(text))
    number = lambda t: int(np.uint64(hm.END).view(np.int64)) if t is None else int(hm.K.hash_text([t]).view(np.int64)[0])
    rank = {int(t): int(r) for t, r in zip(counts.tokens.view(np.int64), counts.ranks, strict=True)}
    want = {t: np.zeros(3) for t in seen}
    for i, text in texts:
        if fold(i, 10):
            tokens = plain_tokens(text)
            for t, p in zip(tokens, plain_forward_backward(model, [model.emissions[min(rank.get(number(t), counts.tied), counts.tied)] for t in tokens])[1], strict=True):
                want[t] += p
    assert len(got) == len(seen) > 40 and (len(rank) == 0) == (known == 0)
    for t, c in seen.items():
        assert got[number(t)][0] == c and np.allclose(got[number(t)][1], want[t], atol=1e-3)
    states = sum(want.values())
    monkeypatch.setattr(hm, "train", lambda *_: model)
    scores = {r.doc_id: r.score for r in hm.score_documents(docs.select("doc_id", "text"), n_states=3, tied=15, known=known).collect()}
    total, distinct = sum(seen.values()), len(seen)
    for i, text in texts:
        likely = []
        for t in plain_tokens(text):
            u = (seen[t] + 0.1) / (total + 0.1 * (distinct + 1))
            likely.append((1 - hm.BACKGROUND) * want.get(t, np.zeros(3)) / states + hm.BACKGROUND * u)
        assert scores[i] == pytest.approx(plain_forward_backward(model, likely)[0], abs=1e-2, rel=1e-3)


def test_scores_are_finite(spark):
    """Awkward rows, one text repeated, and fewer documents than states."""
    few = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id bigint, text string")
    same = spark.createDataFrame([(i, "the same words again " * 20) for i in range(40)], "doc_id bigint, text string")
    for docs in (X.awkward_documents(spark)[0], few, same, few.filter("doc_id = 0 - 1")):
        rows = hm.score_documents(docs).collect()
        assert len(rows) == docs.count() and all(math.isfinite(r.score) and r.score <= 0 for r in rows)


def test_the_model_beats_its_base_on_held_out_texts(spark):
    rows = queries.op7_hidden_markov(spark, "/root/testdata/sf0.01").filter("held_out").collect()
    assert len(rows) > 50 and sum(r.score for r in rows) > sum(r.base_score for r in rows) * 0.98


def test_language_model_of_nothing(spark):
    assert hm.score_documents(X.empty_documents(spark)).count() == 0


# neighbours


def plain_search(rows, top=5):
    best = {}
    for i, v in rows:
        if i is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v):
            best[i] = min(best.get(i, v), v)
    ids = sorted(best)
    x = np.array([best[i] for i in ids], dtype=np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    out = {}
    for q in (i for i in ids if i % 50 == 0):
        s = x @ x[ids.index(q)]
        out[q] = sorted(((-round(float(v), 12), i) for v, i in zip(s, ids, strict=True) if i != q))[:top]
    return out


def test_recall_and_order(spark):
    vectors = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    want = plain_search([(r.vec_id, r.embedding) for r in vectors.collect()])
    got = {}
    for r in neighbours.search(vectors).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    assert set(got) == set(want)
    hits = sum(len({i for _, i, _ in got[q]} & {i for _, i in want[q]}) for q in want)
    assert hits >= 0.9 * sum(map(len, want.values()))
    plain = {r.vec_id: r.embedding for r in vectors.collect()}
    for q, rows in got.items():
        assert [r for r, _, _ in sorted(rows)] == [1, 2, 3, 4, 5] and [s for _, _, s in sorted(rows)] == sorted((s for *_, s in rows), reverse=True)
        for _, i, score in rows:
            a, b = plain[q], plain[i]
            assert score == pytest.approx(math.fsum(x * y for x, y in zip(a, b, strict=True)) / math.sqrt(math.fsum(x * x for x in a)) / math.sqrt(math.fsum(x * x for x in b)), abs=1e-12)


def test_recall_beyond_the_sample(spark, monkeypatch):
    monkeypatch.setattr(neighbours, "SAMPLE", 100)
    test_recall_and_order(spark)


def test_fitting_holds_few_distances_at_once():
    """The sample of 16 million vectors, against 1,250 lists: far less memory than a table of all distances (400 MB with places)."""
    x = np.random.default_rng(2).normal(size=(20_000, 16)).astype(np.float32)
    tracemalloc.start()
    made = neighbours.train(x, 16_000_000)
    near = made.nearest_lists(x, 3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(made.centroids) == 1250 and peak < 40e6
    gap = ((x[:300, None, :] - made.centroids[None]) ** 2).sum(axis=2)
    assert np.allclose(np.take_along_axis(gap, near[:300].astype(np.int64), 1), np.sort(gap, axis=1)[:, :3], rtol=1e-4)


def test_the_sample_is_that_of_the_smallest_hashes(spark, monkeypatch):
    monkeypatch.setattr(neighbours, "sample_size", lambda total: 200)
    classes = spark.range(5000).selectExpr("id as cls", "array(double(id % 7 + 1), double(id % 11)) as v")
    names, vectors = neighbours.sampled(classes, 5000)
    want = classes.selectExpr("cls", "v", "xxhash64(cls) as h").orderBy("h").limit(200).collect()
    assert names.tolist() == [r.cls for r in want]
    assert np.allclose(vectors, [np.array(r.v) / np.linalg.norm(r.v) for r in want], atol=1e-6)


def test_a_crowd_of_equal_queries(spark):
    """A third of all rows share a vector that is also asked for."""
    rng = random.Random(5)
    rows = [(i, [rng.gauss(0, 1) for _ in range(8)]) for i in range(1, 400)] + [(i, [1.0, 2.0] * 4) for i in range(400, 600)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = {}
    for r in neighbours.search(df).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    assert set(got) == set(range(50, 600, 50))
    for q in (400, 450, 500, 550):
        assert [i for _, i in sorted(got[q])] == [i for i in range(400, 406) if i != q][:5]


def test_awkward_vectors_and_copies(spark):
    rng = random.Random(4)
    good = [(i, [rng.gauss(0, 1) for _ in range(8)]) for i in range(1, 60)]
    copies = [(i, [1.0] * 8) for i in range(100, 160)]
    bad = [(0, None), (50, [0.0] * 8), (200, [None] * 8), (201, [float("nan")] * 8), (202, [float("inf")] * 8), (203, [1.0]), (None, [1.0] * 8), (250, []), (100, [1.0] * 8), (300, [2.0] * 8)]
    rows = good + copies + bad
    rng.shuffle(rows)
    df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id bigint, embedding array<float>, label string")
    got = {}
    for r in neighbours.search(df).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    assert [i for _, i in sorted(got[100])] == [101, 102, 103, 104, 105] and [i for _, i in sorted(got[150])] == [100, 101, 102, 103, 104]
    assert set(got) == {50, 100, 150, 300}
    few = df.filter("vec_id in (100, 101, 3)")
    assert sorted(r.vec_id for r in neighbours.search(few).collect()) == [3, 101]
    assert neighbours.search(df.filter("vec_id = 50")).count() == 0 and neighbours.search(df.filter("vec_id = 100").limit(1)).count() == 0


def test_blocks_of_crowded_lists(spark, monkeypatch):
    monkeypatch.setattr(neighbours, "LIST_BLOCK", 16)
    monkeypatch.setattr(neighbours, "QUERY_BLOCK", 2)
    test_recall_and_order(spark)


def _recall(spark, x):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "vec_id bigint, embedding array<double>")
    got = {}
    for r in neighbours.search(df).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    hits = []
    for q in range(0, len(x), 50):
        score = unit @ unit[q]
        score[q] = -np.inf
        hits.append(len(got.get(q, set()) & set(np.argsort(-score)[:5].tolist())) / 5)
    return np.mean(hits)


def test_queries_that_lie_elsewhere_than_most_rows(spark, monkeypatch):
    """Rows lie in crowds, but for those that are asked."""
    monkeypatch.setattr(neighbours, "FIRST", 1)
    rng = np.random.default_rng(1)
    x = rng.normal(size=(40, 64))[rng.integers(0, 40, 8000)] + 0.1 * rng.normal(size=(8000, 64))
    x[::50] = rng.normal(size=(160, 64))
    assert _recall(spark, x) >= 0.95


def test_vectors_of_nearly_one_direction(spark, monkeypatch):
    """They are told apart by their codes: few have to be reranked."""
    seen, plain = [], neighbours.candidates
    monkeypatch.setattr(neighbours, "candidates", lambda indexed, askers, quantiser: seen.append(quantiser.rerank) or plain(indexed, askers, quantiser))
    assert _recall(spark, 1 + 0.02 * np.random.default_rng(2).normal(size=(4000, 16))) >= 0.95 and seen[0] <= 200


def test_lists_that_hold_fewer_than_are_reranked_give_no_bound(spark, monkeypatch):
    """One class in the query's first list and two to be reranked: the other list's class counts too."""
    monkeypatch.setattr(neighbours, "FIRST", 1)
    quantiser = neighbours.Quantiser(np.array([[1.0, 0], [0, 1.0]], dtype=np.float32), np.zeros((1, 1, 2), dtype=np.float32), probes=2, rerank=2)
    indexed = spark.createDataFrame([(1, 0, b"\0"), (2, 1, b"\0")], "cls bigint, list int, codes binary")
    askers = spark.createDataFrame([(9, [1.0, 0.1])], "query bigint, v array<double>")
    assert sorted(r["cls"] for r in neighbours.candidates(indexed, askers, quantiser).collect()) == [1, 2, 9]


def test_the_sample_is_fitted_in_a_task(spark, monkeypatch):
    """The driver receives the quantiser and the asked classes, not the sample."""
    sizes, plain = [], neighbours.sampled
    rng = np.random.default_rng(3)
    rows = spark.createDataFrame([(i, v) for i, v in enumerate(rng.normal(size=(2000, 8)).tolist())], "vec_id bigint, embedding array<double>")
    classes = neighbours.classes_of(neighbours.usable(rows, "vec_id", "embedding"), 5, lambda i: i % 50 == 0)
    made, (_, sample) = neighbours.fitted(classes, 2000), neighbours.sampled(classes, 2000)
    want = neighbours.train(sample, 2000)
    assert np.array_equal(made.centroids, want.centroids) and np.array_equal(made.codebooks, want.codebooks)
    monkeypatch.setattr(neighbours, "sampled", lambda *a: sizes.append(len((found := plain(*a))[0])) or found)
    assert neighbours.search(rows).count() == 200 and sizes == [40]


@pytest.mark.parametrize("held", [1, 7, 1 << 14])
def test_pooling_some_texts_at_a_time(monkeypatch, held):
    """Texts pooled together, with empty ones between them, give exactly what each gives alone."""
    monkeypatch.setattr(toxicity, "POOLED", held)
    rng = np.random.default_rng(0)
    model = toxicity._start([rng.integers(0, toxicity.BUCKETS, (9, 3)) for _ in range(6)], np.array([0, 1, 0, 1, 0, 1]), rng)
    tables, texts = model.tables(), ["", "one", "", "one two three four", "a b", "", "a b c d e f g", ""]
    assert tables.shape == (toxicity.BUCKETS + 1, toxicity.FILTERS * sum(toxicity.WIDTHS))  # one row for a bucket, read once
    ids, bounds = toxicity.word_ids(pa.array(texts))
    together = model.pooled(ids, bounds, tables)
    for i, text in enumerate(texts):
        assert np.array_equal(together[i], model.pooled(*toxicity.word_ids(pa.array([text])), tables)[0])
