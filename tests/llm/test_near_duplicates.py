import random

import numpy as np
import pytest

from segcube.llm import near_duplicates as nd
from tests.llm import fixtures as X


def shingles(text):
    w = X_words(text)
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def X_words(text):
    table = {c: c + 32 for c in range(65, 91)}
    import re

    return re.findall(r"[^\x20\x09-\x0D]+", text.translate(table))


def brute(rows):
    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j]:
                same = len(sets[i] & sets[j])
                if 100 * same >= 80 * (len(sets[i]) + len(sets[j]) - same):
                    root[find(i)] = find(j)
    out = []
    for i, (doc_id, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(rows)) if find(j) == find(i) and rows[j][0] is not None]
        out.append((doc_id, len(sets[i]), min(ids) if ids else None))
    return X.multiset(out)


def family(spark, n, size, seed, base_id=0):
    """A base text and copies edited at different rates."""
    rng = random.Random(seed)
    base = X.words(rng, size, 5000).split()
    rows = []
    for i in range(n):
        text = list(base)
        for _ in range(rng.randrange(0, max(1, size // 40))):
            text[rng.randrange(size)] = f"e{rng.randrange(10**6)}"
        rows.append((base_id + i, " ".join(text)))
    return rows


@pytest.mark.parametrize("light", [64, 4])
def test_components_equal_brute_force(spark, light, monkeypatch):
    monkeypatch.setattr(nd, "BLOCK_ENTRIES", 1 << 12)
    monkeypatch.setattr(nd, "ROW_ENTRIES", 1 << 7)
    rows = family(spark, 120, 90, 1) + family(spark, 40, 200, 2, 1000) + [(5000 + i, t) for i, (_, t) in enumerate(family(spark, 30, 12, 3))] + [(9000, ""), (9001, None), (9002, "a b")]
    passage = X.words(random.Random(9), 60)
    rows += [(7000 + i, X.words(random.Random(i), 100, 5000) + " " + passage) for i in range(80)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4)
    got = nd.find(docs, bits=14, light=light).select("doc_id", "n_shingles", "component_id").collect()
    assert X.multiset(tuple(r) for r in got) == brute([(d, t or "") for d, t in rows])


@pytest.mark.parametrize("which", ["awkward", "sf"])
def test_tables(spark, which):
    docs = X.awkward_documents(spark)[0] if which == "awkward" else X.documents(spark)
    got = nd.find(docs, bits=16).select("doc_id", "n_shingles", "component_id").collect()
    assert X.multiset(tuple(r) for r in got) == brute(X.rows_of(docs))


def test_nothing(spark):
    assert nd.find(X.empty_documents(spark), bits=12).count() == 0


def test_product_block_counts_shared_entries():
    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 300, rng.integers(1, 120)).astype(np.uint64)) for _ in range(60)]
    got = nd.overlaps(sets[:25], sets[25:])
    assert (got == [[len(np.intersect1d(a, b)) for b in sets[25:]] for a in sets[:25]]).all()
