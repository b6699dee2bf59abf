import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from segcube.llm import decontamination as dc
from segcube.llm import queries
from tests.llm import fixtures as X

LOWER = {c: c + 32 for c in range(65, 91)}


def split(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOWER))


def brute(text, items):
    words, hit, found = split(text), set(), set()
    for item, content in items:
        other = split(content)
        n = min(10, len(other))
        for k in range(max(0, len(other) - n + 1) if n else 0):
            for i in range(len(words) - n + 1):
                if words[i : i + n] == other[k : k + n]:
                    hit |= set(range(i, i + n))
                    found.add(item)
    return len(words), len(hit), found


def digest(found):
    return hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()


@pytest.mark.parametrize("limit", [dc.BLOCK_WINDOWS, 7])
def test_hits_equal_brute_force(spark, limit, monkeypatch):
    monkeypatch.setattr(dc, "_CANDIDATES", 50)
    docs, item = X.awkward_documents(spark)
    rng = random.Random(5)
    items = [(1, item), (2, "two words"), (3, ""), (4, None), (None, "a b c d e"), (10, "one"), (10, "moron scum"), (11, X.words(rng, 25, 3)), (12, "w1 w1 w1")]
    texts = [(100 + i, X.words(rng, 200, 3)) for i in range(5)]
    more = spark.createDataFrame(texts, "doc_id bigint, text string")
    docs = docs.select("doc_id", "text").unionByName(more)
    bench = spark.createDataFrame(items, "item_id bigint, text string").withColumn("n_words", F.lit("clash"))
    got = dc.contamination(dc.build_index(docs), bench, limit=limit).select("doc_id", "n_words", "n_hit", F.size("items").alias("n"), dc.items_digest().alias("d")).collect()
    want = []
    for doc_id, text in X.rows_of(docs):
        n, hit, found = brute(text, [("" if i is None else str(i), t) for i, t in items])
        want.append((doc_id, n, hit, len(found), digest(found)))
    assert X.multiset(tuple(r) for r in got) == X.multiset(want)


def test_query(spark):
    got = queries.op4_positional_index(spark, X.SF).collect()
    items = [(str(r.item_id), r.text) for r in spark.read.parquet(f"{X.SF}/benchmark.parquet").collect()]
    want = []
    for doc_id, text in X.rows_of(X.documents(spark)):
        n, hit, found = brute(text, items)
        want.append((doc_id, n, hit, len(found), digest(found), hit > 0))
    assert X.multiset(tuple(r) for r in got) == X.multiset(want) and any(r.contaminated for r in got)


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x beta y gamma"), (2, "gamma alpha beta"), (3, "alpha a a a a a a beta gamma"), (4, "alpha beta"), (5, "alpha"), (6, "beta gamma")], "doc_id bigint, text string")
    items = spark.createDataFrame([(1, "alpha beta gamma")], "item_id bigint, text string")
    index = dc.build_index(docs)
    assert {r.doc_id for r in dc.proximity(index, items, 4).collect()} == {1, 2}
    assert {r.doc_id for r in dc.proximity(index, items, 9).collect()} == {1, 2, 3}


def test_nothing(spark):
    bench = spark.createDataFrame([], "item_id bigint, text string")
    assert dc.contamination(dc.build_index(X.empty_documents(spark)), bench).count() == 0
    docs = X.awkward_documents(spark)[0]
    assert dc.contamination(dc.build_index(docs), bench).filter("n_hit > 0").count() == 0
