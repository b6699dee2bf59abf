from segcube.llm import licenses, queries
from tests.llm import fixtures as X
from tests.llm.test_decontamination import split

PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}


def brute(text):
    words, places, labels = split(text), [], set()
    for phrase, label in PHRASES.items():
        p = phrase.split()
        at = [i for i in range(len(words) - len(p) + 1) if words[i : i + len(p)] == p]
        places += at
        labels |= {label} if at else set()
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels))


def check(rows, texts):
    got = X.multiset((r.doc_id, r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) for r in rows)
    assert got == X.multiset((d, *brute(t)) for d, t in texts)
    for r in rows:
        assert 0 <= r.score <= 1 and set(r.base_labels.split(",")) - {""} <= set(r.labels.split(","))


def test_places_equal_brute_force(spark):
    docs = X.awkward_documents(spark)[0]
    more = spark.createDataFrame([(900, "cc by cc by gnu gnu general public license mit license mit"), (901, "cc"), (902, "by license")], "doc_id bigint, text string")
    docs = docs.select("doc_id", "text").unionByName(more)
    rows = licenses.scan(docs).collect()
    check(rows, X.rows_of(docs))


def test_query_and_empty_table(spark):
    rows = queries.op5_license_diagonals(spark, X.SF).collect()
    check(rows, X.rows_of(X.documents(spark)))
    assert sum(r.n_base for r in rows) > 0
    assert licenses.scan(X.empty_documents(spark)).count() == 0


def test_notices_with_changes_are_found(spark):
    label, text = next((lab, t) for lab, t in licenses.NOTICES if lab == "mit-text")
    words = text.split()
    changed = words[:20] + ["extra", "words"] + words[20:45] + words[47:]
    far = words[:12] + ["filler"] * 200 + words[40:52]
    docs = spark.createDataFrame([(1, "start " + " ".join(changed) + " end"), (2, " ".join(far)), (3, " ".join(reversed(words)))], "doc_id bigint, text string")
    got = {r.doc_id: r for r in licenses.scan(docs).collect()}
    assert label in got[1].labels and got[1].score > 0.8
    span = next(s for s in got[1].spans if s.label == label)
    assert span.low == 1 and span.high == len(split(" ".join(changed)))
    assert label not in got[2].labels and label not in got[3].labels
