import re

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from segcube.llm import encoding, queries, toxicity
from tests.llm import fixtures as X
from tests.llm import test_decontamination as D
from tests.llm import test_near_duplicates as N
from tests.llm import test_pii as P


def test_stages_follow_brute_force(spark):
    docs, sf = X.documents(spark), X.SF
    columns = docs.columns
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, kept = kept, stage(spark, kept, sf)
        rows = spark.createDataFrame(kept.collect(), docs.schema)
        old, new = {r.doc_id: r for r in before.collect()}, {r.doc_id: r for r in rows.collect()}
        assert kept.columns == columns and set(new) <= set(old)
        if name == "toxicity":
            marks = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
            gone = [marks[i] for i in old if i not in new and i in marks]
            assert all(gone) and sum(gone) >= 0.5 * sum(marks.values())
        elif name == "near_duplicates":
            component = {i: c for i, _, c in N.brute([(r.doc_id, r.text or "") for r in old.values()])}
            assert set(new) == {i for i, c in component.items() if i == c}
        elif name == "decontamination":
            items = [(str(r.item_id), r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            assert set(new) == {i for i, r in old.items() if not D.brute(r.text, items)[1]}
        else:
            assert set(new) == set(old)
            for i, r in new.items():
                assert not any(P.base_spans(r.text).values()), r.text
                if not P.base_spans_flat(old[i].text):
                    assert r.text == old[i].text and r.n_chars == old[i].n_chars
                assert r.n_chars == len(r.text)
        if name != "personal_data":
            assert all(new[i] == old[i] for i in new)
        kept = rows
    packed = corpus_pipeline.STAGES[-1][1](spark, kept, sf)
    assert {r.doc_id for r in packed.select("doc_id").collect()} == set(new)


def test_run(spark):
    assert corpus_pipeline.run(spark, X.SF).count() > 100


def test_awkward_rows_pass_through_the_stages(spark):
    docs = X.awkward_documents(spark)[0].drop("n_words", "n")
    for _, stage in corpus_pipeline.STAGES[1:4]:
        docs = spark.createDataFrame(stage(spark, docs, X.SF).collect(), docs.schema)
    rows = docs.collect()
    assert sum(r.doc_id == 6 for r in rows) == 1 and not any(r.doc_id in (7, 9) and r.text != "other text with the same id" for r in rows)
    assert any(r.text == "other text with the same id" for r in rows)
    assert sum(r.text is None for r in rows) == 2
    first = corpus_pipeline.STAGES[0][1]
    given = X.awkward_documents(spark)[0]
    left = first(spark, given, X.SF)
    assert left.columns == given.columns and left.exceptAll(given).count() == 0 and left.count() > 0
    empty = X.empty_documents(spark)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, X.SF).count() == 0


def test_native_operators_have_no_python_in_their_plans(spark):
    for name in ("op2_pii_spans", "op10_url_aliases"):
        plan = queries.QUERIES[name](spark, X.SF)._jdf.queryExecution().toString()
        assert not re.search("Python|Pandas|MapInArrow|Arrow", plan), name


def test_all_queries_are_registered():
    numbers = [int(re.match(r"op(\d+)_", k)[1]) for k in queries.QUERIES]
    assert numbers == list(range(1, 11))
