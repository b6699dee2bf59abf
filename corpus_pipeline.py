"""A corpus pipeline of five stages, each applying one training-data operator to all that its predecessor kept.

A stage takes ``(spark, docs, sf_dir)`` and gives a DataFrame, which is written as Parquet and read again as the next one's
``docs``.  All stages but the last give the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segcube.llm import decontamination, encoding, near_duplicates, packing, pii, shared, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored 0.5 or more go.

    Null and empty texts get the score of a text without words; rows of equal text go or stay together, also when an id or a
    row repeats; without labelled rows of both kinds the share of toxic ones decides for all; an empty table stays empty.
    """
    model = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.score(docs, model, out="_toxic_score").filter("_toxic_score < 0.5").drop("_toxic_score")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of linked documents stays: the one with the smallest id, then with the smallest hash of its text.

    Null and empty texts and texts without words link with nothing and all stay; of rows that repeat an id and its text one stays, and a null id
    comes after all others; an empty table stays empty.
    """
    return near_duplicates.one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten consecutive words of a benchmark item (or a whole shorter one) go.

    Null and empty texts hold none and stay, as do all where the benchmark is empty; repeated rows go or stay together; an empty table stays empty.
    """
    return decontamination.without_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document stays; each span becomes its kind in brackets, and ``n_chars`` the length of the new text.

    Of spans that overlap the first and longest names the bracket; texts without a span, null and empty ones too, keep their text and ``n_chars``; repeated rows
    are masked alike; an empty table stays empty.
    """
    found = pii.find(docs).withColumn("_masked", pii.masked(F.col("text"), F.col("pii_spans")))
    n_chars = F.when(F.size("pii_spans") > 0, F.length("_masked").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    new = {"text": F.col("_masked").alias("text"), "n_chars": n_chars.alias("n_chars")}
    return found.select(*(new.get(c, F.col(c)) for c in docs.columns))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their token ids and places in sequences of at most 2048 tokens.

    A null or empty text is one piece of the end token; repeated rows are packed one by one; among equal lengths the order of
    pieces is free, their places are gapless; an empty table gives no rows.
    """
    return packing.pack(docs, encoding.vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("personal_data", mask_personal_data),
    ("packing", pack_sequences),
]

#: No stage but the third and fourth can be told in SQL; tests hold the run against plain Python instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = shared.materialised(stage(spark, docs, sf_dir), name)
    return docs
