"""The thin ``opN_<name>`` queries: each applies its operator to a whole table and derives the agreed columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segcube.llm import decontamination, encoding, hidden_markov, licenses, near_duplicates, neighbours, packing, pii, shared, sstable, toxicity, url_filter


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared.new_folder(spark, "token-shards")
    manifest = sstable.write_shards(table(spark, sf_dir, "documents"), folder, encoding.vocabulary("word_bpe_49k.json"))
    return sstable.read_shards(manifest)


def op2_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "pii_spans")
    counts = [pii.count_of(F.col("pii_spans"), kind).alias(f"n_{kind}") for kind in pii.BASE]
    spans = F.col("pii_spans")
    return found.select("doc_id", *counts, F.sha2(pii.rendered(pii.base_only(spans)), 256).alias("base_sha256"), pii.rendered(spans).alias("spans"), F.array_max(F.transform(spans, lambda s: s["score"])).alias("top_score"))


def op3_residual_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.search(table(spark, sf_dir, "embeddings"))


def op4_positional_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = decontamination.build_index(table(spark, sf_dir, "documents"))
    found = decontamination.contamination(index, table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), decontamination.items_digest().alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


def op5_license_diagonals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents")).drop("spans")


def op6_toxicity_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model, keep=["doc_id", "lang"])
    own = F.create_map(*(F.lit(x) for pair in sorted(model.thresholds.items()) for x in pair)) if model.thresholds else F.create_map().cast("map<string,double>")
    threshold = F.coalesce(own[F.coalesce("lang", F.lit(""))], F.lit(0.5))
    return scored.select(
        "doc_id", (toxicity.fold(F.col("doc_id"), 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), (F.col("score") >= threshold).cast("int").alias("predicted_by_language")
    )


def op7_hidden_markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hidden_markov.score_documents(table(spark, sf_dir, "documents"))


def op8_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.find(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


def op9_pattern_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = packing.pack(table(spark, sf_dir, "documents"), encoding.vocabulary("byte_bpe_50k.json"))
    return packed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op10_url_aliases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


QUERIES = {
    "op1_token_shards": op1_token_shards,
    "op2_pii_spans": op2_pii_spans,
    "op3_residual_search": op3_residual_search,
    "op4_positional_index": op4_positional_index,
    "op5_license_diagonals": op5_license_diagonals,
    "op6_toxicity_cnn": op6_toxicity_cnn,
    "op7_hidden_markov": op7_hidden_markov,
    "op8_shingle_join": op8_shingle_join,
    "op9_pattern_packing": op9_pattern_packing,
    "op10_url_aliases": op10_url_aliases,
}
ORACLE_SQL: dict[str, str] = {}
