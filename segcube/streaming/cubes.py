"""Cubes of streams: per micro-batch with the grouped method, or continuously for few cuboids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema, Grouping
from segcube.operators.broadcast import messages
from segcube.operators.grouped_phases import grouped_states
from segcube.sources import scratch


def batch_sink(folder: str, grouping: Grouping, prepare=lambda df: df):
    """For ``foreachBatch``: store each batch's unfinished cube under its number; a replayed batch replaces itself."""

    def store(batch: DataFrame, number: int) -> None:
        grouped_states(prepare(batch), grouping).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    return store


def stored_states(spark: SparkSession, folder: str, schema: CubeSchema) -> DataFrame:
    """All stored batches added up."""
    return S.merge(spark.read.option("basePath", folder).parquet(folder), schema)


def compact(spark: SparkSession, folder: str, schema: CubeSchema, target: str) -> None:
    """Write the sum of all batches as one."""
    stored_states(spark, folder, schema).write.mode("overwrite").parquet(target)


def continuous_states(stream: DataFrame, schema: CubeSchema, time: str | None = None, delay: str = "1 hour", window: str | None = None) -> DataFrame:
    """One stateful aggregate over all cuboids' messages; with ``window`` a cube per window, closed by the watermark."""
    if time is None:
        return S.merge(messages(stream, schema), schema)
    timed = stream.withColumn("_time", F.col(time).cast("timestamp")).withWatermark("_time", delay)
    masks = [F.lit(m).cast("bigint") for m in S.legal_masks(schema)]
    leaf = timed.select(*schema.columns, "_time", *(s.init().alias(s.name) for s in schema.states))
    copy = lambda m: F.struct(*(F.when(m.bitwiseAND(F.lit(schema.bit(c))) == 0, F.col(c)).alias(c) for c in schema.columns), m.alias(MASK), *schema.state_names)
    sent = leaf.select("_time", F.explode(F.transform(F.array(*masks), copy)).alias("x")).select("_time", "x.*")
    out = sent.groupBy(F.window("_time", window), *schema.columns, MASK).agg(*(s.merged() for s in schema.states))
    return out.select(F.col("window.start").alias("window_start"), *schema.columns, MASK, *schema.state_names)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now into a stored table: Parquet files for appended rows; for complete results the last state replaces the one before."""
    spark = stream.sparkSession
    target, offsets = scratch.new_folder(spark, "drained"), scratch.new_folder(spark, "offsets")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", offsets).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").start(target)
    else:
        query = writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(target)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(target)
