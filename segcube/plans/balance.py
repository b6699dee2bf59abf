"""How evenly a choice of sharding columns spreads the work."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def shard_share(df: DataFrame, columns) -> DataFrame:
    """One row: keys, rows of the largest key, and its share of all rows."""
    loads = df.groupBy(*columns).agg(F.count(F.lit(1)).alias("load"))
    return loads.agg(F.count(F.lit(1)).alias("keys"), F.max("load").alias("max_rows"), F.sum("load").alias("rows")).withColumn("share", F.try_divide(F.col("max_rows").cast("double"), F.col("rows").cast("double")))


def machine_balance(loads: DataFrame, columns, work: str, machines: int) -> DataFrame:
    """Work of the busiest machine over the mean, keys being dealt to machines by a hash of their text."""
    digest = F.md5(F.concat_ws("|", *(F.coalesce(F.col(c).cast("string"), F.lit("\\N")) for c in columns)))
    number = F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint")
    dealt = loads.groupBy((number % machines).alias("machine")).agg(F.sum(work).alias("work"))
    return dealt.agg(F.max("work").alias("max_work"), F.sum("work").alias("all_work")).withColumn("max_over_mean", F.try_divide(F.col("max_work").cast("double") * machines, F.col("all_work").cast("double")))


def heavy_values(df: DataFrame, column: str, k: int = 10) -> DataFrame:
    """The most frequent values, ties to the smaller."""
    return df.groupBy(column).agg(F.count(F.lit(1)).alias("rows")).orderBy(F.desc("rows"), F.col(column).asc_nulls_first()).limit(k)
