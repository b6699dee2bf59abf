"""Reading the given tables, the wide join, derived dimensions, and writing cubes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from segcube.functions.schema import MASK
from segcube.sources import scratch

FORMATS = ("parquet", "orc", "json", "csv")
#: Rows up to which a hint to broadcast is followed: some 100 bytes each in the driver.
BROADCAST_ROWS = 1_000_000


def read_table(spark: SparkSession, folder: str, name: str, kind: str = "parquet", schema=None) -> DataFrame:
    """A table of a folder; for json and csv give the schema (none is inferred)."""
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind}")
    reader = spark.read.format(kind)
    if kind in ("json", "csv"):
        if schema is None:
            raise ValueError(f"{kind} needs a schema")
        reader = reader.schema(schema).options(**({"header": "true"} if kind == "csv" else {}))
    return reader.load(f"{folder}/{name}.{kind}")


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path)


def band(column: Column, *edges) -> Column:
    """Number of edges that a value reaches."""
    out = F.lit(0)
    for e in edges:
        out = out + F.when(column >= e, 1).otherwise(0)
    return out.cast("int")


def wide(spark: SparkSession, folder: str, join: str | None = None) -> DataFrame:
    """One row per line item with customer, part and supplier columns.

    Nations and regions have a fixed size and are broadcast; for the others Spark chooses by size, or ``join`` hints
    the join of lines and orders (``merge``, ``shuffle_hash``, ``broadcast``).  More than ``BROADCAST_ROWS`` orders are not broadcast but merged, with the same rows: the
    driver and every executor would hold all of them.
    """
    t = lambda name: read_table(spark, folder, name)
    places = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    customers = t("customer").join(F.broadcast(places.select("n_nationkey", F.col("r_name").alias("c_region"), F.col("n_name").alias("c_nation"))), F.col("c_nationkey") == F.col("n_nationkey"))
    suppliers = t("supplier").join(F.broadcast(places.select("n_nationkey", F.col("r_name").alias("s_region"), F.col("n_name").alias("s_nation"))), F.col("s_nationkey") == F.col("n_nationkey"))
    orders = t("orders").select("o_orderkey", F.col("o_custkey").alias("c_custkey"), "o_orderpriority", "o_orderstatus")
    if join == "broadcast" and orders.count() > BROADCAST_ROWS:
        join = "merge"
    lines = t("lineitem").join(orders.hint(join) if join else orders, F.col("l_orderkey") == F.col("o_orderkey"))
    rows = lines.join(customers.select("c_custkey", "c_region", "c_nation", "c_mktsegment"), "c_custkey")
    rows = rows.join(t("part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_type", "p_size"), "l_partkey")
    rows = rows.join(suppliers.select(F.col("s_suppkey").alias("l_suppkey"), "s_region", "s_nation"), "l_suppkey")
    return rows.select(
        "l_orderkey", "c_region", "c_nation", "c_custkey", "c_mktsegment", "o_orderpriority", "o_orderstatus", "p_brand", "l_partkey", "p_type", "p_size", "s_region", "s_nation", "l_suppkey", "l_returnflag", "l_linestatus",
        F.year("l_shipdate").alias("ship_year"), F.month("l_shipdate").alias("ship_month"), F.dayofmonth("l_shipdate").alias("ship_day"), band(F.col("l_discount"), 0.03, 0.07).alias("discount_band"),
        F.lit(1).cast("bigint").alias("rows_1"), F.col("l_quantity").cast("bigint").alias("qty"), F.round(F.col("l_extendedprice") * 100).cast("bigint").alias("cents"),
    )


def skewed(rows: DataFrame) -> DataFrame:
    """``wide`` with ids of which one holds about a third of all rows."""
    hot = lambda n, k, c: F.when(F.col("l_orderkey") % n < k, F.lit(0)).otherwise(F.col(c)).cast("bigint")
    return rows.withColumns({"hot_supp": hot(10, 3, "l_suppkey"), "hot_part": hot(7, 2, "l_partkey"), "hot_cust": hot(11, 3, "c_custkey")})


def encode(df: DataFrame, column: str) -> tuple[DataFrame, DataFrame]:
    """Dictionary coding: ``df`` with integer codes in place of values, and the dictionary (distinct values, numbered in order).

    Values are numbered inside range partitions and shifted by the sizes of the partitions before, not sorted in one task.
    """
    from pyspark.sql import Window

    words = df.select(column).distinct().filter(F.col(column).isNotNull())
    words = scratch.materialised(words.repartitionByRange(column).withColumn("_task", F.spark_partition_id()), "words")
    sizes = words.groupBy("_task").agg(F.count(F.lit(1)).alias("n"))  # a row for each partition
    shifts = sizes.select("_task", F.coalesce(F.sum("n").over(Window.orderBy("_task").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    place = F.row_number().over(Window.partitionBy("_task").orderBy(column))
    words = words.withColumn("place", place).join(F.broadcast(shifts), "_task").select(column, (F.col("place") + F.col("before")).cast("int").alias("code"))
    return df.join(words, column, "left").drop(column).withColumnRenamed("code", column), words


def write_cube(cube: DataFrame, path: str, by: tuple[str, ...] = (MASK,), kind: str = "parquet", mode: str = "overwrite") -> None:
    """Partitioned by mask or phase, so that a lookup reads one cuboid; overwriting replaces only the partitions it has."""
    writer = cube.write.mode(mode).partitionBy(*by)
    if mode == "overwrite":
        writer = writer.option("partitionOverwriteMode", "dynamic")
    writer.format(kind).save(path)


def write_bucketed(cube: DataFrame, name: str, columns, buckets: int) -> None:
    """A table bucketed and sorted by key columns: joins on them need no exchange."""
    cube.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).saveAsTable(name)
