"""Workloads of the remaining operators: the SQL surface, range windows, dates, JSON, maps, heavy values and key parsing."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions import sql
from segcube.functions.schema import MASK
from segcube.operators.grouped_phases import grouped_cube
from segcube.plans import balance
from segcube.sources import tables
from segcube.workloads import _COUNT, _COUNT_SQL, _DAILY, BASIC_SQL, EVENTS_SQL, S5, S8, TIME, WIDE_SQL, _daily, _grouped, big, cube_sql, events, register, shaped


@register("broadcast_by_table_function", cube_sql(S5))
def broadcast_by_table_function(spark, folder):
    """The broadcast method in SQL: each row's segments from a table function, joined laterally."""
    schema, _ = shaped(S5)
    rows = tables.wide(spark, folder)
    sql.register_segments_of(spark, rows, schema, "s5_segments_of")
    rows.createOrReplaceTempView("s5_rows")
    columns, sums = ", ".join(f"s.{c}" for c in schema.columns), ", ".join(f"{v} AS {k}" for k, v in BASIC_SQL.items())
    return spark.sql(f"SELECT {columns}, s.{MASK}, {sums} FROM s5_rows r, LATERAL s5_segments_of({', '.join(f'r.{c}' for c in schema.columns)}) s GROUP BY {columns}, s.{MASK}")


@register("sql_surface", f"SELECT CAST(bit_count(star_mask) AS INTEGER) AS layer, {big('count(*)')} AS segments, {big('sum(n)')} AS n FROM ({cube_sql(TIME)}) GROUP BY 1")
def sql_surface(spark, folder):
    """A cube as a view, asked in SQL with a function of its masks."""
    sql.register_cube(_grouped(TIME)(spark, folder), "time_cube")
    sql.register_star_layer(spark)
    return spark.sql("SELECT star_layer(star_mask) AS layer, count(*) AS segments, sum(n) AS n FROM time_cube GROUP BY 1")


@register("range_window", f"SELECT *, {big('sum(n) OVER (PARTITION BY event_type ORDER BY day RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW)')} AS week FROM ({_DAILY})")
def range_window(spark, folder):
    """The sum over seven days by their dates, whether or not every day has a row."""
    number = F.date_diff("day", F.lit("1970-01-01").cast("date"))
    return _daily(spark, folder).withColumn("week", F.sum("n").over(Window.partitionBy("event_type").orderBy(number).rangeBetween(-6, 0)))


@register(
    "ship_delay_by_month",
    f"SELECT CAST(date_trunc('month', l_shipdate) AS DATE) AS month, make_date(CAST(year(l_shipdate) AS INTEGER), 1, 1) AS year_start, {big('count(*)')} AS n, {big('sum(date_diff(' + chr(39) + 'day' + chr(39) + ', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)))')} AS days "
    "FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
)
def ship_delay_by_month(spark, folder):
    lines, orders = tables.read_table(spark, folder, "lineitem").select("l_orderkey", "l_shipdate"), tables.read_table(spark, folder, "orders").select("o_orderkey", "o_orderdate")
    month, year = F.date_trunc("month", "l_shipdate").cast("date").alias("month"), F.make_date(F.year("l_shipdate"), F.lit(1), F.lit(1)).alias("year_start")
    days = F.date_diff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(month, year).agg(F.count(F.lit(1)).alias("n"), F.sum(days).alias("days"))


@register("json_struct", f"WITH {EVENTS_SQL} SELECT '{{\"type\":\"' || event_type || '\",\"k\":' || k || '}}' AS key, {big('count(*)')} AS n FROM (SELECT event_type, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM ev) GROUP BY 1")
def json_struct(spark, folder):
    """A key written as JSON, from a value parsed out of JSON."""
    parsed = F.from_json("props", "k int")["k"]
    key = F.to_json(F.struct(F.col("event_type").alias("type"), parsed.alias("k")))
    return events(spark, folder).groupBy(key.alias("key")).agg(F.count(F.lit(1)).alias("n"))


_PHASES = {m: S.phase_of_mask(m, shaped(S8)[1]) for m in S.legal_masks(shaped(S8)[0])}


@register("segments_by_phase", f"SELECT CAST(CASE star_mask {' '.join(f'WHEN {m} THEN {p}' for m, p in _PHASES.items())} END AS INTEGER) AS phase, {big('count(*)')} AS segments FROM ({cube_sql(S8)}) GROUP BY 1")
def segments_by_phase(spark, folder):
    """Segments by the phase that makes them, looked up by mask in a map."""
    return _grouped(S8)(spark, folder).groupBy(S.by_mask(_PHASES).alias("phase")).agg(F.count(F.lit(1)).alias("segments"))


@register("heavy_values", f"WITH {WIDE_SQL} SELECT hot_supp, {big('count(*)')} AS rows FROM wide GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")
def heavy_values(spark, folder):
    return balance.heavy_values(tables.skewed(tables.wide(spark, folder)), "hot_supp")


@register("stratified_sample")
def stratified_sample(spark, folder):
    """A sample that takes more of the rare event types; what it counts, scaled up."""
    rows = events(spark, folder).sampleBy("event_type", {"purchase": 0.5, "signup": 0.5, "click": 0.1, "view": 0.1, "error": 0.1}, seed=5)
    share = F.when(F.col("event_type").isin("purchase", "signup"), 0.5).otherwise(0.1)
    return rows.groupBy("event_type").agg(F.count(F.lit(1)).alias("sampled"), F.round(F.sum(1 / share)).cast("bigint").alias("estimate"))


_FLAGS = "p_type | l_returnflag, l_linestatus"


@register("key_parse", f"SELECT p_type, l_returnflag, l_linestatus, n FROM ({cube_sql(_FLAGS, values=_COUNT_SQL)})")
def key_parse(spark, folder):
    """Written keys read back, a batch of them at a time; stars come back as nulls."""
    schema, grouping = shaped(_FLAGS, _COUNT)

    @F.arrow_udf("array<string>")
    def parsed(keys: pa.Array) -> pa.Array:
        return pa.array([[None if part is ... else part for part in S.parse_key(k)] for k in keys.to_pylist()], pa.list_(pa.string()))

    keys = grouped_cube(tables.wide(spark, folder), grouping).select(parsed(S.render_key(schema)).alias("parts"), "n")
    return keys.select(*(F.col("parts")[i].alias(c) for i, c in enumerate(schema.columns)), "n")
