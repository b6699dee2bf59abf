"""Workloads on streams, each with DuckDB SQL for what has to come out once all files are read."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from segcube.functions import measures as M
from segcube.functions import segments as S
from segcube.sources import scratch, tables
from segcube.streaming import cubes
from segcube.workloads import _COUNT, _COUNT_SQL, _EVENTS, EVENTS_SQL, _event_columns, big, cube_sql, register, shaped


def _event_stream(spark, folder):
    path = f"{folder}/events.parquet"
    shape = spark.read.parquet(path).schema
    return _event_columns(spark.readStream.schema(shape).option("pathGlobFilter", "events.parquet").parquet(folder))


@register("stream_micro_batch", cube_sql(_EVENTS, EVENTS_SQL, {"n": big("count(*)"), "sum_cents": big("sum(cents)")}))
def stream_micro_batch(spark, folder):
    """Each micro-batch is cubed by the grouped method and stored; the stored cubes add up to that of all events."""
    schema, grouping = shaped(_EVENTS, (M.count("n"), M.total("cents")))
    target = scratch.new_folder(spark, "stream")
    run = _event_stream(spark, folder).writeStream.foreachBatch(cubes.batch_sink(target, grouping)).option("checkpointLocation", scratch.new_folder(spark, "offsets")).trigger(availableNow=True).start()
    run.awaitTermination()
    return S.finalise(cubes.stored_states(spark, target, schema), schema)


@register("stream_complete", cube_sql("event_type | hour", EVENTS_SQL, _COUNT_SQL))
def stream_complete(spark, folder):
    """One stateful aggregate over all cuboids of the stream."""
    schema, _ = shaped("event_type | hour", _COUNT)
    states = cubes.continuous_states(_event_stream(spark, folder), schema)
    return S.finalise(cubes.drain(states, "complete"), schema)


#: The last event, less the allowed delay of an hour.
_PASSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM ev)"
_DAYS_SQL = (
    f"WITH {EVENTS_SQL} SELECT CAST(day AS TIMESTAMP) AS window_start, event_type, hour, {big('GROUPING(event_type, hour)')} AS star_mask, {big('count(*)')} AS n "
    f"FROM ev WHERE CAST(day AS TIMESTAMP) + INTERVAL 1 DAY <= {_PASSED} GROUP BY CAST(day AS TIMESTAMP), ROLLUP(event_type), ROLLUP(hour)"
)


def _plain_time(df, *columns):
    """Times without a zone, as the events have them."""
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in columns})


@register("stream_watermark", _DAYS_SQL)
def stream_watermark(spark, folder):
    """A cube per day, given out when the watermark has passed it (the last days stay open)."""
    schema, _ = shaped("event_type | hour", _COUNT)
    states = cubes.continuous_states(_event_stream(spark, folder), schema, time="ts", window="1 day")
    return _plain_time(cubes.drain(states), "window_start")


_SESSION_SQL = (
    f"WITH {EVENTS_SQL}, marked AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM ev), "
    "numbered AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM marked) "
    f'SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS "end", {big("count(*)")} AS n FROM numbered GROUP BY user_id, session HAVING max(ts) + INTERVAL 2 HOUR <= {_PASSED}'
)


def _timed(stream):
    return stream.withColumn("time", F.col("ts").cast("timestamp")).withWatermark("time", "1 hour")


@register("stream_session", _SESSION_SQL)
def stream_session(spark, folder):
    """Sessions of a user's events, closed after two idle hours."""
    sessions = _timed(_event_stream(spark, folder)).groupBy(F.session_window("time", "2 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")
    return _plain_time(cubes.drain(sessions), "start", "end")


_SLIDING_SQL = (
    f"WITH {EVENTS_SQL}, halves AS (SELECT CAST(day AS TIMESTAMP) + CASE WHEN hour >= 12 THEN INTERVAL 12 HOUR ELSE INTERVAL 0 HOUR END AS half, event_type FROM ev) "
    f"SELECT half - back * INTERVAL 12 HOUR AS window_start, event_type, {big('count(*)')} AS n FROM halves, (VALUES (0), (1)) AS b(back) GROUP BY ALL"
)


@register("stream_sliding", _SLIDING_SQL)
def stream_sliding(spark, folder):
    """Days that begin every twelve hours."""
    counted = _event_stream(spark, folder).groupBy(F.window(F.col("ts").cast("timestamp"), "1 day", "12 hours").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return _plain_time(cubes.drain(counted.select(F.col("w.start").alias("window_start"), "event_type", "n"), "complete"), "window_start")


@register("stream_dedup", f"SELECT event_type, {big('count(*)')} AS n FROM events GROUP BY 1")
def stream_dedup(spark, folder):
    """Every event arrives twice and counts once; the state of an identifier ends with the watermark."""
    twice = _timed(_event_stream(spark, folder).unionByName(_event_stream(spark, folder)))
    return cubes.drain(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_type")).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@register("stream_static_join", cube_sql("c_mktsegment | event_type", "je AS (SELECT c.c_mktsegment, e.event_type FROM events e JOIN customer c ON e.user_id = c.c_custkey)", _COUNT_SQL))
def stream_static_join(spark, folder):
    """Events with their customer's segment, cubed continuously."""
    customers = tables.read_table(spark, folder, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    schema, _ = shaped("c_mktsegment | event_type", _COUNT)
    states = cubes.continuous_states(_event_stream(spark, folder).join(customers, "user_id"), schema)
    return S.finalise(cubes.drain(states, "complete"), schema)


@register(
    "stream_interval_join",
    "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
)
def stream_interval_join(spark, folder):
    """Clicks with the same user's purchases of the next hour; both sides' state ends with the watermark."""
    side = lambda kind, name: _timed(_event_stream(spark, folder).filter(F.col("event_type") == kind)).select(F.col("user_id").alias(f"{name}_user"), F.col("event_id").alias(f"{name}_id"), F.col("time").alias(f"{name}_time"))
    near = "click_user = purchase_user AND purchase_time >= click_time AND purchase_time <= click_time + INTERVAL 1 HOUR"
    joined = side("click", "click").join(side("purchase", "purchase"), F.expr(near))
    return cubes.drain(joined.select("click_id", "purchase_id"))


def _add_up(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    n, cents = state.get if state.exists else (0, 0)
    for batch in batches:
        n, cents = n + len(batch), cents + int(batch["cents"].sum())
    state.update((n, cents))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "sum_cents": [cents]})


@register("stream_user_state", f"WITH {EVENTS_SQL} SELECT user_id, {big('count(*)')} AS n, {big('sum(cents)')} AS sum_cents FROM ev GROUP BY 1")
def stream_user_state(spark, folder):
    """Any state of one's own: a user's running totals, given out after each batch; the state is two numbers."""
    out = "user_id bigint, n bigint, sum_cents bigint"
    states = _event_stream(spark, folder).select("user_id", "cents").groupBy("user_id").applyInPandasWithState(_add_up, out, "n bigint, cents bigint", "append", GroupStateTimeout.NoTimeout)
    return cubes.drain(states).groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("sum_cents", "n").alias("sum_cents"))
