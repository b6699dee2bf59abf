"""Runs the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import re
import time

from pyspark.sql import SparkSession

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
#: The headline queries; their seconds add up to ``value``.
NAMES = ("s5_grouped", "s5_grouping_sets", "s5_broadcast", "s5_layered", "s5_batch_area", "s8_grouped", "s8_grouping_sets", "change_significant", "skewed_cube", "events_cube")
#: Measured beside them, as far as the time goes: kernels, the other methods on S8.
EXTRA = ("s5_kernel_layers", "s8_grouped_layers", "s8_broadcast", "s8_layered", "s8_batch_area", "skewed_cube_whole")
#: Seconds after which no further query is begun.
LIMIT = float(os.environ.get("BENCH_LIMIT_S", "900"))


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g")).config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from segcube.workloads import QUERIES

    QUERIES["s5_grouped"](spark, FOLDER).limit(1).count()  # starts the JVM's code and the file cache
    seconds: dict[str, float] = {}
    rows: dict[str, int] = {}
    began = time.perf_counter()
    for name in NAMES + EXTRA:
        if time.perf_counter() - began > LIMIT:
            break
        start = time.perf_counter()
        rows[name] = _drain(QUERIES[name](spark, FOLDER))
        seconds[name] = round(time.perf_counter() - start, 2)
    scale = re.search(r"sf([0-9.]+)", FOLDER)
    extra = {"rows": rows, "rows_per_s": {n: round(rows[n] / s) for n, s in seconds.items() if s}, "cpus": int(CPUS)}
    if time.perf_counter() - began < LIMIT:
        extra["messages"] = {r.method: [r.remote_msgs, r.local_msgs] for r in QUERIES["method_messages_s5"](spark, FOLDER).collect()}
        extra["run_s8"] = [r.asDict() for r in QUERIES["s8_run_times"](spark, FOLDER).collect()]
        extra["sizes_s5"] = {r.what: [r.rows, r.bytes] for r in QUERIES["cube_bytes"](spark, FOLDER).collect()}
    small = os.path.join(os.path.dirname(FOLDER.rstrip("/")), "sf0.001")
    if time.perf_counter() - began < LIMIT and os.path.isdir(small):  # the full shape, at the smallest size only
        start = time.perf_counter()
        extra["s14_at_sf0.001"] = {"rows": _drain(QUERIES["s14_change_significant"](spark, small)), "seconds": round(time.perf_counter() - start, 2)}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.get(n, 0) for n in NAMES), 2), "unit": "sec", "queries": seconds, "sf": float(scale[1]) if scale else None, **extra}))
    spark.stop()


def _drain(df) -> int:
    """Compute every column of every row, and count them."""
    from pyspark.sql import Observation
    from pyspark.sql import functions as F

    seen = Observation()
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    return seen.get["n"]


if __name__ == "__main__":
    main()
