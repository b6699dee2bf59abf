"""Cost measures: remote and local messages, blow-up, locality, balance; per phase and for each method.

A message is one copy-add.  A phase's remote messages are its input rows (one routed row each); its local messages are, over all its output
segments, the primary parents within the phase's group.  Adding equal input vectors up is kept apart (``h0_inserts``), and
writing output is not counted.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema, Grouping
from segcube.operators.grouped_phases import phase_outputs

PHASE_ROW = (
    "phase int, input_rows bigint, remote_msgs bigint, h0_inserts bigint, output_rows bigint, local_msgs bigint, phase_blow_up double, local_per_remote double, "
    "max_nodes_per_key bigint, max_local_per_key bigint, node_share double, local_share double, shuffle_records bigint, seconds double"
)


def _over(a, b):
    return float(a) / b if b else None


def key_loads(output: DataFrame, grouping: Grouping, phase: int) -> DataFrame:
    """Nodes and local messages of each local problem (each key of the phase)."""
    schema, group = grouping.schema, grouping.group(phase)
    other_mask = F.col(MASK).bitwiseAND(F.lit(schema.bits(grouping.others(phase)))).alias("other_mask")
    return output.groupBy(*grouping.others(phase), other_mask).agg(F.count(F.lit(1)).alias("nodes"), F.sum(S.number_of_parents(schema, group)).alias("local_msgs"))


def run_phases(df: DataFrame, grouping: Grouping, **options) -> tuple[list[tuple], DataFrame]:
    """A tuple of ``PHASE_ROW`` for each phase, and the cube's states.

    Seconds cover computing and storing the phase.  ``shuffle_records`` are the rows that really go into its shuffle: its
    input rows, or what combiners leave of them.
    """
    rows, before, output, read = [], None, None, Observation()
    routed = {p: Observation() for p in grouping.phases}
    began = time.perf_counter()
    outputs = phase_outputs(df, grouping, store=True, read=read, routed=routed, **options)
    for phase in grouping.phases:
        output = next(outputs)
        seconds = time.perf_counter() - began
        before = read.get["n"] if before is None else before
        x = key_loads(output, grouping, phase).agg(F.sum("nodes").alias("n"), F.sum("local_msgs").alias("m"), F.max("nodes").alias("top_n"), F.max("local_msgs").alias("top_m")).first()
        n, m = x.n or 0, x.m or 0
        rows.append((phase, before, before, before, n, m, _over(n, before), _over(m, before), x.top_n or 0, x.top_m or 0, _over(x.top_n or 0, n), _over(x.top_m or 0, m), routed[phase].get["n"], seconds))
        before, began = n, time.perf_counter()
    return rows, output


def phase_stats(df: DataFrame, grouping: Grouping, **options) -> list[tuple]:
    return run_phases(df, grouping, **options)[0]


def phase_ledger(df: DataFrame, grouping: Grouping, **options) -> DataFrame:
    return df.sparkSession.createDataFrame(phase_stats(df, grouping, **options), PHASE_ROW)


def totals(rows: list[tuple]) -> dict[str, float | None]:
    """Sums over the phases and the ratios that the method is judged by."""
    remote, local, raw, cube = sum(r[2] for r in rows), sum(r[5] for r in rows), rows[0][1], rows[-1][4]
    later = remote - raw
    return {
        "input_rows": raw, "cube_rows": cube, "output_rows": sum(r[4] for r in rows), "remote_msgs": remote, "remote_msgs_after_first": later, "local_msgs": local,
        "h0_inserts": sum(r[3] for r in rows), "local_with_h0": local + sum(r[3] for r in rows), "locality": _over(local, local + later), "blow_up": _over(cube, raw), "local_per_segment": _over(local, cube),
        "messages_per_segment": _over(local + remote, cube), "remote_per_input_row": _over(remote, raw), "remote_after_first_per_input_row": _over(later, raw), "shuffle_records": sum(r[12] for r in rows), "seconds": sum(r[13] for r in rows),
        "largest_local_share": max((r[11] or 0 for r in rows), default=0), "largest_node_share": max((r[10] or 0 for r in rows), default=0),
    }


def broadcast_messages(rows: int, schema: CubeSchema, own: bool = False) -> int:
    """A row's own key is no message unless ``own``."""
    return rows * (len(S.legal_masks(schema)) - (0 if own else 1))


def layered_messages(cube: DataFrame, schema: CubeSchema) -> int:
    return cube.agg(F.sum(S.number_of_parents(schema))).first()[0] or 0


def method_messages(spark: SparkSession, df: DataFrame, grouping: Grouping, areas: Callable[[DataFrame], int]) -> DataFrame:
    """Logical messages of each method on one input; ``areas`` gives from the cube's states the number of batch areas of a plan for it."""
    rows, cube = run_phases(df, grouping)
    all_, raw = totals(rows), rows[0][1]
    chain = layered_messages(cube, grouping.schema)
    out = [
        ("grouped", all_["remote_msgs"], all_["local_msgs"]), ("layered", raw + chain, 0), ("broadcast", broadcast_messages(raw, grouping.schema), 0), ("batch_area", raw * areas(cube), None),
    ]
    return spark.createDataFrame(out, "method string, remote_msgs bigint, local_msgs bigint")


def total_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """``measure, value``: the totals of a run, without its seconds."""
    kept = [(k, None if v is None else float(v)) for k, v in totals(rows).items() if k != "seconds"]
    return spark.createDataFrame(kept, "measure string, value double")


def primary_parent_histogram(cube: DataFrame, schema: CubeSchema) -> DataFrame:
    """Segments by number of primary parents; never more than there are dimensions."""
    return cube.groupBy(S.number_of_parents(schema).alias("parents")).agg(F.count(F.lit(1)).alias("segments"))


def sizes(path: str, spark: SparkSession) -> tuple[int, int]:
    """Rows and bytes of a stored table."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    return spark.read.parquet(path).count(), files.getContentSummary(folder).getLength()
