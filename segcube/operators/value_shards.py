"""Cubes by value: a segment is added up where the first of its values that is not heavy has its home.

``by`` names columns of many values.  A segment with a value in the first of them is made in the task that has all rows of that value; one
with a star there goes by the second column, and so on.  A row is therefore sent once for each column of ``by``, with stars in the columns before, and all its
segments are made inside the task, where the grouped method sends nearly all segments of all phases but the last.

Heavy values, which hold more than a share of all rows, give no home: their segments go by the next column as those with a star do, next to them.  Segments without
any home have heavy values and stars only in ``by``; their rows are added up first and sent to each segment.  Which values count as heavy changes no
result.  For shapes whose columns outside ``by`` have few values together: the last step's rows are as many as these have.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema
from segcube.sources import scratch

#: A value is heavy above this many rows and one part in so many of all rows; so there are fewer than that in a column.
HEAVY_ROWS, HEAVY_PARTS = 10_000, 256
#: Segments that a task makes on average, if none of them were equal.
TASK_SEGMENTS = 400_000


def heavy_values(leaves: DataFrame, column: str, above: int) -> list:
    """Values of more than ``above`` rows; None is the null value."""
    return [r[0] for r in leaves.groupBy(column).count().filter(F.col("count") > above).select(column).collect()]


def _is_one_of(column: str, values: list) -> Column:
    known = F.col(column).isin([v for v in values if v is not None])
    return F.coalesce(known, F.lit(None in values))


def expand(df: DataFrame, schema: CubeSchema, masks: list[int]) -> DataFrame:
    """Each segment's copies for those of the masks that keep its stars; columns with a star in none of the masks pass by."""
    sent = df.withColumn("_to", F.explode(F.array(*(F.lit(m).cast("bigint") for m in masks)))).filter(F.col("_to").bitwiseAND(F.col(MASK)) == F.col(MASK))
    some = reduce(lambda a, b: a | b, masks, 0)
    columns = [F.when(~S.has_star(schema, c, "_to"), F.col(c)).alias(c) if some & schema.bit(c) else F.col(c) for c in schema.columns]
    return sent.select(*columns, F.col("_to").alias(MASK), *schema.state_names)


def value_sharded_states(df: DataFrame, schema: CubeSchema, by) -> DataFrame:
    """The whole cube with unfinished measures.  The input is stored, and heavy values are counted, when this is called."""
    with scratch.shuffles_freed(df.sparkSession):
        leaves = scratch.materialised(S.lift(df, schema), "leaves")
        rows = leaves.count()
        heavy = {c: heavy_values(leaves, c, max(HEAVY_ROWS, rows // HEAVY_PARTS)) for c in by}
    parts, now, legal = [], leaves, S.legal_masks(schema)
    for c in by:
        home = ~S.has_star(schema, c) & ~_is_one_of(c, heavy[c])
        masks = [m for m in legal if not m & schema.bit(c)]
        at_home = now.filter(home).repartition(max(8, -(-rows * len(masks) // TASK_SEGMENTS)), c)
        parts.append(S.merge(expand(at_home, schema, masks), schema))
        starred = (c, *S.lower_levels(schema, c))
        columns = [F.when(~home, F.col(x)).alias(x) if x in starred else F.col(x) for x in schema.columns]
        mask = F.when(home, F.col(MASK).bitwiseOR(F.lit(schema.bits(starred)))).otherwise(F.col(MASK))
        now = now.select(*columns, mask.alias(MASK), *schema.state_names)
    parts.append(S.merge(expand(S.merge(now, schema), schema, legal), schema))
    return reduce(DataFrame.unionByName, parts)


def value_sharded_cube(df: DataFrame, schema: CubeSchema, by, keep=None) -> DataFrame:
    return S.finalise(value_sharded_states(df, schema, by), schema, keep)
