"""The broadcast baseline: every row is sent to every segment it belongs to."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema

#: Grouping sets beyond this number make Spark's generated code too large.
MAX_SETS = 512


def messages(df: DataFrame, schema: CubeSchema, masks: list[int] | None = None) -> DataFrame:
    """One row per input row and legal mask."""
    return sent(S.lift(df, schema), schema, masks)


def sent(leaf: DataFrame, schema: CubeSchema, masks: list[int] | None = None) -> DataFrame:
    """Each leaf segment once for each mask: the masks are generated, the stars put in behind, both in generated code."""
    masks = S.legal_masks(schema) if masks is None else masks
    rows = leaf.drop(MASK).withColumn(MASK, F.explode(F.array(*(F.lit(m).cast("bigint") for m in masks))))
    return rows.select(*(F.when(~S.has_star(schema, c), F.col(c)).alias(c) for c in schema.columns), MASK, *schema.state_names)


def broadcast_states(df: DataFrame, schema: CubeSchema, combine: bool = True) -> DataFrame:
    """Equal leaves are added up before they are sent; ``combine=False`` shuffles every message by itself: partial sums cannot form before the exchange."""
    if not combine:
        return S.merge(messages(df, schema).repartition(*schema.columns, MASK), schema)
    return S.merge(sent(S.merge(S.lift(df, schema), schema), schema), schema)


def grouping_sets_states(df: DataFrame, schema: CubeSchema, masks: list[int] | None = None) -> DataFrame:
    """The same through Spark's own grouping sets (one ``Expand`` of all sets)."""
    masks = S.legal_masks(schema) if masks is None else masks
    if len(masks) > MAX_SETS:
        raise ValueError(f"{len(masks)} grouping sets; at most {MAX_SETS}")
    leaf = S.merge(S.lift(df, schema), schema).drop(MASK)  # equal leaves are added up before they are sent
    sets = [[F.col(c) for c in schema.columns if not m & schema.bit(c)] for m in masks]
    out = leaf.groupingSets(sets, *schema.columns).agg(F.grouping_id(*schema.columns).alias(MASK), *(s.merged() for s in schema.states))
    # without input SQL gives an all-star row; a cube of nothing is empty
    return out.join(F.broadcast(df.limit(1).select(F.lit(1).alias("_some"))), F.lit(True), "left_semi")


def flat_cube_states(df: DataFrame, schema: CubeSchema) -> DataFrame:
    """One-column dimensions: the plain ``CUBE``."""
    if any(len(d.columns) > 1 for d in schema.dims):
        raise ValueError("CUBE stars columns one by one; use grouping sets for hierarchies")
    leaf = S.merge(S.lift(df, schema), schema).drop(MASK)
    out = leaf.cube(*schema.columns).agg(F.grouping_id(*schema.columns).alias(MASK), *(s.merged() for s in schema.states))
    return out.join(F.broadcast(df.limit(1).select(F.lit(1).alias("_some"))), F.lit(True), "left_semi")


def broadcast_cube(df: DataFrame, schema: CubeSchema, style: str = "explode", combine: bool = True, keep=None) -> DataFrame:
    made = {"explode": lambda: broadcast_states(df, schema, combine), "grouping_sets": lambda: grouping_sets_states(df, schema), "cube": lambda: flat_cube_states(df, schema)}[style]()
    return S.finalise(made, schema, keep)
