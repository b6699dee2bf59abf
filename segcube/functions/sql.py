"""The engine in SQL: a table function of a row's segments, and functions of star masks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema


def _quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def register_segments_of(spark: SparkSession, df: DataFrame, schema: CubeSchema, name: str = "segments_of") -> None:
    """``name(columns...)``: a table of all segments that a row with these values belongs to, for lateral joins.

    It is a SQL function, so a query with it is planned as one with an explode: no Python runs.
    """
    kinds = {c: df.schema[c].dataType.simpleString() for c in schema.columns}
    given = ", ".join(f"{_quoted('of_' + c)} {kinds[c]}" for c in schema.columns)
    out = ", ".join(f"{_quoted(c)} {kinds[c]}" for c in schema.columns)
    values = ", ".join(f"IF(m & {schema.bit(c)}L = 0L, {_quoted('of_' + c)}, NULL)" for c in schema.columns)
    masks = ", ".join(f"{m}L" for m in S.legal_masks(schema))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {_quoted(name)}({given}) RETURNS TABLE ({out}, {MASK} BIGINT) RETURN SELECT {values}, m FROM explode(array({masks})) AS t(m)")


def register_star_layer(spark: SparkSession, name: str = "star_layer") -> None:
    """``name(mask)``: the number of stars."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {_quoted(name)}(mask BIGINT) RETURNS INT RETURN bit_count(mask)")


def register_cube(cube: DataFrame, name: str) -> None:
    """The cube as a view."""
    cube.createOrReplaceTempView(name)
