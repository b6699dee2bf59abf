"""Questions to a finished cube (columns, ``star_mask``, measures)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema
from segcube.sources import scratch


def mask_of(schema: CubeSchema, concrete) -> int:
    mask = schema.bits(c for c in schema.columns if c not in set(concrete))
    if not S.legal(mask, schema):
        raise ValueError(f"{tuple(concrete)} leaves out a higher level")
    return mask


def segment(cube: DataFrame, schema: CubeSchema, **values) -> DataFrame:
    """The one row of a segment; columns not named are stars, a value of None is the null value."""
    out = cube.filter(F.col(MASK) == mask_of(schema, values))
    for c, v in values.items():
        out = out.filter(F.col(c).eqNullSafe(F.lit(v)))
    return out


def slice_(cube: DataFrame, schema: CubeSchema, fixed: dict, free) -> DataFrame:
    """All segments with the ``fixed`` values and any value in the ``free`` columns."""
    out = cube.filter(F.col(MASK) == mask_of(schema, [*fixed, *free]))
    for c, v in fixed.items():
        out = out.filter(F.col(c).eqNullSafe(F.lit(v)))
    return out


def dice(cube: DataFrame, schema: CubeSchema, chosen: dict, free=()) -> DataFrame:
    """Like :func:`slice_` with a list of values per column."""
    out = cube.filter(F.col(MASK) == mask_of(schema, [*chosen, *free]))
    for c, values in chosen.items():
        out = out.filter(F.col(c).isin(list(values)))
    return out


def answer(cube: DataFrame, schema: CubeSchema, group_columns) -> DataFrame | None:
    """A ``GROUP BY`` from the cube; None where the columns skip a higher level and the base must be asked."""
    mask = schema.bits(c for c in schema.columns if c not in set(group_columns))
    if not S.legal(mask, schema) or not set(group_columns) <= set(schema.columns):
        return None
    return cube.filter(F.col(MASK) == mask).select(*group_columns, *(m.name for m in schema.measures))


def _next_level(schema: CubeSchema, dim: str, mask: int) -> str | None:
    return next((c for c in next(d for d in schema.dims if d.name == dim).columns if mask & schema.bit(c)), None)


def drill_down(cube: DataFrame, schema: CubeSchema, dim: str, **values) -> DataFrame:
    """The children of a segment along one dimension."""
    level = _next_level(schema, dim, mask_of(schema, values))
    if level is None:
        raise ValueError(f"{dim} has no lower level here")
    return slice_(cube, schema, values, [level])


def roll_up(cube: DataFrame, schema: CubeSchema, dim: str, **values) -> DataFrame:
    """The parent of a segment along one dimension."""
    held = [c for c in next(d for d in schema.dims if d.name == dim).columns if c in values]
    if not held:
        raise ValueError(f"{dim} is a star already")
    return segment(cube, schema, **{c: v for c, v in values.items() if c != held[-1]})


def primary_children(cube: DataFrame, schema: CubeSchema, **values) -> DataFrame:
    slot = S.child_slot(mask_of(schema, values), schema)
    return cube.limit(0) if slot is None else slice_(cube, schema, values, [slot])


def check_children_sum(states: DataFrame, schema: CubeSchema) -> DataFrame:
    """Segments whose states differ from the sum over their primary children; none in a right cube."""
    carried = list(schema.state_names)
    sent = []
    for column, on, off in S.parent_steps(schema, schema.columns):
        ready = (F.col(MASK).bitwiseAND(F.lit(on)) == on) & (F.col(MASK).bitwiseAND(F.lit(off)) == 0)
        sent.append(F.when(ready, S.starred(schema, column, carried)))
    again = S.merge(states.select(F.inline(F.filter(F.array(*sent), lambda x: x.isNotNull()))), schema)
    return again.exceptAll(states.filter(F.col(MASK) != 0)).unionByName(states.filter(F.col(MASK) != 0).exceptAll(again))


def with_parent_share(cube: DataFrame, schema: CubeSchema, dim: str, measure: str) -> DataFrame:
    """Segments with a value in ``dim``, with their share of the parent that stars its lowest level there."""
    columns = next(d for d in schema.dims if d.name == dim).columns
    parts = []
    for k, c in enumerate(columns):
        below = schema.bits(columns[k + 1 :])
        own = cube.filter(~S.has_star(schema, c) & (F.col(MASK).bitwiseAND(F.lit(below)) == below))
        parent = cube.filter(S.has_star(schema, c) & (S.concrete_in(schema, columns[:k]) if k else F.lit(True)))
        parent = parent.select(*(F.col(x).alias(f"p_{x}") for x in schema.columns), F.col(MASK).alias("p_mask"), F.col(measure).alias("parent_value"))
        same = F.col("p_mask") == F.col(MASK).bitwiseOR(F.lit(schema.bit(c)))
        for x in schema.columns:
            if x != c:
                same &= F.col(x).eqNullSafe(F.col(f"p_{x}"))
        parts.append(own.join(parent, same).select(*cube.columns, "parent_value", F.try_divide(F.col(measure).cast("double"), F.col("parent_value").cast("double")).alias("share")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def top_segments(cube: DataFrame, schema: CubeSchema, k: int, by: Column) -> DataFrame:
    """The ``k`` first segments in a total order (ties by mask and key)."""
    return cube.orderBy(by, MASK, *(F.col(c).asc_nulls_first() for c in schema.columns)).limit(k)


def rank_in_cuboid(cube: DataFrame, schema: CubeSchema, measure: str) -> DataFrame:
    """Row number, rank, dense rank, quarter and percent rank by ``measure`` inside each cuboid.

    A large cuboid is not sorted in one task: rows are range-partitioned by mask and order, ranked inside their task, and
    shifted by the numbers of rows and of distinct values of the tasks before (a row for each task and mask).
    """
    order = [F.col(MASK), F.desc(measure), *(F.col(c).asc_nulls_first() for c in schema.columns)]
    dealt = scratch.materialised(cube.repartitionByRange(F.col(MASK), F.desc(measure)).sortWithinPartitions(*order).withColumn("_task", F.spark_partition_id()), "ranked")
    local = Window.partitionBy("_task", MASK)
    # equal values are in one task, as tasks are cut by mask and value only
    by_row, by_value = local.orderBy(*order[1:]), local.orderBy(F.desc(measure))
    here = dealt.withColumns({"_row": F.row_number().over(by_row), "_rank": F.rank().over(by_value), "_dense": F.dense_rank().over(by_value)})
    sizes = dealt.groupBy("_task", MASK).agg(F.count(F.lit(1)).alias("_n"), F.countDistinct(F.struct(measure)).alias("_v"))
    earlier = Window.partitionBy(MASK).orderBy("_task").rowsBetween(Window.unboundedPreceding, -1)
    shifts = sizes.select("_task", MASK, F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_n0"), F.coalesce(F.sum("_v").over(earlier), F.lit(0)).alias("_v0"), F.sum("_n").over(Window.partitionBy(MASK)).alias("_all"))
    out = here.join(shifts, ["_task", MASK])
    row, rank, size = F.col("_row") + F.col("_n0"), F.col("_rank") + F.col("_n0"), F.col("_all")
    small = F.floor(size / 4)  # quarters: the first ``size % 4`` hold one row more
    longer = size % 4
    in_longer = row <= longer * (small + 1)
    quarter = F.when(in_longer, F.floor((row - 1) / (small + 1)) + 1).otherwise(longer + F.floor((row - 1 - longer * (small + 1)) / F.greatest(small, F.lit(1))) + 1)
    percent = F.when(size > 1, (rank - 1).cast("double") / (size - 1).cast("double")).otherwise(0.0)
    return out.select(*cube.columns, row.cast("int").alias("row_number"), rank.cast("int").alias("rank"), (F.col("_dense") + F.col("_v0")).cast("int").alias("dense_rank"), quarter.cast("int").alias("quarter"), percent.alias("percent"))


def inner_members(cube: DataFrame, schema: CubeSchema, column: str) -> DataFrame:
    """Segments of the cube without its innermost ``column``, a row for each of their members there; the mask is that of the outer cube."""
    if schema.columns[-1] != column:
        raise ValueError(f"{column} is not the innermost column")
    outer = [c for c in cube.columns if c != MASK]
    return cube.filter(~S.has_star(schema, column)).select(*outer, F.shiftright(MASK, 1).alias(MASK))


def distinct_members(cube: DataFrame, schema: CubeSchema, column: str, name: str) -> DataFrame:
    """Exact distinct counts at any cardinality: the column was cubed as the innermost one, its values are counted (nulls are none)."""
    return inner_members(cube, schema, column).groupBy(*schema.columns[:-1], MASK).agg(F.count(column).alias(name))


def top_members(cube: DataFrame, schema: CubeSchema, column: str, measure: str, k: int) -> DataFrame:
    """The ``k`` members of each segment with the largest ``measure``, ties to the smaller member, with their ``place``."""
    order = Window.partitionBy(*schema.columns[:-1], MASK).orderBy(F.desc(measure), F.col(column).asc_nulls_first())
    members = inner_members(cube, schema, column).withColumn("place", F.row_number().over(order))
    return members.filter(F.col("place") <= k).select(*schema.columns, MASK, "place", measure)


def containing_segments(cube: DataFrame, schema: CubeSchema, rows: DataFrame) -> DataFrame:
    """Pairs of a segment and a row in it: for small cubes and checks.

    One equality join per cuboid, so no side has to be broadcast and no pair is tried in vain.
    """
    out = None
    for mask in S.legal_masks(schema):
        held = [c for c in schema.columns if not mask & schema.bit(c)]
        same = F.lit(True)
        for c in held:
            same &= F.col(f"s.{c}").eqNullSafe(F.col(f"r.{c}"))
        one = cube.filter(F.col(MASK) == mask).alias("s")
        # the segment of all stars is a single row
        pairs = one.join(rows.alias("r"), same) if held else F.broadcast(one.limit(1).alias("s")).join(rows.alias("r"), F.lit(True))
        pairs = pairs.select(F.struct("s.*").alias("s"), F.struct("r.*").alias("r"))
        out = pairs if out is None else out.unionByName(pairs)
    return out


def merge_cubes(one: DataFrame, two: DataFrame, schema: CubeSchema) -> DataFrame:
    """The cube of two disjoint inputs, from their unfinished cubes."""
    return S.merge(one.unionByName(two), schema)


def subtract_cubes(whole: DataFrame, part: DataFrame, schema: CubeSchema, rows: str) -> DataFrame:
    """Take a part's rows out again (sums only); ``rows`` is the state that counts rows, segments left without any go."""
    if not all(s.merge == "sum" for s in schema.states):
        raise ValueError("only sums can be subtracted")
    minus = part.select(*schema.columns, MASK, *((-F.col(s)).alias(s) for s in schema.state_names))
    return S.merge(whole.unionByName(minus), schema).filter(F.col(rows) > 0)


def compare(before: DataFrame, after: DataFrame, schema: CubeSchema, measure: str) -> DataFrame:
    """Both cubes' value of a measure side by side (null-safe full join), missing segments as 0."""
    b = before.select(*(F.col(c).alias(f"b_{c}") for c in schema.columns), F.col(MASK).alias("b_mask"), F.col(measure).alias("b_value"))
    a = after.select(*(F.col(c).alias(f"a_{c}") for c in schema.columns), F.col(MASK).alias("a_mask"), F.col(measure).alias("a_value"))
    same = F.col("b_mask") == F.col("a_mask")
    for c in schema.columns:
        same &= F.col(f"b_{c}").eqNullSafe(F.col(f"a_{c}"))
    key = [F.coalesce(f"b_{c}", f"a_{c}").alias(c) for c in schema.columns]
    zero = F.lit(0).cast("bigint")
    return b.join(a, same, "full").select(*key, F.coalesce("b_mask", "a_mask").alias(MASK), F.coalesce("b_value", zero).alias("before"), F.coalesce("a_value", zero).alias("after"))
