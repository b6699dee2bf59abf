"""The batched-areas baseline: cuboids are gathered into areas, each row sends one message per area, areas are computed locally.

How areas are built is a reconstruction.  An area is a set of cuboids with shard columns that all its cuboids
keep concrete (otherwise a segment would be split over tasks); areas are picked greedily, each time the one
that covers most cuboids still open, among shards whose largest key, estimated from a sample, stays under a bound.  A cuboid
whose own largest key is beyond the bound is value-partitioned along its big dimension: the dimension, with all its levels, whose values split that key
best, and another one as long as the bound is not met.  Its parts are computed in the area of the finer cuboid and combined in a later round, so it costs no further
message per row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.functions import measures as M
from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema
from segcube.operators.broadcast import sent
from segcube.sources import scratch


@dataclass(frozen=True)
class Area:
    shard: tuple[str, ...]
    masks: tuple[int, ...]  # cuboids that are whole in each task
    partitioned: tuple[int, ...] = ()  # value-partitioned cuboids, combined later


def sample_load(df: DataFrame, schema: CubeSchema, fraction: float, seed: int = 7) -> DataFrame:
    """``star_mask, max_load``: the estimated rows of the largest key of each cuboid."""
    sampled = df.sample(fraction=fraction, seed=seed) if fraction < 1 else df
    counts = CubeSchema(schema.dims, (M.count("load"),))
    counted = S.merge(sent(S.merge(S.lift(sampled, counts), counts), counts), counts)
    return counted.groupBy(MASK).agg(F.ceil(F.max("load") / fraction).cast("bigint").alias("max_load"))


def estimate_load(df: DataFrame, schema: CubeSchema, fraction: float = 0.1, seed: int = 7) -> dict[int, int]:
    return {r[MASK]: r.max_load for r in sample_load(df, schema, fraction, seed).collect()}  # one row per cuboid


def _finer(mask: int, schema: CubeSchema, load: dict[int, int], max_load: int) -> int:
    """The cuboid whose area computes the parts of a cuboid: big dimensions get their values until the largest key fits (or none is left)."""
    while mask and load.get(mask, 0) > max_load:
        mask = min((mask & ~schema.bits(d.columns) for d in schema.dims if mask & schema.bits(d.columns)), key=lambda m: (load.get(m, 0), m))
    return mask


def plan_batch_areas(schema: CubeSchema, load: dict[int, int], max_load: int) -> list[Area]:
    masks, columns = S.legal_masks(schema), schema.columns
    fits = [m for m in masks if load.get(m, 0) <= max_load or not m]  # leaves cannot be split further
    open_, areas = set(fits), []
    while open_:
        best = max(fits, key=lambda m: (sum(1 for n in open_ if not n & ~m), m))
        mine = {n for n in open_ if not n & ~best}
        areas.append((best, mine))
        open_ -= mine
    area_of = {m: i for i, (_, mine) in enumerate(areas) for m in mine}
    parts: dict[int, list[int]] = {}
    for m in masks:
        if m not in area_of:
            parts.setdefault(area_of[_finer(m, schema, load, max_load)], []).append(m)
    return [Area(tuple(c for c in columns if not best & schema.bit(c)), tuple(sorted(mine)), tuple(parts.get(i, ()))) for i, (best, mine) in enumerate(areas)]


def area_messages(df: DataFrame, schema: CubeSchema, areas: list[Area]) -> DataFrame:
    """One row per leaf segment (equal input rows are added up before) and area, with the key that it is routed by."""
    columns = list(schema.columns)
    copies = [F.struct(F.lit(i).alias("area"), F.xxhash64(F.lit(i), *a.shard).alias("shard")) for i, a in enumerate(areas)]
    return S.merge(S.lift(df, schema), schema).select(*columns, MASK, *schema.state_names, F.inline(F.array(*copies)))


def batch_area_states(df: DataFrame, schema: CubeSchema, areas: list[Area]) -> DataFrame:
    """All areas by one shuffle; inside its task a row goes to all cuboids of its area, and one aggregate adds up.  Value partitions are combined last."""
    now = area_messages(df, schema, areas).repartition("shard")
    masks = lambda area: F.array(*(F.lit(m).cast("bigint") for m in (*area.masks, *area.partitioned)))

    chosen = masks(areas[0])
    for i, area in enumerate(areas[1:], 1):
        chosen = F.when(F.col("area") == i, masks(area)).otherwise(chosen)
    # masks are generated first and stars put in behind, both in generated code
    now = now.drop(MASK).withColumn(MASK, F.explode(chosen))
    stars = [F.when(~S.has_star(schema, c), F.col(c)).alias(c) for c in schema.columns]
    now = S.merge(now.select("shard", "area", *schema.state_names, *stars, MASK), schema, "shard", "area")
    split = [m for a in areas for m in a.partitioned]
    if not split:
        return now.drop("shard", "area")
    now = scratch.materialised(now.drop("shard", "area"), "areas")
    return now.filter(~F.col(MASK).isin(split)).unionByName(S.merge(now.filter(F.col(MASK).isin(split)), schema))


def batch_area_cube(df: DataFrame, schema: CubeSchema, max_load: int, fraction: float = 0.1, keep=None) -> DataFrame:
    areas = plan_batch_areas(schema, estimate_load(df, schema, fraction), max_load)
    return S.finalise(batch_area_states(df, schema, areas), schema, keep)
