"""The layer-by-layer chain: segments with k + 1 stars from those with k, one shuffle per layer."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import CubeSchema
from segcube.operators.grouped_phases import layer_step
from segcube.sources import scratch


def layered_states(df: DataFrame, schema: CubeSchema, carry: bool = True, checkpoint: str = "none") -> DataFrame:
    """``carry``: finished layers pass through each aggregate, in one plan.  Otherwise every layer is a data frame of its own,
    and with ``checkpoint='each'`` a separate round that is written and read back."""
    keep = lambda layer, k: scratch.materialised(layer, f"layer-{k}") if checkpoint == "each" else layer
    now = keep(S.merge(S.lift(df, schema), schema), 0)
    layers = [now]
    for k in range(1, len(schema.columns) + 1):
        now = layer_step(now, schema, schema.columns, k)
        if not carry:
            now = now.filter(S.layer() == k)
        now = keep(now, k)
        layers.append(now)
    if carry:
        return now
    out = layers[0]
    for layer in layers[1:]:
        out = out.unionByName(layer)
    return out


def layered_cube(df: DataFrame, schema: CubeSchema, keep=None, **options) -> DataFrame:
    return S.finalise(layered_states(df, schema, **options), schema, keep)


def layer_sizes(cube: DataFrame) -> DataFrame:
    """Segments by number of stars."""
    return cube.groupBy(S.layer().cast("int").alias("layer")).agg(F.count(F.lit(1)).alias("segments"))
