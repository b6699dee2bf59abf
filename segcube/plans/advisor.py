"""Choice of column order, groups and method."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.functions import segments as S
from segcube.functions.schema import CubeSchema, Dimension, Grouping
from segcube.plans import ledger
from segcube.sources import scratch


@dataclass(frozen=True)
class Advice:
    schema: CubeSchema
    grouping: Grouping
    cardinalities: dict[str, int]
    expected: dict[str, float | None]


def cardinalities(df: DataFrame, schema: CubeSchema, rsd: float = 0.02) -> DataFrame:
    """``column, values``: approximate numbers of distinct values, one pass."""
    row = df.agg(*(F.approx_count_distinct(c, rsd).alias(c) for c in schema.columns))
    return row.select(F.explode(F.array(*(F.struct(F.lit(c).alias("column"), F.col(c).alias("values")) for c in schema.columns))).alias("x")).select("x.*")


def _cuts(n: int, g: int):
    if g == 1:
        yield (n,)
        return
    for first in range(1, n - g + 2):
        for rest in _cuts(n - first, g - 1):
            yield (first, *rest)


def advise_grouping(df: DataFrame, schema: CubeSchema, g: int = 3, sample: float = 0.01, max_share: float = 0.05, seed: int = 11) -> Advice:
    """Dimensions with few values go right (they are processed first); every cut into ``g`` groups is
    tried on a cube of a stored sample, and the one with the best locality whose largest key stays under ``max_share`` is taken."""
    known = {r["column"]: r["values"] for r in cardinalities(df, schema).collect()}
    dims = sorted(schema.dims, key=lambda d: (-max(known[c] for c in d.columns), d.name))
    ordered = CubeSchema(tuple(Dimension(d.name, d.columns) for d in dims), schema.measures)
    sampled = scratch.materialised(df.sample(fraction=sample, seed=seed) if sample < 1 else df, "sample")
    g = min(g, len(dims))
    cuts = sorted(_cuts(len(dims), g), key=lambda c: c[0], reverse=True)
    best = None
    for cut in cuts:
        groups, at = [], 0
        for n in cut:
            groups.append([c for d in dims[at : at + n] for c in d.columns])
            at += n
        grouping = Grouping.of(ordered, groups)
        if g == 1:
            return Advice(ordered, grouping, known, {})
        expected = ledger.totals(ledger.phase_stats(sampled, grouping))
        share = max(expected["largest_local_share"], expected["largest_node_share"])
        score = (share <= max_share, expected["locality"] or 0.0, -share)
        if best is None or score > best[0]:
            best = (score, Advice(ordered, grouping, known, expected))
    return best[1]


def choose_method(rows: int, distinct_leaves: int, schema: CubeSchema) -> str:
    """Few cuboids and little overlap between rows: Spark's grouping sets; otherwise the grouped method."""
    cuboids = len(S.legal_masks(schema))
    return "grouping_sets" if cuboids <= 16 or (cuboids <= 64 and rows < 4 * distinct_leaves and rows < 10_000_000) else "grouped"
