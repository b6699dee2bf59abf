"""The grouped method: one shuffle per group of columns, then all stars of the group inside the partition.

Phase ``i`` clusters its input by the columns of all other groups; all segments that differ only in group ``i`` are then in
one task, and every local step (kernel ``layers``: star by star from primary children; ``direct``: all stars at once) is an aggregation without an exchange: hash partitioning by a subset of the grouping columns
satisfies it, and ``inline`` keeps that partitioning (``Expand`` would not).  The mask is a grouping column but never a
clustering column.  Rows of finished layers are carried through the later aggregates, so the plan stays linear.

A single group leaves no column to shard by; its layers are then exchanged one by one, as in the layer chain, at any size.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql import types as T

from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema, Grouping
from segcube.sources import scratch

#: Cuboids of a group up to which its rows are sent to all of them at once.
MAX_DIRECT = 64
#: Segments that a task of :func:`sliced_cube` makes on average, if none of them were equal.
TASK_SEGMENTS = 150_000
#: Rows that a task's combiner holds at most before it adds them up.
COMBINE_ROWS = 500_000


def cluster_by_other_groups(df: DataFrame, grouping: Grouping, phase: int, partitions: int | None = None) -> DataFrame:
    """The phase's only shuffle: one message per row, routed by the other groups' values.

    Adaptive execution sizes partitions by what goes into a phase; where much more comes out, ``partitions`` fixes a larger number.
    """
    others = grouping.others(phase)
    if not others:
        return df
    return df.repartition(partitions, *others) if partitions else df.repartition(*others)


def layer_step(df: DataFrame, schema: CubeSchema, group, k: int, also: tuple[str, ...] = (), guard: bool = False) -> DataFrame:
    """Rows with ``k - 1`` stars in the group send themselves to their primary parents; all rows pass on; equal keys add up."""
    return S.merge(S.send(df, schema, group, _ready(schema, group, k, guard), also), schema, *also)


def _ready(schema: CubeSchema, group, k: int, guard: bool, done: frozenset[str] = frozenset()) -> list:
    """Which columns a row with ``k - 1`` stars in the group sends its starred copies for."""
    mask, bits, out = F.col(MASK), schema.bits(group), []
    for column, on, off in S.parent_steps(schema, group):
        if k == 1 and column in done:
            continue
        yes = (S.layer(MASK, bits) == k - 1) & (mask.bitwiseAND(F.lit(on)) == on) & (mask.bitwiseAND(F.lit(off)) == 0)
        out.append((column, yes & _levels_below_are_stars(schema, column) if guard else yes))
    return out


def _levels_below_are_stars(schema: CubeSchema, column: str):
    below = schema.bits(S.lower_levels(schema, column))
    return F.col(MASK).bitwiseAND(F.lit(below)) == below


def _layered(df, schema, group, guard):
    """Carry-through layers: as many local aggregates as the group has columns."""
    for k in range(1, len(group) + 1):
        df = layer_step(df, schema, group, k, guard=guard)
    return df


def _sweep(df, schema, group, guard, also=()):
    """One column after the other, right to left: each row passes on and, where legal, sends its starred copy."""
    for column in reversed(group):
        yes = _levels_below_are_stars(schema, column) & ~S.has_star(schema, column)
        df = S.merge(S.send(df, schema, (column,), [(column, yes)], also), schema, *also)
    return df


def _direct(df, schema, group, guard):
    """Every merged row sends itself to all its segments of the group at once, and one aggregate adds them up.

    More copy-adds inside the task than by primary children (one for each cuboid of the group and row), but each row is hashed once and not again in
    every layer it is carried through, which is what counts in Spark.
    """
    parts = schema.dims_of(group)
    ready = []
    for kept in product(*(range(len(p), -1, -1) for p in parts)):
        starred = [(p, p[k:]) for p, k in zip(parts, kept, strict=True) if k < len(p)]
        if not starred:
            continue
        yes = None
        if guard:  # levels in another group have to be stars already
            below = schema.bits(c for p, _ in starred for c in S.lower_levels(schema, p[-1]))
            yes = F.col(MASK).bitwiseAND(F.lit(below)) == below
        ready.append((schema.bits(c for _, cs in starred for c in cs), yes))
    return S.merge(S.send_masks(df, schema, group, ready), schema)


def _union(df, schema, group, guard):
    """One aggregate per layer, the layers put together by union (each layer is computed again for those above it)."""
    layers = [df]
    for k in range(1, len(group) + 1):
        last, bits = layers[-1], schema.bits(group)
        layers.append(layer_step(last, schema, group, k, guard=guard).filter(S.layer(MASK, bits) == k))
    out = layers[0]
    for part in layers[1:]:
        out = out.unionByName(part)
    return out


def _arrow(df, schema, group, guard, others):
    """The same layers in Arrow tables, one local problem at a time; for comparison only."""
    if any(s.merge not in ("sum", "min", "max") for s in schema.states):
        raise ValueError("the Arrow kernel knows sum, min and max")
    kinds, steps, names = [(s.name, s.merge) for s in schema.states], S.parent_steps(schema, group), [*schema.columns, MASK]
    out_schema = df.schema

    def run(table: pa.Table) -> pa.Table:
        arrow_schema = table.schema
        add = lambda t: t.group_by(names).aggregate(kinds).rename_columns([*names, *(n for n, _ in kinds)]).select(arrow_schema.names).cast(arrow_schema)
        layers = [add(table)]
        for _ in range(len(group)):
            sent = []
            mask = layers[-1].column(MASK).to_numpy()
            for column, on, off in steps:
                part = layers[-1].filter(pa.array((mask & on == on) & (mask & off == 0)))
                if part.num_rows:
                    part = part.set_column(part.schema.get_field_index(column), arrow_schema.field(column), pa.nulls(part.num_rows, arrow_schema.field(column).type))
                    starred = pa.array(part.column(MASK).to_numpy() | schema.bit(column))
                    sent.append(part.set_column(part.schema.get_field_index(MASK), arrow_schema.field(MASK), starred))
            if not sent:
                break
            layers.append(add(pa.concat_tables(sent)))
        return pa.concat_tables(layers)

    if guard or not others:
        raise ValueError("the Arrow kernel has no guard for dimensions over a border, and needs a column to shard by")
    return df.groupBy(*others).applyInArrow(run, out_schema)


KERNELS = {"layers": _layered, "sweep": _sweep, "direct": _direct, "union": _union}


def kernel_for(schema: CubeSchema, group) -> str:
    """``direct`` while the group has few cuboids, which its columns alone decide; else ``layers``, whose plan grows with the columns only."""
    cuboids = 1
    for part in schema.dims_of(group):
        cuboids *= len(part) + 1
    return "direct" if cuboids <= MAX_DIRECT else "layers"


def materialise_locally(df: DataFrame, grouping: Grouping, phase: int, kernel: str = "auto") -> DataFrame:
    """Merge equal vectors of the group, then all its stars, without an exchange (but for a single group)."""
    schema, group = grouping.schema, grouping.group(phase)
    if kernel == "auto":
        kernel = kernel_for(schema, group) if grouping.others(phase) else "layers"
    if kernel == "arrow":
        return _arrow(df, schema, group, grouping.guard, grouping.others(phase))
    return KERNELS[kernel](S.merge(df, schema), schema, group, grouping.guard)


def combined_in_tasks(df: DataFrame, schema: CubeSchema) -> DataFrame:
    """Equal segments of a task added up before any shuffle, ``COMBINE_ROWS`` at a time: a combiner of sums, minima and maxima.

    Spark's own partial aggregates always bring their exchange (by all columns) along, so this one is in Arrow.  Other
    states are left as they are, to be merged behind the shuffle.
    """
    plain = (T.NumericType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)
    if any(s.merge not in ("sum", "min", "max") or not isinstance(df.schema[s.name].dataType, plain) for s in schema.states):
        return df
    keys, kinds = [*schema.columns, MASK], [(s.name, s.merge) for s in schema.states]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = 0

        def added() -> pa.Table:
            table = pa.Table.from_batches(held)
            sums = table.group_by(keys).aggregate(kinds).rename_columns([*keys, *(n for n, _ in kinds)])
            return sums.select(table.schema.names).cast(table.schema)

        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= COMBINE_ROWS:
                table = added()
                held, rows = table.to_batches(), table.num_rows
                if rows > COMBINE_ROWS // 2:  # little in common: pass on
                    yield from held
                    held, rows = [], 0
        if held:
            yield from added().to_batches()

    return df.mapInArrow(run, df.schema)


def precombine(df: DataFrame, grouping: Grouping, phase: int, heavy: str) -> DataFrame:
    """For a very large dimension: rows send their first-layer parents before the shuffle, where each task combines them.

    ``last_parent``: the one parent that stars the group's last dimension; ``all_parents``: one per dimension of the group.
    """
    schema, group = grouping.schema, grouping.group(phase)
    parts = schema.dims_of(group)
    first = {p[-1] for p in (parts[-1:] if heavy == "last_parent" else parts)}
    ready = [(c, _levels_below_are_stars(schema, c) if grouping.guard else F.lit(True)) for c in group if c in first]
    return combined_in_tasks(S.send(df, schema, group, ready), schema)


def _after_precombining(df: DataFrame, grouping: Grouping, phase: int, heavy: str) -> DataFrame:
    """The remaining messages of a phase whose first-layer parents exist already."""
    schema, group = grouping.schema, grouping.group(phase)
    parts = schema.dims_of(group)
    done = frozenset(p[-1] for p in (parts[-1:] if heavy == "last_parent" else parts))
    df = S.merge(df, schema)
    for k in range(1, len(group) + 1):
        ready = _ready(schema, group, k, grouping.guard, done)
        if ready:
            df = S.merge(S.send(df, schema, group, ready), schema)
    return df


def run_phase(df: DataFrame, grouping: Grouping, phase: int, kernel: str = "auto", heavy: str | None = None, routed: Observation | None = None, partitions: int | None = None) -> DataFrame:
    """``routed`` observes ``n``, the rows that go into the phase's shuffle."""
    if heavy:
        df = precombine(df, grouping, phase, heavy)
    if routed is not None:
        df = df.observe(routed, F.count(F.lit(1)).alias("n"))
    df = cluster_by_other_groups(df, grouping, phase, partitions)
    return _after_precombining(df, grouping, phase, heavy) if heavy else materialise_locally(df, grouping, phase, kernel)


def phase_outputs(
    df: DataFrame, grouping: Grouping, kernel: str = "auto", heavy: str | None = None, premerge: bool = False, store: bool = False, read: Observation | None = None,
    routed: dict[int, Observation] | None = None, partitions: int | None = None,
) -> Iterator[DataFrame]:
    """The output of each phase in turn; with ``store`` each is written and read back, a point to restart from.

    ``read`` observes ``n``, the input rows, and ``routed`` the rows into each phase's shuffle.
    """
    schema = grouping.schema
    now = S.lift(df, schema)
    if read is not None:
        now = now.observe(read, F.count(F.lit(1)).alias("n"))
    if premerge:  # combines equal keys before the first shuffle by other groups
        now = S.merge(now, schema)
    for phase in grouping.phases:
        now = run_phase(now, grouping, phase, kernel, heavy, (routed or {}).get(phase), partitions)
        if store:
            now = scratch.materialised(now, f"phase-{phase}")
        yield now


def grouped_states(df: DataFrame, grouping: Grouping, **options) -> DataFrame:
    """The whole cube with unfinished measures; no row at all for no input."""
    *_, last = phase_outputs(df, grouping, **options)
    return last


def grouped_cube(df: DataFrame, grouping: Grouping, keep=None, **options) -> DataFrame:
    """All segments of ``df``; ``keep`` filters finished rows in the stage of the last layer and prunes nothing before."""
    return S.finalise(grouped_states(df, grouping, **options), grouping.schema, keep)


def _first_phase_slice(df: DataFrame, grouping: Grouping, bits: int, partitions: int | None) -> DataFrame:
    """Of the first phase's output the segments whose stars in its group are ``bits``.

    Stars depend on the leaves' mask, which no plan knows to be 0: constants would be taken out of the later phases' keys, and with them the partitioning.
    """
    schema = grouping.schema
    df = cluster_by_other_groups(df, grouping, 1, partitions)
    columns = [F.when(S.has_star(schema, c), F.col(c)).alias(c) if bits & schema.bit(c) else F.col(c) for c in schema.columns]
    return S.merge(df.select(*columns, F.col(MASK).bitwiseOR(F.lit(bits)).alias(MASK), *schema.state_names), schema)


def sliced_cube(df: DataFrame, grouping: Grouping, keep=None, kernel: str = "auto") -> DataFrame:
    """As :func:`grouped_cube`, one slice after the other: all phases for one choice of stars in the first phase's group at a time.

    Later phases never bring together segments that differ in those stars, so every slice is whole and together they are the cube.  The
    disk holds the input, one slice's shuffles and the segments that pass ``keep``, which still filters finished rows only: for very large
    cubes of which few are kept.  Slices are written when this is called.
    """
    schema, spark = grouping.schema, df.sparkSession
    with scratch.shuffles_freed(spark):
        leaves = scratch.materialised(S.lift(df, schema), "leaves")
    made, partitions = leaves.count(), {}
    for phase in grouping.phases:  # by what a phase makes of one slice: few tasks write large blocks for the many of the next phase
        made *= len(S.group_masks(schema, grouping.group(phase))) if phase > 1 else 1
        partitions[phase] = max(8, -(-made // TASK_SEGMENTS))
    path = scratch.new_folder(spark, "slices")
    for bits in S.group_masks(schema, grouping.group(1)):
        now = _first_phase_slice(leaves, grouping, bits, partitions[1])
        for phase in grouping.phases[1:]:
            now = run_phase(now, grouping, phase, kernel, partitions=partitions[phase])
        out = S.finalise(now, schema, keep)
        with scratch.shuffles_freed(spark):
            out.write.mode("append").parquet(path)
    return spark.read.schema(out.schema).parquet(path)


def phase_deltas(df: DataFrame, grouping: Grouping, **options) -> Iterator[tuple[int, DataFrame]]:
    """What each phase adds to its input (phase 0: the leaves); disjoint, and together the cube."""
    schema = grouping.schema
    for phase, out in zip(grouping.phases, phase_outputs(df, grouping, store=True, **options), strict=True):
        if phase == 1:
            yield 0, out.filter(F.col(MASK) == 0)
        yield phase, out.filter(S.aggregated_in(schema, grouping.group(phase)))
