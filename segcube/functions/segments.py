"""Star masks: which segments are legal, which aggregate into which, and how keys are written."""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from segcube.functions.schema import MASK, CubeSchema, Grouping


def legal_masks(schema: CubeSchema) -> list[int]:
    """All masks in which every dimension's stars are its lowest levels; their number is the product of (levels + 1)."""
    choices = [[schema.bits(d.columns[k:]) for k in range(len(d.columns), -1, -1)] for d in schema.dims]
    return sorted(sum(c) for c in product(*choices))


def group_masks(schema: CubeSchema, columns) -> list[int]:
    """The stars, as bits, that a group's columns can have; few first."""
    choices = [[schema.bits(p[k:]) for k in range(len(p), -1, -1)] for p in schema.dims_of(columns)]
    return sorted((sum(c) for c in product(*choices)), key=lambda bits: (stars(bits), bits))


def legal(mask: int, schema: CubeSchema) -> bool:
    return all(not (mask & schema.bit(a) and not mask & schema.bit(b)) for d in schema.dims for a, b in zip(d.columns, d.columns[1:], strict=False))


def is_legal(schema: CubeSchema, mask: str = MASK) -> Column:
    bad = [has_star(schema, a, mask) & ~has_star(schema, b, mask) for d in schema.dims for a, b in zip(d.columns, d.columns[1:], strict=False)]
    return ~reduce(lambda x, y: x | y, bad, F.lit(False))


def has_star(schema: CubeSchema, column: str, mask: str = MASK) -> Column:
    return F.col(mask).bitwiseAND(F.lit(schema.bit(column))) != 0


def stars(mask: int) -> int:
    return mask.bit_count()


def layer(mask: str = MASK, bits: int | None = None) -> Column:
    """Number of stars, of those in ``bits`` if given."""
    return F.bit_count(F.col(mask) if bits is None else F.col(mask).bitwiseAND(F.lit(bits)))


def child_slot(mask: int, schema: CubeSchema, columns=None) -> str | None:
    """Where a segment's primary children have a value: in the rightmost dimension with a star, its highest starred level."""
    for part in reversed(schema.dims_of(columns or schema.columns)):
        for c in part:
            if mask & schema.bit(c):
                return c
    return None


def primary_parents(mask: int, schema: CubeSchema, columns=None) -> list[int]:
    """Masks that a segment of this mask is a primary child of: at most one per dimension."""
    out = []
    for part in reversed(schema.dims_of(columns or schema.columns)):
        values = [c for c in part if not mask & schema.bit(c)]
        if values:
            out.append(mask | schema.bit(values[-1]))
        if len(values) < len(part):
            break
    return out


def parent_steps(schema: CubeSchema, columns) -> list[tuple[str, int, int]]:
    """For each column of a group: the bits that must be stars and those that must not be, for its star to give a primary parent."""
    parts, out = schema.dims_of(columns), []
    for i, part in enumerate(parts):
        right = schema.bits(c for p in parts[i + 1 :] for c in p)
        for k, c in enumerate(part):
            out.append((c, schema.bits(part[k + 1 :]), schema.bits(part[: k + 1]) | right))
    return out


def starred(schema: CubeSchema, column: str, carried: list[str]) -> Column:
    """The row with a star in ``column``, as a struct of all cube columns, the mask and what is carried along."""
    fields = [(F.lit(None) if c == column else F.col(c)).alias(c) for c in schema.columns]
    return F.struct(*fields, F.col(MASK).bitwiseOR(F.lit(schema.bit(column))).alias(MASK), *carried)


def send(df: DataFrame, schema: CubeSchema, columns, ready: list[tuple[str, Column]], also: tuple[str, ...] = ()) -> DataFrame:
    """Each row itself and, for every ``(column, condition)`` that holds, its copy with a star there.

    Only ``columns`` and the mask are generated; all else passes by, so a partitioning by the other columns is kept.
    """
    return send_masks(df, schema, columns, [(schema.bit(column), yes) for column, yes in ready], also)


def send_masks(df: DataFrame, schema: CubeSchema, columns, ready: list[tuple[int, Column | None]], also: tuple[str, ...] = ()) -> DataFrame:
    """The same for copies with several stars at once, given as bits; a condition of None always holds."""
    copies = []
    for bits, yes in ready:
        copy = F.struct(*((F.lit(None) if bits & schema.bit(c) else F.col(c)).alias(c) for c in columns), F.col(MASK).bitwiseOR(F.lit(bits)).alias(MASK))
        copies.append(copy if yes is None else F.when(yes, copy))
    passing = [*also, *(c for c in schema.columns if c not in set(columns)), *schema.state_names]
    sent = df.select(*passing, F.inline(F.array(F.struct(*columns, MASK), *copies)))
    # a filter behind the generator stays in generated code, one inside the array would not
    return sent if all(yes is None for _, yes in ready) else sent.filter(F.col(MASK).isNotNull())


def lower_levels(schema: CubeSchema, column: str) -> tuple[str, ...]:
    columns = next(d.columns for d in schema.dims if column in d.columns)
    return columns[columns.index(column) + 1 :]


def phase_of_mask(mask: int, grouping: Grouping) -> int:
    """The phase that makes a segment: that of its leftmost group with a star; 0 for leaves."""
    return max((p for p in grouping.phases if mask & grouping.schema.bits(grouping.group(p))), default=0)


def phase_of(grouping: Grouping, mask: str = MASK) -> Column:
    out = F.lit(0)
    for p in grouping.phases:
        out = F.when(F.col(mask).bitwiseAND(F.lit(grouping.schema.bits(grouping.group(p)))) != 0, p).otherwise(out)
    return out


def concrete_in(schema: CubeSchema, group, mask: str = MASK) -> Column:
    return F.col(mask).bitwiseAND(F.lit(schema.bits(group))) == 0


def aggregated_in(schema: CubeSchema, group, mask: str = MASK) -> Column:
    return ~concrete_in(schema, group, mask)


def phase_input(grouping: Grouping, phase: int) -> Column:
    """Segments that phase ``phase`` reads: no star in its own group or those still to come."""
    return concrete_in(grouping.schema, [c for p in grouping.phases if p >= phase for c in grouping.group(p)])


def phase_output(grouping: Grouping, phase: int) -> Column:
    return concrete_in(grouping.schema, [c for p in grouping.phases if p > phase for c in grouping.group(p)])


def by_mask(values: dict[int, int], mask: str = MASK) -> Column:
    """A number looked up by mask."""
    table = F.create_map(*(F.lit(x) for pair in sorted(values.items()) for x in pair))
    return table[F.col(mask)]


def number_of_parents(schema: CubeSchema, columns=None, mask: str = MASK) -> Column:
    """How many primary parents a row's segment has in a group, in arithmetic on its mask (no table of masks)."""
    steps = parent_steps(schema, columns or schema.columns)
    terms = [F.when((F.col(mask).bitwiseAND(F.lit(on)) == on) & (F.col(mask).bitwiseAND(F.lit(off)) == 0), 1).otherwise(0) for _, on, off in steps]
    return reduce(lambda a, b: a + b, terms).cast("bigint")


def render_key(schema: CubeSchema, mask: str = MASK) -> Column:
    """``(US, CA, *)``: values with backslash, comma, star and parentheses escaped, null as ``\\N``."""
    text = [F.when(has_star(schema, c, mask), "*").when(F.col(c).isNull(), "\\N").otherwise(F.regexp_replace(F.col(c).cast("string"), r"([\\,*()])", r"\\$1")) for c in schema.columns]
    return F.concat(F.lit("("), F.concat_ws(", ", *text), F.lit(")"))


def parse_key(text: str) -> list[str | None]:
    """The parts of a rendered key: ``"*"`` as ``...`` (Ellipsis), null as None, else the value's text."""
    parts, now, i, body = [], "", 0, text[1:-1]
    raw: list[str] = []
    while i <= len(body):
        if i == len(body) or body.startswith(", ", i):
            parts.append(... if raw == ["*"] else None if raw == ["\\N"] else now)
            now, raw, i = "", [], i + 2
        elif body[i] == "\\":
            now += body[i + 1]
            raw.append(body[i : i + 2])
            i += 2
        else:
            now += body[i]
            raw.append(body[i])
            i += 1
    return parts


def lift(df: DataFrame, schema: CubeSchema) -> DataFrame:
    """Input rows as leaf segments: cube columns, an empty mask, and each measure's states."""
    schema.validate(df)
    sketched = [s for s in schema.states if s.merge in ("hll", "kll")]
    states = [s.init().alias(s.name) for s in schema.states]
    leaf = df.select(*schema.columns, F.lit(0).cast("bigint").alias(MASK), *states)
    if sketched:  # sketches begin as aggregates of equal rows
        first = {"hll": F.hll_sketch_agg, "kll": F.kll_sketch_agg_bigint}
        leaf = leaf.groupBy(*schema.columns, MASK).agg(*(first[s.merge](s.name).alias(s.name) if s in sketched else s.merged() for s in schema.states))
    return leaf


def merge(df: DataFrame, schema: CubeSchema, *also: str) -> DataFrame:
    """Add the states of equal segments."""
    return df.groupBy(*also, *schema.columns, MASK).agg(*(s.merged() for s in schema.states))


def finalise(cube: DataFrame, schema: CubeSchema, keep=None) -> DataFrame:
    """Columns, mask and finished measures; ``keep`` filters on measures, after everything is aggregated."""
    out = cube.select(*schema.columns, MASK, *(m.finalize().alias(m.name) for m in schema.measures))
    return out if keep is None else out.filter(keep)
