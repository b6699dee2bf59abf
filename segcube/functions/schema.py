"""What a cube is over: hierarchical dimensions, additive measures, and a grouping of the columns."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from segcube.functions.measures import Measure

MASK = "star_mask"
_DISCRETE = (T.StringType, T.BooleanType, T.IntegralType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DecimalType)


@dataclass(frozen=True)
class Dimension:
    """Columns of one hierarchy, the highest level first; a level has a value only where all higher ones have."""

    name: str
    columns: tuple[str, ...]


@dataclass(frozen=True)
class CubeSchema:
    dims: tuple[Dimension, ...]
    measures: tuple[Measure, ...]

    def __post_init__(self):
        columns = self.columns
        if not columns or any(not d.columns for d in self.dims):
            raise ValueError("a cube needs at least one column, and every dimension one")
        if len(set(columns)) != len(columns) or MASK in columns:
            raise ValueError("columns of a cube must differ")
        if len(columns) > 63:
            raise ValueError("at most 63 columns fit into a star mask")

    @property
    def columns(self) -> tuple[str, ...]:
        return tuple(c for d in self.dims for c in d.columns)

    @property
    def states(self) -> tuple:
        """All states of all measures, each once."""
        return tuple(dict((s.name, s) for m in self.measures for s in m.states).values())

    @property
    def state_names(self) -> tuple[str, ...]:
        return tuple(s.name for s in self.states)

    def bit(self, column: str) -> int:
        """The leftmost column has the most significant bit, as in ``grouping_id``."""
        return 1 << (len(self.columns) - 1 - self.columns.index(column))

    def bits(self, columns) -> int:
        return sum(self.bit(c) for c in columns)

    def dims_of(self, columns) -> list[tuple[str, ...]]:
        """The parts of the dimensions that lie in a set of columns, left to right."""
        chosen = set(columns)
        parts = [tuple(c for c in d.columns if c in chosen) for d in self.dims]
        return [p for p in parts if p]

    def validate(self, df: DataFrame) -> None:
        types = {f.name: f.dataType for f in df.schema.fields}
        for c in self.columns:
            if c not in types:
                raise ValueError(f"no column {c}")
            if not isinstance(types[c], _DISCRETE):
                raise ValueError(f"{c} is {types[c].simpleString()}; a cube's columns must be discrete")

    @staticmethod
    def parse(shape: str, measures) -> tuple[CubeSchema, Grouping]:
        """From text such as ``region>nation>customer | type, nation2``: ``>`` joins levels, ``|`` parts groups (the leftmost is processed last)."""
        groups = [[tuple(x.strip() for x in dim.split(">")) for dim in part.split(",")] for part in shape.split("|")]
        dims = tuple(Dimension(d[0], d) for g in groups for d in g)
        schema = CubeSchema(dims, tuple(measures))
        return schema, Grouping.of(schema, [[c for d in g for c in d] for g in groups])


@dataclass(frozen=True)
class Grouping:
    """Consecutive groups of columns, left to right; phase 1 works on the rightmost."""

    schema: CubeSchema
    groups: tuple[tuple[str, ...], ...]
    guard: bool = False

    @staticmethod
    def of(schema: CubeSchema, groups, straddle: str = "reject") -> Grouping:
        """``straddle``: a dimension that reaches over a border is refused, or with ``guard`` allowed (its higher levels then wait for the lower ones)."""
        groups = tuple(tuple(g) for g in groups)
        if any(not g for g in groups) or tuple(c for g in groups for c in g) != schema.columns:
            raise ValueError("groups must be non-empty and, in order, give all columns")
        cut = [d.name for d in schema.dims if len({i for i, g in enumerate(groups) for c in d.columns if c in g}) > 1]
        if cut and straddle != "guard":
            raise ValueError(f"dimensions {cut} lie in more than one group")
        return Grouping(schema, groups, bool(cut))

    @staticmethod
    def by_sizes(schema: CubeSchema, sizes, straddle: str = "reject") -> Grouping:
        groups, at = [], 0
        for n in sizes:
            groups.append(schema.columns[at : at + n])
            at += n
        return Grouping.of(schema, groups, straddle)

    @staticmethod
    def by_entity(schema: CubeSchema, entity_of: dict[str, str], order) -> Grouping:
        """A group for each entity (users, websites, advertisers), in ``order`` from left to right, over the schema with its dimensions put together so."""
        missing = [d.name for d in schema.dims if entity_of.get(d.name) not in order]
        if missing:
            raise ValueError(f"dimensions {missing} belong to no entity in the order")
        dims = [[d for d in schema.dims if entity_of[d.name] == e] for e in order]
        arranged = CubeSchema(tuple(d for part in dims for d in part), schema.measures)
        return Grouping.of(arranged, [[c for d in part for c in d.columns] for part in dims if part])

    def group(self, phase: int) -> tuple[str, ...]:
        return self.groups[len(self.groups) - phase]

    def others(self, phase: int) -> tuple[str, ...]:
        mine = set(self.group(phase))
        return tuple(c for c in self.schema.columns if c not in mine)

    @property
    def phases(self) -> range:
        return range(1, len(self.groups) + 1)
