"""Measures as finite tuples of mergeable states with a finaliser.

A method calls ``init`` once per input row, merges states at every copy-add and applies ``finalize`` at the end only, so
any measure works with any method.  Sums are exact where their input is integral or decimal.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

MERGES: dict[str, Callable[[str], Column]] = {
    "sum": F.sum,
    "min": F.min,
    "max": F.max,
    "set": lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_list(c)))),
    "hll": F.hll_union_agg,
    "kll": F.kll_merge_agg_bigint,
}


@dataclass(frozen=True)
class State:
    name: str
    init: Callable[[], Column]
    merge: str = "sum"

    def merged(self) -> Column:
        return MERGES[self.merge](self.name).alias(self.name)


@dataclass(frozen=True)
class Measure:
    name: str
    states: tuple[State, ...]
    finalize: Callable[[], Column]

    @property
    def subtractable(self) -> bool:
        return all(s.merge == "sum" for s in self.states)


def _one(name: str, init: Callable[[], Column], merge: str = "sum") -> Measure:
    return Measure(name, (State(name, init, merge),), lambda: F.col(name))


def count(name: str = "n") -> Measure:
    return _one(name, lambda: F.lit(1).cast("bigint"))


def total(column: str, name: str | None = None, kind: str = "bigint") -> Measure:
    return _one(name or f"sum_{column}", lambda: F.col(column).cast(kind))


def least(column: str, name: str | None = None) -> Measure:
    return _one(name or f"min_{column}", lambda: F.col(column), "min")


def greatest(column: str, name: str | None = None) -> Measure:
    return _one(name or f"max_{column}", lambda: F.col(column), "max")


def total_where(column: str, condition: Callable[[], Column], name: str) -> Measure:
    return _one(name, lambda: F.when(condition(), F.col(column)).otherwise(0).cast("bigint"))


def _moment(column: str, kind: str) -> State:
    value = lambda: F.col(column).cast("decimal(38,0)")
    if kind == "n":
        return State(f"{column}_n", lambda: F.col(column).isNotNull().cast("bigint"))
    return State(f"{column}_{kind}", {"s": value, "ss": lambda: (F.col(column).cast("decimal(18,0)") * F.col(column).cast("decimal(18,0)")).cast("decimal(38,0)")}[kind])


def mean(column: str, name: str | None = None) -> Measure:
    n, s = _moment(column, "n"), _moment(column, "s")
    return Measure(name or f"avg_{column}", (n, s), lambda: F.try_divide(F.col(s.name).cast("double"), F.col(n.name).cast("double")))


def variance(column: str, name: str | None = None, sample: bool = False) -> Measure:
    """Population (or sample) variance of an integral column, from exact sums: ``(n ss - s^2) / n^2``."""
    n, s, ss = (_moment(column, k) for k in ("n", "s", "ss"))
    up = lambda: (F.col(n.name).cast("decimal(38,0)") * F.col(ss.name) - F.col(s.name) * F.col(s.name)).cast("double")
    down = lambda: F.col(n.name).cast("double") * (F.col(n.name).cast("double") - (1 if sample else 0))
    return Measure(name or f"var_{column}", (n, s, ss), lambda: F.try_divide(up(), down()))


def deviation(column: str, name: str | None = None, sample: bool = False) -> Measure:
    inner = variance(column, "_", sample)
    return Measure(name or f"std_{column}", inner.states, lambda: F.sqrt(inner.finalize()))


def ratio(over: str, under: str, name: str) -> Measure:
    a, b = total(over).states[0], total(under).states[0]
    return Measure(name, (a, b), lambda: F.try_divide(F.col(a.name).cast("double"), F.col(b.name).cast("double")))


def covariance(x: str, y: str, name: str | None = None) -> Measure:
    """Population covariance of two integral columns without nulls."""
    n, sx, sy = _moment(x, "n"), _moment(x, "s"), _moment(y, "s")
    xy = State(f"{x}_{y}_s", lambda: (F.col(x).cast("decimal(18,0)") * F.col(y).cast("decimal(18,0)")).cast("decimal(38,0)"))
    up = lambda: (F.col(n.name).cast("decimal(38,0)") * F.col(xy.name) - F.col(sx.name) * F.col(sy.name)).cast("double")
    return Measure(name or f"cov_{x}_{y}", (n, sx, sy, xy), lambda: F.try_divide(up(), F.col(n.name).cast("double") * F.col(n.name).cast("double")))


def correlation(x: str, y: str, name: str | None = None) -> Measure:
    cov, vx, vy = covariance(x, y, "_"), variance(x, "_"), variance(y, "_")
    states = tuple(dict((s.name, s) for m in (cov, vx, vy) for s in m.states).values())
    return Measure(name or f"corr_{x}_{y}", states, lambda: F.try_divide(cov.finalize(), F.sqrt(vx.finalize() * vy.finalize())))


def change(column: str, before: Callable[[], Column], after: Callable[[], Column], name: str = "change") -> tuple[Measure, ...]:
    """Sums before and after, their difference, and the difference relative to before."""
    b, a = total_where(column, before, "before"), total_where(column, after, "after")
    states = b.states + a.states
    return (
        b, a, Measure(name, states, lambda: F.col("after") - F.col("before")),
        Measure(f"relative_{name}", states, lambda: F.try_divide((F.col("after") - F.col("before")).cast("double"), F.abs("before").cast("double"))),
    )


def distinct_estimate(column: str, name: str | None = None, bits: int = 12) -> Measure:
    """An estimated number of distinct values: a HyperLogLog sketch per segment."""
    state = State(f"{column}_hll", lambda: F.col(column), "hll")
    return Measure(name or f"distinct_{column}", (State(state.name, lambda: F.col(column), "hll"),), lambda: F.hll_sketch_estimate(state.name))


def distinct_exact(column: str, name: str | None = None) -> Measure:
    """The exact number of distinct values as a set per segment; for small cardinalities (else cube the column and count)."""
    state = State(f"{column}_set", lambda: F.when(F.col(column).isNotNull(), F.array(column)).otherwise(F.array().cast("array<bigint>")), "set")
    return Measure(name or f"distinct_{column}", (state,), lambda: F.size(state.name).cast("bigint"))


def quantile_estimate(column: str, share: float, name: str | None = None) -> Measure:
    state = State(f"{column}_kll", lambda: F.col(column).cast("bigint"), "kll")
    return Measure(name or f"quantile_{column}", (state,), lambda: F.kll_sketch_get_quantile_bigint(state.name, F.lit(share)))


def top_member(member: str, value: str, name: str | None = None) -> Measure:
    """The member with the single largest row value, ties to the larger member."""
    state = State(f"{member}_top", lambda: F.struct(F.col(value).alias("value"), F.col(member).alias("member")), "max")
    return Measure(name or f"top_{member}", (state,), lambda: F.col(state.name)["member"])
