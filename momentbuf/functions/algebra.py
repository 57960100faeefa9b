"""Aggregates as (lift, merge, finish): what a bin stores, how pieces combine, what a query returns.

A state is a few columns. `lift` gives the aggregate expressions that turn cells into
a state with a given origin, `merge` those that combine states, `shift` moves a state's
origin (only moments have one), `finish` turns a state into the answer.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG, binomial_shift, power


@dataclass(frozen=True)
class AggSpec:
    name: str
    state: tuple[str, ...]
    lift: Callable[[Column, Column, Column], list[Column]]
    merge: Callable[[], list[Column]]
    finish: Callable[[], Column]
    linear: bool = False
    invertible: bool = False
    distributive: bool = False
    order: int = -1
    most: int = 0  # values a state holds at most, where it is a list
    exact: bool = False  # moments are lifted and shifted in DECIMAL(38,0)

    def shift(self, distance: Column) -> list[Column]:
        """State columns about an origin `distance` cells before the state's own."""
        if self.order < 0:
            return [F.col(c) for c in self.state]
        moments = [F.col(f"m{j}") for j in range(self.order + 1)]
        distance = distance.cast(BIG) if self.exact else distance
        return [x.alias(f"m{j}") for j, x in enumerate(binomial_shift(moments, distance))] + [F.col(c) for c in self.state if not c.startswith("m")]

    def unit(self, offset: Column) -> list[Column]:
        """State of a single cell of value one: a linear update adds delta times this."""
        if not self.linear:
            raise ValueError(f"{self.name} is not linear")
        return [(power(offset, int(c[1:])) if c.startswith("m") else F.lit(0 if c == "cnt" else 1).cast("long")).alias(c) for c in self.state]

    def invert(self, total: Column, others: Column) -> Column:
        """The part x with F(x, others) = total."""
        if not self.invertible:
            raise ValueError(f"{self.name} is not invertible")
        return total - others


def _sums(*names: str) -> Callable[[], list[Column]]:
    return lambda: [F.sum(n).alias(n) for n in names]


def count_spec() -> AggSpec:
    return AggSpec("count", ("cnt",), lambda i, v, o: [F.count(v).alias("cnt")], _sums("cnt"), lambda: F.coalesce("cnt", F.lit(0)).cast("long"), True, True, True)


def sum_spec() -> AggSpec:
    return AggSpec("sum", ("s",), lambda i, v, o: [F.sum(v).alias("s")], _sums("s"), lambda: F.coalesce("s", F.lit(0)), True, True, True)


def max_spec() -> AggSpec:
    return AggSpec("max", ("hi",), lambda i, v, o: [F.max(v).alias("hi")], lambda: [F.max("hi").alias("hi")], lambda: F.col("hi"), distributive=True)


def min_spec() -> AggSpec:
    return AggSpec("min", ("lo_v",), lambda i, v, o: [F.min(v).alias("lo_v")], lambda: [F.min("lo_v").alias("lo_v")], lambda: F.col("lo_v"), distributive=True)


def topn_spec(k: int) -> AggSpec:
    """The k largest values. A state holds at most k; a bin's cells are at most b, so what a build collects is bounded. Queries merge states by `merged_states`."""
    best = lambda x: F.slice(F.sort_array(x, asc=False), 1, k)
    return AggSpec(f"top{k}", ("top",), lambda i, v, o: [best(F.collect_list(v)).alias("top")], lambda: [best(F.flatten(F.collect_list("top"))).alias("top")], lambda: F.col("top"), most=k)


def avg_spec() -> AggSpec:
    return AggSpec("avg", ("s", "cnt"), lambda i, v, o: [F.sum(v).alias("s"), F.count(v).alias("cnt")], _sums("s", "cnt"), lambda: F.try_divide(F.col("s").cast("double"), F.col("cnt").cast("double")))


def moment_spec(order: int, exact: bool = False) -> AggSpec:
    """m_0 .. m_order about the piece's origin. exact: powers, products and sums in DECIMAL(38,0)."""
    kind = BIG if exact else "long"
    names = tuple(f"m{j}" for j in range(order + 1))
    lift = lambda i, v, o: [F.sum((power((i - o).cast(kind), j) * v).cast(kind)).alias(f"m{j}") for j in range(order + 1)]
    return AggSpec(f"moment{order}", names, lift, _sums(*names), lambda: F.coalesce(F.col(f"m{order}"), F.lit(0)), True, True, False, order, exact=exact)


def center_of_mass_spec() -> AggSpec:
    """Centre of mass relative to the range's start."""
    s = moment_spec(1)
    return AggSpec("center", s.state, s.lift, s.merge, lambda: F.try_divide(F.col("m1").cast("double"), F.nullif(F.col("m0"), F.lit(0)).cast("double")), True, True, False, 1)


def std_spec() -> AggSpec:
    """Standard deviation of a histogram: positions weighted by counts."""
    s = moment_spec(2)

    def finish() -> Column:
        n = F.nullif(F.col("m0"), F.lit(0)).cast("double")
        mean = F.col("m1").cast("double") / n
        return F.sqrt(F.greatest(F.lit(0.0), F.col("m2").cast("double") / n - mean * mean))

    return AggSpec("std", s.state, s.lift, s.merge, finish, True, True, False, 2)


def joint(*specs: AggSpec) -> AggSpec:
    """Several specs in one scan; their states must not share column names. The answer is a struct."""
    state = tuple(c for s in specs for c in s.state)
    if len(set(state)) < len(state):
        raise ValueError("states share column names")
    order = max(s.order for s in specs)
    return AggSpec(
        "+".join(s.name for s in specs), state, lambda i, v, o: [c for s in specs for c in s.lift(i, v, o)], lambda: [c for s in specs for c in s.merge()], lambda: F.struct(*[s.finish().alias(s.name) for s in specs]),
        all(s.linear for s in specs), all(s.invertible for s in specs), all(s.distributive for s in specs), order, exact=any(s.exact for s in specs),
    )


def merged_states(df: DataFrame, by: list[str], spec: AggSpec) -> DataFrame:
    """by and one state for each group. Lists are merged by rank, of which each task keeps the first few alone, so no row gathers a group's lists."""
    if not spec.most:
        return df.groupBy(*by).agg(*spec.merge())
    (c,) = spec.state
    rank = F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("_x")))
    best = df.select(*by, F.explode(c).alias("_x")).withColumn("_r", rank).where(F.col("_r") <= spec.most)
    return best.groupBy(*by).agg(F.sort_array(F.collect_list("_x"), asc=False).alias(c))


def local_moment(moments: list[Column], p: Column, c: Column, k: int) -> Column:
    """Moment of order k about c from moments about p."""
    return binomial_shift(moments[: k + 1], p - c)[k]


def check_distributive(spec: AggSpec, df: DataFrame, cut: int) -> DataFrame:
    """Rows (one at most) where merging both sides of a cut differs from the whole: idx, val columns expected."""
    i, v = F.col("idx"), F.col("val")
    whole = df.agg(*spec.lift(i, v, F.lit(0))).select(spec.finish().alias("whole"))
    parts = df.groupBy((i < cut).alias("side")).agg(*spec.lift(i, v, F.lit(0))).agg(*spec.merge()).select(spec.finish().alias("parts"))
    return whole.join(parts, ~F.col("whole").eqNullSafe(F.col("parts")))


def check_linear(spec: AggSpec, df: DataFrame, factor: int = 3) -> DataFrame:
    """Rows (one at most) where scaling the cells doesn't scale the answer."""
    i, v = F.col("idx"), F.col("val")
    one = df.agg(*spec.lift(i, v, F.lit(0))).select((spec.finish() * factor).alias("one"))
    other = df.agg(*spec.lift(i, v * factor, F.lit(0))).select(spec.finish().alias("other"))
    return one.join(other, ~F.col("one").eqNullSafe(F.col("other")))


def check_invertible(spec: AggSpec, df: DataFrame, cut: int) -> DataFrame:
    """Rows (one at most) where a part can't be had back from the whole and the other part."""
    i, v = F.col("idx"), F.col("val")
    c = spec.state[0]
    whole = df.agg(*spec.lift(i, v, F.lit(0))).select(F.col(c).alias("w"))
    side = lambda cond, n: df.where(cond).agg(*spec.lift(i, v, F.lit(0))).select(F.col(c).alias(n))
    return whole.join(side(i < cut, "x")).join(side(i >= cut, "y")).where(~F.col("x").eqNullSafe(spec.invert(F.col("w"), F.col("y"))))
