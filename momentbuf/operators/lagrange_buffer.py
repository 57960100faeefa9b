"""Lagrange moment buffer: one number per cell serves all local moments below order N.

A level holds the level below spread by interpolation weights. A query polynomial f, cut
to [p, q], is interpolated from its samples at the top level's cells; what the interpolant
misses (delta) is non-zero only in N - 1 bins around each end and is added from there, at
every level down to the array. Cells of a level at multiples of b belong to the next level
(delta is zero there), so levels share one storage.

Three modes: "exact" for whole-number cells (scaled whole-number weights in DECIMAL(38,0);
cells grow by the weights' scale with every level), "residue" for whole numbers at any
length and number of levels (see `operators/residues`), "double" for any cells.
"auto" takes "exact" while the scale leaves room, else "residue".
"""

from __future__ import annotations

from collections.abc import Callable, Mapping
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG, power
from momentbuf.functions.weights import Stencil, num_levels
from momentbuf.operators import residues as R
from momentbuf.operators.binbuf import add_cells, few
from momentbuf.operators.ranges import beside, ends, inside, match, needed, settled
from momentbuf.sources.arrays import IndexedArray

Poly = Callable[[Column], Column]
#: Greatest product of the levels' weight scales for which exact mode is taken: sums up to 10^26 times it fit DECIMAL(38,0).
EXACT = 10**12
#: Up to this b^N the sums of a bin's powers times values stay in longs (values below 2^30; beyond that an overflow raises).
LONGS = 1 << 32


@dataclass(frozen=True)
class LagrangeBuffer:
    df: DataFrame  # (keys,) level, pos, v (residue mode: r0, r1, ..); pos is the cell's number on its own level. Rows of one cell add up.
    b: int
    n: int
    levels: int
    stencil: Stencil
    mode: str = "exact"
    keys: tuple[str, ...] = ()
    stored: bool = False  # read from files: bounds on pos reach the scan

    @property
    def values(self) -> tuple[str, ...]:
        return R.COLUMNS if self.mode == "residue" else ("v",)

    @property
    def cells(self) -> DataFrame:
        """Cells by their number on level 1, as stored in place."""
        width = F.element_at(F.array(*[F.lit(self.b ** (lv - 1)) for lv in range(1, self.levels + 1)]), F.col("level").cast("int"))
        return self.df.select(*self.keys, (F.col("pos") * width).alias("cell"), "level", *self.values)


class Power:
    """(x - at)^k in whole numbers, as a function of columns and as SQL text; `mod` gives it modulo a prime, whatever its size."""

    def __init__(self, k: int, at: str):
        self.k, self.at = k, at

    def __call__(self, x: Column) -> Column:
        return power((x - F.expr(self.at)).cast("long"), self.k) if self.k else F.lit(1).cast("long")

    def text(self, x: str) -> str:
        return "*".join([f"CAST({x} - ({self.at}) AS BIGINT)"] * self.k) if self.k else "1L"

    def mod(self, x: str, m: int) -> str:
        base = f"pmod({x} - ({self.at}), {m}L)"
        out = base if self.k else "1L"
        for _ in range(self.k - 1):
            out = f"({out} * {base} % {m}L)"
        return out


def moment_poly(k: int, c: str | int = "c") -> Poly:
    """(i - c)^k with c a column of the ranges or a number, in whole numbers."""
    return Power(k, str(c))


ONE = Power(0, "0")


def _type(mode: str) -> str:
    return BIG if mode == "exact" else "DOUBLE"


def _num(mode: str, x: Column) -> Column:
    return x.cast(_type(mode))


def _big(x: int) -> Column:
    """A literal of any size that DECIMAL(38,0) holds."""
    return F.expr(f"CAST('{x}' AS {BIG})")


def _weight(st: Stencil, mode: str, k: int, r: str, b: int) -> str:
    """SQL of a weight, in exact mode times its scale."""
    return f"CAST({st.whole(k, r, b) if mode == 'exact' else st.weight(k, r, b)} AS {_type(mode)})"


def spread(df: DataFrame, b: int, st: Stencil, mode: str, limit: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys,) pos, v of the next level: N sums per bin in one aggregation, then folded onto the cells they belong to. limit: number of cells kept.

    Whole-number cells that fit a long are summed up with powers of their offsets, in
    longs, and weighted once a bin; others are weighted one by one.
    """
    kind, r = _type(mode), f"(pos % {b})"
    if mode == "exact" and df.schema["v"].dataType.simpleString() == "bigint":
        moments = [F.expr(f"sum({'*'.join(['v', *[r] * d])}) AS m{d}") for d in range(st.n)]
        sums = df.groupBy(*keys, F.expr(f"pos div {b} AS bin")).agg(*moments)
        scale = st.scale(b)
        value = lambda k: " + ".join(f"CAST(CAST('{int(c * scale / b**d)}' AS {BIG}) * CAST(m{d} AS {BIG}) AS {BIG})" for d, c in enumerate(st.polynomial(k)) if c)
        cells = ", ".join(f"struct(bin + {k} AS pos, CAST({value(k)} AS {BIG}) AS v)" for k in st.nodes)
    else:
        sums = df.groupBy(*keys, F.expr(f"pos div {b} AS bin")).agg(*[F.expr(f"sum(CAST({_weight(st, mode, k, r, b)} * v AS {kind})) AS s{i}") for i, k in enumerate(st.nodes)])
        cells = ", ".join(f"struct(bin + {k} AS pos, s{i} AS v)" for i, k in enumerate(st.nodes))
    return sums.select(*keys, F.expr(f"inline(array({cells}))")).where(f"pos >= 0 AND pos < {limit}").groupBy(*keys, "pos").agg(F.expr(f"CAST(sum(v) AS {kind}) AS v"))


def sparse_pays(non_zero: int, n: int, order: int, levels: int) -> bool:
    """Whether building by updates is the cheaper way: few non-zero cells beside n / (N levels)."""
    return non_zero < n / (order * levels)


def build_lagrange(arr: IndexedArray, b: int, order: int = 4, levels: int | None = None, mode: str = "auto", stencil: Stencil | None = None, strategy: str = "sparse", hold: Callable[[DataFrame], DataFrame] | None = None) -> LagrangeBuffer:
    """All levels in one lazy plan; a level's aggregation is one exchange that both its uses share.

    hold: may keep a level between its uses instead (`store.held` writes it).
    strategy: "sparse" builds from the rows there are, "dense" fills the array with zeros
    first; "auto" counts the non-zero cells and takes sparse where there are fewer
    than n / (N levels).
    """
    from momentbuf.sources.arrays import densify, sparsify

    st = stencil or Stencil.of(order)
    levels = levels or num_levels(arr.n, b, st.n)
    if mode == "auto":
        mode = "exact" if st.scale(b) ** levels <= EXACT else "residue"
    if mode == "exact" and st.scale(b) ** levels >= 10**37:
        raise ValueError(f"cells of {levels} levels at b={b}, N={st.n} outgrow {BIG}; use mode='residue' or 'double'")
    if strategy == "auto":
        strategy = "sparse" if sparse_pays(sparsify(arr).df.count(), arr.n, st.n, levels) else "dense"
    if strategy == "dense":
        arr = densify(arr)
    values = R.COLUMNS if mode == "residue" else ("v",)
    longs = mode == "residue" or (mode == "exact" and b**st.n <= LONGS and arr.df.schema["val"].dataType.simpleString() in ("bigint", "int", "smallint", "tinyint"))
    cur = arr.df.select(*arr.keys, F.col("idx").alias("pos"), F.col("val").cast("long").alias("v") if longs else _num(mode, F.col("val")).alias("v"))
    out = None
    for lv in range(1, levels + 1):
        limit = -(-arr.n // b**lv)
        cur = R.spread(cur, b, st, limit, arr.keys, first=lv == 1) if mode == "residue" else spread(cur, b, st, mode, limit, arr.keys)
        if hold and lv < levels:
            cur = hold(cur)
        # A test of a value beside that of the position keeps this filter above the aggregation, so that its exchange is the next level's too.
        part = cur if lv == levels else cur.where(f"pos % {b} <> 0 OR {values[0]} IS NULL")
        part = part.select(*arr.keys, F.lit(lv).alias("level"), "pos", *values)
        out = part if out is None else out.unionByName(part)
    return LagrangeBuffer(out, b, arr.n, levels, st, mode, arr.keys)


def from_bin_moments(bins: DataFrame, b: int, n: int, order: int) -> LagrangeBuffer:
    """One-level buffer as a linear map of disjoint-bin moments m_0 .. m_{N-1} about bin starts, in double precision."""
    st = Stencil.of(order)
    cells = [F.struct((F.col("bin") + k).alias("pos"), sum((F.lit(float(c / b**j)) * F.col(f"m{j}").cast("double") for j, c in enumerate(st.polynomial(k))), F.lit(0.0)).alias("v")) for k in st.nodes]
    rows = bins.select(F.inline(F.array(*cells))).where((F.col("pos") >= 0) & (F.col("pos") * b < n))
    return LagrangeBuffer(rows.groupBy("pos").agg(F.sum("v").alias("v")).select(F.lit(1).alias("level"), "pos", "v"), b, n, 1, st, "double")


def candidates(ranges: DataFrame, b: int, level: int, st: Stencil, bins: int) -> DataFrame:
    """Range columns and bin: bins of a level in which delta may be non-zero, each once for a range. N - 1 around each end."""
    g = b**level
    step = g * b
    first, last = f"(p + {step - 1}) div {step}", f"q div {step}"
    head = f"sequence({first} - {st.M}, {first} + {st.Mp - 2})" if st.n > 1 else f"array({first})"
    near = f"concat({head}, sequence({last} + {1 - st.M}, {last} + {st.Mp - 1}), array((p + {g - 1}) div {g} div {b}, q div {g} div {b}))"
    return ranges.select("*", F.expr(f"explode(array_distinct({near})) AS bin")).where(f"bin >= 0 AND bin < {bins}")


def _at(f: Poly, x: str, mode: str) -> Column:
    """f, cut to [p, q], at the position that the text x gives."""
    kind = _type(mode)
    if hasattr(f, "text"):
        return F.expr(f"CASE WHEN {x} BETWEEN p AND q THEN CAST({f.text(f'({x})')} AS {kind}) ELSE CAST(0 AS {kind}) END")
    return F.when(F.expr(f"{x} BETWEEN p AND q"), f(F.expr(x)).cast(kind)).otherwise(F.lit(0).cast(kind))


def _delta(f: Poly, level: int, b: int, st: Stencil, mode: str) -> Column:
    """Residual at the cell `pos` of a level (level 0: the array) in `bin`, times the weights' scale in exact mode."""
    g, kind = b**level, _type(mode)
    r = f"(pos - bin * {b})"
    if hasattr(f, "text"):
        cut = lambda x: f"CASE WHEN {x} BETWEEN p AND q THEN CAST({f.text(f'({x})')} AS {kind}) ELSE CAST(0 AS {kind}) END"
        own = f"({cut(f'(pos * {g})')})" + (f" * CAST('{st.scale(b)}' AS {kind})" if mode == "exact" else "")
        taken = "".join(f" - CAST(({cut(f'((bin + {k}) * {g * b})')}) * {_weight(st, mode, k, r, b)} AS {kind})" for k in st.nodes)
        return F.expr(f"CAST({own}{taken} AS {kind})")
    out = _at(f, f"(pos * {g})", mode) * _num(mode, _big(st.scale(b)) if mode == "exact" else F.lit(1.0))
    for k in st.nodes:
        out = out - _num(mode, _at(f, f"((bin + {k}) * {g * b})", mode) * F.expr(_weight(st, mode, k, r, b)))
    return _num(mode, out)


def asked_of(known: np.ndarray, b: int, level: int, st: Stencil) -> tuple[np.ndarray, np.ndarray]:
    """Positions of a level, as intervals, that hold every candidate bin of a batch."""
    p, q = known[:, 0], known[:, 1]
    g = b**level
    first, last = -(-p // (g * b)), q // (g * b)
    pb, qb = -(-p // g) // b, q // g // b
    lo = np.r_[np.minimum(first - st.M, pb), np.minimum(last + 1 - st.M, qb)]
    hi = np.r_[np.maximum(first + st.Mp - 2, pb), np.maximum(last + st.Mp - 1, qb)]
    return np.maximum(lo, 0) * b, hi * b + b - 1


def _top(buf: LagrangeBuffer, ranges: DataFrame) -> DataFrame:
    """Top-level cells joined with the ranges whose ends they lie between."""
    known, up = ends(ranges), buf.b**buf.levels
    runs = ranges.selectExpr("*", f"(p + {up - 1}) div {up} AS lo_", f"q div {up} AS hi_").where("lo_ <= hi_")
    cells, lengths = buf.df.where(f"level = {buf.levels}"), None
    if known is not None:
        lo, hi = -(-known[:, 0] // up), known[:, 1] // up
        cells, lengths = cells.where(inside("pos", lo, hi)) if buf.stored else cells, hi - lo + 1
    return match(cells, "pos", runs, "lo_", "hi_", -(-buf.n // up), known, lengths)


def _near(arr: IndexedArray | None, buf: LagrangeBuffer, ranges: DataFrame, level: int) -> DataFrame:
    """Cells of a level (0: the array) joined with the ranges near whose ends their bin lies; their intervals are pushed into the scan."""
    b, known = buf.b, ends(ranges)
    lo, hi = (None, None) if known is None else asked_of(known, b, level, buf.stencil)
    if level == 0:
        rows = needed(arr, lo, hi).selectExpr(*buf.keys, "idx AS pos", "val AS v", f"idx div {b} AS bin")
    else:
        rows = buf.df.where(f"level = {level}")
        rows = (rows.where(inside("pos", lo, hi)) if buf.stored and lo is not None else rows).selectExpr(*buf.keys, "pos", *buf.values, f"pos div {b} AS bin")
    bins = -(-(-(-buf.n // b**level)) // b)
    return rows.join(beside(candidates(ranges, b, level, buf.stencil, bins), known), "bin")


COUNTS = {"a": "cells_array", "c": "cells_buffer", "f_evals": "poly_evals", "w_evals": "weight_evals"}


def counted(rows: str, level: int, n: int) -> list[Column]:
    """Cells read from the array (a; level 0) and the buffer (c; level -1: the top one), and how often f and a weight were evaluated for them."""
    top = level < 0
    return [F.expr(x) for x in (f"{rows if level == 0 else '0L'} AS a", f"{'0L' if level == 0 else rows} AS c", f"{rows} * {1 if top else n + 1} AS f_evals", f"{'0L' if top else f'{rows} * {n}'} AS w_evals")]


def _parts(arr: IndexedArray | None, buf: LagrangeBuffer, ranges: DataFrame, fs: Mapping[str, Poly], only_top: bool = False) -> DataFrame:
    """(keys,) qid, one column for each function, and counts: contributions of the top level and of what each level below misses."""
    b, st, mode, top = buf.b, buf.stencil, buf.mode, buf.levels
    by = [*buf.keys, "qid"]
    out = _top(buf, ranges).groupBy(*by).agg(*[F.sum(_num(mode, _at(f, f"(pos * {b**top})", mode) * F.col("v"))).alias(k) for k, f in fs.items()], *counted("count(*)", -1, st.n))
    for level in range(0 if only_top else top):
        sums = []
        for k, f in fs.items():
            x = _num(mode, _delta(f, level, b, st, mode) * F.col("v"))
            up = st.scale(b) ** (top - level - 1)
            sums.append(F.sum(_num(mode, x * _big(up)) if mode == "exact" and up > 1 else x).alias(k))
        out = out.unionByName(_near(arr, buf, ranges, level).groupBy(*by).agg(*sums, *counted("count(*)", level, st.n)))
    return out


def _result(buf: LagrangeBuffer, x: str = "x", wide: bool = False) -> Column:
    """The sum less the weights' scale. `div` gives a long whatever its operands, and wraps; dividing a multiple doesn't."""
    if buf.mode == "exact":
        total, scale = f"coalesce(sum({x}), CAST(0 AS {BIG}))", f"CAST('{buf.stencil.scale(buf.b) ** buf.levels}' AS {BIG})"
        return F.expr(f"CAST(({total} - {total} % {scale}) / {scale} AS {BIG if wide else 'BIGINT'})")
    return F.coalesce(F.sum(x), F.lit(0.0))


def query_many(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame, fs: Mapping[str, Poly], costs: bool = False, wide: bool = False) -> DataFrame:
    """(keys,) qid and, for each named f, the sum over [p, q] of f(i) a_i, all from one pass; f as in query_lagrange."""
    by, ranges = [*buf.keys, "qid"], settled(ranges)
    if buf.mode == "residue":
        parts = _top(buf, ranges).groupBy(*by).agg(*R.top_sums(fs, f"(pos * {buf.b**buf.levels})"), *counted("count(*)", -1, buf.stencil.n))
        for level in range(buf.levels):
            parts = parts.unionByName(R.near_sums(_near(arr, buf, ranges, level), by, ranges.columns, fs, level, buf.b, buf.stencil, counted("sum(rows_)", level, buf.stencil.n)))
        results = [F.expr(f"sum({c}) AS {c}") for k in fs for c in R.names(k)]
        none = F.lit(0).cast(BIG if wide else "long")
    else:
        parts = _parts(arr, buf, ranges, fs)
        results = [_result(buf, k, wide).alias(k) for k in fs]
        none = F.lit(0).cast(BIG if wide else "long") if buf.mode == "exact" else F.lit(0.0)
    got = parts.groupBy(*by).agg(*results, *([F.sum(c).alias(to) for c, to in COUNTS.items()] if costs else []))
    if buf.mode == "residue":
        got = R.whole(got, by, list(fs), wide, list(COUNTS.values()) if costs else [])
    every = ranges.select("qid") if not buf.keys else ranges.select("qid").join(F.broadcast(buf.df.select(*buf.keys).distinct()))
    more = [F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in COUNTS.values()] if costs else []
    return every.join(got, by, "left").select(*by, *[F.coalesce(k, none).alias(k) for k in fs], *more)


def query_lagrange(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame, f: Poly | None = None, costs: bool = False, wide: bool = False) -> DataFrame:
    """(keys,) qid, result = sum over [p, q] of f(i) a_i for a polynomial f of degree below N (default: 1).

    f takes the position and may use the ranges' columns. A batch of at most
    `ranges.BATCH` ranges is broadcast, and the bins at its ends are pushed into the scans
    of the array and the buffer; a larger batch is joined by exchange. Whole-number
    results are BIGINT and an overflow raises; wide: DECIMAL(38,0), in residue mode right
    up to 2^122, in exact mode while it and the levels' scale fit 38 digits. costs: cells read, and evaluations of f and of weights.
    """
    return query_many(arr, buf, ranges, {"result": f or ONE}, costs, wide)


def delta_cells(buf: LagrangeBuffer, updates: DataFrame) -> DataFrame:
    """The buffer's cells of the updates (keys, idx, delta) alone: at most 2N a level for each."""
    delta = IndexedArray(updates.groupBy(*buf.keys, "idx").agg(F.sum("delta").alias("val")), buf.n, buf.keys)
    return build_lagrange(delta, buf.b, levels=buf.levels, mode=buf.mode, stencil=buf.stencil).df


def update_lagrange(buf: LagrangeBuffer, updates: DataFrame, how: str = "merge") -> LagrangeBuffer:
    """Batch update: the buffer of the deltas alone, added. Every step is linear, so this equals a rebuild.

    how: "append" leaves the buffer untouched and lists the deltas' cells behind it (queries add
    rows of one cell up; `compacted` folds them); "merge" adds them cell by cell. A batch
    that is small moves no cell of the buffer either way.
    """
    new = delta_cells(buf, updates)
    if how == "append":
        return replace(buf, df=buf.df.unionByName(new), stored=False)
    key = [*buf.keys, "level", "pos"]
    if few(updates):
        return replace(buf, df=add_cells(buf.df.select(*key, *buf.values), new, key, {c: _sum_of(buf.mode, F.col(c) + F.col(f"d_{c}")) for c in buf.values}), stored=False)
    return compacted(replace(buf, df=buf.df.unionByName(new)))


def _sum_of(mode: str, x: Column) -> Column:
    return x if mode == "residue" else _num(mode, x)


def compacted(buf: LagrangeBuffer) -> LagrangeBuffer:
    """One row a cell, after appended updates."""
    return replace(buf, df=buf.df.groupBy(*buf.keys, "level", "pos").agg(*[_sum_of(buf.mode, F.sum(c)).alias(c) for c in buf.values]), stored=False)


def set_values(arr: IndexedArray, buf: LagrangeBuffer, new: DataFrame) -> LagrangeBuffer:
    """Replace cells: new (idx, val); the delta is had from the old value."""
    old = arr.df.select(*arr.keys, "idx", F.col("val").alias("old"))
    rows = new.join(old, [*arr.keys, "idx"], "left").select(*arr.keys, "idx", (F.col("val") - F.coalesce("old", F.lit(0))).alias("delta"))
    return update_lagrange(buf, rows)


def touched(changes: DataFrame, b: int, st: Stencil, levels: int, n: int) -> DataFrame:
    """level, j, cell: the cells of each level that a change at index j reaches, for many changes at once."""
    out, cur = None, changes.selectExpr("j", "j AS cell")
    for lv in range(1, levels + 1):
        reach = f"explode(CASE WHEN cell % {b} = 0 THEN array(0) ELSE sequence({1 - st.Mp}, {st.M}) END)"
        cur = cur.select("j", "cell", F.expr(reach).alias("k")).selectExpr("j", f"cell div {b} + k AS cell").where(f"cell >= 0 AND cell * {b**lv} < {n}").distinct()
        part = cur.select(F.lit(lv).alias("level"), "j", "cell")
        out = part if out is None else out.unionByName(part)
    return out


def update_dag(spark, j: int, b: int, st: Stencil, levels: int, n: int) -> DataFrame:
    """level, cell, parent: which cells of the next level a change at index j reaches; multiples of b reach their own cell alone."""
    rows, cur = [], {j}
    for lv in range(1, levels + 1):
        new = set()
        for i in sorted(cur):
            for p in [i // b] if i % b == 0 else [i // b + k for k in st.nodes]:
                if 0 <= p * b**lv < n:
                    rows.append((lv, i, p))
                    new.add(p)
        cur = new
    return spark.createDataFrame(rows, "level int, cell long, parent long")


def update_edges(changes: DataFrame, b: int, st: Stencil, levels: int, n: int) -> DataFrame:
    """level, cell, parent: update_dag for all changes (column j) at once, each edge once."""
    out, cur = None, changes.selectExpr("j AS cell").distinct()
    for lv in range(1, levels + 1):
        reach = f"explode(CASE WHEN cell % {b} = 0 THEN array(0) ELSE sequence({1 - st.Mp}, {st.M}) END)"
        edges = cur.select("cell", F.expr(reach).alias("k")).selectExpr(f"{lv} AS level", "cell", f"cell div {b} + k AS parent").where(f"parent >= 0 AND parent * {b**lv} < {n}")
        out, cur = edges if out is None else out.unionByName(edges), edges.selectExpr("parent AS cell").distinct()
    return out


def endpoint_table(spark, b: int, st: Stencil, mode: str = "double") -> DataFrame:
    """off, d, at, rest: for a step at offset `off` of a bin, what interpolation misses of the monomial (i/b)^d from there on, at cell `at` counted from the step's bin.

    For small b: b offsets times N monomials times the cells of N bins; cells without a rest are left out.
    Exact mode: whole numbers, rests of i^d times the weights' scale.
    """
    from decimal import Decimal
    from fractions import Fraction

    held = (lambda x, d: Decimal(int(x * b**d * st.scale(b)))) if mode == "exact" else (lambda x, d: float(x))

    rows = []
    for off in range(b):
        for d in range(st.n):
            f = lambda x: Fraction(x, b) ** d if x >= off else Fraction(0)  # noqa: B023, E731
            for bin_ in range(-st.n, st.n + 1):
                for r in range(b):
                    rest = f(bin_ * b + r) - sum(f((bin_ + k) * b) * st.exact(k, r, b) for k in st.nodes)
                    if rest:
                        rows.append((off, d, bin_ * b + r, held(rest, d)))
    return spark.createDataFrame(rows, f"off int, d int, at long, rest {_type(mode)}")


def query_tabulated(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame, table: DataFrame, coef: list[str]) -> DataFrame:
    """qid, result of a one-level buffer for f(i) = sum of coef[d] ((i - p) / b)^d, with the ends' rests looked up instead of evaluated.

    A range is a step up at p and a step down at q + 1; seen from a step's bin, f is a
    polynomial in (i - start of bin) / b, whose coefficients follow by the binomial rule.
    A buffer in exact mode takes a table in exact mode and whole coefficients; everything is
    then b^(len(coef) - 1) times as large and whole until the last division, and the result BIGINT.
    """
    from math import comb

    if buf.mode not in ("exact", "double") or buf.levels != 1 or (table.schema["rest"].dataType.simpleString() == "double") != (buf.mode == "double"):
        raise ValueError("a buffer of one level, and a table of its own mode, exact or double")
    b, n, ranges, exact = buf.b, buf.stencil.n, settled(ranges), buf.mode == "exact"
    num = lambda x: _num(buf.mode, x)
    part = lambda d: num(F.lit(b ** (len(coef) - 1 - d) if exact else 1))
    powers = lambda x, d: reduce(lambda a, _: num(a * x), range(d), num(F.lit(1)))
    known, lo, hi = ends(ranges), None, None
    if known is not None:
        at = np.r_[known[:, 0], known[:, 1] + 1] // b
        lo, hi = np.maximum(0, at - n) * b, (at + n + 1) * b - 1
    steps = ranges.select("qid", F.col("p").alias("origin"), *coef, F.inline(F.array(F.struct(F.col("p").alias("x"), F.lit(1).alias("sign")), F.struct((F.col("q") + 1).alias("x"), F.lit(-1).alias("sign")))))
    start = F.expr(f"x div {b}") * b
    scaled = lambda x: num(x) if exact else num(x) / float(b)
    u = scaled(start - F.col("origin"))
    local = [num(sum((num(num(F.lit(comb(e, d))) * num(F.col(coef[e])) * part(e)) * powers(u, e - d) for e in range(d, len(coef))), num(F.lit(0)))) for d in range(len(coef))]
    steps = steps.select("qid", "sign", F.expr(f"CAST(x % {b} AS INT)").alias("off"), start.alias("start"), F.inline(F.array(*[F.struct(F.lit(d).alias("d"), c.alias("w")) for d, c in enumerate(local)])))
    rests = steps.join(F.broadcast(table), ["off", "d"]).groupBy("qid", (F.col("start") + F.col("at")).alias("idx")).agg(num(F.sum(num(F.col("sign") * F.col("w") * F.col("rest")))).alias("rest"))
    near = needed(arr, lo, hi).join(beside(rests, known), "idx").groupBy("qid").agg(F.sum(num(F.col("rest") * num(F.col("val")))).alias("x"))
    at = scaled(F.col("pos") * b - F.col("p"))
    f = num(sum((num(num(F.col(c)) * part(d)) * powers(at, d) for d, c in enumerate(coef)), num(F.lit(0))))
    tops = _top(buf, ranges).groupBy("qid").agg(F.sum(num(f * F.col("v"))).alias("x"))
    got = tops.unionByName(near.withColumn("x", num(F.col("x")))).groupBy("qid").agg(num(F.sum("x")).alias("x"))
    got = got.withColumn("x", (F.col("x") / _big(buf.stencil.scale(b) * b ** (len(coef) - 1))).cast("long")) if exact else got
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("x", F.lit(0).cast("long") if exact else F.lit(0.0)).alias("result"))
