"""Applications of moments: price statistics, strips, moving grids, local polynomial fits, segmentation, rollups."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG, power
from momentbuf.operators.lagrange_buffer import LagrangeBuffer, moment_poly, query_lagrange, query_many
from momentbuf.operators.ranges import beside, ends, match
from momentbuf.sources.arrays import IndexedArray


def moments_of_ranges(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame, order: int, c: str = "p", wide: bool = False) -> DataFrame:
    """(keys,) qid and m0 .. m{order} about column c, all from one pass over the one buffer. wide: whole numbers beyond longs, in DECIMAL."""
    return query_many(arr, buf, ranges, {f"m{k}": moment_poly(k, c) for k in range(order + 1)}, wide=wide)


def _ratio(a: Column, b: Column) -> Column:
    return F.try_divide(a.cast("double"), b.cast("double"))


def _wide(m: DataFrame, c: str) -> Column:
    """A moment as it is in double precision, else in DECIMAL: times a length it may outgrow a long."""
    return F.col(c) if m.schema[c].dataType.simpleString() == "double" else F.col(c).cast(BIG)


def price_stats(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame) -> DataFrame:
    """qid, items, value (sum of position times count), mean and std of positions in each range of a histogram."""
    m = moments_of_ranges(arr, buf, ranges, 2).join(F.broadcast(ranges.select("qid", "p")), "qid")
    mean = _ratio(F.col("m1"), F.col("m0"))
    std = F.sqrt(F.greatest(F.lit(0.0), _ratio(F.col("m2"), F.col("m0")) - mean * mean))
    return m.select("qid", F.col("m0").alias("items"), (F.col("m1") + F.col("p") * F.col("m0")).alias("value"), (F.col("p") + mean).alias("mean"), std.alias("std"))


def strip_stats(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame) -> DataFrame:
    """qid, mass, mean density and centre of mass of each stretch."""
    m = moments_of_ranges(arr, buf, ranges, 1).join(F.broadcast(ranges.select("qid", "p", "q")), "qid")
    return m.select("qid", F.col("m0").alias("mass"), _ratio(F.col("m0"), F.col("q") - F.col("p") + 1).alias("density"), (F.col("p") + _ratio(F.col("m1"), F.col("m0"))).alias("center"))


def grid_ranges(spark: SparkSession, lo: int, hi: int, cells: int) -> DataFrame:
    """One range for each of `cells` equal parts of [lo, hi]."""
    x, w = F.col("id"), hi - lo + 1
    return spark.range(cells).select(x.alias("qid"), (F.lit(lo) + F.expr(f"(id * {w}) div {cells}")).alias("p"), (F.lit(lo) + F.expr(f"((id + 1) * {w}) div {cells}") - 1).alias("q")).where("p <= q")


def fit_line(m: DataFrame) -> DataFrame:
    """qid, intercept, slope of the least-squares line over a dense range: moments about p, and power sums in closed form with their common factors taken out."""
    n, m0, m1 = (F.col("q") - F.col("p") + 1).cast(BIG), _wide(m, "m0"), _wide(m, "m1")
    slope = _ratio(12 * m1 - 6 * (n - 1) * m0, n * (n * n - 1))
    return m.select("qid", _ratio((4 * n - 2) * m0 - 6 * m1, n * (n + 1)).alias("intercept"), slope.alias("slope"))


def fit_poly(m: DataFrame, degree: int) -> DataFrame:
    """qid, coef, explained: least-squares polynomial in u = (i - p) / (q - p + 1) from m0 .. m{degree}.

    Degrees 0 to 2 are projections on orthogonal polynomials with whole-number coefficients,
    exact up to the last division where the moments are whole; higher ones are solved from
    power sums in Arrow batches, all ranges of a batch at once. explained: coef times
    right-hand side, which the sum of squares exceeds by the residual. Ranges with
    fewer cells than coefficients have null coefficients.
    """
    n = (F.col("q") - F.col("p") + 1).cast("double")
    if degree <= 2:
        w = (F.col("q") - F.col("p") + 1).cast(BIG)
        ms = [_wide(m, f"m{k}") for k in range(degree + 1)]
        sides = [ms[0]]  # sums of 1, 2x - (n-1) and 6x^2 - 6(n-1)x + (n-1)(n-2), x = i - p, times the cells
        if degree > 0:
            sides.append(2 * ms[1] - (w - 1) * ms[0])
        if degree > 1:
            sides.append(6 * ms[2] - 6 * (w - 1) * ms[1] + (w - 1) * (w - 2) * ms[0])
        norms = [n, n * (n * n - 1) / 3, n * (n * n - 1) * (n * n - 4) / 5]
        rows = m.select("qid", n.alias("n"), *[s.cast("double").alias(f"s{k}") for k, s in enumerate(sides)], *[F.when(n > degree, F.try_divide(s.cast("double"), norms[k])).alias(f"a{k}") for k, s in enumerate(sides)])
        n, (a0, a1, a2) = F.col("n"), [F.col(f"a{k}") if k <= degree else F.lit(0.0) for k in range(3)]
        coef = [a0 - (n - 1) * a1 + (n - 1) * (n - 2) * a2, n * (2 * a1 - 6 * (n - 1) * a2), n * n * 6 * a2][: degree + 1]
        return rows.select("qid", F.array(*coef).alias("coef"), reduce(lambda x, y: x + y, [F.col(f"a{k}") * F.col(f"s{k}") for k in range(degree + 1)]).alias("explained"))

    y = [F.col(f"m{k}").cast("double") / (F.pow(n, F.lit(float(k))) if k else F.lit(1.0)) for k in range(degree + 1)]

    def solve(batches):
        import numpy as np
        import pandas as pd

        from momentbuf.functions.scalars import bernoulli_sums

        polys = [[float(c) for c in bernoulli_sums(k)] for k in range(2 * degree + 1)]
        for d in batches:
            n = d["n"].to_numpy(float)
            u = np.stack([sum(c * n ** (j - k) for j, c in enumerate(p) if c) for k, p in enumerate(polys)], 1)  # sum of (i/n)^k over i < n
            a = u[:, np.add.outer(np.arange(degree + 1), np.arange(degree + 1))]
            y = d[[f"y{k}" for k in range(degree + 1)]].to_numpy(float)
            fine = n > degree
            x = np.full(y.shape, np.nan)
            if fine.any():
                x[fine] = np.linalg.solve(a[fine], y[fine][:, :, None])[:, :, 0]
            yield pd.DataFrame({"qid": d["qid"], "coef": [r.tolist() if ok else [None] * (degree + 1) for r, ok in zip(x, fine)], "explained": [float(v) if ok else None for v, ok in zip((x * y).sum(1), fine)]})

    return m.select("qid", n.alias("n"), *[x.alias(f"y{k}") for k, x in enumerate(y)]).mapInPandas(solve, "qid long, coef array<double>, explained double")


def residual(fit: DataFrame, squares: DataFrame) -> DataFrame:
    """qid, residual: sum of squares (from a second buffer) minus what the fit explains."""
    return fit.join(squares.withColumnRenamed("result", "yy"), "qid").select("qid", F.greatest(F.lit(0.0), F.col("yy").cast("double") - F.col("explained")).alias("residual"))


def segment(arr: IndexedArray, buf: LagrangeBuffer, squares: LagrangeBuffer, arr2: IndexedArray, segments: int, degree: int = 1, tries: int = 32) -> list[tuple[int, int, float]]:
    """Top-down segmentation: the segment with the greatest residual is split where the two fits leave least.

    Cuts are tried at `tries` even places, then again between the neighbours of the best
    one, until the places tried stand next to each other. Each round is one batch of ranges.
    Fewer than eight tries are taken as eight: two or three would try the same places for ever.
    """
    spark, steps = arr.df.sparkSession, max(8, tries) - 1

    def energies(spans: list[tuple[int, int]]) -> list[float]:
        r = spark.createDataFrame([(i, p, q) for i, (p, q) in enumerate(spans)], "qid long, p long, q long")
        m = moments_of_ranges(arr, buf, r, degree, wide=True).join(F.broadcast(r), "qid")
        got = residual(fit_poly(m, degree), query_lagrange(arr2, squares, r, wide=True)).collect()  # one row for each asked span
        by = {x["qid"]: x["residual"] for x in got}
        return [by[i] if by[i] is not None else 0.0 for i in range(len(spans))]

    done = [(0, arr.n - 1, energies([(0, arr.n - 1)])[0])]
    while len(done) < segments:
        done.sort(key=lambda x: x[2])
        p, q, _ = done[-1]
        lo, hi, known = p + degree + 1, q - degree, {}
        if lo > hi:
            break
        while True:
            cuts = sorted({lo + (hi - lo) * i // steps for i in range(steps + 1)} - known.keys())
            if cuts:
                e = energies([s for c in cuts for s in ((p, c - 1), (c, q))])
                known |= {c: (e[2 * i], e[2 * i + 1]) for i, c in enumerate(cuts)}
            tried = sorted(known)
            at = min(range(len(tried)), key=lambda i: (sum(known[tried[i]]), i))
            left, right = tried[max(0, at - 1)], tried[min(len(tried) - 1, at + 1)]
            if right - left <= 2:
                break
            lo, hi = left, right
        c = tried[at]
        done[-1:] = [(p, c - 1, known[c][0]), (c, q, known[c][1])]
    return sorted(done)


def additive_moments(df: DataFrame, dims: list[str], idx: Column, val: Column, order: int, how: str = "rollup", sets: list[list[str]] | None = None) -> DataFrame:
    """dims, m0 .. m{order} with subtotals by rollup, cube or grouping sets: raw moments add up over groups."""
    rows = df.select(*dims, idx.cast("long").alias("i"), val.alias("v"))
    aggs = [F.sum((power(F.col("i"), k) * F.col("v")).cast(BIG)).cast("long").alias(f"m{k}") for k in range(order + 1)]
    if how == "grouping_sets":
        return rows.groupingSets([[F.col(c) for c in s] for s in sets], *dims).agg(*aggs)
    return getattr(rows, how)(*dims).agg(*aggs)


def rect_moments(cells: DataFrame, rects: DataFrame, b: int) -> DataFrame:
    """qid, sum, m1x over rectangles of a two-dimensional array (i0, i1, val) by a product of hat weights.

    cells of the buffer: weighted sums over b x b bins and their neighbours; the residual is
    read along the rectangles' borders (the frame), where the product of interpolants errs.
    Whole numbers throughout: weights times b * b, divided once at the end.
    """
    big = lambda x: x.cast(BIG)
    f0 = lambda x: F.when((x >= F.col("p0")) & (x <= F.col("q0")), 1).otherwise(0)
    f1 = lambda x: F.when((x >= F.col("p1")) & (x <= F.col("q1")), 1).otherwise(0)
    g0 = lambda x: f0(x) * x
    c = cells.withColumn("b0", F.expr(f"i0 div {b}")).withColumn("b1", F.expr(f"i1 div {b}"))
    t0, t1 = (F.expr(f"i{a} % {b}") for a in (0, 1))
    w = {(u, v): (t0 if u else b - t0) * (t1 if v else b - t1) for u in (0, 1) for v in (0, 1)}
    sums = c.groupBy("b0", "b1").agg(*[big(F.sum(big(big(x) * big(F.col("val"))))).alias(f"s{u}{v}") for (u, v), x in w.items()])
    buf = sums.select(F.inline(F.array(*[F.struct((F.col("b0") + u).alias("k0"), (F.col("b1") + v).alias("k1"), F.col(f"s{u}{v}").alias("v")) for u, v in w]))).groupBy("k0", "k1").agg(big(F.sum("v")).alias("v"))
    # Buffer cells inside a rectangle: pieces of the first axis by equality, the second axis by its bounds.
    n0 = rects.select(*[F.expr(f"(p{a} + {b - 1}) div {b}").alias(f"first{a}") for a in (0, 1)], *[F.expr(f"q{a} div {b}").alias(f"last{a}") for a in (0, 1)], "*").where("first0 <= last0")
    known = ends(rects.select(F.col("p0").alias("p"), F.col("q0").alias("q")))
    lengths = None if known is None else known[:, 1] // b + (-known[:, 0] // b) + 1
    inner = match(buf, "k0", n0, "first0", "last0", 1 << 40, known, lengths).where(F.col("k1").between(F.col("first1"), F.col("last1")))
    inner = inner.select("qid", F.col("v").alias("x"), big(F.col("v") * big(F.col("k0") * b)).alias("y"))
    # The frame: bins of three strips across each axis, each strip by equality; those across the second axis leave out what the others hold.
    strips = lambda a: F.array_distinct(F.array(F.expr(f"p{a} div {b}"), F.expr(f"p{a} div {b}") - 1, F.expr(f"q{a} div {b}")))
    within = lambda x, a: F.col(x).between(F.expr(f"p{a} div {b}") - 1, F.expr(f"q{a} div {b}"))
    across0 = c.join(beside(rects.withColumn("b0", F.explode(strips(0))), known), "b0").where(within("b1", 1))
    across1 = c.join(beside(rects.withColumn("b1", F.explode(strips(1))), known), "b1").where(within("b0", 0) & ~F.array_contains(strips(0), F.col("b0")))
    frame = across0.unionByName(across1)

    def rest(h0, h1):
        out = h0(F.col("i0")) * h1(F.col("i1")) * b * b
        for (u, v), x in w.items():
            out = out - h0((F.col("b0") + u) * b) * h1((F.col("b1") + v) * b) * x
        return out

    outer = frame.select("qid", *[big(big(rest(h, f1)) * big(F.col("val"))).alias(c) for c, h in (("x", f0), ("y", g0))])
    got = inner.unionByName(outer).groupBy("qid").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
    answer = lambda c: F.coalesce((big(F.col(c)) / big(F.lit(b * b))).cast("long"), F.lit(0).cast("long"))
    return rects.select("qid").join(got, "qid", "left").select("qid", answer("x").alias("total"), answer("y").alias("m1"))
