"""Approximate answers from the buffer alone, bettered by one endpoint bin after another."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momentbuf.functions.weights import Stencil, lagrange_eval
from momentbuf.operators.lagrange_buffer import ONE, LagrangeBuffer, Poly, _delta, _near, _parts, _result
from momentbuf.operators.ranges import settled
from momentbuf.sources.arrays import IndexedArray


def approx_lagrange(buf: LagrangeBuffer, ranges: DataFrame, f: Poly | None = None) -> DataFrame:
    """qid, estimate: sum of the samples times the top cells; no array access."""
    if buf.mode == "residue":
        raise ValueError("remainders have no size, so they give no estimates: build in mode 'exact' or 'double'")
    f, ranges = f or ONE, settled(ranges)
    got = _parts(None, buf, ranges, {"x": f}, only_top=True).groupBy("qid").agg(_result(buf).alias("estimate"))
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("estimate", F.lit(0).cast("long") if buf.mode == "exact" else F.lit(0.0)).alias("estimate"))


def progressive(arr: IndexedArray, buf: LagrangeBuffer, ranges: DataFrame, f: Poly | None = None, kappa: float = 0.0) -> DataFrame:
    """qid, ring, estimate, bound of a one-level buffer: ring 0 is the buffer alone, ring j adds the bins whose distance from an end's bin is below j.

    One scan of all N - 1 bins at each end; rings are a running sum.
    """
    f, ranges = f or ONE, settled(ranges)
    b, st = buf.b, buf.stencil
    ring = F.least(F.abs(F.col("bin") - F.expr(f"p div {b}")), F.abs(F.col("bin") - F.expr(f"q div {b}"))) + 1
    cells = _near(arr, buf, ranges, 0).withColumn("v", F.col("v").cast("double")).withColumn("ring", ring)
    rest = cells.groupBy("qid", "ring").agg(F.sum(_delta(f, 0, b, st, "double") * F.col("v")).alias("x"))
    start = _parts(None, buf, ranges, {"x": f}, only_top=True).groupBy("qid").agg(_result(buf).cast("double").alias("x")).select("qid", F.lit(0).cast("long").alias("ring"), "x")
    rings = ranges.select("qid", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(st.n).cast("long"))).alias("ring"))
    have = rings.join(start.unionByName(rest), ["qid", "ring"], "left")
    run = Window.partitionBy("qid").orderBy("ring").rowsBetween(Window.unboundedPreceding, 0)
    return have.select("qid", "ring", F.coalesce(F.sum("x").over(run), F.lit(0.0)).alias("estimate"), (F.lit(2.0 * kappa * b) * (F.col("ring") < st.n).cast("double")).alias("bound"))


def residual_profile(n: int, b: int) -> dict[int, list[float]]:
    """delta of the step function that starts in the middle of a bin, by the bin's distance."""
    st = Stencil.of(n)
    at = b // 2
    f = lambda x: Fraction(int(x >= at))
    out = {}
    for d in range(1 - st.M, st.Mp):
        out[d] = [float(f(d * b + r) - sum(f((d + k) * b) * st.exact(k, r, b) for k in st.nodes)) for r in range(b)]
    return out


def error_share(n: int, b: int, kept: int) -> dict[str, float]:
    """Share of the endpoint error that `kept` centre bins remove, under four readings of the measure."""
    prof = residual_profile(n, b)
    near = set(sorted(prof, key=lambda d: (abs(d), d))[:kept])
    l1 = lambda ds: sum(abs(x) for d in ds for x in prof[d])
    l2 = lambda ds: sum(x * x for d in ds for x in prof[d])
    sup = lambda ds: max((abs(x) for d in ds for x in prof[d]), default=0.0)
    rest = [d for d in prof if d not in near]
    side = l1([d for d in rest if d > 0])
    return {"l1": 1 - l1(rest) / l1(prof), "energy": 1 - l2(rest) / l2(prof), "sup": 1 - sup(rest) / sup(prof), "one_side": 1 - side / (l1(prof) / 2) if side else 1.0}


def measured_share(arr: IndexedArray, n: int, b: int, kept: int) -> DataFrame:
    """error_share over the cells of an array, for steps in the middle of every bin: what a step leaves at a cell, times the cell."""
    prof, v = residual_profile(n, b), F.col("val").cast("double")
    near = sorted(prof, key=lambda d: (abs(d), d))[:kept]
    table = arr.df.sparkSession.createDataFrame([(d, r, x) for d, xs in prof.items() for r, x in enumerate(xs)], "d int, r long, rest double")
    cells = arr.df.groupBy(F.expr(f"idx % {b}").alias("r")).agg(F.sum(F.abs(v)).alias("a"), F.sum(v * v).alias("e"), F.max(F.abs(v)).alias("m")).join(F.broadcast(table), "r")
    l1, l2, sup = F.col("a") * F.abs("rest"), F.col("e") * F.col("rest") * F.col("rest"), F.col("m") * F.abs("rest")
    far = lambda x: F.when(~F.col("d").isin(near), x).otherwise(0.0)
    share = lambda agg, x: 1 - agg(far(x)) / agg(x)
    side = F.sum(F.when(F.col("d") > 0, far(l1)).otherwise(0.0))
    return cells.agg(share(F.sum, l1).alias("l1"), share(F.sum, l2).alias("energy"), share(F.max, sup).alias("sup"), (1 - side / (F.sum(l1) / 2)).alias("one_side"))


def influence(n: int) -> dict[int, float]:
    """Largest weight that a sample has in a bin, by the sample's distance."""
    st = Stencil.of(n)
    return {k: max(abs(float(st.exact(k, r, 256))) for r in range(257)) for k in st.nodes}


def step_profile(spark: SparkSession, n: int, b: int, span: int | None = None) -> DataFrame:
    """i, f, h: a step function and its bin-wise interpolant."""
    st = Stencil.of(n)
    span = span or 2 * n
    at = span * b // 2 + b // 2
    f = lambda x: Fraction(int(x >= at))
    rows = [(i, float(f(i)), float(lagrange_eval({k: f((i // b + k) * b) for k in st.nodes}, Fraction(i % b, b)))) for i in range(span * b)]
    return spark.createDataFrame(rows, "i long, f double, h double")


def error_bound(method: str, n_moments: int, K: int, n: int, kappa: float) -> float:
    """Worst error of a range sum from the buffer alone for |a| <= kappa at K numbers of memory."""
    if method == "bins_inner":
        return 2 * kappa * n_moments * n / K
    if method == "bins_half":
        return kappa * n_moments * n / K
    return kappa * n / K if n_moments == 2 else 2 * kappa * n / K
