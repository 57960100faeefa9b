"""Overlapped buffer with any weights: cell k of the buffer is the weighted sum of the cells around position k b."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG
from momentbuf.functions.weights import Stencil
from momentbuf.operators.lagrange_buffer import asked_of, candidates
from momentbuf.operators.ranges import beside, ends, match, needed, settled
from momentbuf.sources.arrays import IndexedArray

Weight = Callable[[Column, int], Column]


def num(x: Column, scale: int) -> Column:
    """Whole numbers where there is a scale, else as they come."""
    return x.cast(BIG) if scale else x


def whole(weight: Weight, scale: int) -> Weight:
    """The weight, or its multiple as a whole number."""
    return (lambda offset, b: F.rint(weight(offset, b) * float(scale)).cast("long")) if scale else weight


def build_overlap(arr: IndexedArray, b: int, M: int, Mp: int, weight: Weight, guard: bool = False, scale: int = 0) -> DataFrame:
    """cell, v. A bin's cells are summed once for each of the M + M' buffer cells they reach; only these sums move.

    weight(offset, b): weight of a cell `offset` after the buffer cell's position.
    guard: keep cells that stand outside the array (queries never need them).
    scale: what the weights' multiples are whole for; cells then hold so many times their sums, in DECIMAL.
    """
    weight = whole(weight, scale)
    bin_, r = F.expr(f"idx div {b}"), F.expr(f"idx % {b}")
    ks = range(1 - Mp, M + 1)
    sums = arr.df.groupBy(bin_.alias("bin")).agg(*[F.sum(num(weight(r - k * b, b) * num(F.col("val"), scale), scale)).alias(f"s{i}") for i, k in enumerate(ks)])
    out = sums.select(F.inline(F.array(*[F.struct((F.col("bin") + k).alias("cell"), F.col(f"s{i}").alias("v")) for i, k in enumerate(ks)])))
    if not guard:
        out = out.where((F.col("cell") >= 0) & (F.col("cell") * b < arr.n))
    return out.groupBy("cell").agg(num(F.sum("v"), scale).alias("v"))


def delta_expr(f: Callable[[Column], Column], idx: Column, b: int, M: int, Mp: int, weight: Weight, scale: int = 0) -> Column:
    """What the buffer leaves to the array at a cell, times the scale if there is one: f minus its reconstruction from samples at the bins' edges."""
    weight = whole(weight, scale)
    bin_, r = F.call_function("div", idx, F.lit(b)), F.pmod(idx, F.lit(b))
    out = f(idx) * scale if scale else f(idx)
    for k in range(1 - Mp, M + 1):
        out = out - f((bin_ + k) * b) * weight(r - k * b, b)
    return out


def query_overlap(arr: IndexedArray, buf: DataFrame, b: int, M: int, Mp: int, weight: Weight, f: Callable[[Column], Column], ranges: DataFrame, scan: str = "full", scale: int = 0) -> DataFrame:
    """qid, result of sum f(i) a_i for any f, which sees position and the range's columns and is cut to [p, q].

    scan: "full" reads the residual from every cell of the range and of the bins its
    samples reach; "candidates" only from the bins around its ends, which is the whole
    residual where the weights reproduce f inside (a hat: lines; N nodes: degrees below N).
    Both are joins by equality; cells whose residual is zero for want of samples don't meet a range.
    scale: that of a buffer in whole numbers; f and the array must then be whole, and results are exact BIGINT.
    """
    if scan not in ("full", "candidates"):
        raise ValueError(f"scan must be full or candidates, not {scan}")
    cut = lambda x: F.when((x >= F.col("p")) & (x <= F.col("q")), f(x).cast("long") if scale else f(x)).otherwise(F.lit(0).cast("long") if scale else F.lit(0.0))
    ranges = settled(ranges)
    known = ends(ranges)
    runs = ranges.withColumn("first_", F.expr(f"(p + {b - 1}) div {b}")).withColumn("last_", F.expr(f"q div {b}"))
    lo = hi = lengths = kn = None
    if known is not None:
        p, q = known[:, 0], known[:, 1]
        first, last = -(-p // b), q // b
        kn = last - first + 1
        lo, hi = np.minimum(p, (first - M) * b), np.maximum(q, (last + Mp) * b - 1)
        lengths = hi - lo + 1
    samples = match(buf, "cell", runs.where("first_ <= last_"), "first_", "last_", -(-arr.n // b), known, kn).select("qid", num(cut(F.col("cell") * b) * F.col("v"), scale).alias("x"))
    if scan == "full":
        wide = runs.withColumn("lo_", F.least("p", F.greatest(F.lit(0), (F.col("first_") - M) * b))).withColumn("hi_", F.greatest("q", (F.col("last_") + Mp) * b - 1))
        near = match(needed(arr, lo, hi), "idx", wide, "lo_", "hi_", arr.n + Mp * b, known, lengths)
    else:
        st = Stencil(M, Mp)
        span = (None, None) if known is None else asked_of(known, b, 0, st)
        near = needed(arr, *span).withColumn("bin", F.expr(f"idx div {b}")).join(beside(candidates(ranges, b, 0, st, -(-arr.n // b)), known), "bin")
    near = near.withColumn("delta_", delta_expr(cut, F.col("idx"), b, M, Mp, weight, scale))
    near = near.where("delta_ <> 0") if scale else near
    rest = near.select("qid", num(F.col("delta_") * num(F.col("val"), scale), scale).alias("x"))
    got = samples.unionByName(rest).groupBy("qid").agg(F.sum("x").alias("result"))
    got = got.withColumn("result", (num(F.col("result"), scale) / F.lit(scale).cast(BIG)).cast("long")) if scale else got
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("result", F.lit(0).cast("long") if scale else F.lit(0.0)).alias("result"))


def check_edge_condition(b: int, M: int, Mp: int, weight: Callable[[int], float]) -> bool:
    """Whether the weight at the other buffer cells' positions is zero and at the own one is one."""
    return all(abs(weight(k * b) - (k == 0)) < 1e-12 for k in range(-M, Mp))
