"""Pyramid bin buffer: bins of bins, in storage of their own or in place.

Level 1 has bins of b cells, level l bins of b^l. In place, a cell whose number is
divisible by b holds its highest level's state; what it held before is had back by
inverting the merge: parent minus siblings.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momentbuf.functions.algebra import AggSpec, merged_states
from momentbuf.functions.weights import num_levels
from momentbuf.operators.binbuf import BinBuffer, add_cells, build_bins, few
from momentbuf.operators.ranges import ends, match, needed, settled
from momentbuf.sources.arrays import IndexedArray


@dataclass(frozen=True)
class PyramidBuffer:
    df: DataFrame  # level, cell, state
    b: int
    n: int
    levels: int
    spec: AggSpec
    inplace: bool = False


def build_pyramid(arr: IndexedArray, spec: AggSpec, b: int, levels: int | None = None, inplace: bool = False) -> PyramidBuffer:
    """Each level aggregates the one below; states about a bin's start are moved to its parent's start first."""
    levels = levels or num_levels(arr.n, b, 2)
    if inplace and not spec.invertible:
        raise ValueError(f"{spec.name} can't be stored in place: overwritten states could not be had back")
    cur = build_bins(arr, spec, b).df.select(F.col("bin").alias("cell"), *spec.state)
    out = cur.withColumn("level", F.lit(1))
    for lv in range(2, levels + 1):
        width = b ** (lv - 1)
        cur = cur.select(F.expr(f"cell div {b}").alias("cell"), *spec.shift(F.expr(f"cell % {b}") * width)).groupBy("cell").agg(*spec.merge())
        out = out.unionByName(cur.withColumn("level", F.lit(lv)))
    pyr = PyramidBuffer(out.select("level", "cell", *spec.state), b, arr.n, levels, spec)
    return to_inplace(pyr) if inplace else pyr


def to_inplace(pyr: PyramidBuffer) -> PyramidBuffer:
    """One state a level-1 cell: that of its highest level. No exchange: a level keeps the cells its parent level doesn't overwrite."""
    kept = pyr.df.where((F.col("level") == pyr.levels) | (F.col("cell") % pyr.b != 0))
    return replace(pyr, df=kept, inplace=True)


def recover(pyr: PyramidBuffer) -> PyramidBuffer:
    """All levels of an in-place pyramid: from the top down, an overwritten cell is its parent minus its b - 1 siblings."""
    if not pyr.inplace:
        return pyr
    spec, b = pyr.spec, pyr.b
    out = pyr.df.where(F.col("level") == pyr.levels)
    upper = out
    for lv in range(pyr.levels - 1, 0, -1):
        own = pyr.df.where(F.col("level") == lv)
        width = b**lv
        moved = own.select(F.expr(f"cell div {b}").alias("parent"), *spec.shift(F.expr(f"cell % {b}") * width)).groupBy("parent").agg(*spec.merge())
        sib = moved.select("parent", *[F.col(c).alias(f"o_{c}") for c in spec.state])
        first = upper.join(sib, upper["cell"] == sib["parent"], "left").select(F.lit(lv).alias("level"), (F.col("cell") * b).alias("cell"), *[spec.invert(F.col(c), F.coalesce(f"o_{c}", F.lit(0))).alias(c) for c in spec.state])
        upper = own.select("level", "cell", *spec.state).unionByName(first)
        out = out.unionByName(upper)
    return replace(pyr, df=out, inplace=False)


def cover(ranges: DataFrame, b: int, levels: int) -> DataFrame:
    """qid, p, level, cell: the two-sided greedy cover; level 0 are array cells. At most 2(b-1) cells a level below the top."""
    r = ranges.select("qid", "p", "q").withColumn("lo", F.col("p")).withColumn("hi", F.col("q") + 1)
    out = None
    for lv in range(levels + 1):
        if lv == levels:
            cells = F.when(F.col("lo") < F.col("hi"), F.sequence("lo", F.col("hi") - 1))
            part = r.select("qid", "p", F.lit(lv).alias("level"), F.explode(cells).alias("cell"))
        else:
            up_lo, down_hi = F.expr(f"(lo + {b - 1}) div {b}"), F.expr(f"hi div {b}")
            r = r.withColumn("up", up_lo).withColumn("down", down_hi)
            meet = F.col("up") <= F.col("down")
            left_end = F.when(meet, F.col("up") * b).otherwise(F.col("hi"))
            right = F.when(meet & (F.col("down") * b < F.col("hi")), F.sequence(F.col("down") * b, F.col("hi") - 1)).otherwise(F.array().cast("array<bigint>"))
            left = F.when(F.col("lo") < left_end, F.sequence(F.col("lo"), left_end - 1)).otherwise(F.array().cast("array<bigint>"))
            part = r.select("qid", "p", F.lit(lv).alias("level"), F.explode(F.concat(left, right)).alias("cell"))
            r = r.select("qid", "p", "q", F.when(meet, F.col("up")).otherwise(0).alias("lo"), F.when(meet, F.col("down")).otherwise(0).alias("hi"))
        out = part if out is None else out.unionByName(part)
    return out


def cover_runs(ranges: DataFrame, b: int, levels: int, inplace: bool = False) -> DataFrame:
    """qid, p, level, lo, hi, sign: the cover as runs of cells, at most two a level.

    In place, the first cell of a right-hand run is overwritten wherever its level isn't
    the top one. It is its parent minus its siblings; together with the rest of the run
    that is the parent minus the siblings behind the run, and so on upwards while the
    parent is overwritten too. So only cells of the flank are read, none is restored.
    """
    r = ranges.select("qid", "p", F.col("p").alias("lo"), (F.col("q") + 1).alias("hi"))
    none = F.lit(None).cast("struct<level:int,lo:bigint,hi:bigint,sign:int>")

    def run(level: int, lo: Column, hi: Column, sign: int = 1) -> Column:
        return F.struct(F.lit(level).alias("level"), lo.cast("long").alias("lo"), hi.cast("long").alias("hi"), F.lit(sign).alias("sign"))

    out = None
    for lv in range(levels + 1):
        lo, hi = F.col("lo"), F.col("hi")
        if lv == levels:
            runs = [run(lv, lo, hi - 1)]
        else:
            up, down = F.expr(f"(lo + {b - 1}) div {b}"), F.expr(f"hi div {b}")
            meet = up <= down
            runs = [run(lv, lo, F.when(meet, up * b).otherwise(hi) - 1)]
            right = meet & (down * b < hi)
            if not inplace or lv == 0:
                runs.append(F.when(right, run(lv, down * b, hi - 1)).otherwise(none))
            else:
                runs.append(F.when(right, run(lv, hi, down * b + b - 1, -1)).otherwise(none))
                wanted = right
                for above in range(lv + 1, levels + 1):
                    parent = F.expr(f"hi div {b ** (above - lv)}")
                    if above == levels:
                        runs.append(F.when(wanted, run(above, parent, parent)).otherwise(none))
                    else:
                        lost = parent % b == 0
                        runs.append(F.when(wanted & ~lost, run(above, parent, parent)).otherwise(none))
                        runs.append(F.when(wanted & lost, run(above, parent + 1, parent + b - 1, -1)).otherwise(none))
                        wanted = wanted & lost
        part = r.select("qid", "p", F.inline(F.filter(F.array(*runs), lambda x: x.isNotNull())))
        out = part if out is None else out.unionByName(part)
        if lv < levels:
            r = r.select("qid", "p", F.when(meet, up).otherwise(0).alias("lo"), F.when(meet, down).otherwise(0).alias("hi"))
    return out.where("lo <= hi")


def query_pyramid(arr: IndexedArray, pyr: PyramidBuffer, ranges: DataFrame, costs: bool = False) -> DataFrame:
    """qid, result of each range from its cover; of the array only the fragments' own intervals are asked."""
    spec, b, top, ranges = pyr.spec, pyr.b, pyr.levels, settled(ranges)
    known = ends(ranges)
    runs = cover_runs(ranges, b, top, pyr.inplace)
    lo = hi = short = long = None
    if known is not None:
        p, q = known[:, 0], known[:, 1]
        first, last = -(-p // b), (q + 1) // b
        one = first > last
        lo, hi = np.r_[p, np.maximum(last * b, p)], np.r_[np.where(one, q, first * b - 1), q]
        short = np.unique(np.minimum(hi, lo + b) - lo + 1)
        long = np.unique(np.r_[1, b, (q - p) // b**top + 2])
    zero = F.lit(0).cast("long")
    base = match(needed(arr, lo, hi), "idx", runs.where("level = 0").withColumnsRenamed({"lo": "lo_", "hi": "hi_"}), "lo_", "hi_", arr.n, known, short)
    low = base.groupBy("qid").agg(*spec.lift(F.col("idx"), F.col("val"), F.col("p")), F.count("*").alias("cells_array")).withColumn("cells_buffer", zero)
    width = F.element_at(F.array(*[F.lit(b**lv) for lv in range(1, top + 1)]), F.col("level").cast("int"))
    met = match(pyr.df, "cell", runs.where("level > 0").withColumnsRenamed({"lo": "lo_", "hi": "hi_"}), "lo_", "hi_", -(-pyr.n // b), known, long, ("level",))
    high = met.select("qid", "sign", *spec.shift(F.col("cell") * width - F.col("p")))
    if pyr.inplace:
        high = high.select("qid", *[(F.col("sign") * F.col(c)).alias(c) for c in spec.state])
    if spec.most:
        high = merged_states(high, ["qid"], spec).join(high.groupBy("qid").agg(F.count("*").alias("cells_buffer")), "qid").withColumn("cells_array", zero)
    else:
        high = high.groupBy("qid").agg(*spec.merge(), F.count("*").alias("cells_buffer")).withColumn("cells_array", zero)
    both = low.unionByName(high)
    got = merged_states(both, ["qid"], spec).join(both.groupBy("qid").agg(F.sum("cells_array").alias("cells_array"), F.sum("cells_buffer").alias("cells_buffer")), "qid") if spec.most else both.groupBy("qid").agg(*spec.merge(), F.sum("cells_array").alias("cells_array"), F.sum("cells_buffer").alias("cells_buffer"))
    more = [F.coalesce(c, zero).alias(c) for c in ("cells_array", "cells_buffer")] if costs else []
    return ranges.select("qid").join(got, "qid", "left").select("qid", spec.finish().alias("result"), *more)


def update_pyramid(pyr: PyramidBuffer, updates: DataFrame) -> PyramidBuffer:
    """Linear update of the path to the root; in place, of the cells that still hold their own level. A batch that is small leaves the buffer where it lies."""
    spec, b, key = pyr.spec, pyr.b, ["level", "cell"]
    kinds = {f.name: f.dataType for f in pyr.df.schema}
    rows = updates.select("delta", "idx", F.explode(F.sequence(F.lit(1), F.lit(pyr.levels))).alias("level"))
    width = F.element_at(F.array(*[F.lit(b**lv).cast("long") for lv in range(1, pyr.levels + 1)]), F.col("level"))
    rows = rows.withColumn("width", width).withColumn("cell", F.expr("idx div width"))
    if pyr.inplace:
        rows = rows.where((F.col("level") == pyr.levels) | (F.col("cell") % b != 0))
    unit = spec.unit(F.col("idx") - F.col("cell") * F.col("width"))
    delta = rows.select(*key, *[(u * F.col("delta")).alias(c) for u, c in zip(unit, spec.state, strict=True)]).groupBy(*key).agg(*spec.merge())
    delta = delta.select(*key, *[F.col(c).cast(kinds[c]).alias(c) for c in spec.state])
    if few(updates):
        return replace(pyr, df=add_cells(pyr.df, delta, key, {c: (F.col(c) + F.col(f"d_{c}")).cast(kinds[c]) for c in spec.state}))
    return replace(pyr, df=pyr.df.unionByName(delta).groupBy(*key).agg(*spec.merge()))


def refresh_pyramid(arr: IndexedArray, pyr: PyramidBuffer, touched: DataFrame) -> PyramidBuffer:
    """General update: touched bins from the (changed) array, then each touched parent from its b children."""
    spec, b = pyr.spec, pyr.b
    bins = touched.select(F.expr(f"idx div {b}").alias("cell")).distinct()
    near = arr.df.withColumn("cell", F.expr(f"idx div {b}")).join(F.broadcast(bins), "cell", "left_semi")
    fresh = build_bins(arr.with_df(near.select("idx", "val")), spec, b).df.select(F.col("bin").alias("cell"), *spec.state)
    out = None
    for lv in range(1, pyr.levels + 1):
        old = pyr.df.where(F.col("level") == lv).select("cell", *spec.state)
        level = old.join(F.broadcast(bins), "cell", "left_anti").unionByName(fresh)
        out = level.withColumn("level", F.lit(lv)) if out is None else out.unionByName(level.withColumn("level", F.lit(lv)))
        parents = bins.select(F.expr(f"cell div {b}").alias("cell")).distinct()
        kids = level.withColumn("parent", F.expr(f"cell div {b}")).join(F.broadcast(parents.withColumnRenamed("cell", "parent")), "parent", "left_semi")
        fresh = kids.select(F.col("parent").alias("cell"), *spec.shift(F.expr(f"cell % {b}") * b**lv)).groupBy("cell").agg(*spec.merge())
        bins = parents
    return replace(pyr, df=out.select("level", "cell", *spec.state))


def as_bins(pyr: PyramidBuffer) -> BinBuffer:
    return BinBuffer(recover(pyr).df.where("level = 1").select(F.col("cell").alias("bin"), *pyr.spec.state), pyr.b, pyr.n, pyr.spec)
