"""Disjoint-bin buffer: one state per bin; a range is whole bins from the buffer and two fragments from the array."""

from __future__ import annotations

from dataclasses import dataclass
from math import isqrt

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momentbuf.functions.algebra import AggSpec, merged_states
from momentbuf.operators.ranges import BATCH, beside, ends, inside, match, needed, settled, split_to_bins
from momentbuf.sources.arrays import IndexedArray


@dataclass(frozen=True)
class BinBuffer:
    df: DataFrame
    b: int
    n: int
    spec: AggSpec
    keys: tuple[str, ...] = ()
    stored: bool = False  # read from files: bounds on bin reach the scan


def optimal_bin(n: int) -> int:
    """The bin size that balances whole bins and fragments: the root of n, rounded up."""
    r = isqrt(max(0, n - 1)) + 1 if n > 1 else 1
    return r


def build_bins(arr: IndexedArray, spec: AggSpec, b: int) -> BinBuffer:
    """One aggregation; states are combined within tasks, so an array clustered by index moves about a row per bin."""
    rows = arr.df.withColumn("bin", F.expr(f"idx div {b}"))
    return BinBuffer(rows.groupBy(*arr.keys, "bin").agg(*spec.lift(F.col("idx"), F.col("val"), F.col("bin") * b)), b, arr.n, spec, arr.keys)


def with_count(buf: BinBuffer) -> DataFrame:
    """The buffer with each bin's number of cells, which fixed bins need not store."""
    return buf.df.withColumn("cells", F.least(F.lit(buf.b), F.lit(buf.n) - F.col("bin") * buf.b).cast("long"))


def _fragments(arr: IndexedArray, spec: AggSpec, ranges: DataFrame, frags: DataFrame, b: int) -> DataFrame:
    """States of fragments about each range's start. The array is joined by bin, and only the fragments' own intervals are asked of its scan."""
    known, lo, hi = ends(ranges), None, None
    if known is not None:
        p, q = known[:, 0], known[:, 1]
        first, last = -(-p // b), (q + 1) // b
        lo, hi = np.r_[p, np.maximum(last * b, p)], np.r_[np.minimum(first * b - 1, q), q]
    rows = needed(arr, lo, hi).withColumn("bin", F.expr(f"idx div {b}")).join(beside(frags, known), "bin").where(F.col("idx").between(F.col("lo"), F.col("hi")))
    lifted = rows.groupBy(*arr.keys, "qid").agg(*spec.lift(F.col("idx"), F.col("val"), F.col("p")), F.count("*").alias("cells_array"))
    return lifted


def _middles(buf: BinBuffer, ranges: DataFrame, middles: DataFrame) -> DataFrame:
    """States of whole bins about each range's start, and how many there are."""
    known, lengths, cells = ends(ranges), None, buf.df
    if known is not None:
        first, last = -(-known[:, 0] // buf.b), (known[:, 1] + 1) // buf.b - 1
        lengths = last - first + 1
        cells = cells.where(inside("bin", first - 1, last + 1)) if buf.stored else cells  # one more on either side: some rules count bins that are partly covered
    rows = match(cells, "bin", middles, "first", "last", -(-buf.n // buf.b), known, lengths)
    by = [*buf.keys, "qid"]
    moved = rows.select(*by, *buf.spec.shift(F.col("bin") * buf.b - F.col("p")))
    if buf.spec.most:
        return merged_states(moved, by, buf.spec).join(moved.groupBy(*by).agg(F.count("*").alias("cells_buffer")), by)
    return moved.groupBy(*by).agg(*buf.spec.merge(), F.count("*").alias("cells_buffer"))


def query_bins(arr: IndexedArray, buf: BinBuffer, ranges: DataFrame, costs: bool = False, aligned_only: bool = False) -> DataFrame:
    """qid (and keys), result of each range; costs: cells read from the array and the buffer too.

    A batch of at most `ranges.BATCH` ranges is broadcast and its ends are pushed into
    the array's scan; a larger one is joined by exchange. aligned_only says that all
    ranges are whole bins and leaves the array out of the plan.
    """
    spec, ranges = buf.spec, settled(ranges)
    frags, middles = split_to_bins(ranges, buf.b)
    zero = F.lit(0).cast("long")
    by = [*buf.keys, "qid"]
    parts = _middles(buf, ranges, middles).withColumn("cells_array", zero)
    if not aligned_only:
        parts = parts.unionByName(_fragments(arr, spec, ranges, frags, buf.b).withColumn("cells_buffer", zero))
    counts = [F.sum("cells_array").alias("cells_array"), F.sum("cells_buffer").alias("cells_buffer")]
    got = merged_states(parts, by, spec).join(parts.groupBy(*by).agg(*counts), by) if spec.most else parts.groupBy(*by).agg(*spec.merge(), *counts)
    every = ranges.select("qid") if not buf.keys else ranges.select("qid").join(F.broadcast(buf.df.select(*buf.keys).distinct()))
    out = every.join(got, by, "left")
    more = [F.coalesce(c, zero).alias(c) for c in ("cells_array", "cells_buffer")] if costs else []
    return out.select(*by, spec.finish().alias("result"), *more)


def add_cells(base: DataFrame, delta: DataFrame, key: list[str], values: dict[str, Column]) -> DataFrame:
    """Base with delta added cell by cell, without moving base: delta is broadcast, and cells that base lacks are appended.

    delta must be small and have each key once; values: for each value column the sum of
    it and the delta's column d_<name>, both never null.
    """
    d = F.broadcast(delta.select(*key, *[F.col(c).alias(f"d_{c}") for c in values]))
    both = base.join(d, key, "left").select(*key, *[F.when(F.col(f"d_{c}").isNull(), F.col(c)).otherwise(x).alias(c) for c, x in values.items()])
    met = base.join(F.broadcast(delta.select(*key)), key, "left_semi").select(*key)
    return both.unionByName(delta.join(F.broadcast(met), key, "left_anti").select(*key, *values))


def few(df: DataFrame) -> bool:
    """Whether a batch of updates is small enough to broadcast the cells it touches."""
    return df.select(F.lit(1)).limit(BATCH + 1).count() <= BATCH


def apply_updates(buf: BinBuffer, updates: DataFrame) -> BinBuffer:
    """Linear update: deltas times the unit response, added to their bins. updates: (keys,) idx, delta. A batch that is small leaves the buffer where it lies."""
    spec, key = buf.spec, [*buf.keys, "bin"]
    rows = updates.withColumn("bin", F.expr(f"idx div {buf.b}"))
    unit = spec.unit(F.col("idx") - F.col("bin") * buf.b)
    kinds = {f.name: f.dataType for f in buf.df.schema}
    lifted = rows.select(*key, *[(u * F.col("delta")).alias(c) for u, c in zip(unit, spec.state, strict=True)]).groupBy(*key).agg(*spec.merge())
    lifted = lifted.select(*key, *[F.col(c).cast(kinds[c]).alias(c) for c in spec.state])
    if few(updates):
        both = add_cells(buf.df.select(*key, *spec.state), lifted, key, {c: (F.col(c) + F.col(f"d_{c}")).cast(kinds[c]) for c in spec.state})
    else:
        both = buf.df.select(*key, *spec.state).unionByName(lifted).groupBy(*key).agg(*spec.merge())
    return BinBuffer(both, buf.b, buf.n, spec, buf.keys)


def updated(arr: IndexedArray, updates: DataFrame) -> IndexedArray:
    """The array with deltas added."""
    rows = arr.df.select(*arr.keys, "idx", "val").unionByName(updates.select(*arr.keys, "idx", F.col("delta").alias("val")))
    return arr.with_df(rows.groupBy(*arr.keys, "idx").agg(F.sum("val").alias("val")))


def rebuild_bins(arr: IndexedArray, buf: BinBuffer, touched: DataFrame) -> BinBuffer:
    """General update: bins that hold a touched index are aggregated anew from the (changed) array, the others stay."""
    bins = touched.select(*buf.keys, F.expr(f"idx div {buf.b}").alias("bin")).distinct()
    cells = arr.df.withColumn("bin", F.expr(f"idx div {buf.b}")).join(F.broadcast(bins), [*buf.keys, "bin"], "left_semi")
    fresh = build_bins(arr.with_df(cells.select(*arr.keys, "idx", "val")), buf.spec, buf.b).df
    kept = buf.df.join(F.broadcast(bins), [*buf.keys, "bin"], "left_anti")
    return BinBuffer(kept.unionByName(fresh), buf.b, buf.n, buf.spec, buf.keys)


def approx_bins(buf: BinBuffer, ranges: DataFrame, rule: str = "inner") -> DataFrame:
    """Estimates from the buffer alone: whole bins, or (rule half) every bin of which more than half is covered."""
    b, ranges = buf.b, settled(ranges)
    if rule == "inner":
        first, last = F.expr(f"(p + {b - 1}) div {b}"), F.expr(f"(q + 1) div {b} - 1")
    else:  # a bin from x counts if min(q, x+b-1) - max(p, x) + 1 > b/2
        first = F.expr(f"CASE WHEN 2 * (p % {b}) < {b} THEN p div {b} ELSE p div {b} + 1 END")
        last = F.expr(f"CASE WHEN 2 * (q % {b} + 1) > {b} THEN q div {b} ELSE q div {b} - 1 END")
    runs = ranges.withColumn("first", first).withColumn("last", last)
    if rule == "half":  # a range within one bin counts it only if it covers more than half
        one = F.expr(f"p div {b}") == F.expr(f"q div {b}")
        runs = runs.withColumn("last", F.when(one & (2 * (F.col("q") - F.col("p") + 1) <= b), F.col("first") - 1).otherwise(F.col("last")))
    got = _middles(buf, ranges, runs.where("first <= last").select("qid", "p", "q", "first", "last"))
    return ranges.select("qid").join(got, "qid", "left").select("qid", buf.spec.finish().alias("estimate"))
