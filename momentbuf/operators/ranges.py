"""Query ranges: deterministic generators, checks, splitting along bins, joins by containment, and what of an array a batch needs."""

from __future__ import annotations

from collections.abc import Iterable
from weakref import WeakKeyDictionary

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.sources.arrays import IndexedArray

#: Multipliers and offsets of the generator, fixed values: pairs are spread over the array and repeat only after n draws.
U, U0, V, V0 = 2654435761, 13, 2246822519, 71
#: So many ranges at most are known to the driver and broadcast; a larger batch prunes nothing and is joined by exchange.
BATCH = 100_000
#: Intervals pushed into a scan; more are merged across their smallest gaps.
PUSHED = 32
#: Pieces a run is cut into at most (and one more), whatever its length.
FAN = 64
_ends: WeakKeyDictionary = WeakKeyDictionary()
_local: WeakKeyDictionary = WeakKeyDictionary()


def random_ranges(spark: SparkSession, n: int, count: int, edges: bool = True, b: int = 32) -> DataFrame:
    """qid, p, q: `count` draws (equal ends skipped) and, with edges, the hand-picked cases."""
    x = F.col("id")
    u, v = (x * U + U0) % n, (x * V + V0) % n
    df = spark.range(count).select(x.alias("qid"), F.least(u, v).alias("p"), (F.greatest(u, v) - 1).alias("q")).where("q >= p")
    return df.union(spark.createDataFrame(edge_cases(n, count, b), "qid long, p long, q long")) if edges else df


def edge_cases(n: int, first: int, b: int) -> list[tuple[int, int, int]]:
    """Whole array, first cell, last cell, inside a bin, whole bins, across one bin edge."""
    picked = [(0, n - 1), (0, 0), (n - 1, n - 1), (1, min(2, n - 1)), (b, 3 * b - 1), (b - 1, b)]
    return [(first + i, p, q) for i, (p, q) in enumerate(picked) if p <= q < n]


def validate_ranges(ranges: DataFrame, n: int) -> DataFrame:
    """Ranges clipped to the array, with a flag for those that are empty."""
    p, q = F.greatest("p", F.lit(0)), F.least("q", F.lit(n - 1))
    return ranges.withColumn("p", p).withColumn("q", q).withColumn("empty", F.col("p") > F.col("q"))


def split_to_bins(ranges: DataFrame, b: int) -> tuple[DataFrame, DataFrame]:
    """Fragments (qid, p, bin, lo, hi) of partly covered bins, at most two a range; and runs of whole bins (qid, p, first, last)."""
    r = ranges.selectExpr("qid", "p", "q", f"(p + {b - 1}) div {b} AS first", f"(q + 1) div {b} - 1 AS last")
    one_bin = f"p div {b} = q div {b} AND first > last"
    left = f"struct(p div {b} AS bin, p AS lo, CASE WHEN {one_bin} THEN q ELSE first * {b} - 1 END AS hi)"
    right = f"struct(q div {b} AS bin, greatest((last + 1) * {b}, p) AS lo, q AS hi)"
    frags = r.selectExpr("qid", "p", "q", f"inline(CASE WHEN {one_bin} THEN array({left}) ELSE array({left}, {right}) END)").where("lo <= hi")
    return frags, r.where("first <= last")


def settled(ranges: DataFrame) -> DataFrame:
    """The batch as a local table, so that no later plan computes it again; the frame itself where there are more than BATCH ranges."""
    if ranges not in _local:
        got = ranges.limit(BATCH + 1).toArrow()
        frame = ranges.sparkSession.createDataFrame(got, ranges.schema) if got.num_rows <= BATCH else ranges
        _local[ranges] = _local[frame] = frame
        _ends[frame] = np.stack([got[c].to_numpy() for c in ("p", "q")], 1).astype(np.int64) if got.num_rows <= BATCH else None
    return _local[ranges]


def ends(ranges: DataFrame) -> np.ndarray | None:
    """p and q of a settled batch's ranges as two columns, or None where there are more than BATCH (nothing is collected beyond that)."""
    return _ends[settled(ranges)]


def beside(df: DataFrame, known: np.ndarray | None) -> DataFrame:
    """A frame made from a batch: broadcast where the batch's size is known to be small, else as Spark sees fit."""
    return F.broadcast(df) if known is not None else df


def merged(lo: np.ndarray, hi: np.ndarray, most: int = PUSHED) -> list[tuple[int, int]]:
    """Disjoint intervals that hold all of [lo, hi], `most` of them at most."""
    on = lo <= hi
    lo, hi = lo[on], hi[on]
    if not len(lo):
        return []
    o = np.argsort(lo, kind="stable")
    lo, top = lo[o], np.maximum.accumulate(hi[o])
    gap = lo[1:] - top[:-1]
    cuts = np.flatnonzero(gap > 1)
    if len(cuts) >= most:
        cuts = np.sort(cuts[np.argsort(-gap[cuts], kind="stable")[: most - 1]])
    return list(zip(lo[np.r_[0, cuts + 1]].tolist(), top[np.r_[cuts, len(top) - 1]].tolist(), strict=True))


def inside(at: str, lo: np.ndarray, hi: np.ndarray) -> Column:
    """Whether a position lies in one of the intervals, for the scan to prune by."""
    return F.expr(" OR ".join(f"{at} BETWEEN {p} AND {q}" for p, q in merged(lo, hi)) or "false")


def needed(arr: IndexedArray, lo: np.ndarray | None, hi: np.ndarray | None) -> DataFrame:
    """The array's rows within the intervals (a few more where there are many): whole chunks are skipped by folder, others by row-group bounds."""
    if lo is None or not arr.stored:  # bounds on a computed index would only be evaluated again
        return arr.df
    rows = arr.df
    if arr.chunk:
        on = lo <= hi
        c = sorted({x for p, q in zip((lo[on] // arr.chunk).tolist(), (hi[on] // arr.chunk).tolist(), strict=True) for x in range(p, q + 1)}) if on.any() else []
        if len(c) <= BATCH:
            rows = arr.source.where(F.col("chunk").isin(c) if c else F.lit(False)).select(*arr.keys, "idx", "val")
    return rows.where(inside("idx", lo, hi))


def _widths(span: int) -> list[int]:
    out = [FAN]
    while span > FAN * out[-1]:
        out.append(FAN * out[-1])
    return out


def match(cells: DataFrame, at: str, runs: DataFrame, lo: str, hi: str, span: int, known: np.ndarray | None, lengths: Iterable[int] | None = None, on: tuple[str, ...] = ()) -> DataFrame:
    """Cells joined with the runs [lo, hi] that hold their position `at`, by equality of pieces.

    A run is cut at the smallest of a few widths that leaves it about FAN pieces; a
    cell looks for runs once for each width in use. span: number of positions;
    lengths: the runs' lengths where the driver knows them; on: further equal columns.
    """
    ws = _widths(span)
    if known is not None and lengths is not None:
        x = np.asarray(lengths)
        used = {next((w for w in ws if n <= FAN * w), ws[-1]) for n in (np.unique(x[x > 0]).tolist() if x.size else [])}
        ws = sorted(used) or ws[:1]
    cases = " ".join(f"WHEN {hi} - {lo} < {FAN * w} THEN {w}L" for w in ws[:-1])
    cut = runs.withColumn("_w", F.expr(f"CASE {cases} ELSE {ws[-1]}L END" if cases else f"{ws[-1]}L")).withColumn("_piece", F.expr(f"explode(sequence({lo} div _w, {hi} div _w))"))
    if len(ws) == 1:
        rows = cells.selectExpr("*", f"{ws[0]}L AS _w", f"{at} div {ws[0]} AS _piece")
    else:
        looks = ", ".join(f"struct({w}L AS _w, {at} div {w} AS _piece)" for w in ws)
        rows = cells.select("*", F.expr(f"inline(array({looks}))"))
    return rows.join(beside(cut, known), [*on, "_w", "_piece"]).where(f"{at} BETWEEN {lo} AND {hi}").drop("_w", "_piece")
