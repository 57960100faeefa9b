"""Operators around the buffers: interval and as-of joins, windows over arrays, rankings, set operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from momentbuf.operators.baselines import before
from momentbuf.operators.ranges import ends, match, needed, settled
from momentbuf.sources.arrays import IndexedArray


def range_join(arr: IndexedArray, ranges: DataFrame) -> DataFrame:
    """qid, idx, val of all cells in each range, by pieces of equal width."""
    ranges = settled(ranges)
    known = ends(ranges)
    cells = arr.df if known is None else needed(arr, known[:, 0], known[:, 1])
    return match(cells, "idx", ranges, "p", "q", arr.n, known, None if known is None else known[:, 1] - known[:, 0] + 1).select("qid", "idx", "val")


def interval_join(events: DataFrame, at: str, windows: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of events with the windows [lo, hi] that hold their `at` (whole numbers), joined on slots of the given width."""
    cut = windows.withColumn("slot", F.explode(F.sequence(F.expr(f"{lo} div {width}"), F.expr(f"{hi} div {width}"))))
    return events.withColumn("slot", F.expr(f"{at} div {width}")).join(cut, "slot").where(F.col(at).between(F.col(lo), F.col(hi))).drop("slot")


def asof_last(arr: IndexedArray, points: DataFrame, chunk: int = 4096) -> DataFrame:
    """qid, point, idx, val of the last present cell at or before each point.

    Windows run within chunks of indices; what a chunk inherits is carried over a window
    of one row for each chunk.
    """
    c = arr.df.select("idx", "val", F.expr(f"idx div {chunk}").alias("chunk"))
    none = F.lit(None).cast(c.select(F.struct("idx", "val").alias("cell")).schema["cell"].dataType)
    own = c.select(F.col("idx").alias("at"), F.lit(None).cast("long").alias("qid"), F.struct("idx", "val").alias("cell"), "chunk")
    rows = own.unionByName(points.select(F.col("point").alias("at"), "qid", none.alias("cell"), F.expr(f"point div {chunk}").alias("chunk")))
    within = Window.partitionBy("chunk").orderBy("at", F.col("qid").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    got = rows.withColumn("last", F.last("cell", ignorenulls=True).over(within)).where("qid is not null")
    last = c.groupBy("chunk").agg(F.max(F.struct("idx", "val")).alias("end")).unionByName(points.select(F.expr(f"point div {chunk}").alias("chunk"), none.alias("end"))).groupBy("chunk").agg(F.max("end").alias("end"))
    carry = before(last, "chunk", {"end": "carried"}, -(-arr.n // chunk), F.max)  # cells ascend, so the greatest is the last
    out = got.join(carry, "chunk", "left").withColumn("hit", F.coalesce("last", "carried"))
    return out.select("qid", F.col("at").alias("point"), F.col("hit.idx").alias("idx"), F.col("hit.val").alias("val"))


def moving_moment(arr: IndexedArray, width: int, k: int, chunk: int = 4096) -> DataFrame:
    """idx, result: sum of i^k a_i over the last `width` indices; chunks carry a halo of the cells before them."""
    from momentbuf.functions.scalars import power

    rows = arr.df.select("idx", (power(F.col("idx"), k) * F.col("val")).alias("x"), F.expr(f"idx div {chunk}").alias("own"))
    halo = rows.withColumn("chunk", F.explode(F.sequence(F.col("own"), F.expr(f"(idx + {width - 1}) div {chunk}"))))
    w = Window.partitionBy("chunk").orderBy("idx").rangeBetween(-(width - 1), 0)
    return halo.withColumn("result", F.sum("x").over(w)).where("own = chunk").select("idx", "result")


def window_ranks(df: DataFrame, by: str, tie: str, parts: Column | None = None) -> DataFrame:
    """Row number, rank, dense rank, quartile, percent rank and neighbours' gap of rows, within the given parts."""
    w = Window.partitionBy(*([parts] if parts is not None else [])).orderBy(F.desc(by), tie)
    r = Window.partitionBy(*([parts] if parts is not None else [])).orderBy(F.desc(by))
    return df.withColumn("rn", F.row_number().over(w)).withColumn("rk", F.rank().over(r)).withColumn("dense", F.dense_rank().over(r)).withColumn("quarter", F.ntile(4).over(w)).withColumn("gap", F.col(by) - F.lead(by).over(w))


def rank_bins(buf: DataFrame, by: str, k: int, cell: str = "bin") -> DataFrame:
    """The k bins with the largest state; a partial top-k in each task."""
    return buf.orderBy(F.desc(by), cell).limit(k)


def range_length_deciles(answers: DataFrame, ranges: DataFrame) -> DataFrame:
    """decile of range length, mean length and mean cells read."""
    d = answers.join(ranges.select("qid", (F.col("q") - F.col("p") + 1).alias("len")), "qid").withColumn("decile", F.ntile(10).over(Window.orderBy("len", "qid")))
    return d.groupBy("decile").agg(F.avg("len").alias("length"), F.avg("cells_array").alias("cells_array"), F.avg("cells_buffer").alias("cells_buffer"))


def semi_touched(buf: DataFrame, updates: DataFrame, b: int) -> DataFrame:
    return buf.join(updates.select(F.expr(f"idx div {b}").alias("bin")).distinct(), "bin", "left_semi")


def anti_untouched(buf: DataFrame, updates: DataFrame, b: int) -> DataFrame:
    return buf.join(updates.select(F.expr(f"idx div {b}").alias("bin")).distinct(), "bin", "left_anti")


def diff_buffers(x: DataFrame, y: DataFrame) -> DataFrame:
    """Rows of either buffer that the other lacks."""
    return x.exceptAll(y).withColumn("side", F.lit("left")).unionByName(y.exceptAll(x).withColumn("side", F.lit("right")))
