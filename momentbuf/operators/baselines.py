"""Baselines: unbuffered scans, prefix sums, blocked prefix sums, Haar coefficients."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from momentbuf.functions.algebra import AggSpec
from momentbuf.functions.scalars import power
from momentbuf.operators.binbuf import optimal_bin
from momentbuf.operators.ranges import beside, ends, match, needed, settled
from momentbuf.sources.arrays import IndexedArray


def scan_ranges(arr: IndexedArray, ranges: DataFrame, spec: AggSpec) -> DataFrame:
    """Every range from the array itself, of which only what some range covers is asked."""
    ranges = settled(ranges)
    known = ends(ranges)
    cells = arr.df if known is None else needed(arr, known[:, 0], known[:, 1])
    rows = match(cells, "idx", ranges, "p", "q", arr.n, known, None if known is None else known[:, 1] - known[:, 0] + 1)
    got = rows.groupBy(*arr.keys, "qid").agg(*spec.lift(F.col("idx"), F.col("val"), F.col("p")))
    every = ranges.select("qid") if not arr.keys else ranges.select("qid").join(F.broadcast(arr.df.select(*arr.keys).distinct()))
    return every.join(got, [*arr.keys, "qid"], "left").select(*arr.keys, "qid", spec.finish().alias("result"))


#: Rows that one task may run a window over; totals of more rows are summed by blocks first.
ROWS = 1 << 16


def before(totals: DataFrame, key: str, cols: dict[str, str], keys: int, agg=F.sum) -> DataFrame:
    """key and, for each column, the aggregate over all rows of smaller keys (null for the first), under a new name.

    totals: one row a key, of `keys` possible ones. More than ROWS are cut into blocks of
    keys, whose own aggregates are carried on the same way.
    """
    if keys <= ROWS:
        w = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
        return totals.select(key, *[agg(c).over(w).alias(to) for c, to in cols.items()])
    block = 1 << 12
    rows = totals.withColumn("_block", F.expr(f"{key} div {block}"))
    carried = before(rows.groupBy("_block").agg(*[agg(c).alias(c) for c in cols]), "_block", {c: f"_c_{to}" for c, to in cols.items()}, -(-keys // block), agg)
    w = Window.partitionBy("_block").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    both = rows.select(key, "_block", *[agg(c).over(w).alias(f"_o_{to}") for c, to in cols.items()]).join(carried, "_block")
    join = (lambda a, b: F.coalesce(a + b, a, b)) if agg is F.sum else (lambda a, b: F.coalesce(a, b))
    return both.select(key, *[join(F.col(f"_o_{to}"), F.col(f"_c_{to}")).alias(to) for to in cols.values()])


def prefix_moments(arr: IndexedArray, order: int = 0, b: int | None = None) -> DataFrame:
    """idx, p0 .. p{order}: running sums of i^k a_i. Bin totals first, a window over the n/b totals, then windows within bins; never one window over all cells."""
    b = b or optimal_bin(arr.n)
    cells = arr.df.select("idx", F.expr(f"idx div {b}").alias("bin"), *[(power(F.col("idx"), k) * F.col("val")).alias(f"x{k}") for k in range(order + 1)])
    totals = cells.groupBy("bin").agg(*[F.sum(f"x{k}").alias(f"t{k}") for k in range(order + 1)])
    offsets = before(totals, "bin", {f"t{k}": f"o{k}" for k in range(order + 1)}, -(-arr.n // b)).fillna(0)
    within = Window.partitionBy("bin").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return cells.join(offsets, "bin").select("idx", "bin", *[(F.col(f"o{k}") + F.sum(f"x{k}").over(within)).alias(f"p{k}") for k in range(order + 1)])


def query_prefix(prefix: DataFrame, ranges: DataFrame, order: int = 0) -> DataFrame:
    """qid, result: raw moment of an order from two prefixes (dense arrays: a prefix at every index)."""
    ranges = settled(ranges)
    both = ranges.select("qid", F.inline(F.array(F.struct(F.col("q").alias("idx"), F.lit(1).alias("sign")), F.struct((F.col("p") - 1).alias("idx"), F.lit(-1).alias("sign")))))
    got = prefix.join(beside(both, ends(ranges)), "idx").groupBy("qid").agg(F.sum(F.col("sign") * F.col(f"p{order}")).alias("x"))
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("x", F.lit(0)).cast("long").alias("result"))


def blocked_prefix(arr: IndexedArray, b: int) -> tuple[DataFrame, DataFrame]:
    """In-bin prefixes (idx, bin, w) and prefixes over bins (bin, o): a change moves b cells and n/b totals at most, not n."""
    cells = arr.df.select("idx", F.expr(f"idx div {b}").alias("bin"), "val")
    inner = cells.select("idx", "bin", F.sum("val").over(Window.partitionBy("bin").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)).alias("w"))
    totals = cells.groupBy("bin").agg(F.sum("val").alias("t"))
    outer = before(totals, "bin", {"t": "o"}, -(-arr.n // b)).fillna(0)
    return inner, outer


def query_blocked(inner: DataFrame, outer: DataFrame, ranges: DataFrame) -> DataFrame:
    ranges = settled(ranges)
    both = ranges.select("qid", F.inline(F.array(F.struct(F.col("q").alias("idx"), F.lit(1).alias("sign")), F.struct((F.col("p") - 1).alias("idx"), F.lit(-1).alias("sign")))))
    got = inner.join(beside(both, ends(ranges)), "idx").join(outer, "bin").groupBy("qid").agg(F.sum(F.col("sign") * (F.col("w") + F.col("o"))).alias("x"))
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("x", F.lit(0)).cast("long").alias("result"))


#: Levels of coefficients that come from the cells themselves; the others come from sums over 2^HAAR_LOW cells.
HAAR_LOW = 10


def haar_transform(arr: IndexedArray) -> tuple[DataFrame, int]:
    """level, cell, s, d of all levels and their number: sums of pairs and left minus right halves, unnormalised whole numbers.

    Every cell adds to one coefficient of each level, so one aggregation gives many
    levels: the lower ones from the cells, the upper ones from the sums over blocks.
    """
    levels = max(1, (arr.n - 1).bit_length())

    def some(rows: DataFrame, low: int, high: int) -> DataFrame:
        """Levels low + 1 .. high of rows (cell of level low, s)."""
        ups = rows.select("s", F.col("cell").alias("c"), F.explode(F.sequence(F.lit(1), F.lit(high - low))).alias("up"))
        at = ups.select((F.col("up") + low).alias("level"), F.expr("shiftright(c, up)").alias("cell"), "s", F.when(F.expr("shiftright(c, up - 1) % 2 = 0"), F.col("s")).otherwise(-F.col("s")).alias("d"))
        return at.groupBy("level", "cell").agg(F.sum("s").alias("s"), F.sum("d").alias("d"))

    low = min(HAAR_LOW, levels)
    out = some(arr.df.select(F.col("idx").alias("cell"), F.col("val").alias("s")), 0, low)
    if levels > low:
        blocks = arr.df.groupBy(F.expr(f"shiftright(idx, {low})").alias("cell")).agg(F.sum("val").alias("s"))
        out = out.unionByName(some(blocks, low, levels))
    return out, levels


def query_haar(coefs: DataFrame, levels: int, ranges: DataFrame, keep: int | None = None) -> DataFrame:
    """qid, result of range sums from coefficients: the total's share plus, for each level, the two coefficients whose support an end cuts.

    A prefix up to x of a block of 2^l cells is (x / 2^l) of its sum plus the details below.
    keep: only so many coefficients of greatest energy (d^2 / 2^level) are used, an approximation.
    """
    if keep is not None:
        best = coefs.withColumn("e", F.col("d").cast("double") * F.col("d") / F.pow(F.lit(2.0), "level")).orderBy(F.desc("e"), "level", "cell").limit(keep)
        coefs = best.drop("e").unionByName(coefs.where(F.col("level") == levels).withColumn("d", F.lit(0).cast(coefs.schema["d"].dataType)))
        coefs = coefs.groupBy("level", "cell").agg(F.max("s").alias("s"), F.sum("d").alias("d"))
    ranges = settled(ranges)
    edges = ranges.select("qid", F.inline(F.array(F.struct((F.col("q") + 1).alias("x"), F.lit(1.0).alias("sign")), F.struct(F.col("p").alias("x"), F.lit(-1.0).alias("sign")))))
    # One more entry, behind the levels, asks for the total's share.
    asked = edges.select("x", "qid", "sign", F.explode(F.sequence(F.lit(1), F.lit(levels + 1))).alias("step"))
    whole = F.col("step") > levels
    asked = asked.withColumn("level", F.least("step", F.lit(levels))).withColumn("cell", F.when(whole, F.lit(0).cast("long")).otherwise(F.expr("shiftright(x, step)")))
    size = F.expr("shiftleft(CAST(1 AS BIGINT), level)")
    asked = asked.withColumn("r", F.expr("x - shiftleft(cell, level)"))
    # Share of a block's detail in its prefix of r cells: r/size up to the middle, (size - r)/size behind it.
    tent = F.when(whole, F.lit(0.0)).otherwise(F.least("r", size - F.col("r")).cast("double") / size)
    share = F.when(whole, F.col("x").cast("double") / float(1 << levels)).otherwise(F.lit(0.0))
    asked = asked.where(whole | (F.col("r") > 0)).select("qid", "level", "cell", (F.col("sign") * tent).alias("of_d"), (F.col("sign") * share).alias("of_s"))
    got = coefs.join(beside(asked, ends(ranges)), ["level", "cell"]).groupBy("qid").agg(F.sum(F.col("d") * F.col("of_d") + F.col("s") * F.col("of_s")).alias("v"))
    return ranges.select("qid").join(got, "qid", "left").select("qid", F.coalesce("v", F.lit(0.0)).alias("result"))
