"""The paper-shaped experiments: one frame of measurements for each, over the given tables or a sine array.

Cells read and cells touched are exact and comparable on any machine; seconds are this
machine's. Registered as `exp_*` queries by the workloads.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions import algebra as A
from momentbuf.functions.weights import Stencil, num_levels
from momentbuf.operators import baselines as D
from momentbuf.operators import binbuf as B
from momentbuf.operators import lagrange_buffer as L
from momentbuf.operators import progressive as G
from momentbuf.operators.ranges import random_ranges
from momentbuf.operators.relational import range_length_deciles
from momentbuf.plans import cost as C
from momentbuf.sources.arrays import IndexedArray, density, virtual_array
from momentbuf.sources.fixtures import fixture
from momentbuf.sources.store import hold_lagrange, read_array, shared_path, write_array

Experiment = Callable[[SparkSession, str], DataFrame]


def seconds(df: DataFrame) -> float:
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - t, 4)


def _held(arr: IndexedArray) -> IndexedArray:
    return arr.with_df(arr.df.persist())


def _cells(arr: IndexedArray, buf: L.LagrangeBuffer, ranges: DataFrame, k: int = 0) -> tuple[float, float]:
    r = L.query_lagrange(arr, buf, ranges, L.moment_poly(k, "p"), costs=True).agg(F.avg("cells_array"), F.avg("cells_buffer")).first()
    return round(r[0], 2), round(r[1], 2)


def _build(arr: IndexedArray, b: int, order: int, levels: int | None = None) -> tuple[L.LagrangeBuffer, float]:
    buf = L.build_lagrange(arr, b, order, levels, "double")
    df = buf.df.persist()
    s = seconds(df)
    return L.LagrangeBuffer(df, b, arr.n, buf.levels, buf.stencil, "double"), s


def query_over_bin_size(spark: SparkSession, d: str, bins: tuple[int, ...] = (8, 32, 128, 1024), count: int = 200) -> DataFrame:
    """Sums and first moments at order 4: cells read grow like b over log b, and are the same for both."""
    arr = _held(fixture(spark, d, "event_value"))
    r = random_ranges(spark, arr.n, count, edges=False).persist()
    rows = []
    for b in bins:
        buf, built = _build(arr, b, 4)
        for k in (0, 1):
            rows.append((b, buf.levels, k, *_cells(arr, buf, r, k), seconds(L.query_lagrange(arr, buf, r, L.moment_poly(k, "p"))), built))
    return spark.createDataFrame(rows, "b int, levels int, moment int, cells_array double, cells_buffer double, query_s double, build_s double")


def query_over_order(spark: SparkSession, d: str, orders: tuple[int, ...] = (2, 4, 8, 16), count: int = 200) -> DataFrame:
    """Cells and seconds by N, one scale and hierarchical; fitted coefficients of N and N^2 for the cells."""
    arr = _held(fixture(spark, d, "event_value"))
    r = random_ranges(spark, arr.n, count, edges=False).persist()
    rows = []
    for levels in (1, 2):
        cells = []
        for n in orders:
            buf, built = _build(arr, 16, n, levels)
            a, c = _cells(arr, buf, r)
            cells.append(a + c)
            rows.append([levels, n, a, c, seconds(L.query_lagrange(arr, buf, r)), built])
        lin, quad = C.fit_shape(list(map(float, orders)), cells, [lambda x: x, lambda x: x * x])
        for x in rows[-len(orders) :]:
            x += [float(lin), float(quad)]
    return spark.createDataFrame([tuple(x) for x in rows], "levels int, N int, cells_array double, cells_buffer double, query_s double, build_s double, per_N double, per_N2 double")


def query_over_length(spark: SparkSession, d: str) -> DataFrame:
    """Cells read by decile of range length: nearly flat for the array, sloping slightly with the top level's cells."""
    arr = fixture(spark, d, "price_cents")
    r = random_ranges(spark, arr.n, 200, edges=False)
    out = None
    for levels in (1, 3):
        buf = L.build_lagrange(arr, 64, 4, levels, "double")
        one = range_length_deciles(L.query_lagrange(arr, buf, r, costs=True), r).withColumn("levels", F.lit(levels))
        out = one if out is None else out.unionByName(one)
    return out


def build_over_grid(spark: SparkSession, d: str, n: int = 1 << 17) -> DataFrame:
    """Build seconds over bin sizes and orders on a sine array: roughly flat in b, linear in N."""
    arr = _held(virtual_array(spark, n))
    arr.df.count()
    rows = [(b, o, num_levels(n, b, o), C.buffer_sizes(n, b, o)["lagrange"], _build(arr, b, o)[1]) for b, o in ((32, 4), (128, 4), (1024, 4), (128, 2), (128, 8), (128, 16))]
    return spark.createDataFrame(rows, "b int, N int, levels int, cells long, build_s double")


def updates_over_grid(spark: SparkSession, d: str, n: int = 1 << 17, count: int = 2000) -> DataFrame:
    """Cells that an update touches (mean and most, against 2N a level) and seconds of a batch, by bin size and order."""
    x, st = F.col("id"), Stencil.of
    upd = spark.range(count).select(((x * 2654435761 + 13) % n).alias("idx"), ((x * 31) % 200 - 100).cast("double").alias("delta")).persist()
    rows = []
    for b, o in ((32, 4), (128, 4), (1024, 4), (128, 2), (128, 8), (128, 16)):
        levels = num_levels(n, b, o)
        cells = L.touched(upd.select(F.col("idx").alias("j")).distinct(), b, st(o), levels, n).groupBy("j").agg(F.count("*").alias("c"))
        t = cells.agg(F.avg("c").alias("mean"), F.max("c").alias("most")).first()
        delta = IndexedArray(upd.withColumnRenamed("delta", "val").groupBy("idx").agg(F.sum("val").alias("val")), n)
        rows.append((b, o, levels, t["mean"], t["most"], C.touched_cells(o, levels), seconds(L.build_lagrange(delta, b, o, levels, "double").df)))
    return spark.createDataFrame(rows, "b int, N int, levels int, touched_mean double, touched_most int, bound int, batch_s double")


def scan_comparison(spark: SparkSession, d: str) -> DataFrame:
    """Unbuffered scan against buffers on the same ranges: cells, speed-up in cells, seconds, queries to break even."""
    arr = _held(fixture(spark, d, "order_total"))
    r = random_ranges(spark, arr.n, 100, edges=False).persist()
    length = r.agg(F.avg(F.col("q") - F.col("p") + 1)).first()[0]
    scan = seconds(D.scan_ranges(arr, r, A.moment_spec(0)))
    rows = [("scan", float(length), 1.0, scan, 0.0)]
    for name, b, levels in (("one_scale", B.optimal_bin(arr.n), 1), ("hierarchical", 16, None)):
        buf, built = _build(arr, b, 4, levels)
        s = seconds(L.query_lagrange(arr, buf, r))
        c = sum(_cells(arr, buf, r))
        rows.append((name, c, length / c, s, C.break_even(built, scan / 100, s / 100) if scan > s else -1.0))
    bins = B.build_bins(arr, A.sum_spec(), B.optimal_bin(arr.n))
    c = B.query_bins(arr, bins, r, costs=True).agg(F.avg(F.col("cells_array") + F.col("cells_buffer"))).first()[0]
    rows.append(("disjoint_bins", c, length / c, seconds(B.query_bins(arr, bins, r)), -1.0))
    return spark.createDataFrame(rows, "method string, cells double, cells_speedup double, query_s double, break_even double")


def disk_array(spark: SparkSession, d: str, n: int = 1 << 16) -> DataFrame:
    """A 32-bit sine array in clustered files: answers of plain queries over it, rows read and files opened against the whole."""
    path = shared_path(spark, "disk")
    write_array(virtual_array(spark, n), path, chunk=n // 16, single=True)
    whole = read_array(spark, path)
    buf = hold_lagrange(L.build_lagrange(whole, 64, 4, 1, "double"))
    files = C.blocks_read(whole.df)
    rows = []
    for p, q in ((1000, 50_000), (123, 4567), (30_000, 30_100)):
        r = spark.createDataFrame([(0, p, q)], "qid long, p long, q long")
        answer = L.query_lagrange(whole, buf, r)
        want = whole.df.where(F.col("idx").between(p, q)).agg(F.sum(F.col("val").cast("double"))).first()[0]
        read = C.scan_metrics(answer, "val")
        rows.append((p, q, abs(answer.first()["result"] - want) < 1e-6, read["rows"], read["files"], files))
    return spark.createDataFrame(rows, "p long, q long, equal boolean, rows_read long, files_read int, files_all int")


def sparse_and_dense(spark: SparkSession, d: str) -> DataFrame:
    """Density, seconds of both strategies, and the choice between them, for sparse and dense arrays."""
    rows = []
    for name in ("event_second", "event_minute", "event_value"):
        arr = _held(fixture(spark, d, name))
        pays = L.sparse_pays(arr.df.count(), arr.n, 4, num_levels(arr.n, 32, 4))
        rows.append((name, density(arr), *(seconds(L.build_lagrange(arr, 32, 4, mode="double", strategy=s).df) for s in ("sparse", "dense")), pays))
    return spark.createDataFrame(rows, "array string, density double, sparse_s double, dense_s double, updates_pay boolean")


def progressive_errors(spark: SparkSession, d: str) -> DataFrame:
    """Mean share of the buffer-only error that is left after each ring of endpoint bins, by order."""
    arr = fixture(spark, d, "order_total")
    r = random_ranges(spark, arr.n, 100, edges=False)
    truth = D.scan_ranges(arr, r, A.sum_spec()).withColumnRenamed("result", "truth")
    out = None
    for n in (4, 16):
        e = G.progressive(arr, L.build_lagrange(arr, 64, n, 1, "double"), r).join(truth, "qid")
        one = e.groupBy("ring").agg(F.avg(F.abs(F.col("estimate") - F.col("truth"))).alias("mean_error")).withColumn("N", F.lit(n))
        out = one if out is None else out.unionByName(one)
    return out


def published_and_measured(spark: SparkSession, d: str) -> DataFrame:
    """The reported curves beside the cells this engine reads, by bin size at order 4 (shapes, not constants)."""
    arr = fixture(spark, d, "event_value")
    n = arr.n
    r = random_ranges(spark, n, 60, edges=False)
    rows = []
    for b in (16, 64, 256, 1024):
        buf = L.build_lagrange(arr, b, 4, mode="double")
        a, c = _cells(arr, buf, r)
        rows.append((b, C.published_curves(b, 4)["query_b"], a, c, sum(C.expected_cells(n, b, 4, buf.levels, 0)[k] for k in ("lagrange",))))
    return spark.createDataFrame(rows, "b int, published_s double, cells_array double, cells_buffer double, bound double")


EXPERIMENTS: dict[str, Experiment] = {
    "exp_query_over_bin_size": query_over_bin_size,
    "exp_query_over_order": query_over_order,
    "exp_query_over_length": query_over_length,
    "exp_build_over_grid": build_over_grid,
    "exp_updates_over_grid": updates_over_grid,
    "exp_scan_comparison": scan_comparison,
    "exp_disk_array": disk_array,
    "exp_sparse_and_dense": sparse_and_dense,
    "exp_progressive_errors": progressive_errors,
    "exp_published_and_measured": published_and_measured,
}
