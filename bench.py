"""Headline queries, timed; prints one JSON line.

Reads BENCH_SF_DIR (default /root/testdata/sf0.1) on local[BENCH_CPUS]. Beside the
queries' seconds it reports cells read by buffered queries and by scans on a sine array
(the paper-shaped measure that doesn't depend on hardware), build and update seconds.
"""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

HEADLINE = [
    "bin_build_moments", "bin_query_sum", "bin_query_sum_sqrt", "bin_query_max", "bin_update_linear", "pyr_query_sum", "pyr_query_max", "lag_build_n4", "lag_query_sum", "lag_query_m1", "lag_query_hier_sum", "lag_query_price_hier",
    "lag_update_batch", "lag_sparse_build", "prog_rings_final", "scan_sum", "prefix_query_sum", "blocked_prefix_query", "haar_query_full", "ship_strip_stats", "region_rollup", "stream_tumbling",
]


def shape(spark: SparkSession, n: int, ranges: int) -> dict:
    """One sine array held as files: seconds to scan, build, query (sum and first moment) and update, and cells read, by bin size."""
    from momentbuf.functions import algebra as A
    from momentbuf.operators.baselines import scan_ranges
    from momentbuf.operators.lagrange_buffer import build_lagrange, delta_cells, moment_poly, query_lagrange
    from momentbuf.operators.ranges import random_ranges
    from momentbuf.sources.arrays import IndexedArray, virtual_array

    arr = virtual_array(spark, n)
    arr = IndexedArray(arr.df.persist(), n)
    arr.df.count()
    r = random_ranges(spark, n, ranges, edges=False).persist()
    m = r.count()

    def timed(df) -> float:
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        return round(time.perf_counter() - t, 3)

    few = r.limit(20).persist()
    few.count()
    out = {"n": n, "ranges": m, "scan_20_s": timed(scan_ranges(arr, few, A.moment_spec(0)))}
    length = r.agg(F.avg(F.col("q") - F.col("p") + 1)).first()[0]
    for b, order in ((32, 4), (128, 4), (1024, 4), (128, 2), (128, 8)):
        buf = build_lagrange(arr, b, order, mode="double")
        held = buf.df.persist()
        row = {"levels": buf.levels, "build_s": timed(held)}
        buf = buf.__class__(held, buf.b, buf.n, buf.levels, buf.stencil, buf.mode)
        row["sum_s"] = timed(query_lagrange(arr, buf, r))
        row["first_moment_s"] = timed(query_lagrange(arr, buf, r, moment_poly(1, "p")))
        c = query_lagrange(arr, buf, r, costs=True).agg(F.avg("cells_array").alias("a"), F.avg("cells_buffer").alias("c")).first()
        row |= {"cells_array": round(c["a"], 1), "cells_buffer": round(c["c"], 1), "cells_speedup": round(length / (c["a"] + c["c"]), 1)}
        x = F.col("id")
        upd = spark.range(2000).select(((x * 2654435761 + 13) % n).alias("idx"), ((x * 31) % 200 - 100).cast("double").alias("delta"))
        row["update_2000_s"] = timed(delta_cells(buf, upd))  # what an appended update writes
        out[f"b{b}_N{order}"] = row
        held.unpersist()
    return out


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from momentbuf.workloads import QUERIES

    seconds: dict[str, float] = {}
    spark.range(10).count()
    for name in HEADLINE:
        t = time.perf_counter()
        QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - t, 3)
    line = {"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf)}
    if os.environ.get("BENCH_SHAPE", "1") == "1":
        line["shape"] = shape(spark, 1 << 20, 2000)
    print(json.dumps(line))
    spark.stop()


if __name__ == "__main__":
    main()
