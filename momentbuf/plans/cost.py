"""Cost and accuracy measures: closed forms, and what they are compared with."""

from __future__ import annotations

from math import log

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions.weights import num_levels


def buffer_sizes(n: int, b: int, order: int) -> dict[str, int]:
    """Numbers stored by each buffer for N moments over n cells."""
    bins = -(-n // b)
    return {"bins_with_count": (order + 1) * bins, "bins": order * bins, "pyramid": order * sum(-(-n // b**lv) for lv in range(1, num_levels(n, b, 2) + 1)), "pyramid_inplace": order * bins, "lagrange": bins, "prefix": order * n, "haar": n}


def expected_cells(n: int, b: int, order: int, levels: int, length: int) -> dict[str, float]:
    """Most cells a range query reads, by method."""
    return {"scan": length, "bins": 2 * (b - 1) + length / b, "pyramid": 2 * (b - 1) * levels + n / b**levels, "lagrange": 2 * (order - 1) * b * levels + n / b**levels + 1}


def touched_cells(order: int, levels: int) -> int:
    """Most buffer cells an update reaches."""
    return 2 * order * levels


def equal_memory(order: int, K: int, n: int, bin_cost: float) -> dict[str, float]:
    """Query cost N * E_b + K and bin sizes of both families at K numbers of memory; the disjoint family reads two fragments."""
    return {"b_bins": order * n / K, "b_lagrange": n / max(1, K - 1), "cost": order * bin_cost + K}


def array_free_ranges(K: int, order: int) -> tuple[int, int]:
    """Ranges answered from disjoint bins alone, by edges and (as often quoted) by bins."""
    k = K // order
    return (k + 1) * k // 2, k * (k - 1) // 2


def break_even(build_s: float, scan_query_s: float, buffered_query_s: float = 0.0) -> float:
    """Queries after which building has paid for itself."""
    return build_s / max(1e-12, scan_query_s - buffered_query_s)


def sparse_break_even(build_s: float, update_s: float) -> float:
    """Non-zero cells up to which building by updates is faster than a full build."""
    return build_s / max(1e-12, update_s)


def published_curves(b: int, order: int) -> dict[str, float]:
    """The reported fits in seconds, for shapes: query time over b, build and query time over N."""
    return {"query_b": b / (5000 * log(b)), "build_n": 268 * order + 450, "query_n_one": 0.007 * order**2 + 0.08 * order, "query_n_hier": (order**2 + 11.7 * order) / 11700}


def fit_shape(xs: list[float], ys: list[float], basis: list) -> list[float]:
    """Least-squares coefficients of ys over basis functions of xs."""
    import numpy as np

    a = np.array([[f(x) for f in basis] for x in xs])
    return np.linalg.lstsq(a, np.array(ys), rcond=None)[0].tolist()


def blocks_read(df: DataFrame) -> int:
    """Files a (filtered) scan touches: the block granularity of small bins."""
    return df.select(F.input_file_name().alias("f")).distinct().count()


def scan_metrics(df: DataFrame, column: str) -> dict[str, int]:
    """Run a query; files opened and rows given by those of its scans that read the named column."""
    execution = df._jdf.queryExecution()
    list_ = execution.executedPlan().executeCollect()
    del list_
    found = {"files": 0, "rows": 0}

    def walk(node) -> None:
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if name.endswith("QueryStageExec"):
            return walk(node.plan())
        if name == "FileSourceScanExec" and f"{column}#" in node.output().mkString(","):
            m = node.metrics()
            found["files"] += m.apply("numFiles").value()
            found["rows"] += m.apply("numOutputRows").value()
        for i in range(node.children().size()):
            walk(node.children().apply(i))

    walk(execution.executedPlan())
    return found


def relative_error(a: DataFrame, b: DataFrame, spark: SparkSession | None = None) -> DataFrame:
    """Largest relative deviation of two answer sets (qid, result)."""
    j = a.select("qid", F.col("result").cast("double").alias("x")).join(b.select("qid", F.col("result").cast("double").alias("y")), "qid")
    return j.agg(F.max(F.abs(F.col("x") - F.col("y")) / F.greatest(F.lit(1.0), F.abs("y"))).alias("worst"))
