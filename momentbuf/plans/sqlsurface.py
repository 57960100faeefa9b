"""SQL surface: views over buffers, table functions for covers and spreads, functions for weights, and Python aggregates for parity."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions.weights import Stencil


@F.udtf(returnType="level int, cell bigint")
class RangeCells:
    """Two-sided greedy cover of [p, q] by cells of levels 0 .. levels."""

    def eval(self, p: int, q: int, b: int, levels: int):
        lo, hi = p, q + 1
        for lv in range(levels + 1):
            if lv == levels:
                for c in range(lo, hi):
                    yield lv, c
                return
            up, down = -(-lo // b), hi // b
            if up <= down:
                for c in [*range(lo, up * b), *range(down * b, hi)]:
                    yield lv, c
                lo, hi = up, down
            else:
                for c in range(lo, hi):
                    yield lv, c
                return


@F.udtf(returnType="cell bigint, w double")
class LagrangeCells:
    """Cells of the first level that a change at an index reaches, with their weights."""

    def eval(self, idx: int, b: int, n: int):
        st = Stencil.of(n)
        for k in st.nodes:
            w = float(st.exact(k, idx % b, b))
            if w:
                yield idx // b + k, w


def moments_udaf(order: int):
    """Grouped Python aggregate of one moment about an origin, for parity checks of the built-in expressions."""

    @F.pandas_udf("double")
    def moment(idx: pd.Series, val: pd.Series) -> float:
        return float((((idx - idx.min()) ** order) * val).sum())

    return moment


def register_sql(spark: SparkSession, views: dict[str, DataFrame], b: int = 32) -> None:
    """Views of arrays and buffers, table functions range_cells and lagrange_cells, scalar functions hat_w (r) and cubic_w (r, node)."""
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    spark.udtf.register("range_cells", RangeCells)
    spark.udtf.register("lagrange_cells", LagrangeCells)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION hat_w(r BIGINT) RETURNS DOUBLE RETURN 1.0D - abs(r) / {float(b)}D")
    cubic = " ".join(f"WHEN {k} THEN {Stencil.of(4).weight(k, 'r', b)}" for k in Stencil.of(4).nodes)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cubic_w(r BIGINT, k INT) RETURNS DOUBLE RETURN CASE k {cubic} END")


def local_moment_sql(array: str, bins: str, b: int, p: int, q: int, c: int, k: int) -> str:
    """Text of one local moment from an array view (idx, val) and a view of disjoint-bin moments (bin, m0, m1): whole bins from the latter, fragments from the former."""
    if k > 1:
        raise ValueError("the text form serves sums and first moments")
    first, last = -(-p // b), (q + 1) // b - 1
    whole = "m0" if k == 0 else f"m1 + (bin * {b} - {c}) * m0"
    term = "val" if k == 0 else f"(idx - {c}) * val"
    edge = f"(idx < {first * b} OR idx >= {(last + 1) * b})" if first <= last else "true"
    mid = f"SELECT {whole} AS x FROM {bins} WHERE bin BETWEEN {first} AND {last} UNION ALL " if first <= last else ""
    return f"SELECT CAST(coalesce(sum(x), 0) AS BIGINT) AS result FROM ({mid}SELECT {term} AS x FROM {array} WHERE idx BETWEEN {p} AND {q} AND {edge})"
