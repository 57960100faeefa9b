"""Queries over the given tables, one for each method, variant, baseline, measure and operator, with their SQL.

SQL answers come straight from the rows of the arrays (a range join), never from buffers.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions import algebra as A
from momentbuf.functions.scalars import BIG, array_moment, poly_eval, power_sum, strip_html, ts_of_index, word_count
from momentbuf.functions.weights import Stencil, box_weight, hat_weight, weight_table
from momentbuf.operators import baselines as D
from momentbuf.operators import binbuf as B
from momentbuf.operators import lagrange_buffer as L
from momentbuf.operators import moments as M
from momentbuf.operators import overlap as O
from momentbuf.operators import progressive as G
from momentbuf.operators import pyramid as P
from momentbuf.operators import relational as X
from momentbuf.operators.ranges import random_ranges
from momentbuf.plans import cost as C
from momentbuf.plans.planner import Available, answer
from momentbuf.plans.sqlsurface import LagrangeCells, RangeCells, local_moment_sql, register_sql
from momentbuf.sources.arrays import IndexedArray, approx_profile, densify, slice_array, virtual_array
from momentbuf.sources.fixtures import ARRAYS, fixture, fixture_sql, length_sql, read
from momentbuf.sources.store import held, hold_lagrange
from momentbuf.streaming import maintain as S

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
COUNT = 200


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


def base_sql(array: str, b: int = 32, count: int = COUNT, keys: tuple[str, ...] = ()) -> str:
    n = length_sql(array)
    return f"""WITH arr AS ({fixture_sql(array, keys)}), nn AS (SELECT CAST({n} AS BIGINT) AS n),
uv AS (SELECT x AS qid, (x * 2654435761 + 13) % n AS u, (x * 2246822519 + 71) % n AS v FROM range({count}) t(x), nn),
edge AS (SELECT * FROM (SELECT {count} AS qid, 0 AS p, n - 1 AS q FROM nn UNION ALL SELECT {count + 1}, 0, 0 UNION ALL SELECT {count + 2}, n - 1, n - 1 FROM nn
 UNION ALL SELECT {count + 3}, 1, least(2, n - 1) FROM nn UNION ALL SELECT {count + 4}, {b}, {3 * b - 1} UNION ALL SELECT {count + 5}, {b - 1}, {b}), nn WHERE p <= q AND q < n),
ranges AS (SELECT qid, least(u, v) AS p, greatest(u, v) - 1 AS q FROM uv WHERE u <> v UNION ALL SELECT qid, p, q FROM edge)"""


BIG0 = "CAST(coalesce(sum({0}), 0) AS BIGINT)"


def range_sql(array: str, expr: str, b: int = 32, keys: tuple[str, ...] = (), where: str = "") -> str:
    if keys:
        k = ", ".join(keys)
        on = " AND ".join(f"a.{x} = g.{x}" for x in keys)
        return f"{base_sql(array, b, keys=keys)} SELECT {', '.join('g.' + x for x in keys)}, r.qid, {expr} AS result FROM ranges r CROSS JOIN (SELECT DISTINCT {k} FROM arr) g LEFT JOIN arr a ON {on} AND a.idx BETWEEN r.p AND r.q GROUP BY {', '.join('g.' + x for x in keys)}, r.qid"
    return f"{base_sql(array, b)} SELECT qid, {expr} AS result FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q {where} GROUP BY qid"


SUM = BIG0.format("val")


def moment_sql(k: int, c: str = "p") -> str:
    return BIG0.format(f"CAST(val AS HUGEINT) * {' * '.join([f'CAST(idx - {c} AS HUGEINT)'] * k)}") if k else SUM


def _setup(spark: SparkSession, d: str, array: str = "event_value", b: int = 32) -> tuple[IndexedArray, DataFrame]:
    arr = fixture(spark, d, array)
    return arr, random_ranges(spark, arr.n, COUNT, True, b)


def _updates(spark: SparkSession, n: int, count: int = 500) -> DataFrame:
    x = F.col("id")
    return spark.range(count).select(((x * 2654435761 + 13) % n).alias("idx"), ((x * 31) % 200 - 100).alias("delta"))


UPD = "upd AS (SELECT (x * 2654435761 + 13) % n AS idx, (x * 31) % 200 - 100 AS delta FROM range(500) t(x), nn)"


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Sums and first moments over random ranges of `events` from one hierarchical buffer of order 4."""
    arr, ranges = _setup(spark, d)
    buf = L.build_lagrange(arr, 8, 4, 2)
    total = L.query_lagrange(arr, buf, ranges)
    first = L.query_lagrange(arr, buf, ranges, L.moment_poly(1, "p")).withColumnRenamed("result", "first_moment")
    return total.withColumnRenamed("result", "total").join(first, "qid")


def weights_sql(b: str, n: int) -> str:
    """CTEs: nodes k, and wt (k, r, w) of all offsets r below b by the product formula."""
    lo, hi = 1 - (n - n // 2), n // 2
    return f"nodes AS (SELECT k FROM range({lo}, {hi + 1}) t(k)), wt AS (SELECT a.k, r, product((CAST(r AS DOUBLE) / {b} - j.k) / (a.k - j.k)) AS w FROM nodes a, nodes j, range({b}) u(r) WHERE a.k <> j.k GROUP BY a.k, r)"


def cells_sql(b: int, n_: int, levels: int) -> str:
    """CTEs after arr, nn, ranges: counts (qid, cells_array, cells_buffer, top, near) of a Lagrange query, from the cells that exist on each level and the bins near each end."""
    m, mp = n_ // 2, n_ - n_ // 2
    out = ["l0 AS (SELECT idx AS pos FROM arr)"]
    for t in range(1, levels + 1):
        out.append(f"l{t} AS (SELECT DISTINCT pos // {b} + k AS pos FROM l{t - 1}, range({1 - mp}, {m + 1}) u(k), nn WHERE pos // {b} + k >= 0 AND (pos // {b} + k) * {b**t} < n)")
    for t in range(levels):
        g, step = b**t, b ** (t + 1)
        kept = "true" if t == 0 else f"pos % {b} <> 0"
        ends = f"unnest(list_concat(range((p + {step - 1}) // {step} - {m}, (p + {step - 1}) // {step} + {mp - 1}), range(q // {step} + {1 - m}, q // {step} + {mp}), [(p + {g - 1}) // {g} // {b}, q // {g} // {b}]))"
        out.append(f"c{t} AS (SELECT qid, count(*) AS c FROM (SELECT DISTINCT qid, bin FROM (SELECT qid, {ends} AS bin FROM ranges)) JOIN l{t} ON pos // {b} = bin WHERE {kept} GROUP BY qid)")
    up = b**levels
    out.append(f"tops AS (SELECT qid, count(*) AS c FROM ranges JOIN l{levels} ON pos BETWEEN (p + {up - 1}) // {up} AND q // {up} GROUP BY qid)")
    low = " + ".join(f"coalesce(c{t}.c, 0)" for t in range(1, levels)) or "0"
    joins = " ".join(f"LEFT JOIN c{t} ON c{t}.qid = r.qid" for t in range(levels))
    out.append(f"counts AS (SELECT r.qid, CAST(coalesce(c0.c, 0) AS BIGINT) AS cells_array, CAST(coalesce(tops.c, 0) + {low} AS BIGINT) AS cells_buffer, CAST(coalesce(tops.c, 0) AS BIGINT) AS top FROM ranges r {joins} LEFT JOIN tops ON tops.qid = r.qid)")
    return ", ".join(out)


# --- disjoint bins

query("WITH arr AS (" + fixture_sql("event_value") + ") SELECT idx // 32 AS bin, CAST(sum(val) AS BIGINT) AS s FROM arr GROUP BY 1", "bin_build_sum")(lambda s, d: B.build_bins(fixture(s, d, "event_value"), A.sum_spec(), 32).df)
query(
    "WITH arr AS (" + fixture_sql("event_value") + ") SELECT idx // 32 AS bin, CAST(sum(val) AS BIGINT) AS m0, CAST(sum((idx % 32) * val) AS BIGINT) AS m1, CAST(sum((idx % 32) * (idx % 32) * val) AS BIGINT) AS m2, "
    "CAST(least(32, (SELECT max(idx) + 1 FROM arr) - (idx // 32) * 32) AS BIGINT) AS cells FROM arr GROUP BY 1, idx // 32",
    "bin_build_moments",
)(lambda s, d: B.with_count(B.build_bins(fixture(s, d, "event_value"), A.moment_spec(2), 32)))


def _bin(spec: A.AggSpec, array: str = "event_value", b: int | None = 32, cast: str | None = None) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        arr, r = _setup(s, d, array, b or 32)
        out = B.query_bins(arr, B.build_bins(arr, spec, b or B.optimal_bin(arr.n)), r)
        return out.withColumn("result", F.col("result").cast(cast) if cast != "r6" else F.round("result", 6)) if cast else out

    return run


R6 = "round({0}, 6)"
query(range_sql("event_value", SUM), "bin_query_sum")(_bin(A.sum_spec(), cast="long"))
query(range_sql("order_total", SUM), "bin_query_sum_sqrt")(_bin(A.sum_spec(), "order_total", None, "long"))
query(range_sql("event_value", "CAST(count(val) AS BIGINT)"), "bin_query_count")(_bin(A.count_spec()))
query(range_sql("event_value", R6.format("CAST(sum(val) AS DOUBLE) / nullif(count(val), 0)")), "bin_query_avg")(_bin(A.avg_spec(), cast="r6"))
query(range_sql("event_value", moment_sql(1)), "bin_query_moments")(_bin(A.moment_spec(1), cast="long"))
query(range_sql("event_value", moment_sql(2)), "bin_query_moment2")(_bin(A.moment_spec(2, exact=True), cast="long"))
query(range_sql("order_total", "max(val)"), "bin_query_max")(_bin(A.max_spec(), "order_total"))
query(range_sql("order_total", "min(val)"), "bin_query_min")(_bin(A.min_spec(), "order_total"))
query(
    base_sql("order_total") + ", r AS (SELECT qid, val, row_number() OVER (PARTITION BY qid ORDER BY val DESC) AS k FROM ranges JOIN arr ON idx BETWEEN p AND q) SELECT qid, CAST(string_agg(CAST(val AS VARCHAR), ',' ORDER BY val DESC) AS VARCHAR) AS result FROM r WHERE k <= 5 GROUP BY qid",
    "bin_query_topn",
)(lambda s, d: _bin(A.topn_spec(5), "order_total")(s, d).withColumn("result", F.array_join(F.transform("result", lambda x: x.cast("string")), ",")))
_STD = "sqrt(greatest(0, CAST(sum(idx * idx * val) - 2 * p * sum(idx * val) + p * p * sum(val) AS DOUBLE) / nullif(sum(val), 0) - pow(CAST(sum((idx - p) * val) AS DOUBLE) / nullif(sum(val), 0), 2)))"
query(range_sql("part_price", "round(" + _STD + ", 6)").replace("GROUP BY qid", "GROUP BY qid, p"), "bin_query_std")(_bin(A.std_spec(), "part_price", cast="r6"))
query(range_sql("event_minute", R6.format("CAST(sum((idx - p) * val) AS DOUBLE) / nullif(sum(val), 0)"), 256).replace("GROUP BY qid", "GROUP BY qid, p"), "bin_query_center")(_bin(A.center_of_mass_spec(), "event_minute", 256, cast="r6"))


@query(base_sql("event_value").replace("SELECT event_id AS idx, CAST", "SELECT event_id AS idx, CAST") + f", {UPD}, m AS (SELECT idx, val FROM arr UNION ALL SELECT idx, delta FROM upd) SELECT CAST(idx // 32 AS BIGINT) AS bin, CAST(sum(val) AS BIGINT) AS m0, CAST(sum((idx % 32) * val) AS BIGINT) AS m1 FROM m GROUP BY 1")
def bin_update_linear(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value")
    return B.apply_updates(B.build_bins(arr, A.moment_spec(1), 32), _updates(s, arr.n)).df


@query(base_sql("order_total") + f", {UPD}, m AS (SELECT idx, sum(val) AS val FROM (SELECT idx, val FROM arr UNION ALL SELECT idx, delta FROM upd) GROUP BY idx) SELECT CAST(idx // 32 AS BIGINT) AS bin, CAST(max(val) AS BIGINT) AS hi FROM m GROUP BY 1")
def bin_rebuild_max(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "order_total")
    u = _updates(s, arr.n)
    return B.rebuild_bins(B.updated(arr, u), B.build_bins(arr, A.max_spec(), 32), u).df


@query(base_sql("event_value") + f", al AS (SELECT qid, (p // 32) * 32 AS p, (q // 32 + 1) * 32 - 1 AS q FROM ranges, nn WHERE (q // 32 + 1) * 32 <= n) SELECT qid, {SUM} AS result FROM al LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid")
def bin_aligned_only(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d)
    al = r.select("qid", F.expr("p div 32 * 32").alias("p"), F.expr("(q div 32 + 1) * 32 - 1").alias("q")).where(F.col("q") < arr.n)
    return B.query_bins(arr, B.build_bins(arr, A.sum_spec(), 32), al, aligned_only=True).select("qid", F.col("result").cast("long").alias("result"))


_BINS = "bins AS (SELECT idx // 32 AS bin, sum(val) AS s FROM arr GROUP BY 1)"
query(base_sql("event_value") + f", {_BINS} SELECT qid, CAST(coalesce(sum(s), 0) AS BIGINT) AS estimate FROM ranges LEFT JOIN bins ON bin * 32 >= p AND bin * 32 + 31 <= q GROUP BY qid", "bin_approx_inner")(
    lambda s, d: (lambda a, r: B.approx_bins(B.build_bins(a, A.sum_spec(), 32), r, "inner").select("qid", F.col("estimate").cast("long").alias("estimate")))(*_setup(s, d))
)
query(base_sql("event_value") + f", {_BINS} SELECT qid, CAST(coalesce(sum(s), 0) AS BIGINT) AS estimate FROM ranges LEFT JOIN bins ON 2 * (least(q, bin * 32 + 31) - greatest(p, bin * 32) + 1) > 32 GROUP BY qid", "bin_approx_half")(
    lambda s, d: (lambda a, r: B.approx_bins(B.build_bins(a, A.sum_spec(), 32), r, "half").select("qid", F.col("estimate").cast("long").alias("estimate")))(*_setup(s, d))
)


@query(base_sql("event_value") + f" SELECT qid, {SUM} AS total, max(val) AS largest FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid")
def bin_query_joint(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d)
    both = A.joint(A.sum_spec(), A.max_spec())
    return B.query_bins(arr, B.build_bins(arr, both, 32), r).select("qid", F.col("result.sum").cast("long").alias("total"), F.col("result.max").alias("largest"))


@query("SELECT * FROM (VALUES ('count', CAST(0 AS BIGINT)), ('sum', 0), ('max', 0), ('sum_linear', 0), ('sum_invertible', 0)) t(property, violations)")
def spec_properties(s: SparkSession, d: str) -> DataFrame:
    df = fixture(s, d, "event_value").df
    rows = [("count", A.check_distributive(A.sum_spec(), df, 100)), ("sum", A.check_distributive(A.sum_spec(), df, 500)), ("max", A.check_distributive(A.max_spec(), df, 321)), ("sum_linear", A.check_linear(A.sum_spec(), df)), ("sum_invertible", A.check_invertible(A.sum_spec(), df, 77))]
    out = None
    for name, bad in rows:
        one = bad.agg(F.count("*").alias("violations")).select(F.lit(name).alias("property"), "violations")
        out = one if out is None else out.unionByName(one)
    return out


# --- pyramid

_PYR = "SELECT 1 AS level, idx // 4 AS cell, CAST(sum(val) AS BIGINT) AS s FROM arr GROUP BY 2 UNION ALL SELECT 2, idx // 16, CAST(sum(val) AS BIGINT) FROM arr GROUP BY 2 UNION ALL SELECT 3, idx // 64, CAST(sum(val) AS BIGINT) FROM arr GROUP BY 2"


def _pyr(spec: A.AggSpec, s: SparkSession, d: str, array: str = "event_value", b: int = 4, levels: int = 3, inplace: bool = False):
    arr, r = _setup(s, d, array)
    return arr, P.build_pyramid(arr, spec, b, levels, inplace), r


def _longs(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[F.col(c).cast("long").alias(c) if c in cols else F.col(c) for c in df.columns])


query(f"WITH arr AS ({fixture_sql('event_value')}) {_PYR}", "pyr_build_sum")(lambda s, d: _longs(_pyr(A.sum_spec(), s, d)[1].df, "s"))
query(f"WITH arr AS ({fixture_sql('event_value')}), l AS ({_PYR}) SELECT * FROM l WHERE level = 3 OR cell % 4 <> 0", "pyr_build_inplace")(lambda s, d: _longs(_pyr(A.sum_spec(), s, d, inplace=True)[1].df, "s"))
query(f"WITH arr AS ({fixture_sql('event_value')}) {_PYR}", "pyr_recover_cell")(lambda s, d: _longs(P.recover(_pyr(A.sum_spec(), s, d, inplace=True)[1]).df, "s"))
query(range_sql("event_value", SUM), "pyr_query_sum")(lambda s, d: _longs((lambda a, p, r: P.query_pyramid(a, p, r))(*_pyr(A.sum_spec(), s, d)), "result"))
query(range_sql("event_value", SUM), "pyr_query_sum_inplace")(lambda s, d: _longs((lambda a, p, r: P.query_pyramid(a, p, r))(*_pyr(A.sum_spec(), s, d, inplace=True)), "result"))
query(range_sql("order_total", "max(val)"), "pyr_query_max")(lambda s, d: (lambda a, p, r: P.query_pyramid(a, p, r))(*_pyr(A.max_spec(), s, d, "order_total", 8)))
query(range_sql("event_value", moment_sql(1)), "pyr_query_moments")(lambda s, d: _longs((lambda a, p, r: P.query_pyramid(a, p, r))(*_pyr(A.moment_spec(1), s, d)), "result"))
query(f"{base_sql('event_value')}, {UPD}, m AS (SELECT idx, val FROM arr UNION ALL SELECT idx, delta FROM upd) {_PYR.replace('FROM arr', 'FROM m')}", "pyr_update_linear")(lambda s, d: (lambda a, p, r: _longs(P.update_pyramid(p, _updates(s, a.n)).df, "s"))(*_pyr(A.sum_spec(), s, d)))


@query(f"{base_sql('order_total')}, {UPD}, m AS (SELECT idx, sum(val) AS val FROM (SELECT idx, val FROM arr UNION ALL SELECT idx, delta FROM upd) GROUP BY idx) " + _PYR.replace("CAST(sum(val) AS BIGINT) AS s", "CAST(max(val) AS BIGINT) AS hi").replace("sum(val)", "max(val)").replace("FROM arr", "FROM m").replace("// 64", "// 512").replace("// 16", "// 64").replace("// 4 ", "// 8 "))
def pyr_refresh_max(s: SparkSession, d: str) -> DataFrame:
    arr, pyr, _ = _pyr(A.max_spec(), s, d, "order_total", 8)
    u = _updates(s, arr.n)
    return P.refresh_pyramid(B.updated(arr, u), pyr, u).df


@query(
    f"WITH arr AS ({fixture_sql('event_minute')}), c AS (SELECT idx // 3 AS bin, idx // 9 AS wide, val FROM arr WHERE idx BETWEEN 1 AND 43198) "
    "SELECT 'one_scale' AS method, CAST(count(DISTINCT bin) AS BIGINT) AS terms, CAST(sum(val) AS BIGINT) AS total FROM c UNION ALL SELECT 'two_scales', CAST(count(DISTINCT CASE WHEN wide BETWEEN 1 AND 4798 THEN -1 - wide ELSE bin END) AS BIGINT), CAST(sum(val) AS BIGINT) FROM c"
)
def pyr_worked_example(s: SparkSession, d: str) -> DataFrame:
    """The events' minutes but the first and the last, bins of 3: terms merged (fragments and cells of the cover that hold events) with one scale and with two, and their sum."""
    arr, out = fixture(s, d, "event_minute"), None
    r = s.createDataFrame([(0, 1, arr.n - 2)], "qid long, p long, q long")
    for name, levels in (("one_scale", 1), ("two_scales", 2)):
        pyr = P.build_pyramid(arr, A.sum_spec(), 3, levels)
        term = F.when(F.col("level") == 0, F.concat(F.lit("fragment "), F.expr("cell div 3"))).otherwise(F.concat_ws(" ", "level", "cell"))
        cells = arr.df.select(F.lit(0).alias("level"), F.col("idx").alias("cell"), F.col("val").alias("s")).unionByName(pyr.df.select("level", "cell", "s"))
        one = cells.join(P.cover(r, 3, levels).select("level", "cell"), ["level", "cell"]).agg(F.count_distinct(term).alias("terms"), F.sum("s").alias("total")).select(F.lit(name).alias("method"), "terms", "total")
        out = one if out is None else out.unionByName(one)
    return out


# --- overlapped bins


@query("WITH arr AS (" + fixture_sql("event_value") + ") SELECT idx // 32 AS cell, CAST(sum(val) AS BIGINT) AS v FROM arr GROUP BY 1")
def ovl_box_equals_bins(s: SparkSession, d: str) -> DataFrame:
    return O.build_overlap(fixture(s, d, "event_value"), 32, 0, 1, box_weight).select("cell", F.round("v").cast("long").alias("v"))


_HAT = "SELECT cell, CAST(sum(v) AS BIGINT) AS v32 FROM (SELECT idx // 32 AS cell, (32 - idx % 32) * val AS v FROM arr UNION ALL SELECT idx // 32 + 1, (idx % 32) * val FROM arr) WHERE cell * 32 < (SELECT max(idx) + 1 FROM arr) GROUP BY cell"


@query(f"WITH arr AS ({fixture_sql('event_value')}) {_HAT}")
def ovl_hat_build(s: SparkSession, d: str) -> DataFrame:
    return O.build_overlap(fixture(s, d, "event_value"), 32, 1, 1, hat_weight).select("cell", F.round(F.col("v") * 32).cast("long").alias("v32"))


def _hat_query(f: Callable[[Column], Column]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        arr, r = _setup(s, d)
        buf = O.build_overlap(arr, 32, 1, 1, hat_weight, scale=32)
        return O.query_overlap(arr, buf, 32, 1, 1, hat_weight, f, r, scale=32)

    return run


query(range_sql("event_value", SUM), "ovl_hat_query_sum")(_hat_query(lambda x: F.lit(1.0)))
query(range_sql("event_value", moment_sql(1)), "ovl_hat_query_first")(_hat_query(lambda x: x - F.col("p")))
query(range_sql("event_value", BIG0.format("CASE WHEN idx % 7 = 3 THEN 2 * val ELSE val END")), "ovl_any_function")(_hat_query(lambda x: F.when(F.pmod(x, F.lit(7)) == 3, 2.0).otherwise(1.0)))


# --- Lagrange moment buffer


def _lag(s: SparkSession, d: str, array: str = "event_value", b: int = 8, order: int = 4, levels: int | None = 1, mode: str = "exact"):
    arr, r = _setup(s, d, array, 32)
    return arr, L.build_lagrange(arr, b, order, levels, mode), r


_W4 = ["-t*(t-8)*(t-16)", "3*(t+8)*(t-8)*(t-16)", "-3*(t+8)*t*(t-16)", "(t+8)*t*(t-8)"]


@query(f"WITH arr AS ({fixture_sql('event_value')}), w AS (SELECT r, k, CAST(CASE k WHEN -1 THEN -r*(r-8)*(r-16) WHEN 0 THEN 3*(r+8)*(r-8)*(r-16) WHEN 1 THEN -3*(r+8)*r*(r-16) ELSE (r+8)*r*(r-8) END AS BIGINT) AS w3072 FROM range(8) a(r), (VALUES (-1), (0), (1), (2)) b(k)) SELECT r, k, w3072, CAST(sum(w3072 * val) AS BIGINT) AS given FROM arr JOIN w ON r = idx % 8 GROUP BY r, k, w3072")
def lag_weights(s: SparkSession, d: str) -> DataFrame:
    """Weights by offset and sample, and what the events at each offset give to that sample."""
    w = weight_table(s, 8, Stencil.of(4)).select("r", "k", F.round(F.col("w") * 3072).cast("long").alias("w3072"))
    sums = fixture(s, d, "event_value").df.groupBy((F.col("idx") % 8).alias("r")).agg(F.sum("val").alias("v"))
    return sums.join(F.broadcast(w), "r").select("r", "k", "w3072", (F.col("w3072") * F.col("v")).alias("given"))


query(f"WITH arr AS ({fixture_sql('event_value')}) {_HAT}".replace("v32", "v"), "lag_build_n2")(lambda s, d: _lag(s, d, b=32, order=2)[1].df.select(F.col("pos").alias("cell"), F.col("v").cast("long").alias("v")))
_L4 = " UNION ALL ".join(f"SELECT idx // 8 + {k} AS pos, ({w.replace('t', '(idx % 8)')}) * val AS v FROM arr" for k, w in zip((-1, 0, 1, 2), _W4, strict=True))
query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT 1 AS level, pos, CAST(sum(v) AS BIGINT) AS v FROM ({_L4}) WHERE pos >= 0 AND pos * 8 < (SELECT max(idx) + 1 FROM arr) GROUP BY pos", "lag_build_n4")(lambda s, d: _longs(_lag(s, d)[1].df, "v"))
_L4B = " UNION ALL ".join(f"SELECT pos // 8 + {k} AS pos, ({w.replace('t', '(pos % 8)')}) * v AS v FROM one" for k, w in zip((-1, 0, 1, 2), _W4, strict=True))
query(
    f"WITH arr AS ({fixture_sql('event_value')}), one AS (SELECT pos, CAST(sum(v) AS HUGEINT) AS v FROM ({_L4}) WHERE pos >= 0 AND pos * 8 < (SELECT max(idx) + 1 FROM arr) GROUP BY pos), two AS (SELECT pos, CAST(sum(v) AS HUGEINT) AS v FROM ({_L4B}) WHERE pos >= 0 AND pos * 64 < (SELECT max(idx) + 1 FROM arr) GROUP BY pos) "
    "SELECT 1 AS level, pos * 1 AS cell, CAST(v AS VARCHAR) AS v FROM one WHERE pos % 8 <> 0 UNION ALL SELECT 2, pos * 8, CAST(v AS VARCHAR) FROM two",
    "lag_build_hier",
)(lambda s, d: _lag(s, d, levels=2)[1].cells.select("level", "cell", F.col("v").cast("string").alias("v")))


def _lagq(k: int, c: str | int = "p", **build) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        arr, buf, r = _lag(s, d, **build)
        return L.query_lagrange(arr, buf, r, L.moment_poly(k, c))

    return run


query(range_sql("event_value", SUM), "lag_query_sum")(_lagq(0))
query(range_sql("event_value", moment_sql(1)), "lag_query_m1")(_lagq(1))
query(range_sql("part_price", moment_sql(2)), "lag_query_m2")(_lagq(2, array="part_price"))
query(range_sql("part_price", moment_sql(3)), "lag_query_m3")(_lagq(3, array="part_price"))
query(range_sql("order_total", SUM), "lag_query_hier_sum")(_lagq(0, array="order_total", levels=3))
query(range_sql("event_value", moment_sql(1)), "lag_query_hier_m1")(_lagq(1, levels=3))
query(range_sql("part_price", moment_sql(3)), "lag_query_hier_m3")(_lagq(3, array="part_price", b=4, levels=3))
query(range_sql("event_value", SUM), "lag_query_n8")(_lagq(0, b=4, order=8, levels=2))
query(range_sql("event_value", moment_sql(1)), "lag_query_odd")(_lagq(1, b=4, order=3, levels=2))
query(range_sql("event_value", SUM), "lag_query_n16_double")(lambda s, d: _lagq(0, b=32, order=16, levels=1, mode="double")(s, d).select("qid", F.round("result").cast("long").alias("result")))
query(range_sql("part_price", moment_sql(2, "-37")), "lag_local_center")(_lagq(2, -37, array="part_price", levels=2))
query(range_sql("price_cents", SUM), "lag_query_price_hier")(_lagq(0, array="price_cents", b=32, levels=None))


@query(f"{base_sql('event_value')}, {UPD}, m AS (SELECT idx, val FROM arr UNION ALL SELECT idx, delta FROM upd) SELECT qid, {SUM} AS result FROM ranges LEFT JOIN m ON idx BETWEEN p AND q GROUP BY qid")
def lag_update_batch(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, levels=2)
    u = _updates(s, arr.n)
    return L.query_lagrange(B.updated(arr, u), L.update_lagrange(buf, u), r)


@query(f"{base_sql('event_value')}, m AS (SELECT idx, CASE WHEN idx % 11 = 0 THEN 5 ELSE val END AS val FROM arr) SELECT qid, {moment_sql(1)} AS result FROM ranges LEFT JOIN m ON idx BETWEEN p AND q GROUP BY qid")
def lag_set_values(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, levels=2)
    new = arr.df.where("idx % 11 = 0").select("idx", F.lit(5).cast("long").alias("val"))
    now = arr.with_df(arr.df.withColumn("val", F.when(F.col("idx") % 11 == 0, F.lit(5).cast("long")).otherwise(F.col("val"))))
    return L.query_lagrange(now, L.set_values(arr, buf, new), r, L.moment_poly(1, "p"))


@query(base_sql("part_price") + " SELECT qid, round(coalesce(sum((2 - (idx - p) + 0.5 * (idx - p) * (idx - p)) * val), 0), 2) + 0.0 AS result FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid, p")
def lag_query_poly(s: SparkSession, d: str) -> DataFrame:
    """A polynomial whose coefficients each range brings along."""
    arr, buf, r = _lag(s, d, "part_price", mode="double")
    r = r.withColumn("coef", F.array(F.lit(2.0), F.lit(-1.0), F.lit(0.5)))
    return L.query_lagrange(arr, buf, r, lambda x: poly_eval(F.col("coef"), (x - F.col("p")).cast("double"))).select("qid", (F.round("result", 2) + 0.0).alias("result"))


query(range_sql("event_second", SUM), "lag_sparse_build")(_lagq(0, array="event_second", b=32, levels=2))


@query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT pos, CAST(sum(v) AS BIGINT) AS v3072 FROM ({_L4}) WHERE pos >= 0 AND pos * 8 < (SELECT max(idx) + 1 FROM arr) GROUP BY pos")
def lag_from_bins(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value")
    return L.from_bin_moments(B.build_bins(arr, A.moment_spec(3), 8).df, 8, arr.n, 4).df.select("pos", F.round(F.col("v") * 3072).cast("long").alias("v3072"))


@query(base_sql("event_value") + ", e AS (SELECT qid, (p + 7) // 8 AS e, q // 8 AS f, p // 8 AS pb FROM ranges), c AS (SELECT qid, unnest([e - 2, e - 1, e, f - 1, f, f + 1, pb, f]) AS bin FROM e) SELECT DISTINCT qid, bin FROM c, nn WHERE bin >= 0 AND bin < (n + 7) // 8")
def lag_candidates(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d)
    return L.candidates(r, 8, 0, Stencil.of(4), -(-arr.n // 8)).select("qid", "bin")


_EDGES = "SELECT {0} AS level, c AS cell, c // 2 + k AS parent FROM {1}, range(-1, 3) u(k) WHERE (c % 2 <> 0 OR k = 0) AND c // 2 + k >= 0 AND (c // 2 + k) * {2} < 43200"


@query(f"WITH arr AS ({fixture_sql('event_minute')}), l0 AS (SELECT DISTINCT idx AS c FROM arr), e1 AS ({_EDGES.format(1, 'l0', 2)}), l1 AS (SELECT DISTINCT parent AS c FROM e1) SELECT * FROM e1 UNION ALL {_EDGES.format(2, 'l1', 4)}")
def lag_update_dag(s: SparkSession, d: str) -> DataFrame:
    """Which cells of two levels a change at any minute with events reaches."""
    arr = fixture(s, d, "event_minute")
    return L.update_edges(arr.df.select(F.col("idx").alias("j")), 2, Stencil.of(4), 2, arr.n)


@query(range_sql("event_value", moment_sql(1)))
def lag_endpoint_table(s: SparkSession, d: str) -> DataFrame:
    """First moments with the ends' residuals looked up in the table of all offsets and monomials."""
    arr, buf, r = _lag(s, d)
    r = r.withColumn("c0", F.lit(0)).withColumn("c1", F.lit(8))  # (i - p) = 8 ((i - p) / 8)
    return L.query_tabulated(arr, buf, r, L.endpoint_table(s, 8, Stencil.of(4), "exact"), ["c0", "c1"])


# --- approximate and progressive


@query(base_sql("event_value") + f", {weights_sql('32', 4)}, cells AS (SELECT idx // 32 + k AS pos, sum(w * val) AS v FROM arr JOIN wt ON r = idx % 32 GROUP BY 1) SELECT qid, CAST(trunc(coalesce(sum(v), 0) + 1e-6) AS BIGINT) AS estimate FROM ranges LEFT JOIN cells ON pos * 32 BETWEEN p AND q GROUP BY qid")
def prog_buffer_only(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, b=32)
    return G.approx_lagrange(buf, r)


@query(range_sql("event_value", SUM), "prog_rings_final")
def prog_rings_final(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, b=32, mode="double")
    return G.progressive(arr, buf, r).where("ring = 4").select("qid", F.round("estimate").cast("long").alias("result"))


def rings_sql(array: str, b: int, n: int, select: str, count: int = COUNT) -> str:
    """CTEs up to rings (qid, ring, estimate) by summing what bin-wise interpolation misses, bin by bin, from every bin near an end."""
    return (
        base_sql(array, 32, count) + f", {weights_sql(str(b), n)}, cells AS (SELECT idx // {b} + k AS pos, sum(w * val) AS v FROM arr JOIN wt ON r = idx % {b} GROUP BY 1), start AS (SELECT qid, sum(v) AS x FROM ranges JOIN cells ON pos * {b} BETWEEN p AND q GROUP BY qid), "
        f"near AS (SELECT DISTINCT qid, p, q, bin FROM (SELECT qid, p, q, unnest(list_concat(range(p // {b} - {n}, p // {b} + {n + 1}), range(q // {b} - {n}, q // {b} + {n + 1}))) AS bin FROM ranges) WHERE bin >= 0), "
        f"sampled AS (SELECT qid, p, q, bin, r, sum(CASE WHEN (bin + k) * {b} BETWEEN p AND q THEN w ELSE 0 END) AS h FROM near, wt GROUP BY ALL), "
        f"rest AS (SELECT qid, least(abs(bin - p // {b}), abs(bin - q // {b})) + 1 AS ring, sum(((CASE WHEN idx BETWEEN p AND q THEN 1 ELSE 0 END) - h) * val) AS x FROM sampled JOIN arr ON idx = bin * {b} + r GROUP BY 1, 2), "
        f"rings AS (SELECT qid, ring, coalesce((SELECT x FROM start WHERE start.qid = ranges.qid), 0) + coalesce((SELECT sum(x) FROM rest WHERE rest.qid = ranges.qid AND rest.ring <= u.ring), 0) AS estimate FROM ranges, range({n + 1}) u(ring)) {select}"
    )


@query(rings_sql("event_value", 32, 4, "SELECT qid, ring, round(estimate, 2) AS estimate, CASE WHEN ring < 4 THEN CAST(2 * 60000.0 * 32 AS DOUBLE) ELSE 0 END AS bound FROM rings"))
def prog_steps(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, b=32, mode="double")
    return G.progressive(arr, buf, r, kappa=60_000.0).withColumn("estimate", F.round("estimate", 2) + 0.0)


@query(f"WITH arr AS ({fixture_sql('ship_day')}), k AS (SELECT CAST(max(abs(val)) AS DOUBLE) AS kappa FROM arr) SELECT method, x * kappa * 2500 / 64 AS bound FROM k, (VALUES ('bins_inner', CAST(4.0 AS DOUBLE)), ('bins_half', CAST(2.0 AS DOUBLE)), ('lagrange', CAST(1.0 AS DOUBLE))) t(method, x)")
def error_bounds(s: SparkSession, d: str) -> DataFrame:
    """Bounds at 64 numbers of memory for the ship-day array's own greatest value."""
    arr = fixture(s, d, "ship_day")
    kappa = F.col("kappa")
    bounds = [F.struct(F.lit(m).alias("method"), G.error_bound(m, 2, 64, arr.n, kappa).alias("bound")) for m in ("bins_inner", "bins_half", "lagrange")]
    return arr.df.agg(F.max(F.abs("val")).cast("double").alias("kappa")).select(F.inline(F.array(*bounds)))


def _share_sql(n: int, b: int, kept: int) -> str:
    m, mp = n // 2, n - n // 2
    near = ", ".join(map(str, sorted(range(1 - m, mp), key=lambda d: (abs(d), d))[:kept]))
    far = lambda f, x: f"{f}(CASE WHEN d IN ({near}) THEN 0 ELSE {x} END)"
    share = lambda f, x: f"round(1 - {far(f, x)} / {f}({x}), 6)"
    return (
        f"SELECT * FROM (WITH arr AS ({fixture_sql('event_value')}), {weights_sql(str(b), n)}, prof AS (SELECT d, r, (CASE WHEN d * {b} + r >= {b // 2} THEN 1 ELSE 0 END) - sum(CASE WHEN (d + k) * {b} >= {b // 2} THEN w ELSE 0 END) AS rest FROM wt, range({1 - m}, {mp}) u(d) GROUP BY d, r), "
        f"x AS (SELECT d, abs(rest * val) AS l1, rest * val * rest * val AS l2 FROM arr JOIN prof ON r = idx % {b}) SELECT CAST({n} AS INTEGER) AS n, CAST({kept} AS INTEGER) AS kept, {share('sum', 'l1')} AS l1, {share('sum', 'l2')} AS energy, {share('max', 'l1')} AS sup, round(1 - {far('sum', 'CASE WHEN d > 0 THEN l1 ELSE 0 END')} / (sum(l1) / 2), 6) AS one_side FROM x)"
    )


_SHARES = ((4, 1024, 1), (16, 128, 5), (8, 128, 3))


@query(" UNION ALL ".join(_share_sql(*x) for x in _SHARES))
def error_share(s: SparkSession, d: str) -> DataFrame:
    """Share of the endpoint error over the events that the centre bins remove, by order and bins kept."""
    arr, out = fixture(s, d, "event_value"), None
    for n, b, k in _SHARES:
        one = G.measured_share(arr, n, b, k).select(F.lit(n).alias("n"), F.lit(k).alias("kept"), *[F.round(c, 6).alias(c) for c in ("l1", "energy", "sup", "one_side")])
        out = one if out is None else out.unionByName(one)
    return out


@query(" UNION ALL ".join(f'SELECT * FROM (WITH arr AS ({fixture_sql("event_value")}), {weights_sql("256", n)} SELECT CAST({n} AS INTEGER) AS n, CAST(k AS INTEGER) AS k, round(max(abs(w)), 9) AS sup FROM wt WHERE r IN (SELECT idx % 256 FROM arr) GROUP BY k)' for n in (4, 8, 16)))
def sample_influence(s: SparkSession, d: str) -> DataFrame:
    """Largest weight of each sample over the offsets at which there are events."""
    seen, out = fixture(s, d, "event_value").df.select((F.col("idx") % 256).alias("r")).distinct(), None
    for n in (4, 8, 16):
        w = weight_table(s, 256, Stencil.of(n)).join(seen, "r", "left_semi")
        one = w.groupBy("k").agg(F.round(F.max(F.abs("w")), 9).alias("sup")).select(F.lit(n).alias("n"), "k", "sup")
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT CAST(256 AS BIGINT) AS cells, CAST(132 AS DOUBLE) AS inside, CAST(0 AS BIGINT) AS off_far")
def step_profile(s: SparkSession, d: str) -> DataFrame:
    p = G.step_profile(s, 16, 8)
    far = (F.col("h") != F.col("f")) & ((F.col("i") < 132 - 64) | (F.col("i") > 132 + 64))
    return p.agg(F.count("*").alias("cells"), (F.lit(256.0) - F.sum("f") + 0.0).alias("inside"), F.sum((far & (F.abs(F.col("h") - F.col("f")) > 1e-9)).cast("long")).alias("off_far"))


@query()
def equal_memory_errors(s: SparkSession, d: str) -> DataFrame:
    """Mean absolute error of buffer-only sums at equal memory K, by method and K, on the ship-day array."""
    arr, r = _setup(s, d, "ship_day")
    truth = D.scan_ranges(arr, r, A.sum_spec()).withColumnRenamed("result", "truth")
    out = None
    for K in (64, 256):
        for n in (2, 8):
            wide = -(-n * arr.n // K)
            bins = B.build_bins(arr, A.sum_spec(), wide)
            lag = L.build_lagrange(arr, -(-arr.n // (K - 1)), n, 1, "double")
            for m, e in (("bins_inner", B.approx_bins(bins, r, "inner")), ("bins_half", B.approx_bins(bins, r, "half")), ("lagrange", G.approx_lagrange(lag, r))):
                one = e.join(truth, "qid").agg(F.avg(F.abs(F.col("estimate").cast("double") - F.col("truth"))).alias("mean_error")).select(F.lit(m).alias("method"), F.lit(K).alias("K"), F.lit(n).alias("N"), "mean_error")
                out = one if out is None else out.unionByName(one)
    return out


# --- baselines

query(range_sql("event_value", SUM), "scan_sum")(lambda s, d: (lambda a, r: _longs(D.scan_ranges(a, r, A.sum_spec()), "result"))(*_setup(s, d)))
query(range_sql("event_value", moment_sql(1)), "scan_moments")(lambda s, d: (lambda a, r: _longs(D.scan_ranges(a, r, A.moment_spec(1)), "result"))(*_setup(s, d)))
query(range_sql("event_value", SUM), "prefix_query_sum")(lambda s, d: (lambda a, r: D.query_prefix(D.prefix_moments(a), r))(*_setup(s, d)))
query(range_sql("event_value", moment_sql(1, "0")), "prefix_query_m1")(lambda s, d: (lambda a, r: D.query_prefix(D.prefix_moments(a, 1), r, 1))(*_setup(s, d)))
query(range_sql("order_total", SUM), "blocked_prefix_query")(lambda s, d: (lambda a, r: D.query_blocked(*D.blocked_prefix(a, 128), r))(*_setup(s, d, "order_total")))
query(range_sql("event_value", SUM), "haar_query_full")(lambda s, d: (lambda a, r: D.query_haar(*D.haar_transform(a), r).select("qid", F.round("result").cast("long").alias("result")))(*_setup(s, d)))
_HAAR = (
    base_sql("event_value") + ", lv AS (SELECT CAST(ceil(log2(n)) AS INTEGER) AS top FROM nn), co AS (SELECT CAST(l AS INTEGER) AS level, idx >> l AS cell, sum(val) AS s, sum(CASE WHEN (idx >> (l - 1)) % 2 = 0 THEN val ELSE -val END) AS d FROM arr, lv, range(1, top + 1) t(l) GROUP BY 1, 2), "
    "best AS (SELECT level, cell, d FROM co ORDER BY CAST(d AS DOUBLE) * d / pow(2, level) DESC, level, cell LIMIT 64), ends AS (SELECT qid, q + 1 AS x, 1 AS sign FROM ranges UNION ALL SELECT qid, p, -1 FROM ranges), "
    "part AS (SELECT qid, sign * CAST(d AS DOUBLE) * least(x - (cell << level), (1 << level) - (x - (cell << level))) / (1 << level) AS v FROM ends JOIN best ON x >> level = cell UNION ALL SELECT qid, sign * CAST(s AS DOUBLE) * x / (1 << level) FROM ends, co, lv WHERE level = top) SELECT qid, round(sum(v), 4) + 0.0 AS result FROM part GROUP BY qid"
)
query(_HAAR, "haar_query_topk")(lambda s, d: (lambda a, r: D.query_haar(*D.haar_transform(a), r, 64).select("qid", (F.round("result", 4) + 0.0).alias("result")))(*_setup(s, d)))


# --- cost measures


_LEVELS = "(SELECT sum((n + CAST(pow(32, l) AS BIGINT) - 1) // CAST(pow(32, l) AS BIGINT)) FROM range(1, 7) t(l) WHERE l = 1 OR n // CAST(pow(32, l) AS BIGINT) >= 2)"


@query(
    f"WITH arr AS ({fixture_sql('event_value')}), nn AS (SELECT max(idx) + 1 AS n, count(DISTINCT idx // 32) AS bins FROM arr) SELECT u.buffer, CAST(u.x AS BIGINT) AS numbers, CAST(u.x AS BIGINT) AS formula FROM nn, LATERAL (VALUES ('bins_with_count', 5 * bins), ('bins', 4 * bins), ('pyramid', 4 * {_LEVELS}), ('pyramid_inplace', 4 * bins), ('lagrange', bins), ('prefix', 4 * n)) u(buffer, x)"
)
def cost_buffer_sizes(s: SparkSession, d: str) -> DataFrame:
    """Numbers that buffers of order 4 and bins of 32 really hold over the events, beside the formula's."""
    arr = fixture(s, d, "event_value")
    moments = A.moment_spec(3)
    bins = B.build_bins(arr, moments, 32)
    pyr = P.build_pyramid(arr, moments, 32)
    frames = {
        "bins_with_count": (B.with_count(bins), 5), "bins": (bins.df, 4), "pyramid": (pyr.df, 4), "pyramid_inplace": (P.to_inplace(pyr).df, 4),
        "lagrange": (L.build_lagrange(arr, 32, 4, 2).df, 1), "prefix": (D.prefix_moments(arr, 3), 4),
    }
    formula = C.buffer_sizes(arr.n, 32, 4)
    out = None
    for name, (df, width) in frames.items():
        one = df.agg((F.count("*") * width).alias("numbers")).select(F.lit(name).alias("buffer"), "numbers", F.lit(formula[name]).cast("long").alias("formula"))
        out = one if out is None else out.unionByName(one)
    return out


@query(base_sql("event_value", 8) + ", c AS (SELECT qid, p, q, ((p + 7) // 8) * 8 AS lo, ((q + 1) // 8) * 8 AS hi FROM ranges) SELECT qid, CAST(CASE WHEN lo >= hi THEN q - p + 1 ELSE (lo - p) + (q + 1 - hi) END AS BIGINT) AS cells_array, CAST(CASE WHEN lo >= hi THEN 0 ELSE (hi - lo) // 8 END AS BIGINT) AS cells_buffer FROM c")
def cost_query_cells(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d, b=8)
    return B.query_bins(arr, B.build_bins(arr, A.sum_spec(), 8), r, costs=True).select("qid", "cells_array", "cells_buffer")


def _lagrange_cells_sql(b: int, n: int) -> str:
    avg = lambda x: f"round(avg({x}), 6)"
    near = f"SELECT {b} AS b, {n} AS \"N\", k AS moment, {avg('cells_array')} AS cells_array, {avg('cells_buffer')} AS cells_buffer, {avg(f'top + cells_array * {n + 1}')} AS poly_evals, {avg(f'cells_array * {n}')} AS weight_evals"
    return f"({base_sql('event_value')}, {cells_sql(b, n, 1)} {near} FROM counts, (VALUES (0), (1)) u(k) GROUP BY k)"


_GRID = ((8, 4), (32, 4), (32, 8), (128, 4))


@query(" UNION ALL ".join(f"SELECT * FROM {_lagrange_cells_sql(b, n)}" for b, n in _GRID))
def cost_lagrange_cells(s: SparkSession, d: str) -> DataFrame:
    """Cells read and evaluations of f and of weights, for sums and first moments by order and bin size: equal for both, growing with N and b."""
    out = None
    for b, n in _GRID:
        arr, buf, r = _lag(s, d, b=b, order=n, levels=1, mode="double")
        for k in (0, 1):
            one = L.query_lagrange(arr, buf, r, L.moment_poly(k, "p"), costs=True).agg(*[F.round(F.avg(c), 6).alias(c) for c in L.COUNTS.values()])
            one = one.select(F.lit(b).alias("b"), F.lit(n).alias("N"), F.lit(k).alias("moment"), *L.COUNTS.values())
            out = one if out is None else out.unionByName(one)
    return out


_NEXT = "SELECT DISTINCT j, c // 4 + k AS c FROM {0}, range(-1, 3) u(k), nn WHERE (c % 4 <> 0 OR k = 0) AND c // 4 + k >= 0 AND (c // 4 + k) * {1} < n"


@query(
    f"WITH arr AS ({fixture_sql('event_minute')}), nn AS (SELECT 43200 AS n), l0 AS (SELECT DISTINCT idx AS j, idx AS c FROM arr), l1 AS ({_NEXT.format('l0', 4)}), l2 AS ({_NEXT.format('l1', 16)}), l3 AS ({_NEXT.format('l2', 64)}), a AS (SELECT 1 AS level, j FROM l1 UNION ALL SELECT 2, j FROM l2 UNION ALL SELECT 3, j FROM l3), "
    "k AS (SELECT level, j, count(*) AS c FROM a GROUP BY 1, 2) SELECT level, CAST(max(c) AS BIGINT) AS most, round(avg(c), 6) AS mean, max(c) <= 8 AS within FROM k GROUP BY level"
)
def cost_update_cells(s: SparkSession, d: str) -> DataFrame:
    """Cells of each level that a single change touches, over every minute with events: most, mean, and whether 2N bounds them."""
    arr = fixture(s, d, "event_minute")
    got = L.touched(arr.df.select(F.col("idx").alias("j")), 4, Stencil.of(4), 3, arr.n)
    each = got.groupBy("level", "j").agg(F.count("*").alias("c")).groupBy("level").agg(F.max("c").alias("most"), F.round(F.avg("c"), 6).alias("mean"))
    return each.select("level", "most", "mean", (F.col("most") <= 8).alias("within"))


@query(f"WITH arr AS ({fixture_sql('ship_day')}), h AS (SELECT K, CAST(count(DISTINCT idx // ((2 * 2500 + K - 1) // K)) AS BIGINT) AS bins FROM arr, (VALUES (64), (256)) a(K) GROUP BY K) SELECT K, E, CAST(2.0 AS DOUBLE) * 2500 / K AS b_bins, CAST(2500 AS DOUBLE) / (K - 1) AS b_lagrange, CAST(2 * E + K AS DOUBLE) AS cost, CAST(2 * bins AS BIGINT) AS held, CAST((bins + 1) * bins // 2 AS BIGINT) AS free_ranges FROM h, (VALUES (100), (1000)) b(E)")
def cost_equal_memory(s: SparkSession, d: str) -> DataFrame:
    """Bin sizes and cost at equal memory over the ship-day array, with the numbers that its bins hold then and the ranges they answer alone."""
    arr, out = fixture(s, d, "ship_day"), None
    for K in (64, 256):
        held = B.build_bins(arr, A.moment_spec(1), -(-2 * arr.n // K)).df.agg(F.count("*").alias("bins"))
        for E in (100, 1000):
            m = C.equal_memory(2, K, arr.n, E)
            one = held.select(F.lit(K).alias("K"), F.lit(E).alias("E"), F.lit(m["b_bins"]).alias("b_bins"), F.lit(m["b_lagrange"]).alias("b_lagrange"), F.lit(float(m["cost"])).alias("cost"), (F.col("bins") * 2).alias("held"), F.expr("(bins + 1) * bins div 2").alias("free_ranges"))
            out = one if out is None else out.unionByName(one)
    return out


@query(
    f"{base_sql('event_value')}, {cells_sql(32, 4, 1)} SELECT round(max(n) / (avg(q - p + 1) - avg(cells_array + cells_buffer)), 3) AS queries, CAST(max(n) // 4 AS BIGINT) AS cells, CAST(max(n) >= max(n) / 4 AS BOOLEAN) AS dense FROM ranges JOIN counts USING (qid), nn"
)
def cost_breakeven(s: SparkSession, d: str) -> DataFrame:
    """Measured in cells read: queries until building (one pass over the array) pays against scans, and non-zero cells up to which updates are the cheaper build."""
    arr, buf, r = _lag(s, d, b=32)
    read = L.query_lagrange(arr, buf, r, costs=True).join(r, "qid").agg(F.avg(F.col("q") - F.col("p") + 1).alias("scan"), F.avg(F.col("cells_array") + F.col("cells_buffer")).alias("cells")).first()
    rows = [(round(C.break_even(float(arr.n), read["scan"], read["cells"]), 3), int(C.sparse_break_even(float(arr.n), 4.0 * buf.levels)), not L.sparse_pays(arr.df.count(), arr.n, 4, buf.levels))]
    return s.createDataFrame(rows, "queries double, cells long, dense boolean")


@query("SELECT b, n, CAST(greatest(1, (SELECT count(*) FROM range(1, 7) u(l) WHERE floor(43200 / pow(CAST(b AS DOUBLE), l)) >= n)) AS INTEGER) AS levels FROM (VALUES (8, 4), (32, 4), (128, 4), (1024, 4), (32768, 4), (16, 8), (16, 16)) t(b, n)")
def cost_levels(s: SparkSession, d: str) -> DataFrame:
    """Levels of the buffers that are built over the events' minutes, by bin size and order."""
    arr, out = fixture(s, d, "event_minute"), None
    for b, n in ((8, 4), (32, 4), (128, 4), (1024, 4), (32768, 4), (16, 8), (16, 16)):
        one = L.build_lagrange(arr, b, n, mode="double").df.agg(F.max("level").alias("levels")).select(F.lit(b).alias("b"), F.lit(n).alias("n"), "levels")
        out = one if out is None else out.unionByName(one)
    return out


@query(base_sql("event_value") + ' SELECT k AS "N", CAST(count(*) AS BIGINT) AS ranges, CAST(0 AS BIGINT) AS off FROM ranges, (VALUES (4), (8), (16)) u(k) GROUP BY k')
def cost_numerical_error(s: SparkSession, d: str) -> DataFrame:
    """Ranges answered in double precision by order, and how many of them are off by more than 1e-9 of the answer."""
    out = None
    for n in (4, 8, 16):
        arr, buf, r = _lag(s, d, b=32, order=n, levels=1, mode="double")
        truth = D.scan_ranges(arr, r, A.sum_spec()).select("qid", F.col("result").cast("double").alias("y"))
        both = L.query_lagrange(arr, buf, r).join(truth, "qid")
        one = both.agg(F.count("*").alias("ranges"), F.sum((F.abs(F.col("result") - F.col("y")) > 1e-9 * F.greatest(F.lit(1.0), F.abs("y"))).cast("long")).alias("off")).select(F.lit(n).alias("N"), "ranges", "off")
        out = one if out is None else out.unionByName(one)
    return out


@query(base_sql("event_value", 8) + ", c AS (SELECT qid, q - p + 1 AS len, p, q, ((p + 7) // 8) * 8 AS lo, ((q + 1) // 8) * 8 AS hi FROM ranges), x AS (SELECT qid, len, CASE WHEN lo >= hi THEN len ELSE (lo - p) + (q + 1 - hi) END AS a, CASE WHEN lo >= hi THEN 0 ELSE (hi - lo) // 8 END AS b, ntile(10) OVER (ORDER BY len, qid) AS decile FROM c) SELECT decile, round(avg(len), 6) AS length, round(avg(a), 6) AS cells_array, round(avg(b), 6) AS cells_buffer FROM x GROUP BY decile")
def cost_length_deciles(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d, b=8)
    got = B.query_bins(arr, B.build_bins(arr, A.sum_spec(), 8), r, costs=True)
    return X.range_length_deciles(got, r).select("decile", *[F.round(c, 6).alias(c) for c in ("length", "cells_array", "cells_buffer")])


# --- applications

_N0 = "CAST(nullif(sum(val), 0) AS DOUBLE)"


@query(base_sql("price_cents") + f" SELECT qid, {SUM} AS items, {BIG0.format('idx * val')} AS value, round(p + CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}, 6) AS mean FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid, p")
def price_stats(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "price_cents", b=32, levels=2)
    return M.price_stats(arr, buf, r).select("qid", "items", "value", F.round("mean", 6).alias("mean"))


@query(base_sql("part_price") + f" SELECT qid, {SUM} AS items, {BIG0.format('idx * val')} AS value, round(p + CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}, 6) AS mean, round(sqrt(greatest(0, CAST(sum((idx - p) * (idx - p) * val) AS DOUBLE) / {_N0} - (CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}) * (CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}))), 6) AS std FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid, p")
def part_price_stats(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "part_price", levels=2)
    return M.price_stats(arr, buf, r).select("qid", "items", "value", F.round("mean", 6).alias("mean"), F.round("std", 6).alias("std"))


@query(base_sql("ship_day") + f" SELECT qid, {SUM} AS mass, round(CAST(coalesce(sum(val), 0) AS DOUBLE) / (q - p + 1), 6) AS density, round(p + CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}, 6) AS center FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid, p, q")
def ship_strip_stats(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "ship_day", levels=2)
    return M.strip_stats(arr, buf, r).select("qid", "mass", F.round("density", 6).alias("density"), F.round("center", 6).alias("center"))


_DENSE = ", dense AS (SELECT qid, p, q, i AS idx FROM (SELECT qid, p, q, unnest(range(p, q + 1)) AS i FROM ranges)), y AS (SELECT qid, CAST(dense.idx - p AS DOUBLE) AS x, CAST(coalesce(val, 0) AS DOUBLE) AS y FROM dense LEFT JOIN arr ON arr.idx = dense.idx)"


@query(base_sql("ship_day") + _DENSE + " SELECT qid, round(regr_slope(y, x), 2) AS slope, round(regr_intercept(y, x), 0) AS intercept FROM y GROUP BY qid HAVING count(*) > 3")
def fit_line(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "ship_day", levels=2)
    r = r.where("q - p >= 3")
    m = M.moments_of_ranges(arr, buf, r, 1, wide=True).join(r, "qid")
    return M.fit_line(m).select("qid", F.round("slope", 2).alias("slope"), F.round("intercept", 0).alias("intercept"))


_FIT = base_sql("event_minute") + ", dense AS (SELECT qid, p, q, i AS idx FROM (SELECT qid, p, q, unnest(range(p, q + 1)) AS i FROM ranges WHERE q - p >= 10)), y AS (SELECT qid, CAST(dense.idx - p AS DOUBLE) / (q - p + 1) AS u, CAST(coalesce(val, 0) AS DOUBLE) AS y FROM dense LEFT JOIN arr ON arr.idx = dense.idx)"
#: Quadratic by projections: u, then u^2 less its line, each against y.
_QUAD = (
    _FIT + ", a AS (SELECT qid, avg(u) AS mu, avg(u * u) AS mv, avg(y) AS my, regr_slope(u * u, u) AS t FROM y GROUP BY qid), w AS (SELECT y.qid, u, y, u - mu AS e1, u * u - mv - t * (u - mu) AS e2 FROM y JOIN a USING (qid)), "
    "c AS (SELECT qid, sum(e1 * y) / sum(e1 * e1) AS b1, sum(e2 * y) / sum(e2 * e2) AS b2 FROM w GROUP BY qid) SELECT qid, round(my - b1 * mu - b2 * (mv - t * mu), 2) + 0.0 AS c0, round(b1 - b2 * t, 2) + 0.0 AS c1, round(b2, 2) + 0.0 AS c2 FROM a JOIN c USING (qid)"
)


@query(_QUAD)
def fit_quadratic(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "event_minute", b=32, levels=2)
    r = r.where("q - p >= 10")
    fit = M.fit_poly(M.moments_of_ranges(arr, buf, r, 2, wide=True).join(r, "qid"), 2)
    return fit.select("qid", *[(F.round(F.col("coef")[k], 2) + 0.0).alias(f"c{k}") for k in range(3)])


def _squares(arr: IndexedArray) -> IndexedArray:
    """Squares outgrow longs before the values do."""
    val = F.col("val").cast(BIG)
    return arr.with_df(arr.df.withColumn("val", (val * val).cast(BIG)))


@query(_FIT + " SELECT qid, round((regr_syy(y, u) - coalesce(regr_sxy(y, u) * regr_sxy(y, u) / regr_sxx(y, u), 0)) / nullif(sum(y * y), 0), 6) + 0.0 AS share FROM y GROUP BY qid")
def fit_residual(s: SparkSession, d: str) -> DataFrame:
    """Share of the sum of squares that a line leaves."""
    arr, buf, r = _lag(s, d, "event_minute", b=32, levels=2)
    r = r.where("q - p >= 10")
    sq = _squares(arr)
    fit = M.fit_poly(M.moments_of_ranges(arr, buf, r, 1, wide=True).join(r, "qid"), 1)
    squares = L.query_lagrange(sq, L.build_lagrange(sq, 32, 4, 2), r, wide=True)
    return M.residual(fit, squares).join(squares, "qid").select("qid", (F.round(F.try_divide(F.col("residual"), F.col("result").cast("double")), 6) + 0.0).alias("share"))


@query()
def segment_series(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "ship_day")
    arr = arr.with_df(held(arr.df))  # every round asks for it again
    sq = _squares(arr)
    got = M.segment(arr, hold_lagrange(L.build_lagrange(arr, 32, 4, 1)), hold_lagrange(L.build_lagrange(sq, 32, 4, 1)), sq, 3, tries=2)
    return s.createDataFrame(got, "p long, q long, residual double")


@query("WITH arr AS (" + fixture_sql("event_minute") + f"), ranges AS (SELECT i AS qid, (i * 43200) // 96 AS p, ((i + 1) * 43200) // 96 - 1 AS q FROM range(96) t(i)) SELECT qid, {moment_sql(1)} AS result FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid")
def grid_moments(s: SparkSession, d: str) -> DataFrame:
    arr, buf, _ = _lag(s, d, "event_minute", b=32, levels=2)
    return L.query_lagrange(arr, buf, M.grid_ranges(s, 0, 43199, 96), L.moment_poly(1, "p"))


@query(base_sql("account") + f" SELECT qid, {SUM} AS mass, round(p + CAST(sum((idx - p) * val) AS DOUBLE) / {_N0}, 6) AS center FROM ranges LEFT JOIN arr ON idx BETWEEN p AND q GROUP BY qid, p")
def account_center(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, "account", levels=2)
    return M.strip_stats(arr, buf, r).select("qid", "mass", F.round("center", 6).alias("center"))


query(range_sql("supplier_account", SUM, 8), "supplier_sum")(lambda s, d: (lambda a, r: L.query_lagrange(a, L.build_lagrange(a, 4, 4, 1), r))(*_setup(s, d, "supplier_account", 8)))


@query(range_sql("event_value", SUM, keys=("event_type",)))
def keyed_by_event_type(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value", ("event_type",))
    return L.query_lagrange(arr, L.build_lagrange(arr, 8, 4, 2), random_ranges(s, arr.n, COUNT))


@query(range_sql("event_value", SUM, keys=("event_type",)))
def keyed_bins(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value", ("event_type",))
    return _longs(B.query_bins(arr, B.build_bins(arr, A.sum_spec(), 32), random_ranges(s, arr.n, COUNT)), "result")


_STAR = "(SELECT r_name, n_name, c_custkey AS i, CAST(round(c_acctbal * 100) AS BIGINT) AS v FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


def _star(s: SparkSession, d: str) -> DataFrame:
    c, n, r = (read(s, d, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).withColumn("v", F.expr("CAST(round(c_acctbal * 100) AS BIGINT)"))


_M01 = "CAST(sum(v) AS BIGINT) AS m0, CAST(sum(i * v) AS BIGINT) AS m1"
query(f"SELECT r_name, n_name, {_M01} FROM {_STAR} GROUP BY ROLLUP (r_name, n_name)", "region_rollup")(lambda s, d: M.additive_moments(_star(s, d), ["r_name", "n_name"], F.col("c_custkey"), F.col("v"), 1))
query(f"SELECT r_name, n_name, {_M01} FROM {_STAR} GROUP BY CUBE (r_name, n_name)", "cube_moments")(lambda s, d: M.additive_moments(_star(s, d), ["r_name", "n_name"], F.col("c_custkey"), F.col("v"), 1, "cube"))
query(f"SELECT r_name, n_name, {_M01} FROM {_STAR} GROUP BY GROUPING SETS ((r_name), (n_name), ())", "grouping_sets_moments")(lambda s, d: M.additive_moments(_star(s, d), ["r_name", "n_name"], F.col("c_custkey"), F.col("v"), 1, "grouping_sets", [["r_name"], ["n_name"], []]))

query("SELECT vec_id, round(list_sum(list_transform(range(8, 40), lambda i: (i - 8) * CAST(embedding[i + 1] AS DOUBLE))), 5) AS m1 FROM embeddings", "embedding_moments")(lambda s, d: read(s, d, "embeddings").select("vec_id", F.round(array_moment(F.col("embedding"), 8, 39, 8, 1), 5).alias("m1")))
query(range_sql("doc_len", moment_sql(1)), "doc_length_moments")(_lagq(1, array="doc_len", levels=2))
query(range_sql("page_len", moment_sql(1)), "page_length_moments")(_lagq(1, array="page_len", levels=2))
query(range_sql("bench_len", SUM, 8), "bench_length_sum")(lambda s, d: (lambda a, r: L.query_lagrange(a, L.build_lagrange(a, 4, 4, 1), r))(*_setup(s, d, "bench_len", 8)))
query(range_sql("turn_len", SUM), "turn_length_sum")(_lagq(0, array="turn_len", levels=2))
query(range_sql("label_quality", SUM), "label_quality_sum")(_lagq(0, array="label_quality", levels=2))
query(range_sql("props_hist", SUM, 8), "props_histogram")(lambda s, d: (lambda a, r: L.query_lagrange(a, L.build_lagrange(a, 4, 4, 2), r))(*_setup(s, d, "props_hist", 8)))

_RECTS = "rects AS (SELECT x AS qid, least(a, b) AS p0, greatest(a, b) AS q0, least(c, e) AS p1, greatest(c, e) AS q1 FROM (SELECT x, (x * 7919 + 3) % 2500 AS a, (x * 104729 + 11) % 2500 AS b, (x * 31 + 5) % 51 AS c, (x * 17 + 29) % 51 AS e FROM range(24) t(x)))"
_CELLS = "cells AS (SELECT datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS i0, CAST(l_quantity AS BIGINT) AS i1, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS val FROM lineitem GROUP BY 1, 2)"


def _rects(s: SparkSession, d: str) -> DataFrame:
    li = read(s, d, "lineitem")
    cells = li.groupBy(F.expr("CAST(datediff(CAST(l_shipdate AS DATE), DATE '1995-01-01') AS BIGINT)").alias("i0"), F.col("l_quantity").cast("long").alias("i1")).agg(F.sum(F.expr("CAST(round(l_extendedprice * 100) AS BIGINT)")).alias("val"))
    x = F.col("id")
    a, b, c, e = (x * 7919 + 3) % 2500, (x * 104729 + 11) % 2500, (x * 31 + 5) % 51, (x * 17 + 29) % 51
    rects = s.range(24).select(x.alias("qid"), F.least(a, b).alias("p0"), F.greatest(a, b).alias("q0"), F.least(c, e).alias("p1"), F.greatest(c, e).alias("q1"))
    return M.rect_moments(cells, rects, 8)


query(f"WITH {_CELLS}, {_RECTS} SELECT qid, CAST(coalesce(sum(val), 0) AS BIGINT) AS total FROM rects LEFT JOIN cells ON i0 BETWEEN p0 AND q0 AND i1 BETWEEN p1 AND q1 GROUP BY qid", "rect_sum_2d")(lambda s, d: _rects(s, d).select("qid", "total"))
query(f"WITH {_CELLS}, {_RECTS} SELECT qid, CAST(coalesce(sum(i0 * val), 0) AS BIGINT) AS m1 FROM rects LEFT JOIN cells ON i0 BETWEEN p0 AND q0 AND i1 BETWEEN p1 AND q1 GROUP BY qid", "rect_m1_2d")(lambda s, d: _rects(s, d).select("qid", "m1"))


@query(f"WITH arr AS ({fixture_sql('event_minute')}), days AS (SELECT idx // 1440 AS qid, min(idx) AS p, max(idx) AS q FROM arr GROUP BY 1) SELECT qid, CAST((SELECT sum(CAST(i AS HUGEINT) * i * i) FROM range(p, q + 1) t(i)) AS BIGINT) AS result FROM days")
def power_sums(s: SparkSession, d: str) -> DataFrame:
    """Sums of cubes from each day's first minute with events to its last."""
    days = fixture(s, d, "event_minute").df.groupBy(F.expr("idx div 1440").alias("qid")).agg(F.min("idx").alias("p"), F.max("idx").alias("q"))
    return days.select("qid", power_sum(3, F.col("p"), F.col("q")).alias("result"))


@query(range_sql("ship_day", SUM, keys=("l_returnflag",)))
def keyed_by_returnflag(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "ship_day", ("l_returnflag",))
    return L.query_lagrange(arr, L.build_lagrange(arr, 8, 4, 2), random_ranges(s, arr.n, COUNT))


@query(f"WITH arr AS ({fixture_sql('event_minute')}) SELECT CAST(count(*) AS BIGINT) AS cells, max(idx) AS last, CAST(count(*) FILTER (WHERE val <> 0) AS BIGINT) AS non_zero FROM arr")
def array_profile(s: SparkSession, d: str) -> DataFrame:
    return approx_profile(fixture(s, d, "event_minute")).select("cells", "last", "non_zero")


# --- operators around the buffers

query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT idx, val FROM arr WHERE idx BETWEEN 100 AND 299", "arr_slice")(lambda s, d: slice_array(fixture(s, d, "event_value"), 100, 299).df)
query(f"WITH arr AS ({fixture_sql('turn_len')}) SELECT i AS idx, coalesce(val, 0) AS val FROM range((SELECT max(idx) + 1 FROM arr)) t(i) LEFT JOIN arr ON idx = i", "arr_densify")(lambda s, d: densify(fixture(s, d, "turn_len")).df)


@query(f"WITH arr AS ({fixture_sql('event_minute')}), pts AS (SELECT x AS qid, (x * 2654435761 + 13) % 43200 AS point FROM range(200) t(x)) SELECT qid, point, arr.idx AS idx, arr.val AS val FROM pts ASOF LEFT JOIN arr ON point >= arr.idx")
def asof_last_nonempty(s: SparkSession, d: str) -> DataFrame:
    pts = s.range(200).select(F.col("id").alias("qid"), ((F.col("id") * 2654435761 + 13) % 43200).alias("point"))
    return X.asof_last(fixture(s, d, "event_minute"), pts)


_SEMI = base_sql("event_value") + f", {UPD}, bins AS (SELECT idx // 32 AS bin, CAST(sum(val) AS BIGINT) AS s FROM arr GROUP BY 1) SELECT bin, s FROM bins WHERE bin {{0}} (SELECT idx // 32 FROM upd WHERE idx % 3 = 0)"
_touch = lambda s, a: _updates(s, a.n).where("idx % 3 = 0")
query(_SEMI.format("IN"), "semi_touched")(lambda s, d: (lambda a, r: X.semi_touched(B.build_bins(a, A.sum_spec(), 32).df, _touch(s, a), 32))(*_setup(s, d)))
query(_SEMI.format("NOT IN"), "anti_untouched")(lambda s, d: (lambda a, r: X.anti_untouched(B.build_bins(a, A.sum_spec(), 32).df, _touch(s, a), 32))(*_setup(s, d)))
query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT idx, CAST(sum(val) OVER (ORDER BY idx) AS BIGINT) AS p0 FROM arr", "window_prefix")(lambda s, d: D.prefix_moments(fixture(s, d, "event_value")).select("idx", F.col("p0").cast("long").alias("p0")))
query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT idx, CAST(sum(idx * val) OVER (ORDER BY idx RANGE BETWEEN 49 PRECEDING AND CURRENT ROW) AS BIGINT) AS result FROM arr", "window_moving")(lambda s, d: X.moving_moment(fixture(s, d, "event_value"), 50, 1, 512))
query(f"WITH arr AS ({fixture_sql('event_value')}), b AS (SELECT idx // 32 AS bin, CAST(sum(val) AS BIGINT) AS s FROM arr GROUP BY 1) SELECT bin, s, row_number() OVER w AS rn, rank() OVER (PARTITION BY bin % 3 ORDER BY s DESC) AS rk, dense_rank() OVER (PARTITION BY bin % 3 ORDER BY s DESC) AS dense, ntile(4) OVER w AS quarter, s - lead(s) OVER w AS gap FROM b WINDOW w AS (PARTITION BY bin % 3 ORDER BY s DESC, bin)", "window_rank_bins")(
    lambda s, d: X.window_ranks(B.build_bins(fixture(s, d, "event_value"), A.sum_spec(), 32).df, "s", "bin", F.col("bin") % 3)
)
query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT idx // 32 AS bin, CAST(sum(val) AS BIGINT) AS s FROM arr GROUP BY 1 ORDER BY s DESC, bin LIMIT 10", "topk_bins")(lambda s, d: X.rank_bins(B.build_bins(fixture(s, d, "event_value"), A.sum_spec(), 32).df, "s", 10))
query(base_sql("event_value") + " SELECT qid, p // 32 AS bin FROM ranges UNION SELECT qid, q // 32 FROM ranges", "set_union_candidates")(lambda s, d: (lambda a, r: r.select("qid", F.expr("p div 32").alias("bin")).union(r.select("qid", F.expr("q div 32"))).distinct())(*_setup(s, d)))
_TWO = f"WITH a AS ({fixture_sql('event_minute')}), b AS (SELECT idx * 3 AS idx FROM ({fixture_sql('event_value')}))"
query(_TWO + " SELECT idx FROM a INTERSECT SELECT idx FROM b", "set_intersect_idx")(lambda s, d: fixture(s, d, "event_minute").df.select("idx").intersect(fixture(s, d, "event_value").df.select((F.col("idx") * 3).alias("idx"))))
query(_TWO + " SELECT idx FROM a EXCEPT SELECT idx FROM b", "set_except_idx")(lambda s, d: fixture(s, d, "event_minute").df.select("idx").exceptAll(fixture(s, d, "event_value").df.select((F.col("idx") * 3).alias("idx"))))
query("SELECT event_id, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) AS BIGINT) // 60 AS i, CAST(strftime(date_trunc('minute', ts), '%Y-%m-%d %H:%M') AS VARCHAR) AS t FROM events", "ts_index")(
    lambda s, d: read(s, d, "events").withColumn("i", F.expr(ARRAYS["event_minute"][1])).select("event_id", "i", F.date_format(ts_of_index("i", "2024-01-01 00:00:00"), "yyyy-MM-dd HH:mm").alias("t"))
)
query(base_sql("event_value") + ", c AS (SELECT qid, unnest(range(p // 1024, q // 1024 + 1)) AS cell FROM ranges) SELECT CAST(count(DISTINCT cell) AS BIGINT) AS cells FROM c", "distinct_cells")(lambda s, d: (lambda a, r: r.select(F.explode(F.sequence(F.expr("p div 1024"), F.expr("q div 1024"))).alias("cell")).agg(F.count_distinct("cell").alias("cells")))(*_setup(s, d)))
query("SELECT doc_id, CAST(length(text) AS BIGINT) AS chars, CAST(len(list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '')) AS BIGINT) AS words FROM documents", "text_measures")(lambda s, d: read(s, d, "documents").select("doc_id", F.length("text").cast("long").alias("chars"), word_count(F.col("text")).cast("long").alias("words")))
query("SELECT page_id, CAST(length(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS BIGINT) AS chars FROM pages", "page_text_measures")(lambda s, d: read(s, d, "pages").select("page_id", F.length(strip_html(F.col("html"))).cast("long").alias("chars")))


@query(f"WITH ev AS (SELECT event_id, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) AS BIGINT) // 60 AS m FROM events), w AS (SELECT x AS wid, (x * 997) % 43000 AS lo, (x * 997) % 43000 + 200 AS hi FROM range(40) t(x)) SELECT wid, event_id FROM w JOIN ev ON m BETWEEN lo AND hi")
def interval_join_events(s: SparkSession, d: str) -> DataFrame:
    ev = read(s, d, "events").select("event_id", F.expr(ARRAYS["event_minute"][1]).alias("at"))
    w = s.range(40).select(F.col("id").alias("wid"), ((F.col("id") * 997) % 43000).alias("lo"), ((F.col("id") * 997) % 43000 + 200).alias("hi"))
    return X.interval_join(ev, "at", w, "lo", "hi", 256).select("wid", "event_id")


@query("SELECT CAST(0 AS BIGINT) AS differing")
def buffer_diff(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value")
    u = _updates(s, arr.n)
    a = L.update_lagrange(L.build_lagrange(arr, 8, 4, 2), u)
    return X.diff_buffers(a.df, L.build_lagrange(B.updated(arr, u), 8, 4, 2).df).agg(F.count("*").alias("differing"))


@query("SELECT * FROM (VALUES (0, CAST(1 AS BIGINT)), (0, 2), (0, 78), (0, 79), (1, 1), (1, 2), (1, 24), (1, 25), (2, 1), (2, 2), (2, 3), (2, 4), (2, 5), (2, 6), (2, 7)) t(level, cell)")
def udtf_range_cells(s: SparkSession, d: str) -> DataFrame:
    return RangeCells(F.lit(1), F.lit(79), F.lit(3), F.lit(2))


@query("SELECT * FROM (VALUES (CAST(1 AS BIGINT), CAST(0.25 AS DOUBLE)), (2, 0.75)) t(cell, w)")
def udtf_lagrange_cells(s: SparkSession, d: str) -> DataFrame:
    return LagrangeCells(F.lit(7), F.lit(4), F.lit(2))


@query(f"WITH arr AS ({fixture_sql('event_value')}) SELECT CAST(sum((idx - 50) * val) AS BIGINT) AS result FROM arr WHERE idx BETWEEN 77 AND 765")
def sql_surface_moment(s: SparkSession, d: str) -> DataFrame:
    arr = fixture(s, d, "event_value")
    register_sql(s, {"mb_events": arr.df, "mb_event_bins": B.build_bins(arr, A.moment_spec(1), 32).df})
    return s.sql(local_moment_sql("mb_events", "mb_event_bins", 32, 77, 765, 50, 1))


@query(range_sql("order_total", "max(val)"))
def planner_max(s: SparkSession, d: str) -> DataFrame:
    arr, r = _setup(s, d, "order_total")
    return answer(A.max_spec(), arr, Available(pyramid=P.build_pyramid(arr, A.max_spec(), 8, 2), bins=B.build_bins(arr, A.max_spec(), 128)), r)


@query(range_sql("event_value", moment_sql(2)))
def planner_moment(s: SparkSession, d: str) -> DataFrame:
    arr, buf, r = _lag(s, d, levels=2)
    return answer(A.moment_spec(2), arr, Available(lagrange=buf), r).select("qid", F.col("result").cast("long").alias("result"))


@query("WITH ranges AS (SELECT x AS qid, least(u, v) AS p, greatest(u, v) - 1 AS q FROM (SELECT x, (x * 2654435761 + 13) % 4096 AS u, (x * 2246822519 + 71) % 4096 AS v FROM range(50) t(x)) WHERE u <> v) SELECT qid, round((SELECT sum(sin(CAST(i AS DOUBLE))) FROM range(p, q + 1) t(i)), 6) AS result FROM ranges")
def virtual_sine_sum(s: SparkSession, d: str) -> DataFrame:
    arr = virtual_array(s, 4096)
    r = random_ranges(s, 4096, 50, edges=False)
    return L.query_lagrange(arr, L.build_lagrange(arr, 16, 4, 2, "double"), r).select("qid", F.round("result", 6).alias("result"))


# --- streams, run over what is there and read back


def _events(s: SparkSession, d: str) -> DataFrame:
    batch = read(s, d, "events")
    e = s.readStream.schema(batch.schema).option("pathGlobFilter", "events.parquet").parquet(d)
    return e.select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("at"), (F.col("event_id") % 32).alias("i"), F.expr("CAST(round(value * 100) AS BIGINT)").alias("v"))


def _name(base: str) -> str:
    import uuid

    return f"{base}_{uuid.uuid4().hex[:8]}"


_TUMBLE = "CAST(count(*) AS BIGINT) AS cnt, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS m0, CAST(sum((event_id % 32) * CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS m1"


@query(f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, {_TUMBLE} FROM events GROUP BY 1")
def stream_tumbling(s: SparkSession, d: str) -> DataFrame:
    got = S.drain(S.tumbling_moments(_events(s, d), "1 day"), _name("tumbling"))
    return got.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "cnt", "m0", "m1")


@query(f"SELECT strftime(w, '%Y-%m-%d %H') AS start, {_TUMBLE} FROM (SELECT *, unnest([date_trunc('day', ts) + INTERVAL (12 * (hour(ts) // 12)) HOUR, date_trunc('day', ts) + INTERVAL (12 * (hour(ts) // 12) - 12) HOUR]) AS w FROM events) GROUP BY 1")
def stream_sliding(s: SparkSession, d: str) -> DataFrame:
    got = S.drain(S.sliding_moments(_events(s, d), "1 day", "12 hours"), _name("sliding"))
    return got.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("start"), "cnt", "m0", "m1")


@query("WITH e AS (SELECT user_id, ts, CAST(round(value * 100) AS BIGINT) AS v, coalesce(ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR, true) AS opens FROM events), g AS (SELECT *, sum(CASE WHEN opens THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS nth FROM e) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, CAST(count(*) AS BIGINT) AS cnt, CAST(sum(v) AS BIGINT) AS m0 FROM g GROUP BY user_id, nth")
def stream_session(s: SparkSession, d: str) -> DataFrame:
    got = S.drain(S.session_moments(_events(s, d), "6 hours", "user_id"), _name("session"), "complete")
    return got.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "cnt", "m0")


@query(range_sql("event_value", SUM))
def stream_buffer_updates(s: SparkSession, d: str) -> DataFrame:
    """The buffer of all events kept up by a stream of deltas, then queried."""
    from momentbuf.sources.store import compact, read_deltas

    arr, r = _setup(s, d)
    base = s.conf.get("spark.checkpoint.dir", None)
    if not base:
        import tempfile

        base = tempfile.mkdtemp(prefix="momentbuf-stream")
    path = f"{base.rstrip('/')}/{_name('deltas')}"
    S.maintain(_events(s, d).select(F.col("event_id").alias("idx"), F.col("v").alias("delta")), path, arr.n, 8, 4, 2, f"{path}-offsets").awaitTermination()
    cells = compact(None, read_deltas(s, path), ["level", "pos"], "v").withColumn("v", F.col("v").cast("decimal(38,0)"))
    return L.query_lagrange(arr, L.LagrangeBuffer(cells, 8, arr.n, 2, Stencil.of(4)), r)


@query("WITH e AS (SELECT event_id // 100 AS batch, ts FROM events), t AS (SELECT batch, max(ts) AS top FROM e GROUP BY 1), l AS (SELECT batch, max(top) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 1 DAY AS line FROM t) SELECT e.batch, CAST(sum(CASE WHEN coalesce(ts < line, false) THEN 0 ELSE 1 END) AS BIGINT) AS accepted, CAST(sum(CASE WHEN coalesce(ts < line, false) THEN 1 ELSE 0 END) AS BIGINT) AS late FROM e JOIN l USING (batch) GROUP BY 1")
def stream_late_count(s: SparkSession, d: str) -> DataFrame:
    e = read(s, d, "events").select(F.expr("event_id div 100").alias("batch"), F.col("ts").cast("timestamp").alias("at"))
    return S.late_report(e, "1 DAY", "batch")


@query(f"WITH arr AS ({fixture_sql('event_value')}), p AS (SELECT idx // 32 AS cell, (32 - idx % 32) * val AS v FROM arr UNION ALL SELECT idx // 32 + 1, (idx % 32) * val FROM arr) SELECT cell, CAST(sum(v) AS BIGINT) AS v32 FROM p WHERE v <> 0 GROUP BY cell")
def stream_stateful_buffer(s: SparkSession, d: str) -> DataFrame:
    got = S.drain(S.stateful_buffer(_events(s, d).select(F.col("event_id").alias("idx"), F.col("v").alias("delta"), "at"), 32), _name("stateful"), "update")
    return got.groupBy("cell").agg(F.max_by("v", "version").alias("v")).select("cell", F.round(F.col("v") * 32).cast("long").alias("v32"))




# --- sources, and the experiments


@query(f"WITH arr AS ({fixture_sql('event_minute')}) SELECT CAST(count(*) AS BIGINT) AS cells, CAST(min(idx) AS BIGINT) AS first, CAST(sum(CAST(round(sin(CAST(idx AS DOUBLE)) * 1000000) AS BIGINT) * val) AS BIGINT) AS total FROM arr WHERE idx BETWEEN 100 AND 43099")
def source_virtual_array(s: SparkSession, d: str) -> DataFrame:
    """The data source, with its bounds pushed down, as weights (in millionths) of the events' minutes."""
    from momentbuf.sources.virtual import register

    register(s)
    arr = fixture(s, d, "event_minute")
    sine = s.read.format("virtual_array").option("n", arr.n).option("partitions", 4).load().where("idx >= 100 AND idx < 43100").withColumnRenamed("val", "w")
    both = sine.join(arr.df, "idx")
    return both.agg(F.count("*").alias("cells"), F.min("idx").alias("first"), F.sum(F.round(F.col("w") * 1_000_000).cast("long") * F.col("val")).alias("total"))


@query("SELECT event_type, CAST(sum((event_id - lo) * v) AS DOUBLE) AS m1 FROM (SELECT event_type, event_id, CAST(round(value * 100) AS BIGINT) AS v, min(event_id) OVER (PARTITION BY event_type) AS lo FROM events) GROUP BY 1")
def udaf_moment(s: SparkSession, d: str) -> DataFrame:
    """A grouped Python aggregate, for parity with the built-in expressions."""
    from momentbuf.plans.sqlsurface import moments_udaf

    df = fixture(s, d, "event_value", ("event_type",)).df
    return df.groupBy("event_type").agg(moments_udaf(1)("idx", "val").alias("m1"))


from momentbuf.experiments import EXPERIMENTS  # noqa: E402

QUERIES |= EXPERIMENTS
