"""Arrays made from the given tables, each with the SQL text of the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.session import ship
from momentbuf.sources.arrays import IndexedArray, make_array

CENTS = "CAST(round({0} * 100) AS BIGINT)"

#: name: table, index, value, aggregate (None: indices are unique), length (None: greatest index plus one)
ARRAYS: dict[str, tuple[str, str, str, str | None, int | None]] = {
    "event_value": ("events", "event_id", CENTS.format("value"), None, None),
    "order_total": ("orders", "o_orderkey", CENTS.format("o_totalprice"), None, None),
    "ship_day": ("lineitem", "datediff(CAST(l_shipdate AS DATE), DATE '1995-01-01')", CENTS.format("l_extendedprice"), "sum", 2500),
    "price_cents": ("lineitem", CENTS.format("l_extendedprice"), "1", "sum", 1 << 24),
    "part_price": ("part", "CAST(round(p_retailprice * 10) AS BIGINT) - 9000", "1", "sum", 1200),
    "event_minute": ("events", "timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)", CENTS.format("value"), "sum", 43200),
    "event_second": ("events", "timestampdiff(SECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)", CENTS.format("value"), "sum", 2592000),
    "props_hist": ("events", "CAST(get_json_object(props, '$.k') AS BIGINT)", "1", "sum", 100),
    "account": ("customer", "c_custkey", CENTS.format("c_acctbal"), None, None),
    "supplier_account": ("supplier", "s_suppkey", CENTS.format("s_acctbal"), None, None),
    "doc_len": ("documents", "doc_id", "length(text)", None, None),
    "page_len": ("pages", "page_id", "length(html)", None, None),
    "bench_len": ("benchmark", "item_id", "length(text)", None, None),
    "turn_len": ("conversations", "conv_id * 8 + turn", "length(text)", None, None),
    "label_quality": ("labels", "doc_id", "quality", None, None),
}

#: What DuckDB writes otherwise.
_DUCK = {
    "datediff(CAST(l_shipdate AS DATE), DATE '1995-01-01')": "datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))",
    "timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)": "CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) AS BIGINT) // 60",
    "timestampdiff(SECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)": "CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) AS BIGINT)",
    "CAST(get_json_object(props, '$.k') AS BIGINT)": "CAST(json_extract_string(props, '$.k') AS BIGINT)",
}


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def fixture(spark: SparkSession, sf_dir: str, name: str, keys: tuple[str, ...] = ()) -> IndexedArray:
    table, idx, val, agg, n = ARRAYS[name]
    df = read(spark, sf_dir, table)
    return make_array(df, F.expr(idx), F.expr(val).cast("long"), n, keys, agg or "sum", unique=agg is None, stored=idx.isidentifier())


def fixture_sql(name: str, keys: tuple[str, ...] = ()) -> str:
    """SQL of the array's rows: (keys,) idx, val."""
    table, idx, val, agg, _ = ARRAYS[name]
    idx = _DUCK.get(idx, idx)
    k = "".join(f"{x}, " for x in keys)
    if agg is None:
        return f"SELECT {k}CAST({idx} AS BIGINT) AS idx, CAST({val} AS BIGINT) AS val FROM {table}"
    return f"SELECT {k}CAST({idx} AS BIGINT) AS idx, CAST({agg}({val}) AS BIGINT) AS val FROM {table} GROUP BY {k}CAST({idx} AS BIGINT)"


def length_sql(name: str) -> str:
    n = ARRAYS[name][4]
    return str(n) if n is not None else "(SELECT max(idx) + 1 FROM arr)"
