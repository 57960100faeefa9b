"""Indexed arrays: a frame of (idx, val), maybe with key columns, and its length.

Absent cells are zero for linear queries and no element for counts and maxima.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class IndexedArray:
    df: DataFrame
    n: int
    keys: tuple[str, ...] = ()
    absent_is_zero: bool = True
    source: DataFrame | None = None  # the rows with the folder column `chunk`, for arrays in files
    chunk: int | None = None
    stored: bool = False  # idx is a column of files (or of a range): bounds on it reach the scan

    def with_df(self, df: DataFrame) -> IndexedArray:
        return replace(self, df=df, source=None, chunk=None, stored=False)


def make_array(df: DataFrame, idx: Column, val: Column, n: int | None = None, keys: tuple[str, ...] = (), agg: str = "sum", unique: bool = False, stored: bool = False) -> IndexedArray:
    """Raw rows to an array. Rows that share an index are added (or combined by `agg`); `unique` says that none do and saves the exchange; `stored` that idx is a plain column of files."""
    rows = df.select(*keys, idx.cast("long").alias("idx"), val.alias("val")).where(F.col("idx").isNotNull() & F.col("val").isNotNull())
    if not unique:
        rows = rows.groupBy(*keys, "idx").agg(getattr(F, agg)("val").alias("val"))
    if n is None:
        n = (rows.agg(F.max("idx")).first()[0] or -1) + 1
    return IndexedArray(rows, n, keys, stored=stored and unique)


def validate(arr: IndexedArray) -> None:
    """Raise unless indices are unique per key, lie in [0, n) and no value is null or not a number."""
    v = F.col("val").cast("double")
    r = arr.df.agg(F.count("*").alias("rows"), F.count("idx").alias("ids"), F.min("idx").alias("lo"), F.max("idx").alias("hi"), F.sum((v.isNull() | F.isnan(v)).cast("long")).alias("bad")).first()
    if r["rows"] and (r["ids"] < r["rows"] or r["lo"] < 0 or r["hi"] >= arr.n or r["bad"]):
        raise ValueError(f"not an array of length {arr.n}: {r.asDict()}")
    if not arr.df.groupBy(*arr.keys, "idx").count().where("count > 1").isEmpty():
        raise ValueError("an index occurs twice")


def slice_array(arr: IndexedArray, p: int, q: int) -> IndexedArray:
    """The part with p <= idx <= q; the bounds reach the scan."""
    return arr.with_df(arr.df.where(F.col("idx").between(p, q)))


def densify(arr: IndexedArray) -> IndexedArray:
    """All n cells (per key), absent ones as zero."""
    spark = arr.df.sparkSession
    cells = spark.range(arr.n).select(F.col("id").alias("idx"))
    if arr.keys:
        fan = 1 << 12  # no row holds a longer sequence, whatever n
        step = fan
        while step < arr.n:
            step *= fan
        cells = arr.df.select(*arr.keys).distinct().withColumn("idx", F.lit(0).cast("long"))
        while step > 1:
            sub = step // fan
            cells = cells.select(*arr.keys, F.explode(F.sequence(F.col("idx"), F.least(F.lit(arr.n - 1).cast("long"), F.col("idx") + (step - sub)), F.lit(sub).cast("long"))).alias("idx"))
            step = sub
    zero = F.lit(0).cast(arr.df.schema["val"].dataType)
    return arr.with_df(cells.join(arr.df, [*arr.keys, "idx"], "left").select(*arr.keys, "idx", F.coalesce("val", zero).alias("val")))


def sparsify(arr: IndexedArray) -> IndexedArray:
    return arr.with_df(arr.df.where("val <> 0"))


def density(arr: IndexedArray) -> float:
    return sparsify(arr).df.count() / arr.n


def approx_profile(arr: IndexedArray) -> DataFrame:
    """One pass over the array: cells, greatest index, non-zero cells, distinct values about, quartiles of values and of indices."""
    return arr.df.agg(F.count("*").alias("cells"), F.max("idx").alias("last"), F.sum((F.col("val") != 0).cast("long")).alias("non_zero"), F.approx_count_distinct("val").alias("values"), F.percentile_approx("val", [0.25, 0.5, 0.75], 1_000_000).alias("value_quartiles"), F.percentile_approx("idx", [0.25, 0.5, 0.75], 1_000_000).alias("index_quartiles"))


def virtual_array(spark: SparkSession, n: int, fn: str = "sin") -> IndexedArray:
    """An array computed on access."""
    return IndexedArray(spark.range(n).select(F.col("id").alias("idx"), getattr(F, fn)(F.col("id").cast("double")).alias("val")), n, stored=True)


def from_rows(spark: SparkSession, rows: list[tuple[int, int]], n: int, kind: str = "long") -> IndexedArray:
    return IndexedArray(spark.createDataFrame(rows, f"idx long, val {kind}"), n)


def import_array(spark: SparkSession, path: str, fmt: str, schema: str, idx: str, val: str, n: int | None = None, **options: str) -> IndexedArray:
    """An array from CSV, JSON, ORC or Parquet files with a declared schema (none is inferred)."""
    return make_array(spark.read.format(fmt).schema(schema).options(**options).load(path), F.col(idx), F.col(val), n)
