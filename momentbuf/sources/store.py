"""Arrays, buffers and delta logs on disk, clustered so that a range of indices is a few files.

All paths go through Spark's readers and writers (metadata too, as a one-row JSON
table), so any store that Spark reaches will do.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.sources.arrays import IndexedArray


def write_array(arr: IndexedArray, path: str, chunk: int = 1 << 24, fmt: str = "parquet", single: bool = False) -> None:
    """Range-clustered files, a folder for each chunk of indices; single: values as 32-bit floats."""
    val = F.col("val").cast("float") if single else F.col("val")
    df = arr.df.select(*arr.keys, "idx", val.alias("val")).withColumn("chunk", F.expr(f"idx div {chunk}"))
    df.repartitionByRange("chunk", "idx").sortWithinPartitions("chunk", "idx").write.mode("overwrite").partitionBy("chunk").format(fmt).save(f"{path}/cells")
    _write_meta(arr.df.sparkSession, path, n=arr.n, keys=",".join(arr.keys), chunk=chunk, fmt=fmt)


def read_array(spark: SparkSession, path: str, p: int | None = None, q: int | None = None) -> IndexedArray:
    """The array, or the part between p and q: whole chunks are skipped by folder, others by row-group bounds.

    Queries over the whole array prune it the same way, by the intervals they need.
    """
    m = _read_meta(spark, path)
    df = spark.read.format(m["fmt"]).load(f"{path}/cells")
    if p is not None and q is not None:
        df = df.where(F.col("chunk").between(p // int(m["chunk"]), q // int(m["chunk"])) & F.col("idx").between(p, q))
    keys = tuple(k for k in m["keys"].split(",") if k)
    return IndexedArray(df.select(*keys, "idx", "val"), int(m["n"]), keys, source=df, chunk=int(m["chunk"]), stored=True)


def assert_clustered(df: DataFrame) -> DataFrame:
    """Overlapping index intervals of files, if any: empty for a clustered array."""
    files = df.groupBy(F.input_file_name().alias("file")).agg(F.min("idx").alias("lo"), F.max("idx").alias("hi"))
    from pyspark.sql import Window

    return files.withColumn("before", F.max("hi").over(Window.orderBy("lo").rowsBetween(Window.unboundedPreceding, -1))).where("before >= lo")


def _write_meta(spark: SparkSession, path: str, **fields: object) -> None:
    spark.createDataFrame([{k: str(v) for k, v in fields.items()}]).coalesce(1).write.mode("overwrite").json(f"{path}/meta")


def _read_meta(spark: SparkSession, path: str) -> dict[str, str]:
    return {k: v or "" for k, v in spark.read.json(f"{path}/meta").first().asDict().items()}


def write_buffer(df: DataFrame, path: str, **meta: object) -> None:
    """A buffer's cells, clustered by position and with a folder for each level, and its parameters (n, b, N, levels, mode, ...)."""
    at = next((c for c in ("pos", "cell", "bin") if c in df.columns), None)
    rows = df.repartitionByRange(*[c for c in ("level", at) if c in df.columns]).sortWithinPartitions(*[c for c in ("level", at) if c in df.columns]) if at else df
    w = rows.write.mode("overwrite")
    (w.partitionBy("level") if "level" in df.columns else w).parquet(f"{path}/cells")
    _write_meta(df.sparkSession, path, **meta)


def read_buffer(spark: SparkSession, path: str) -> tuple[DataFrame, dict[str, str]]:
    return spark.read.parquet(f"{path}/cells"), _read_meta(spark, path)


def shared_path(spark: SparkSession, name: str) -> str:
    """A new folder below the one that the cluster shares (spark.checkpoint.dir). A local master may go without; a cluster may not."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="momentbuf")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def held(df: DataFrame) -> DataFrame:
    """Written to the shared folder and read back: later plans start from the files."""
    path = shared_path(df.sparkSession, "held")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def append_delta(deltas: DataFrame, path: str, batch_id: int) -> None:
    """One batch of cell deltas; a batch that is replayed replaces itself."""
    deltas.write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")


def read_deltas(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("basePath", path).parquet(f"{path}/batch_id=*")


def compact(base: DataFrame | None, deltas: DataFrame, key: list[str], value: str) -> DataFrame:
    """Base cells plus all logged deltas."""
    rows = deltas.select(*key, value)
    return (rows if base is None else base.select(*key, value).unionByName(rows)).groupBy(*key).agg(F.sum(value).alias(value))


def write_lagrange(buf, path: str) -> None:
    """A Lagrange buffer with its parameters."""
    write_buffer(buf.df, path, n=buf.n, b=buf.b, levels=buf.levels, M=buf.stencil.M, Mp=buf.stencil.Mp, mode=buf.mode, keys=",".join(buf.keys))


def read_lagrange(spark: SparkSession, path: str):
    """The buffer that write_lagrange wrote; queries push their bounds into its files."""
    from momentbuf.functions.weights import Stencil
    from momentbuf.operators.lagrange_buffer import LagrangeBuffer

    df, m = read_buffer(spark, path)
    return LagrangeBuffer(df, int(m["b"]), int(m["n"]), int(m["levels"]), Stencil(int(m["M"]), int(m["Mp"])), m["mode"], tuple(k for k in m["keys"].split(",") if k), stored=True)


def hold_lagrange(buf):
    """The buffer written to the shared folder and read back."""
    path = shared_path(buf.df.sparkSession, "lagrange")
    write_lagrange(buf, path)
    return read_lagrange(buf.df.sparkSession, path)


def hold_bins(buf):
    """A disjoint-bin buffer written to the shared folder and read back."""
    from dataclasses import replace

    path = shared_path(buf.df.sparkSession, "bins")
    write_buffer(buf.df, path, n=buf.n, b=buf.b)
    return replace(buf, df=read_buffer(buf.df.sparkSession, path)[0], stored=True)
