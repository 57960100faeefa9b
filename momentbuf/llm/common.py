"""What the operators share: reading tables, cutting lineage, shipping code, small numeric helpers."""

from __future__ import annotations

import ctypes
import gc
import os
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from momentbuf.session import ship


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """The named columns of one of the given tables."""
    ship(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """A new folder below the one that the cluster shares (spark.checkpoint.dir); a temporary one only where that is unset and the master is local."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="momentbuf-shared")
        spark.sparkContext.setCheckpointDir(base)
    path = f"{base.rstrip('/')}/momentbuf-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(p)
    return path


def cut(df: DataFrame) -> DataFrame:
    """Write a frame to the shared folder and read it back: later jobs neither recompute it nor depend on one executor."""
    path = shared_dir(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _give_back() -> None:
    """Return freed memory to the system: workers live on, and the next stage's may be other ones."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:
        pass


#: Rows of an Arrow batch. Texts make wide rows: Spark's default of 10,000 would hold tens of MB in the JVM and in Python at once.
BATCH_ROWS = 1000


#: What a worker keeps between tasks, by operator: tokenizers with their caches.
CACHES: dict[str, dict] = {}


def _only(uses: str | None) -> None:
    """Drop what other operators left in this worker, which Spark uses again for later stages."""
    left = [d for name, d in CACHES.items() if name != uses and d]
    for d in left:
        d.clear()
    if left:
        gc.collect()
        _give_back()


def arrow_map(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | StructType, uses: str | None = None) -> DataFrame:
    """mapInArrow over batches of BATCH_ROWS rows at most (the session's batch size is lowered to it), memory given back at a task's end.

    uses: name of the cache that fn keeps in its worker; others' go.
    """
    conf = df.sparkSession.conf
    if not 0 < int(conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) <= BATCH_ROWS:
        conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _only(uses)
        yield from fn(b.slice(i, BATCH_ROWS) for b in batches for i in range(0, b.num_rows, BATCH_ROWS))
        _give_back()

    return df.mapInArrow(run, schema)


def records(schema: pa.Schema, **cols: object) -> pa.RecordBatch:
    """A record batch from named columns in any order."""
    return pa.RecordBatch.from_arrays([x if isinstance(x := cols[f.name], pa.Array) else pa.array(x, f.type, from_pandas=False) for f in schema], schema=schema)


def text_chunks(texts: list, most: int = 4_000_000) -> Iterator[tuple[int, int]]:
    """Spans of a list whose texts hold about `most` characters together."""
    at = held = 0
    for i, t in enumerate(texts):
        held += len(t or "")
        if held >= most:
            yield at, i + 1
            at, held = i + 1, 0
    if at < len(texts):
        yield at, len(texts)


def local_forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges (u, v) of one partition to stars: every vertex with the smallest one it reaches within the partition."""
    pairs = [(b.column("u").to_numpy(), b.column("v").to_numpy()) for b in batches if b.num_rows]
    if not pairs:
        return
    u, v = (np.concatenate([p[i] for p in pairs]) for i in (0, 1))
    ids, at = np.unique(np.r_[u, v], return_inverse=True)
    p, q = at[: len(u)], at[len(u) :]
    root = np.arange(len(ids))
    while True:  # hook the larger root to the smaller, then halve all paths
        a, b = root[p], root[q]
        if (a == b).all():
            break
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while (root != (up := root[root])).any():
            root = up
    on = np.flatnonzero(root != np.arange(len(ids)))
    yield pa.RecordBatch.from_arrays([pa.array(ids[on]), pa.array(ids[root[on]])], names=["u", "v"])


#: A key with more rows than HOT is dealt out, in parts of about HOT rows and MOST_SALTS at most; so many such keys, the largest ones, are known to the driver.
HOT, MOST_SALTS, HOT_KEYS = 1024, 1 << 14, 1000


def hot_keys(sizes: DataFrame, key: str, n: str) -> dict[int, list]:
    """The keys with most rows, if they have more than HOT, by the number of parts they are dealt into (a power of two): HOT_KEYS at most."""
    parts: dict[int, list] = {}
    for k, rows in sizes.where(F.col(n) > HOT).orderBy(F.desc(n), key).select(key, n).limit(HOT_KEYS).collect():
        parts.setdefault(min(MOST_SALTS, 1 << (-(-rows // HOT) - 1).bit_length()), []).append(k)
    return parts


def salted_join(rows: DataFrame, per_key: DataFrame, key: str, by: str, hot: dict[int, list]) -> DataFrame:
    """Rows joined with the one row a key has in per_key; rows of the hot keys are dealt out by a hash of column `by`, and per_key's row is copied once a part."""
    if not hot:
        return rows.join(per_key, key)
    parts = F.lit(1)
    for n, keys in hot.items():
        parts = F.when(F.col(key).isin(keys), n).otherwise(parts)
    left = rows.withColumn("_salt", F.pmod(F.xxhash64(by), parts).cast("int"))
    right = per_key.withColumn("_salt", F.explode(F.sequence(F.lit(0), parts - 1)))
    return left.join(right, [key, "_salt"]).drop("_salt")


def spread_join(rows: DataFrame, per_key: DataFrame, key: str, by: str, counted: DataFrame | None = None) -> DataFrame:
    """salted_join whose hot keys are counted here, in rows or in another (written) frame that holds a row for each of theirs."""
    return salted_join(rows, per_key, key, by, hot_keys((rows if counted is None else counted).groupBy(key).agg(F.count("*").alias("n")), key, "n"))


#: Edges of one partition in which components are contracted locally.
FOREST = 1_000_000


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """Connected components: (id, component) for every id of an edge, component being its smallest member.

    Partitions of bounded size contract their edges to stars, then alternating
    large-star and small-star steps run over what is left until nothing
    changes; each is an aggregation and a join, so no component is gathered in one
    task. Edges that fit in one partition are done after the contraction.
    """
    e = cut(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v"))
    parts = max(1, -(-e.count() // FOREST))
    e = cut(e.repartition(parts).mapInArrow(local_forest, "u long, v long"))
    was = None
    for _ in range(rounds if parts > 1 else 0):
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        e = cut(large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").union(least.select("u", F.col("m").alias("v"))).distinct())
        now = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == was:
            break
        was = now
    else:
        if parts > 1:
            raise RuntimeError(f"components have not come to rest in {rounds} rounds")
    return e.select(F.col("u").alias("id"), F.col("v").alias("component")).union(e.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())


def worker_limits() -> None:
    """One thread per Python worker: executors have their cores dealt out by Spark."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    sys.setswitchinterval(1)
