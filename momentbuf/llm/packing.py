"""Sum-of-squares packing of documents into sequences of fixed length.

Pieces are interchangeable within a length, so the plan is made on the
histogram of lengths (at most `capacity` numbers), never on the documents: every
placement takes the open gap that makes the sum of squared counts of open
sequences per gap smallest. A histogram of more than `block` pieces is the same
block many times over plus a remainder, which is smaller by the factor
block / capacity and is planned the same way; so the driver's work and the plan
stay bounded however large the corpus is, and each repeated block is packed as
tightly as one block. Documents find their place by their rank within their
length, counted in salted groups.

Defined results: a null or empty text is the end id alone; rows that repeat a
doc_id are documents of their own; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, records, table, text_chunks
from momentbuf.llm.tokens import encoder, vocabulary

CAPACITY = 1024


def sum_of_squares(lengths: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, int]:
    """Place items in the order given; returns each one's bin, its offset there, and the number of bins.

    Of the open gaps that take an item of s, the one is chosen after which the
    sum over gaps of the squared number of open bins is smallest; full bins count
    in no sum. Ties: the smallest gap. A new bin opens only where no gap takes
    the item, since few bins are the aim and all items are known beforehand.
    """
    count = np.zeros(capacity + 1, np.int64)
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]
    bins, offsets, n = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64), 0
    step, never = np.empty(capacity + 1, np.int64), 1 << 40
    for i, s in enumerate(lengths.tolist()):
        gain = step[: capacity - s + 1]  # indexed by gap - s
        np.subtract(count[: capacity - s + 1], count[s:], out=gain)
        gain *= 2
        gain += 2
        gain[0] = 1 - 2 * count[s]
        gain[count[s:] == 0] = never
        at = int(gain.argmin())
        if gain[at] < never:
            gap = at + s
            b = open_bins[gap].pop()
            count[gap] -= 1
        else:
            gap, b, n = capacity, n, n + 1
        bins[i], offsets[i] = b, capacity - gap
        if gap > s:
            open_bins[gap - s].append(b)
            count[gap - s] += 1
    return bins, offsets, n


def plan(histogram: np.ndarray, capacity: int = CAPACITY, block: int = 1 << 16) -> list[dict]:
    """Levels of the plan: each has the pieces of each length a block takes, how often the block repeats, and where each piece lies.

    Level fields: taken (by length), times, base (first sequence), bins (of one
    block), size / slot / bin / offset (arrays, one entry for each piece of a block).
    """
    levels, rest, base = [], histogram.astype(np.int64), 0
    while rest.sum():
        times = 1 if rest.sum() <= block else int(-(-rest.sum() // block))
        taken = rest // times
        if not taken.any():
            times, taken = 1, rest
        sizes = np.repeat(np.arange(capacity, -1, -1), taken[::-1])
        b, o, n = sum_of_squares(sizes, capacity)
        slot = np.arange(len(sizes)) - np.searchsorted(-sizes, -sizes)
        levels.append({"taken": taken, "times": times, "base": base, "bins": n, "size": sizes, "slot": slot, "bin": b, "offset": o})
        base, rest = base + times * n, rest - times * taken
    return levels


_PIECES = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("crcs", pa.list_(pa.int64()))])


def tokenized(docs: DataFrame, vocabulary_path: str, end_id: int = 2, capacity: int = CAPACITY, blanks: bool = True) -> DataFrame:
    """doc_id, n_tokens and the checksum of each piece; only the first piece is shorter than the capacity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, tail, width = encoder(vocabulary_path, blanks), np.uint32(end_id).tobytes(), 4 * capacity
        for b in batches:
            ids, texts = b.column("doc_id").to_pylist(), b.column("text").to_pylist()
            for i, j in text_chunks(texts):
                n, crcs = [], []
                for body in enc.encode(texts[i:j]):
                    body += tail
                    first = len(body) % width or width
                    n.append(len(body) // 4)
                    crcs.append([zlib.crc32(body[max(0, k - width) : k]) for k in range(first, len(body) + 1, width)])
                yield records(_PIECES, doc_id=ids[i:j], n_tokens=n, crcs=crcs)

    return arrow_map(docs.select("doc_id", "text"), run, "doc_id long, n_tokens long, crcs array<long>", uses="tokens")


def pack(pieces: DataFrame, capacity: int = CAPACITY, block: int = 1 << 16, salts: int | None = None) -> DataFrame:
    """One row for each piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    `pieces` must be a written frame (its rows are counted, ranked and placed in
    three passes). Full pieces get sequences of their own.
    """
    spark = pieces.sparkSession
    n = pieces.count()
    salts = salts or max(256, -(-n // 50_000))
    head = ((F.col("n_tokens") - 1) % capacity + 1).cast("int")
    rows = pieces.withColumn("size", head).withColumn("full", F.size("crcs") - 1 + (head == capacity).cast("int"))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n_tokens", F.element_at("crcs", 1)), F.lit(salts)).cast("int"))
    groups = rows.groupBy("size", "salt").agg(F.count("*").alias("n"), F.sum("full").alias("f"))
    within = Window.partitionBy("size").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    groups = cut(groups.withColumn("n0", F.coalesce(F.sum("n").over(within), F.lit(0))).withColumn("f0", F.coalesce(F.sum("f").over(within), F.lit(0))))
    totals = {r["size"]: (r["n"], r["f"]) for r in groups.groupBy("size").agg(F.sum("n").alias("n"), F.sum("f").alias("f")).collect()}  # at most `capacity` rows
    hist = np.array([totals.get(s, (0, 0))[0] if s < capacity else 0 for s in range(capacity + 1)])
    levels = plan(hist, capacity, block)
    packed = sum(x["bins"] * x["times"] for x in levels)
    # The rank range each level takes of each length, and the first sequence of each length's full pieces: at most `capacity` rows.
    ends = np.cumsum([np.zeros(capacity + 1, np.int64), *(x["taken"] * x["times"] for x in levels)], axis=0)
    full0 = packed + np.cumsum([0, *(totals.get(s, (0, 0))[1] for s in range(1, capacity))])
    by_size = spark.createDataFrame(
        [(s, int(full0[s - 1]), [(lv, int(ends[lv, s]), int(x["taken"][s]), x["base"], x["bins"]) for lv, x in enumerate(levels) if x["taken"][s]]) for s in range(1, capacity + 1)],
        "size int, full0 long, levels array<struct<level:int,low:long,taken:long,base:long,bins:long>>",
    )
    placed = [pa.table({"level": np.full(len(x["size"]), lv, np.int32), "size": x["size"].astype(np.int32), "slot": x["slot"], "bin": x["bin"], "offset": x["offset"]}) for lv, x in enumerate(levels)]
    empty = pa.table({"level": pa.array([], pa.int32()), "size": pa.array([], pa.int32()), "slot": pa.array([], pa.int64()), "bin": pa.array([], pa.int64()), "offset": pa.array([], pa.int64())})
    places = spark.createDataFrame(pa.concat_tables(placed) if placed else empty)
    ranked = Window.partitionBy("size", "salt").orderBy("doc_id", "n_tokens", "crcs").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("r", F.count(F.lit(1)).over(ranked)).withColumn("fr", F.coalesce(F.sum("full").over(ranked), F.lit(0)))
    rows = rows.join(F.broadcast(groups.select("size", "salt", "n0", "f0")) if salts <= 256 else groups.select("size", "salt", "n0", "f0"), ["size", "salt"]).join(F.broadcast(by_size), "size")
    rows = rows.withColumn("rank", F.col("n0") + F.col("r")).withColumn("full_id", F.col("full0") + F.col("f0") + F.col("fr"))
    lv = F.filter("levels", lambda x: x["low"] <= F.col("rank"))
    rows = rows.withColumn("lv", F.when(F.col("size") < capacity, F.try_element_at(lv, F.lit(-1)))).withColumn("k", F.col("rank") - F.col("lv.low"))
    # A level interleaves its repeats: rank k of a length is slot k % taken of repeat k div taken.
    rows = rows.withColumn("level", F.col("lv.level")).withColumn("slot", F.col("k") % F.col("lv.taken")).withColumn("repeat", F.expr("k div lv.taken"))
    rows = rows.join(F.broadcast(places), ["level", "size", "slot"], "left")
    out = rows.select("doc_id", "n_tokens", "size", "full_id", (F.col("lv.base") + F.col("repeat") * F.col("lv.bins") + F.col("bin")).alias("seq"), "offset", F.posexplode("crcs").alias("piece", "ids_crc32"))
    own = (F.col("piece") > 0) | (F.col("size") == capacity)
    nth = F.col("piece") - (F.col("size") < capacity).cast("int")
    return out.select(
        "doc_id", F.col("piece").cast("int").alias("piece"), F.when(F.col("piece") == 0, F.lit(0)).otherwise(F.col("size") + (F.col("piece") - 1) * capacity).cast("long").alias("start"),
        F.when(F.col("piece") == 0, F.col("size")).otherwise(capacity).cast("long").alias("length"), "ids_crc32",
        F.when(own, F.col("full_id") + nth).otherwise(F.col("seq")).cast("long").alias("sequence_id"), F.when(own, F.lit(0)).otherwise(F.col("offset")).cast("long").alias("offset"),
    )


def op9_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(cut(tokenized(table(spark, sf_dir, "documents", "doc_id", "text"), vocabulary("byte_bpe_50k.json"))))
