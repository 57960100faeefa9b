"""Exact top-k search by inner product with one KD-tree per shard.

Vectors become whole numbers, so scores are exact. Shards are the leaves of median
splits, fitted on a bounded sample and applied to every row, so that each shard has a
bounding box of its own. Each shard's KD-tree goes on with median splits down to leaves
with tight boxes. A query visits leaves best first by the largest product that a
leaf's box allows, and stops where that bound falls below its kth score so far. A first
pass over the query's home shard gives a kth score that is passed on: the query then
goes only to those shards whose box can hold as good a score.

Of equal vectors only the k + 1 smallest vec_ids can be among anyone's k best, so the
others stay behind as candidates (not as queries); that is why a vector that a third of
all rows hold fills no shard.

Defined results: each row is a query and a candidate of its own, also where vec_ids
repeat; only the query's own row isn't its candidate. Vectors that are null, of another
length than most, or hold null or non-finite components or one of 2^28 or more after
scaling (their scores wouldn't fit a long) take no part; equal scores go to the smaller
vec_id. A null vec_id takes no part.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, hot_keys, records, salted_join, table
from momentbuf.llm.embeddings import usable

LEAF = 64
#: Rows of a shard while there are few shards, and at most; BOXES shards' boxes at most are given to tasks (a few MB), beyond that boxes of neighbours are joined.
SHARD, SHARD_MOST, BOXES = 2048, 1 << 18, 4096
SAMPLE = 1 << 16
#: Queries that one task answers for a shard; a shard with more is given to several tasks.
ASKED = 4096
#: Components below this keep a score and a rank together in a long.
SMALL = 1 << 17


class KDTree:
    """Leaves of at most `leaf` rows with tight boxes; rows keep the order of their ids within the shard."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, leaf: int = LEAF):
        order = np.argsort(ids, kind="stable")
        self.x, self.ids = x[order], ids[order]
        todo, self.leaves = [np.arange(len(x))], []
        while todo:
            rows = todo.pop()
            part = self.x[rows]
            wide = part.max(0) - part.min(0)
            if len(rows) <= leaf or not wide.any():
                self.leaves += [np.sort(rows[i : i + leaf]) for i in range(0, len(rows), leaf)]
                continue
            at = np.argsort(part[:, wide.argmax()], kind="stable")
            todo += [rows[at[: len(rows) // 2]], rows[at[len(rows) // 2 :]]]
        self.low = np.stack([self.x[r].min(0) for r in self.leaves])
        self.high = np.stack([self.x[r].max(0) for r in self.leaves])

    def search(self, q: np.ndarray, own: np.ndarray, least: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query row, id, score) of each query's k best rows with a score of `least` or more, its own id left out."""
        m, n = len(q), len(self.ids)
        shift = max(1, int(n).bit_length())
        bound = np.maximum(q, 0) @ self.high.T + np.minimum(q, 0) @ self.low.T
        best = np.argsort(-bound, axis=1, kind="stable")
        none = np.int64(-(1 << 62))
        top = np.full((m, k), none)  # score and, for ties, the rank of the id from behind
        kth = least.copy()
        for step in range(len(self.leaves)):
            leaf = best[:, step]
            live = np.flatnonzero(bound[np.arange(m), leaf] >= kth)
            if not len(live):
                break
            by = live[np.argsort(leaf[live], kind="stable")]
            for some in np.split(by, np.flatnonzero(np.diff(leaf[by])) + 1):
                rows = self.leaves[leaf[some[0]]]
                s = q[some] @ self.x[rows].T
                s = s.astype(np.int64)
                key = (s << shift) + (n - 1 - rows)
                key[(self.ids[rows] == own[some][:, None]) | (s < kth[some][:, None])] = none
                both = np.concatenate([top[some], key], axis=1)
                top[some] = -np.partition(-both, k - 1, axis=1)[:, :k]
            worst = top.min(1)
            kth = np.maximum(kth, np.where(worst > none, worst >> shift, kth))
        i, j = np.nonzero(top > none)
        key = top[i, j]
        return i, self.ids[n - 1 - (key & ((1 << shift) - 1))], key >> shift


def plain_search(x: np.ndarray, ids: np.ndarray, rows: np.ndarray, q: np.ndarray, own: np.ndarray, least: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same by every product, for components so large that a score and a rank don't fit a long together. rows, own: row numbers."""
    out = []
    for i in range(len(q)):
        s = x @ q[i]
        ok = np.flatnonzero((rows != own[i]) & (s >= least[i]))
        best = ok[np.lexsort((rows[ok], ids[ok], -s[ok]))[:k]]
        out.append((np.full(len(best), i), best, s[best]))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 3


def whole(df: DataFrame, scale: int = 64) -> DataFrame:
    """vec_id and v: floor(scale * x) of every usable vector."""
    near = usable(df).where("vec_id is not null").where(~F.exists("x", lambda x: F.abs(F.lit(float(scale)) * x) >= float(1 << 28)))
    return near.select("vec_id", F.transform("x", lambda x: F.floor(F.lit(float(scale)) * x).cast("int")).alias("v"))


class Splits:
    """Median splits of a sample down to a number of leaves; routes any vector to its leaf."""

    def __init__(self, x: np.ndarray, leaves: int):
        self.axis, self.at = [], []
        groups = [x]
        while len(groups) < leaves:  # level by level, so that leaf numbers of neighbours are siblings
            nxt, axis, at = [], [], []
            for g in groups:
                wide = g.max(0) - g.min(0) if len(g) else np.zeros(x.shape[1], np.int64)
                a = int(wide.argmax())
                cut_ = float(np.median(g[:, a])) if len(g) else 0.0
                left = g[:, a] <= cut_
                if len(g) and left.all():  # more than half share the largest value
                    cut_ = float(g[:, a].max()) - 1
                    left = g[:, a] <= cut_
                axis.append(a)
                at.append(cut_)
                nxt += [g[left], g[~left]]
            self.axis.append(np.array(axis))
            self.at.append(np.array(at))
            groups = nxt

    def route(self, x: np.ndarray) -> np.ndarray:
        leaf = np.zeros(len(x), np.int64)
        for axis, at in zip(self.axis, self.at, strict=True):
            leaf = 2 * leaf + (x[np.arange(len(x)), axis[leaf]] > at[leaf])
        return leaf


_HITS = pa.schema([("query", pa.int64()), ("query_id", pa.int64()), ("vec_id", pa.int64()), ("row", pa.int64()), ("score", pa.int64())])
_HITS_DDL = "query long, query_id long, vec_id long, row long, score long"


def _matrix(col: pa.Array) -> np.ndarray:
    """Rows of packed 32-bit components."""
    return np.frombuffer(b"".join(col.to_pylist()), np.int32).reshape(len(col), -1)


def _kind(*parts: np.ndarray) -> type:
    """Doubles while all products and sums are whole numbers below 2**53."""
    most = max((float(np.abs(x).max(initial=0)) for x in parts), default=0.0)
    return np.float64 if most * most * parts[0].shape[1] < 2.0**52 else np.int64


def _search(rows: DataFrame, k: int) -> DataFrame:
    """rows: shard, lot, query (boolean), row, vec_id, v, least, sorted by shard and lot with candidates first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush(cands: list, asked: list) -> Iterator[pa.RecordBatch]:
            if not cands or not asked:
                return
            ids, nums, x = (np.concatenate(c) for c in zip(*cands, strict=True))
            order = np.lexsort((nums, ids))
            ids, nums, x = ids[order], nums[order], x[order]
            tree = None
            for qid, own, q, least in asked:
                if max(np.abs(x).max(initial=0), np.abs(q).max(initial=0)) >= SMALL:
                    i, at, s = plain_search(x.astype(np.int64), ids, nums, q.astype(np.int64), own, least, k)
                else:
                    kind = _kind(x, q)
                    if tree is None or tree.x.dtype != kind:
                        tree = KDTree(x.astype(kind), np.arange(len(x)))
                    mine = np.full(len(q), -1)  # the place of a query's own row among the candidates
                    by = np.argsort(nums, kind="stable")
                    place = np.minimum(np.searchsorted(nums[by], own), len(nums) - 1)
                    here = nums[by][place] == own
                    mine[here] = by[place[here]]
                    i, at, s = tree.search(q.astype(kind), mine, least, k)
                yield records(_HITS, query=own[i], query_id=qid[i], vec_id=ids[at], row=nums[at], score=s.astype(np.int64))

        cands, asked, at = [], [], None
        for b in batches:
            if not b.num_rows:
                continue
            query = b.column("query").to_numpy(zero_copy_only=False)
            shard = b.column("shard").to_numpy().astype(np.int64) << 32 | b.column("lot").to_numpy()
            cuts = np.flatnonzero(np.r_[True, (shard[1:] != shard[:-1]) | (query[1:] != query[:-1]), True])
            for p, e in zip(cuts[:-1], cuts[1:], strict=True):
                part = b.slice(p, e - p)
                if at is not None and shard[p] != at:
                    yield from flush(cands, asked)
                    cands, asked = [], []
                at = shard[p]
                ids, nums, v = part.column("vec_id").to_numpy(), part.column("row").to_numpy(), _matrix(part.column("v"))
                if query[p]:
                    asked.append((ids, nums, v, part.column("least").to_numpy()))
                else:
                    cands.append((ids, nums, v))
        yield from flush(cands, asked)

    return arrow_map(rows, run, _HITS_DDL)


_DEALT = pa.schema([("shard", pa.int32()), ("row", pa.int64()), ("vec_id", pa.int64()), ("v", pa.binary())])
_BOX = pa.schema([("shard", pa.int32()), ("low", pa.binary()), ("high", pa.binary()), ("n", pa.int64())])


def _routed(df: DataFrame, splits: Splits) -> DataFrame:
    """shard, row, vec_id and v packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = b.column("v").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1).astype(np.int32)
                yield records(_DEALT, shard=splits.route(x).astype(np.int32), row=b.column("row"), vec_id=b.column("vec_id"), v=[r.tobytes() for r in x])

    return arrow_map(df.select("row", "vec_id", "v"), run, "shard int, row long, vec_id long, v binary")


def _boxes(df: DataFrame, packed: str) -> DataFrame:
    """shard, low, high, n: boxes of each task's rows or boxes of a shard; packed: the column of vectors, or none for boxes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            if not b.num_rows:
                continue
            shard = b.column("shard").to_numpy()
            low, high = (_matrix(b.column(packed)),) * 2 if packed else (_matrix(b.column(c)) for c in ("low", "high"))
            n = np.ones(len(shard), np.int64) if packed else b.column("n").to_numpy()
            for s in np.unique(shard).tolist():
                on = shard == s
                part = [low[on].min(0), high[on].max(0), int(n[on].sum())]
                old = held.get(s)
                held[s] = part if old is None else [np.minimum(old[0], part[0]), np.maximum(old[1], part[1]), old[2] + part[2]]
        if held:
            yield records(_BOX, shard=list(held), low=[x[0].tobytes() for x in held.values()], high=[x[1].tobytes() for x in held.values()], n=[x[2] for x in held.values()])

    return arrow_map(df, run, "shard int, low binary, high binary, n long")


def search(vectors: DataFrame, every: int = 20, k: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score: the k best candidates of each row whose vec_id is divisible by `every`. vectors: vec_id, v."""
    spark = vectors.sparkSession
    base = cut(vectors.select("vec_id", "v", F.monotonically_increasing_id().alias("row")))
    same = Window.partitionBy("v").orderBy("vec_id", "row")
    kept = cut(base.withColumn("nth", F.row_number().over(same)).where(F.col("nth") <= k + 1).drop("nth"))
    n = kept.count()
    leaves = 1
    while leaves * SHARD < n and (leaves < BOXES or leaves * SHARD_MOST < n):
        leaves *= 2
    some = np.array([r[0] for r in kept.orderBy(F.xxhash64("row"), "row").limit(SAMPLE).select("v").collect()] if leaves > 1 else [[0]], np.int64)
    splits = Splits(some.reshape(len(some), -1), leaves)
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(leaves, 100_000))
    lowest = -(1 << 62) + 1
    routed = cut(_routed(kept, splits))
    queries = cut(_routed(base.where(F.col("vec_id") % every == 0), splits).withColumn("least", F.lit(lowest)))
    cands = routed.select("shard", F.lit(False).alias("query"), "row", "vec_id", "v", F.lit(lowest).alias("least"))

    def deal(q: DataFrame) -> DataFrame:
        # A shard that many queries ask for (a third may hold one vector) answers them in lots, each with the shard's candidates.
        lots = cut(q.groupBy("shard").agg(F.count("*").alias("n")).withColumn("lots", F.ceil(F.col("n") / ASKED).cast("int")))
        lot = F.pmod(F.xxhash64("row"), F.col("lots")).cast("int")
        asked = salted_join(q, lots, "shard", "row", hot_keys(lots, "shard", "n")).select("shard", lot.alias("lot"), F.lit(True).alias("query"), "row", "vec_id", "v", "least")
        given = cands.join(lots, "shard").select("shard", F.explode(F.sequence(F.lit(0), F.col("lots") - 1)).alias("lot"), "query", "row", "vec_id", "v", "least")
        return given.union(asked).repartition(parts, "shard", "lot").sortWithinPartitions("shard", "lot", "query", "vec_id", "row")

    home = cut(_search(deal(queries), k))
    hits = home
    if leaves > 1:
        least = home.groupBy("query").agg(F.count("*").alias("n"), F.min("score").alias("s")).where(F.col("n") >= k).select(F.col("query").alias("row"), F.col("s").alias("least"))
        known = queries.drop("least").join(least, "row", "left").withColumn("least", F.coalesce("least", F.lit(lowest)))
        # Neighbouring leaves share a box where there are more than BOXES of them, so what tasks are given is bounded.
        shift = max(0, (leaves - 1).bit_length() - (BOXES - 1).bit_length())
        boxes = _boxes(_boxes(routed.select((F.expr(f"shiftright(shard, {shift})")).alias("shard"), "v"), "v").repartition(parts, "shard"), "").collect()  # BOXES rows at most
        at = np.array([r["shard"] for r in boxes], np.int32)
        low, high = (np.stack([np.frombuffer(r[c], np.int32) for r in boxes]).astype(np.int64) for c in ("low", "high"))

        def away(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            schema = pa.schema([("shard", pa.int32()), ("row", pa.int64()), ("vec_id", pa.int64()), ("v", pa.binary()), ("least", pa.int64())])
            lows, highs = low.astype(np.float64), high.astype(np.float64)
            for b in batches:
                if not b.num_rows:
                    continue
                q = _matrix(b.column("v")).astype(np.float64)
                bound = np.maximum(q, 0) @ highs.T + np.minimum(q, 0) @ lows.T
                slack = 1e-9 * np.abs(bound) + 1  # doubles may round a bound of large components down
                i, j = np.nonzero(bound + slack >= b.column("least").to_numpy()[:, None])
                home_of = b.column("shard").to_numpy()
                for up in range(1 << shift):
                    to = (at[j] << shift) + up
                    on = to != home_of[i]
                    take = pa.array(i[on])
                    yield records(schema, shard=to[on].astype(np.int32), row=b.column("row").take(take), vec_id=b.column("vec_id").take(take), v=b.column("v").take(take), least=b.column("least").take(take))

        dealt = arrow_map(known.select("shard", "row", "vec_id", "v", "least"), away, "shard int, row long, vec_id long, v binary, least long")
        hits = home.union(_search(deal(cut(dealt)), k))
    order = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id", "row")
    return hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op4_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(whole(table(spark, sf_dir, "embeddings", "vec_id", "embedding")))
