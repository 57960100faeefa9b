"""Links between near-equal embeddings through an inverted multi-index.

Each half of a unit vector has a codebook of its own (k-means on a bounded
sample); a pair of centroids is a cell of the product grid, and every vector is
listed in its cell. A vector visits cells by multi-sequence traversal, nearest first by
the sum of both halves' squared distances to the cell's borders, and stops where the
sum exceeds a radius: the one that reaches the target recall on sample vectors turned by
exactly the angle of the threshold, in random directions. `traverse` runs the traversal
of many vectors side by side; `multi_sequence` is the same for one, by a heap.
Of two vectors the one in the lower cell visits the other's cell, so each pair meets
once. Every pair that meets is verified by its cosine in double precision.

Crowded cells are dealt out as blocks of members times blocks of visitors; within a
block matches are counted and reduced to a spanning forest, never listed.

Defined results: vectors that are null, zero, of another length than most, or hold
null or non-finite components link with nothing; equal vectors are one vertex
with a count; a null vec_id is its own component.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, components, cut, records, table

COSINE = 0.95
SAMPLE = 20_000
CELL = 192
BLOCK = 512


def multi_sequence(first: np.ndarray, second: np.ndarray) -> Iterator[tuple[float, int, int]]:
    """(sum, i, j) in growing order of first[i] + second[j], by a frontier of a heap: no more of the grid is touched than is asked for."""
    a, b = np.argsort(first, kind="stable"), np.argsort(second, kind="stable")
    heap, seen = [(float(first[a[0]] + second[b[0]]), 0, 0)], {(0, 0)}
    while heap:
        s, i, j = heapq.heappop(heap)
        yield s, int(a[i]), int(b[j])
        for x, y in ((i + 1, j), (i, j + 1)):
            if x < len(a) and y < len(b) and (x, y) not in seen:
                seen.add((x, y))
                heapq.heappush(heap, (float(first[a[x]] + second[b[y]]), x, y))


def traverse(first: np.ndarray, second: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray]:
    """(row, cell) in the order of the multi-sequence traversal, for many rows at once: each row takes its nearest open cell until its sum exceeds the radius.

    A row's frontier holds for each opened rank of the first half the next rank of the
    second one; a step closes the smallest sum and opens the next rank behind the last one
    opened, so only the part of the grid that is asked for is touched.
    """
    k = second.shape[1]
    a, b = np.argsort(first, axis=1, kind="stable"), np.argsort(second, axis=1, kind="stable")
    one, two = np.take_along_axis(first, a, 1), np.take_along_axis(second, b, 1)
    m = len(first)
    rows, cells = [], []
    live = np.flatnonzero(one[:, 0] + two[:, 0] <= radius) if m else np.zeros(0, np.int64)
    at = np.zeros((m, first.shape[1]), np.int64)  # next rank of the second half, for each opened rank of the first
    opened = np.ones(m, np.int64)
    while len(live):
        wide = int(opened[live].max())
        j = at[live, :wide]
        sums = np.where((np.arange(wide) < opened[live][:, None]) & (j < k), one[live, :wide] + np.take_along_axis(two[live], np.minimum(j, k - 1), 1), np.inf)
        i = sums.argmin(1)
        going = sums[np.arange(len(live)), i] <= radius
        live, i = live[going], i[going]
        if not len(live):
            break
        rows.append(live)
        cells.append(a[live, i] * k + b[live, at[live, i]])
        at[live, i] += 1
        opened[live] = np.where((i == opened[live] - 1) & (opened[live] < first.shape[1]), opened[live] + 1, opened[live])
    return (np.concatenate(rows), np.concatenate(cells)) if rows else (np.zeros(0, np.int64), np.zeros(0, np.int64))


class Codebooks:
    """Centroids of both halves; squared distances of points to the borders of the centroids' regions."""

    def __init__(self, unit: np.ndarray, k: int, cosine: float, recall: float, rounds: int = 8):
        rng = np.random.default_rng(7)
        d = unit.shape[1] // 2
        self.half = d
        self.books = [self._means(x, k, rng, rounds) for x in (unit[:, :d], unit[:, d:])]
        self.spread = [np.sqrt(((b[:, None] - b[None]) ** 2).sum(-1)) for b in self.books]
        self.radius = self._calibrate(unit, cosine, recall, rng)

    @staticmethod
    def _means(x: np.ndarray, k: int, rng, rounds: int) -> np.ndarray:
        c = x[rng.choice(len(x), min(k, len(x)), replace=False)]
        for _ in range(rounds):
            near = ((c * c).sum(1) - 2 * x @ c.T).argmin(1)
            n = np.bincount(near, minlength=len(c))
            total = np.stack([np.bincount(near, x[:, i], len(c)) for i in range(x.shape[1])], 1)
            c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
        return np.unique(c, axis=0)

    def borders(self, unit: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
        """Squared distance to each centroid's region for each half (0: inside), and each vector's cell."""
        out, own = [], []
        for x, c, between in zip((unit[:, : self.half], unit[:, self.half :]), self.books, self.spread, strict=True):
            d2 = np.maximum(0, (x * x).sum(1)[:, None] + (c * c).sum(1) - 2 * x @ c.T)
            near = d2.argmin(1)
            gap = (d2 - d2[np.arange(len(x)), near][:, None]) / np.maximum(2 * between[near], 1e-12)
            gap[np.arange(len(x)), near] = 0
            out.append(gap * gap)
            own.append(near)
        return out, own[0] * len(self.books[1]) + own[1]

    def _calibrate(self, unit: np.ndarray, cosine: float, recall: float, rng) -> float:
        a = unit[rng.choice(len(unit), min(4000, len(unit)), replace=False)]
        n = rng.normal(size=a.shape)
        n -= (n * a).sum(1)[:, None] * a
        n /= np.maximum(np.linalg.norm(n, axis=1), 1e-12)[:, None]
        b = cosine * a + np.sqrt(1 - cosine * cosine) * n
        (one, two), _ = self.borders(a)
        _, cell = self.borders(b)
        k, r = len(self.books[1]), np.arange(len(a))
        return float(np.quantile(one[r, cell // k] + two[r, cell % k], recall)) + 1e-9


def usable(df: DataFrame, column: str = "embedding") -> DataFrame:
    """vec_id and the components of vectors that can be compared: of the commonest length, all finite."""
    x = F.col(column).cast("array<double>")
    fine = df.select("vec_id", x.alias("x")).where(F.col("x").isNotNull() & (F.size("x") > 0)).where(~F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))))
    length = fine.groupBy(F.size("x").alias("n")).count().orderBy(F.desc("count"), "n").first()
    return fine.where(F.size("x") == (length["n"] if length else 0))


def _doubles(column: pa.Array) -> np.ndarray:
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 1))


def _packed(x: np.ndarray, single: bool) -> list[bytes]:
    """Rows as bytes: of 32-bit floats where the table has such, else of doubles; nothing is rounded."""
    return [r.tobytes() for r in x.astype(np.float32 if single else np.float64)]


def _unpacked(column: pa.Array, single: bool) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float32 if single else np.float64).reshape(len(column), -1).astype(np.float64)


_BLOCKS = pa.schema([("vec", pa.int64()), ("copies", pa.int64()), ("x", pa.binary()), ("cell", pa.int64()), ("visitor", pa.bool_()), ("own", pa.bool_())])
_FOUND = pa.schema([("vec", pa.int64()), ("links", pa.int64()), ("b", pa.int64())])


def _labels(s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Component labels of the rows and columns of a boolean matrix (labels: row numbers; rows and columns without a match keep -1)."""
    n = s.shape[0]
    rows, cols = np.where(s.any(1), np.arange(n), n), np.full(s.shape[1], n)
    while True:
        new_cols = np.where(s, rows[:, None], n).min(0)
        new_rows = np.minimum(rows, np.where(s, new_cols, n).min(1))
        if (new_rows == rows).all() and (new_cols == cols).all():
            return np.where(rows < n, rows, -1), np.where(cols < n, cols, -1)
        rows, cols = new_rows, new_cols


def link(df: DataFrame, cosine: float = COSINE, recall: float = 0.9995, sample: int = SAMPLE) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of df (vec_id, embedding)."""
    spark = df.sparkSession
    every = cut(df.select("vec_id", "embedding"))
    single = every.schema["embedding"].dataType.simpleString() == "array<float>"
    good = usable(every).where("vec_id is not null").where(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v) > 0)
    reps = cut(good.groupBy("x").agg(F.min("vec_id").alias("vec"), F.count("*").alias("copies")))
    n = reps.count()
    none = every.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    if not n:
        return none
    some = np.array([r["x"] for r in reps.orderBy(F.xxhash64("vec"), "vec").limit(sample).select("x").collect()])
    unit = some / np.linalg.norm(some, axis=1)[:, None]
    books = Codebooks(unit, max(2, min(2048, int(np.sqrt(n / CELL)))), cosine, recall)

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = _doubles(b.column("x"))
            (one, two), own = books.borders(x / np.linalg.norm(x, axis=1)[:, None])
            row, cell = traverse(one, two, books.radius)
            upper = cell > own[row]  # the lower cell's vector visits
            row, cell = row[upper], cell[upper]
            blobs = pa.array(_packed(x, single), pa.binary())
            here = np.arange(len(x))
            for r, c, visitor, at_home in ((here, own, False, False), (here, own, True, True), (row, cell, True, False)):
                yield records(_BLOCKS, vec=b.column("vec").take(pa.array(r)), copies=b.column("copies").take(pa.array(r)), x=blobs.take(pa.array(r)), cell=c.astype(np.int64), visitor=np.full(len(r), visitor), own=np.full(len(r), at_home))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def block(rows: pa.Table) -> Iterator[pa.RecordBatch]:
            side = [rows.filter(pa.compute.equal(rows["visitor"], v)).combine_chunks() for v in (True, False)]
            if not len(side[0]) or not len(side[1]):
                return
            (va, ca), (vb, cb) = (tuple(s[c].to_numpy() for c in ("vec", "copies")) for s in side)
            xa, xb = (_unpacked(s["x"].combine_chunks(), single) for s in side)
            na, nb = (np.linalg.norm(x, axis=1) for x in (xa, xb))
            s = (xa @ xb.T) / (na[:, None] * nb) >= cosine
            s &= ~side[0]["own"].to_numpy(zero_copy_only=False)[:, None] | (va[:, None] < vb)  # a cell's own pairs meet from both sides
            i, j = np.nonzero(s)
            if not len(i):
                return
            links_a = np.bincount(i, cb[j], len(va)).astype(np.int64)
            links_b = np.bincount(j, ca[i], len(vb)).astype(np.int64)
            rows_of, cols_of = _labels(s)
            for v, n_links, lab in ((va, links_a, rows_of), (vb, links_b, cols_of)):
                on = np.flatnonzero(lab >= 0)
                yield records(_FOUND, vec=v[on], links=n_links[on], b=va[lab[on]])

        held, key = [], None
        for b in batches:
            t = pa.Table.from_batches([b])
            keys = np.stack([t[c].to_numpy() for c in ("cell", "i", "j")], 1)
            cuts = np.flatnonzero(np.r_[True, (keys[1:] != keys[:-1]).any(1), True]) if len(keys) else [0]
            for p, q in zip(cuts[:-1], cuts[1:], strict=True):
                k = tuple(keys[p].tolist())
                if key is not None and k != key:
                    yield from block(pa.concat_tables(held))
                    held = []
                key = k
                held.append(t.slice(p, q - p))
        if held:
            yield from block(pa.concat_tables(held))

    met = cut(arrow_map(reps.select("vec", "copies", "x"), visit, "vec long, copies long, x binary, cell long, visitor boolean, own boolean"))
    crowd = met.groupBy("cell").agg(F.ceil(F.sum((~F.col("visitor")).cast("int")) / BLOCK).cast("int").alias("ni"), F.ceil(F.sum(F.col("visitor").cast("int")) / BLOCK).cast("int").alias("nj")).where("ni > 0 and nj > 0")
    lot = lambda n: F.pmod(F.xxhash64("vec"), F.col(n)).cast("int")
    each = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    dealt = met.join(crowd, "cell").withColumn("i", F.explode(F.when(F.col("visitor"), each("ni")).otherwise(F.array(lot("ni"))))).withColumn("j", F.explode(F.when(F.col("visitor"), F.array(lot("nj"))).otherwise(each("nj"))))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    blocks = dealt.repartition(parts, "cell", "i", "j").sortWithinPartitions("cell", "i", "j")
    found = cut(arrow_map(blocks, compare, "vec long, links long, b long"))
    links = found.groupBy("vec").agg(F.sum("links").alias("links"))
    part = components(found.select(F.col("vec").alias("a"), "b"))
    result = reps.join(links, "vec", "left").join(part.withColumnRenamed("id", "vec"), "vec", "left").select("x", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("component", "vec").alias("component"))
    ids = good.join(result, "x").select("vec_id", "links", "component")
    out = every.select("vec_id").join(ids.groupBy("vec_id").agg(F.max("links").alias("links"), F.min("component").alias("component")), "vec_id", "left")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def op1_embedding_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))
