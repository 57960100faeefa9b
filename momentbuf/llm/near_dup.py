"""Near-duplicate documents by a chosen-path set similarity join over word shingles.

Documents with equal shingle sets are one vertex from the start. The others go
down independent random trees: a node picks one coordinate of the minwise sketch
(a second one by chance, so that the mean number of branches is one over the
similarity sought) and sends a document to the child of its minwise token. Nodes
with few unresolved documents are compared exhaustively; larger ones branch on.

A node is resolved as far as its documents are already known to be one
component: first every document is held against its node's smallest (one
candidate each), those links are confirmed on the full sets, and only pairs
across components are left to compare. So a group of n near copies costs about n
comparisons and not their square, and a pair of different components that meets
in any tree is still compared.

Large nodes with much left to compare are of two kinds. Where documents are unlike
on average (they share a passage) further branching parts them, from several roots of
their own where the target recall asks for it. Where they are alike
on average (a cloud of copies around the threshold) it would not, so such nodes are
joined to clusters, and the documents outside a cluster's largest component are
compared with all of the cluster, in blocks, by sketch and then on full
sets within the task; no pairs are moved, and a cloud with few such documents costs
about its own size.

The number of trees follows from the recall: a pair at exactly the threshold meets in a
tree with a chance that the branching fixes (`parted`), and there are as many trees as
leave it with fewer than two meetings in one of 100,000 cases; where nodes are
branched on, as many roots are drawn below each as keep the miss below one in 500.

Defined results: null, empty and wordless texts have no set and link with
nothing; a text of fewer words than a shingle has its whole sequence as the one
shingle; equal rows are one vertex; a null doc_id takes part under no other
document's id and is its own component.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, components, cut, hot_keys, records, salted_join, spread_join, table

SHINGLE = 5
SKETCH = 128
MARGIN = 0.14
#: Least share of pairs at the threshold that share two first nodes at least, and that meet whatever nodes are branched on.
FIRST_RECALL, RECALL = 1 - 1e-5, 0.998
FIRST_LEVELS, NEXT_LEVELS = 2, 4
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_SPACE = np.isin(np.arange(256), [32, *range(9, 14)])
_BASE, _INV = np.uint64(0x9E3779B97F4A7C15), np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]
_rng = np.random.default_rng(20_11)
_MUL = _rng.integers(1, 1 << 63, SKETCH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 1 << 63, SKETCH, dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A finaliser of 64-bit words: every input bit reaches every output bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        n = 1 << int(n).bit_length()
        for i, b in enumerate((_BASE, _INV)):
            _powers[i] = np.r_[np.uint64(1), np.full(n - 1, b)].cumprod(dtype=np.uint64)
    return _powers[0], _powers[1]


def shingles(text: str | None, k: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's k-word shingles."""
    raw = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER)
    c = np.frombuffer(raw, np.uint8)
    solid = np.r_[False, ~_SPACE[c], False]
    edge = np.flatnonzero(solid[1:] != solid[:-1])
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.zeros(0, np.uint64)
    up, down = _power(len(c) + 1)
    total = np.r_[np.uint64(0), ((c.astype(np.uint64) + np.uint64(1)) * up[: len(c)]).cumsum(dtype=np.uint64)]
    word = mix((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64))
    n = max(1, len(word) - k + 1)
    h = np.full(n, np.uint64(min(k, len(word))))
    for i in range(min(k, len(word))):
        h = mix(h * np.uint64(0x2545F4914F6CDD1D) + word[i : i + n])
    return np.unique(h)


def sketch(s: np.ndarray) -> np.ndarray:
    """Minwise values (32 bits) of a set that isn't empty."""
    low = np.full(SKETCH, np.uint64(0xFFFFFFFFFFFFFFFF))
    for at in range(0, len(s), 2048):
        low = np.minimum(low, (s[at : at + 2048, None] * _MUL + _ADD).min(axis=0))
    return (low >> np.uint64(32)).astype(np.uint32)


def planes(values: np.ndarray) -> bytes:
    """A sketch by bytes of equal weight: the lowest byte of every value first. Estimates read those alone (see LOW), walks all."""
    return values.astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()


def unplaned(column: pa.Array) -> np.ndarray:
    """The rows of minwise values that planes has packed."""
    packed = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, 4, SKETCH)
    return np.ascontiguousarray(packed.transpose(0, 2, 1)).view("<u4").reshape(-1, SKETCH)


def lows(column: pa.Array) -> np.ndarray:
    """The rows of lowest bytes of minwise values."""
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, SKETCH)


#: The lowest bytes of a sketch, a quarter of it: equal values have equal bytes, so an estimate from them is never lower, and higher by a 256th of the rest.
LOW = f"substring(sketch, 1, {SKETCH})"


_SIGNED = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("digest", pa.binary()), ("sketch", pa.binary())])


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        n, digest, values = [], [], []
        for t in b.column("text").to_pylist():
            s = shingles(t)
            n.append(len(s))
            digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
            values.append(planes(sketch(s)) if len(s) else None)
        yield records(_SIGNED, doc_id=b.column("doc_id"), n_shingles=n, digest=digest, sketch=values)


def descend(node: np.ndarray, row: np.ndarray, values: np.ndarray, similarity: float, levels: int) -> tuple[np.ndarray, np.ndarray]:
    """Children of (node, row) pairs so many levels down; which coordinates a node looks at depends on the node alone."""
    share = np.uint64(int((1 / similarity - 1) * (1 << 32)))
    for _ in range(levels):
        first = (mix(node ^ np.uint64(0xA5A5A5A5)) % np.uint64(SKETCH)).astype(np.int64)
        more = (mix(node ^ np.uint64(0x5BD1E995)) >> np.uint64(32)) < share
        other = (first + 1 + (mix(node ^ np.uint64(0x1B873593)) % np.uint64(SKETCH - 1)).astype(np.int64)) % SKETCH
        at, of = np.r_[node, node[more]], np.r_[row, row[more]]
        c = np.r_[first, other[more]]
        node, row = mix(mix(at + np.uint64(0x9E3779B97F4A7C15) * (c + 1).astype(np.uint64)) ^ values[of, c].astype(np.uint64)), of
    return node, row


def parted(similarity: float, levels: int, after: float = 0.0) -> float:
    """Chance that a pair of a similarity shares no node so many levels below one it shares; after: the chance that a shared node comes to nothing later."""
    x = after
    for _ in range(levels):
        u = 1 - similarity + similarity * x
        x = (2 - 1 / similarity) * u + (1 / similarity - 1) * u * u
    return x


def trees_for(similarity: float) -> int:
    """Trees in which a pair at the threshold shares two first nodes with a chance of FIRST_RECALL."""
    q, t = parted(similarity, FIRST_LEVELS), 2
    while t * (1 - q) * q ** (t - 1) + q**t > 1 - FIRST_RECALL:
        t += 1
    return t


def roots_for(similarity: float, trees: int, before: list[int]) -> int:
    """Roots to draw below each node that is branched on once more, after stages that drew so many: the fewest that keep RECALL."""

    def missed(stages: list[int]) -> float:
        x = 0.0
        for r in reversed(stages):
            x = parted(similarity, NEXT_LEVELS, x) ** r
        return parted(similarity, FIRST_LEVELS, x) ** trees

    r = 1
    while missed([*before, r]) > 1 - RECALL and r < 64:
        r += 1
    return r


_MEMBERS = pa.schema([("node", pa.int64()), ("doc", pa.int64())])


def _walk(df: DataFrame, similarity: float, levels: int, trees: int = 0, roots: int = 1) -> DataFrame:
    """(node, doc) below the roots of the trees, or below so many roots of their own at each of the nodes that df has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            doc = b.column("doc").to_numpy(zero_copy_only=False)
            values = unplaned(b.column("sketch"))
            if trees:
                node, row = np.repeat(mix(np.arange(1, trees + 1, dtype=np.uint64)), len(doc)), np.tile(np.arange(len(doc)), trees)
            else:
                node, row = b.column("node").to_numpy(zero_copy_only=False).view(np.uint64), np.arange(len(doc))
                node, row = np.concatenate([mix(node + np.uint64(0x632BE59BD9B4E019) * np.uint64(i)) for i in range(roots)]), np.tile(row, roots)
            node, row = descend(node, row, values, similarity, levels)
            yield records(_MEMBERS, node=pa.array(node.view(np.int64)), doc=pa.array(doc[row]))

    return arrow_map(df, run, "node long, doc long").distinct() if not trees else arrow_map(df, run, "node long, doc long")


_PAIRS = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("like", pa.float64())])


def _estimated(pairs: DataFrame, reps: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) whose sizes and sketches allow the similarity: a, b, like."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                u, v = (lows(x.column(c)) for c in ("sa", "sb"))
                like = (u == v).mean(axis=1)
                keep = like >= similarity - MARGIN
                yield records(_PAIRS, a=x.column("a").filter(pa.array(keep)), b=x.column("b").filter(pa.array(keep)), like=like[keep])

    one = lambda s: reps.select(F.col("doc").alias(s), F.expr(LOW).alias(f"s{s}"), F.col("n_shingles").alias(f"n{s}"))
    pairs = cut(pairs.select("a", "b"))
    both = spread_join(spread_join(pairs, one("b"), "b", "a"), one("a"), "a", "b", counted=pairs)
    return arrow_map(both.where(F.least("na", "nb") >= F.greatest("na", "nb") * (similarity - 1e-9)).select("a", "b", "sa", "sb"), run, "a long, b long, like double")


_SETS = pa.schema([("doc", pa.int64()), ("shingles", pa.binary())])
#: So many ids at most are broadcast (a few MB); more are joined by exchange.
BROADCAST_IDS = 200_000


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield records(_SETS, doc=b.column("doc"), shingles=[shingles(t).tobytes() for t in b.column("text").to_pylist()])


_EDGES = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def sets_of(docs: DataFrame, ids: DataFrame, most: int) -> DataFrame:
    """doc and its full shingle set (packed) for the given distinct ids, of which there are at most so many."""
    texts = docs.select(F.col("doc_id").alias("doc"), "text").join(F.broadcast(ids) if most <= BROADCAST_IDS else ids, "doc", "left_semi")
    return cut(arrow_map(texts, _sets, "doc long, shingles binary"))


def confirmed(pairs: DataFrame, docs: DataFrame, percent: int) -> DataFrame:
    """Pairs (a written frame) whose full sets have 100 * intersection >= percent * union."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            keep = []
            for p, q in zip(x.column("ha").to_pylist(), x.column("hb").to_pylist(), strict=True):
                p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                both = len(p) + len(q) - len(np.union1d(p, q))
                keep.append(100 * both >= percent * (len(p) + len(q) - both))
            keep = pa.array(keep, pa.bool_())
            yield records(_EDGES, a=x.column("a").filter(keep), b=x.column("b").filter(keep))

    n = pairs.count()
    if not n:
        return pairs.select("a", "b")
    sets = sets_of(docs, pairs.select(F.col("a").alias("doc")).union(pairs.select(F.col("b").alias("doc"))).distinct(), 2 * n)
    one = lambda s: sets.select(F.col("doc").alias(s), F.col("shingles").alias(f"h{s}"))
    both = spread_join(spread_join(pairs.select("a", "b"), one("b"), "b", "a"), one("a"), "a", "b", counted=pairs)
    return arrow_map(both.select("a", "b", "ha", "hb"), run, "a long, b long")


def _alike(nodes: DataFrame, sketches: DataFrame) -> DataFrame:
    """node, alike: mean estimated similarity of a node's documents to one of them, picked by hash. nodes: node, doc, peer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                u, v = (lows(x.column(c)) for c in ("low", "other"))
                yield pa.RecordBatch.from_arrays([x.column("node"), pa.array((u == v).mean(axis=1))], names=["node", "like"])

    nodes = cut(nodes)
    both = spread_join(nodes, sketches.select(F.col("doc").alias("peer"), F.expr(LOW).alias("other")), "peer", "doc").join(sketches.select("doc", F.expr(LOW).alias("low")), "doc")
    return arrow_map(both.select("node", "low", "other"), run, "node long, like double").groupBy("node").agg(F.avg("like").alias("alike"))


def _exhaust(cluster: DataFrame, sketches: DataFrame, docs: DataFrame, percent: int, block: int = 512) -> DataFrame:
    """Confirmed links (a, b) within clusters (cluster, doc, component, odd), a spanning forest of each block's: each odd document against all; pairs of one component are known."""
    floor = percent / 100 - MARGIN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def compare(rows: list[tuple]) -> pa.RecordBatch:
            u, v = ([r for r in rows if r[3] == side] for side in (0, 1))
            if not u or not v:
                return records(_EDGES, a=[], b=[])
            full = [[np.frombuffer(r[6], np.uint64) for r in x] for x in (u, v)]
            low = [np.frombuffer(b"".join(r[5] for r in x), np.uint8).reshape(-1, SKETCH) for x in (u, v)]
            same = np.zeros((len(u), len(v)), np.int16)
            for c in range(SKETCH):
                same += low[0][:, c, None] == low[1][None, :, c]
            sizes = [np.array([len(s) for s in x]) for x in full]
            fits = np.minimum(sizes[0][:, None], sizes[1]) * 100 >= np.maximum(sizes[0][:, None], sizes[1]) * percent
            i, j = np.nonzero((same >= floor * SKETCH) & fits & (np.array([r[4] for r in u])[:, None] != np.array([r[4] for r in v])))
            best = np.argsort(-same[i, j], kind="stable")
            root: dict[int, int] = {}

            def find(x: int) -> int:
                while (y := root.get(x, x)) != x:
                    root[x] = root.get(y, y)
                    x = y
                return x

            out = []
            for p, q in zip(i[best].tolist(), j[best].tolist(), strict=True):
                x, y = find(u[p][4]), find(v[q][4])
                if x == y:
                    continue
                s, t = full[0][p], full[1][q]
                both = len(np.intersect1d(s, t, assume_unique=True))
                if 100 * both >= percent * (len(s) + len(t) - both):
                    root[x] = y
                    out.append((u[p][7], v[q][7]))
            return records(_EDGES, a=[x for x, _ in out], b=[x for _, x in out])

        held: list[tuple] = []
        for b in batches:
            for r in zip(*(b.column(c).to_pylist() for c in ("cluster", "i", "j", "side", "component", "low", "shingles", "doc")), strict=True):
                if held and r[:3] != held[0][:3]:
                    yield compare(held)
                    held = []
                held.append(r)
        if held:
            yield compare(held)

    sets = sets_of(docs, cluster.select("doc").distinct(), cluster.count())
    chunks = cut(cluster.groupBy("cluster").agg(F.ceil(F.count("*") / block).cast("int").alias("nj"), F.ceil(F.sum(F.col("odd").cast("int")) / block).cast("int").alias("ni"), F.count("*").alias("n")))
    own = salted_join(cluster, chunks.drop("n"), "cluster", "doc", hot_keys(chunks, "cluster", "n"))
    # Each chunk of odd documents (side 0) meets each chunk of all (side 1).
    lot = lambda n: F.pmod(F.xxhash64("doc"), F.col(n)).cast("int")
    row = lambda i, j, side: F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"), F.lit(side).alias("side"))
    as_odd = F.when(F.col("odd"), F.transform(F.sequence(F.lit(0), F.col("nj") - 1), lambda x: row(lot("ni"), x, 0))).otherwise(F.array().cast("array<struct<i:int,j:int,side:int>>"))
    as_any = F.transform(F.sequence(F.lit(0), F.col("ni") - 1), lambda x: row(x, lot("nj"), 1))
    dealt = own.where("ni > 0").select("cluster", "doc", "component", F.inline(F.concat(as_odd, as_any)))
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    rows = dealt.join(sketches.select("doc", F.expr(LOW).alias("low")), "doc").join(sets, "doc").repartition(parts, "cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", "side", "doc")
    return arrow_map(rows.select("cluster", "i", "j", "side", "component", "low", "shingles", "doc"), run, "a long, b long")


def join_components(docs: DataFrame, percent: int = 85, trees: int | None = None, small: int = 4096, dense: float = 0.6) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row of docs (doc_id, text).

    trees: first trees, else as the recall asks; small: most pairs left in a node that is compared pair by pair; dense: mean similarity
    from which a larger node is exhausted in blocks and not branched.
    """
    similarity = percent / 100
    enough = trees_for(similarity)
    trees = trees or enough
    stages: list[int] = []
    signed = cut(arrow_map(docs.select("doc_id", "text"), _sign, "doc_id long, n_shingles long, digest binary, sketch binary"))
    sets = signed.where("digest is not null and doc_id is not null")
    reps = cut(sets.groupBy("digest", "n_shingles").agg(F.min("doc_id").alias("doc"), F.first("sketch").alias("sketch")).select("doc", "n_shingles", "digest", "sketch"))
    sketches = reps.select("doc", "n_shingles", "sketch")
    members = _walk(sketches.select("doc", "sketch"), similarity, FIRST_LEVELS, trees)
    edges = None
    for depth in range(SKETCH):
        members = cut(members)
        nodes = cut(members.groupBy("node").agg(F.count("*").alias("n"), F.min("doc").alias("pivot")).where("n > 1"))
        hot = hot_keys(nodes, "node", "n")
        shared = cut(salted_join(members, nodes, "node", "doc", hot).select("node", "doc", "pivot"))
        if edges is None:
            # One candidate for each document: of its nodes' smallest documents the one it shares most nodes with.
            star = shared.where("doc <> pivot").groupBy("doc", "pivot").agg(F.count("*").alias("k")).groupBy("doc").agg(F.max(F.struct("k", (-F.col("pivot")).alias("p"))).alias("best")).select(F.col("doc").alias("a"), (-F.col("best.p")).alias("b"))
            edges = cut(confirmed(cut(_estimated(star, sketches, similarity).select("a", "b")), docs, percent))
        part = cut(components(edges))
        # What is left: nodes of more than one component. odd: documents outside the node's largest component.
        in_part = shared.join(part.withColumnRenamed("id", "doc"), "doc", "left").withColumn("component", F.coalesce("component", "doc")).select("node", "doc", "component")
        parts = in_part.groupBy("node", "component").agg(F.count("*").alias("k"))
        mixed = parts.groupBy("node").agg(F.sum("k").alias("n"), F.count("*").alias("parts"), F.max(F.struct("k", "component")).alias("main")).where("parts > 1").select("node", "n", (F.col("n") - F.col("main.k")).alias("odd"), F.col("main.component").alias("main"))
        left = cut(salted_join(in_part, mixed, "node", "doc", hot))
        few = F.col("odd") * F.col("n") <= small
        near = left.where(few)
        x = near.where("component <> main").select("node", F.col("doc").alias("a"), F.col("component").alias("ca"))
        y = near.select("node", F.col("doc").alias("b"), F.col("component").alias("cb"), (F.col("component") == F.col("main")).alias("of_main"))
        pairs = x.join(y, "node").where((F.col("ca") != F.col("cb")) & (F.col("of_main") | (F.col("a") < F.col("b")))).groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.count("*").alias("k"))
        large = left.where(~few)
        last = large.isEmpty()
        if depth == 0 and trees >= enough:
            # A pair at the threshold shares two of the first nodes; one of them may be a large one, which isn't counted here.
            pairs = pairs.where("k > 1") if last else pairs.where("k > 1").union(pairs.where("k = 1").join(large.select(F.col("doc").alias("a")).distinct(), "a", "left_semi").select("a", "b", "k"))
        edges = edges.union(confirmed(cut(_estimated(pairs, sketches, similarity).select("a", "b")), docs, percent))
        if last:
            break
        peers = large.groupBy("node").agg(F.min_by("doc", F.xxhash64("node", "doc")).alias("peer"))
        alike = _alike(salted_join(large, peers, "node", "doc", hot).select("node", "doc", "peer"), sketches)
        judged = cut(salted_join(large, alike.join(peers, "node"), "node", "doc", hot).select("node", "doc", "component", "peer", (F.col("alike") >= dense).alias("dense")))
        cloud = judged.where("dense")
        if not cloud.isEmpty():
            group = components(cloud.select(F.col("doc").alias("a"), F.col("peer").alias("b"))).withColumnRenamed("id", "doc").withColumnRenamed("component", "cluster")
            whole = group.join(cloud.select("doc", "component").distinct(), "doc").select("cluster", "doc", "component")
            main = whole.groupBy("cluster", "component").agg(F.count("*").alias("k")).groupBy("cluster").agg(F.max(F.struct("k", "component")).alias("main"), F.sum("k").alias("n"))
            main = cut(main.select("cluster", "n", F.col("main.component").alias("main")))
            whole = cut(salted_join(whole, main.drop("n"), "cluster", "doc", hot_keys(main, "cluster", "n")).select("cluster", "doc", "component", (F.col("component") != F.col("main")).alias("odd")))
            edges = edges.union(_exhaust(whole, sketches, docs, percent))
        edges = cut(edges)
        sparse = judged.where(~F.col("dense"))
        if sparse.isEmpty():
            break
        stages.append(roots_for(similarity, trees, stages))
        members = _walk(sparse.select("node", "doc").join(sketches.select("doc", "sketch"), "doc"), similarity, NEXT_LEVELS, roots=stages[-1])
    else:
        raise RuntimeError(f"nodes are still too large {SKETCH} stages down")
    part = components(edges)
    of_rep = reps.select("digest", "n_shingles", "doc").join(part.withColumnRenamed("id", "doc"), "doc", "left").select("digest", F.coalesce("component", "doc").alias("component_id"))
    out = signed.select("doc_id", "n_shingles", "digest").join(of_rep, "digest", "left")
    component = F.when(F.col("doc_id").isNull(), F.lit(None)).otherwise(F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join_components(table(spark, sf_dir, "documents", "doc_id", "text"))
