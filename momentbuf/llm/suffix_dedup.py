"""Removal of repeated byte strings by merged shard Burrows-Wheeler transforms.

Every byte covered by a string of `width` bytes that also starts earlier goes.

Sorting all suffixes of a corpus isn't needed to find those strings. Each window of
`width` bytes holds a smallest-hash stretch (its anchor), picked by content alone, so
equal windows have equal anchors:

1. a map finds the anchors of every text with the region their windows span;
2. regions with equal anchors meet; equal regions collapse to the earliest, the
   others' windows are repeats. A window reaches half its remaining bytes to one side of
   its anchor at least, so only regions that share an anchor so extended go on;
3. the bytes of those regions are dealt out by anchor. Each task cuts its strings into
   shards, builds every shard's transform, and merges the transforms by iterative
   interleave refinement: each round orders the merged suffixes by one more byte
   through the transforms alone, and a block boundary that appears in round h marks a
   common prefix of h. Blocks left after `width` rounds are the repeated
   intervals; all but the earliest start of a block are repeats;
4. the ranges of a document are joined to its text and cut out.

Defined results: a null text is empty; texts shorter than `width` lose nothing;
rows that repeat a doc_id are ordered by a hash of their text, identical
rows are one document (both keep what it keeps); a null doc_id comes first.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, records, table, text_chunks
from momentbuf.llm.near_dup import _BASE, _power, mix

WIDTH = 100
ANCHOR = 24
SEGMENT = 1 << 18
_PLACE = 24  # bits for a place in a segment; the others are the hash
_ANCHORS = [("v", "<u8"), ("h", "<u8"), ("right", "<u4"), ("left", "<u4"), ("doc", "<i8"), ("ord", "<i4"), ("lo", "<i8"), ("off", "u1"), ("span", "u1")]
_ASKED = np.dtype([("v", "<u8"), ("lo", "<i8"), ("span", "<i4")])
_NULL_ID = -(1 << 63)


def _squeeze(cols: dict[str, np.ndarray]) -> bytes:
    """Columns by byte planes, so that leading zeros cost nothing."""
    n = len(next(iter(cols.values())))
    return zstandard.compress(b"".join(np.ascontiguousarray(cols[k].astype(t).view("u1").reshape(n, -1).T).tobytes() for k, t in _ANCHORS), 1)


def _unsqueeze(blob: bytes) -> dict[str, np.ndarray]:
    raw, out, at = zstandard.decompress(blob), {}, 0
    n = len(raw) // sum(np.dtype(t).itemsize for _, t in _ANCHORS)
    for k, t in _ANCHORS:
        size = np.dtype(t).itemsize
        out[k] = np.ascontiguousarray(np.frombuffer(raw, "u1", size * n, at).reshape(size, n).T).view(t).ravel()
        at += size * n
    return out


def _sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w neighbours; len(x) - w + 1 of them."""
    have, cur = 1, x
    while have * 2 <= w:
        cur = np.minimum(cur[:-have], cur[have:])
        have *= 2
    return np.minimum(cur[: len(x) - w + 1], cur[w - have :]) if have < w else cur


def anchors(raws: list[bytes], width: int = WIDTH, k: int = ANCHOR) -> dict[str, np.ndarray]:
    """Anchors of texts: row, lo (first window), off (anchor - lo), span (last window - lo), v (anchor's hash), h (hash of the region and its shape).

    right, left: short hashes of the anchor with half a window's other bytes behind or before it; 0 where the region is too short.
    """
    found: list[tuple] = []
    pieces, held = [], 0

    def flush() -> None:
        nonlocal pieces, held
        if not pieces:
            return
        c = np.frombuffer(b"".join(p for _, _, p in pieces), np.uint8)
        sizes = np.array([len(p) for _, _, p in pieces])
        start = np.r_[0, sizes.cumsum()[:-1]]
        up, down = _power(len(c) + 1)
        total = np.r_[np.uint64(0), ((c.astype(np.uint64) + np.uint64(1)) * up[: len(c)]).cumsum(dtype=np.uint64)]
        hashed = mix((total[k:] - total[:-k]) * down[: len(c) - k + 1])
        key = (hashed >> np.uint64(_PLACE) << np.uint64(_PLACE)) | np.arange(len(hashed), dtype=np.uint64)
        best = (_sliding_min(key, width - k + 1) & np.uint64((1 << _PLACE) - 1)).astype(np.int64)
        fits = np.zeros(len(c) + 1, np.int8)  # windows that lie in one piece
        np.add.at(fits, start, 1)
        np.add.at(fits, start + sizes - width + 1, -1)
        s = np.flatnonzero(fits[: len(best)].cumsum(dtype=np.int64) > 0)
        at = best[s]
        head = np.flatnonzero(np.r_[True, (at[1:] != at[:-1]) | (s[1:] != s[:-1] + 1) | np.isin(s[1:], start)])
        lo, hi, at = s[head], s[np.r_[head[1:], len(s)] - 1], at[head]
        end = hi + width
        region = mix((total[end] - total[lo]) * down[lo])
        h = mix(region + mix(((at - lo) * 1024 + (hi - lo)).astype(np.uint64)))
        half = (width - k + 1) // 2

        def short(a: np.ndarray, e: np.ndarray, fits: np.ndarray) -> np.ndarray:
            a, e = np.where(fits, a, 0), np.where(fits, e, 0)
            return np.where(fits, (mix((total[e] - total[a]) * down[a]) >> np.uint64(32)) | np.uint64(1), np.uint64(0)).astype(np.uint32)

        right, left = short(at, at + k + half, at + k + half <= end), short(at - half, at + k, at - half >= lo)
        piece = np.searchsorted(start, lo, "right") - 1
        row, base = (np.array([p[i] for p in pieces])[piece] for i in (0, 1))
        found.append((row, lo - start[piece] + base, at - lo, hi - lo, hashed[at], h, right, left))
        pieces, held = [], 0

    for i, raw in enumerate(raws):
        for at in range(0, max(0, len(raw) - width + 1), SEGMENT):
            part = raw[at : at + SEGMENT + width - 1]
            if held + len(part) > 2 * SEGMENT:
                flush()
            pieces.append((i, at, part))
            held += len(part)
    flush()
    names = ("row", "lo", "off", "span", "v", "h", "right", "left")
    return dict(zip(names, (np.concatenate(x) for x in zip(*found, strict=True)), strict=True)) if found else {n: np.zeros(0, np.uint64 if n in ("v", "h", "right", "left") else np.int64) for n in names}


def shard_transform(t: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Suffix array, transform and LF mapping of strings that each end in symbol 0; ends are told apart by their place.

    Prefix doubling from seven symbols; each round sorts only what is still tied.
    """
    n = len(t)
    ends = np.flatnonzero(t == 0)
    padded = np.r_[t, np.zeros(7, t.dtype)].astype(np.int64)
    key, open_ = np.zeros(n, np.int64), np.ones(n, bool)
    for i in range(7):  # nine bits a symbol; what lies behind an end isn't looked at
        key = key * 512 + np.where(open_, padded[i : i + n], 0)
        open_ &= padded[i : i + n] != 0
    key[ends] = np.arange(len(ends)) - len(ends)
    sa = np.argsort(key, kind="stable")
    k = key[sa]
    group = np.maximum.accumulate(np.where(np.r_[True, k[1:] != k[:-1]], np.arange(n), 0))
    rank = np.empty(n + 1, np.int64)
    rank[sa], rank[n] = group, -1
    have = 7
    tied = np.flatnonzero(np.r_[group[1:] == group[:-1], False] | np.r_[False, group[1:] == group[:-1]])
    while len(tied):
        rows = sa[tied]
        both = group[tied] * (n + 1) + rank[np.minimum(rows + have, n)] + 1
        o = np.argsort(both, kind="stable")
        both, rows = both[o], rows[o]
        sa[tied] = rows
        new = np.maximum.accumulate(np.where(np.r_[True, both[1:] != both[:-1]], tied, 0))
        group[tied] = new
        rank[rows] = new
        keep = np.r_[new[1:] == new[:-1], False] | np.r_[False, new[1:] == new[:-1]]
        tied = tied[keep]
        have *= 2
    bwt = np.where(np.r_[True, t[:-1] == 0], 0, np.r_[t[:1], t[:-1]])[sa].astype(np.uint16)
    lf = np.empty(n, np.int64)
    lf[np.argsort(bwt, kind="stable")] = np.arange(n)
    return sa, bwt, lf


def merged_intervals(shards: list[np.ndarray], depth: int) -> list[np.ndarray]:
    """For each shard (strings that end in symbol 0) the repeated interval of each suffix, -1 where its first `depth` symbols occur once.

    The interleave of all shards' rows is refined through their transforms alone: a round
    takes every row to the one of its preceding symbol and orders them by that symbol,
    stably; no suffixes are compared or sorted again. A block is a run of rows whose
    first h symbols agree, so the round that parts two neighbours gives their common
    prefix. Rows alone in their block can't come to share a longer prefix and drop out.
    """
    built = [shard_transform(t) for t in shards]
    base = np.cumsum([0, *(len(t) for t in shards)])
    symbols = np.concatenate([b for _, b, _ in built])
    used = np.flatnonzero(np.bincount(symbols, minlength=1))
    if len(used) <= 256:  # one byte a symbol, in the same order
        narrow = np.zeros(int(used[-1]) + 1, np.uint8)
        narrow[used] = np.arange(len(used)) + (used[0] > 0)
        symbols = narrow[symbols]
    small = np.int32 if base[-1] < 1 << 31 else np.int64
    lf = np.concatenate([m + o for (_, _, m), o in zip(built, base, strict=False)]).astype(small)
    row, block = np.arange(base[-1], dtype=small), np.zeros(base[-1], small)
    for _ in range(depth):
        s = symbols[row]
        order = np.argsort(s, kind="stable")[len(s) - np.count_nonzero(s) :]
        m, b, row = s[order], block[order], lf[row[order]]
        edge = np.ones(len(row) + 1, bool)
        np.not_equal(m[1:], m[:-1], out=edge[1:-1])
        edge[1:-1] |= b[1:] != b[:-1]
        several = ~(edge[:-1] & edge[1:])
        block = edge[:-1].cumsum(dtype=small)[several]
        row = row[several]
    out = np.full(base[-1], -1, np.int64)
    sa = np.concatenate([x + o for (x, _, _), o in zip(built, base, strict=False)])
    out[sa[row]] = block
    return [out[i:j] for i, j in zip(base[:-1], base[1:], strict=True)]


def repeated_windows(regions: list[bytes], order: np.ndarray, width: int = WIDTH, shards: int = 4) -> list[np.ndarray]:
    """For each region the starts of windows that an earlier one repeats. `order`: (n, 3) doc, ord, lo of the regions."""
    sizes = np.array([len(r) for r in regions])
    per = -(-len(regions) // min(shards, len(regions)))
    groups = [range(i, min(i + per, len(regions))) for i in range(0, len(regions), per)]
    texts, at = [], []
    for g in groups:
        t = np.zeros(int(sizes[g.start : g.stop].sum()) + len(g), np.uint16)
        starts = np.r_[0, (sizes[g.start : g.stop] + 1).cumsum()[:-1]]
        for i, s in zip(g, starts.tolist(), strict=True):
            t[s : s + sizes[i]] = np.frombuffer(regions[i], np.uint8).astype(np.uint16) + 1
        texts.append(t)
        at.append(starts)
    blocks = merged_intervals(texts, width)
    count = sizes - width + 1
    who = np.repeat(np.arange(len(regions)), count)
    inner = np.arange(len(who)) - np.repeat(np.r_[0, count.cumsum()[:-1]], count)
    block = np.concatenate([b[np.repeat(s, count[g.start : g.stop]) + inner[(who >= g.start) & (who < g.stop)]] for b, s, g in zip(blocks, at, groups, strict=True)])
    place = order[who, 2] + inner
    hit = np.flatnonzero(block >= 0)
    by = hit[np.lexsort((place[hit], order[who[hit], 1], order[who[hit], 0], block[hit]))]
    again = np.zeros(len(who), bool)
    if len(by):
        first = np.r_[True, block[by][1:] != block[by][:-1]]
        head = by[np.flatnonzero(first)][np.cumsum(first) - 1]  # the earliest window of each one's interval
        again[by] = (order[who[by], 0] != order[who[head], 0]) | (order[who[by], 1] != order[who[head], 1]) | (place[by] != place[head])
    edge = count.cumsum()
    return [np.flatnonzero(again[e - c : e]) for c, e in zip(count.tolist(), edge.tolist(), strict=True)]


_DEALT = pa.schema([("bucket", pa.int32()), ("blob", pa.binary()), ("doc", pa.int64()), ("ord", pa.int32()), ("ranges", pa.binary())])
_DEALT_DDL = "bucket int, blob binary, doc long, ord int, ranges binary"
_DONE = pa.schema([("doc", pa.int64()), ("ord", pa.int32()), ("ranges", pa.binary()), ("asked", pa.binary())])
_DONE_DDL = "doc long, ord int, ranges binary, asked binary"


def _by_doc(doc: np.ndarray, ord_: np.ndarray, body: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
    """Rows of body for each document, as bytes."""
    if len(doc):
        o = np.lexsort((ord_, doc))
        doc, ord_, body = doc[o], ord_[o], body[o]
        cuts = np.flatnonzero(np.r_[True, (doc[1:] != doc[:-1]) | (ord_[1:] != ord_[:-1]), True])
        for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            yield int(doc[i]), int(ord_[i]), body[i:j].tobytes()


def _collapse(a: dict[str, np.ndarray], width: int) -> tuple[dict[str, np.ndarray], dict[str, np.ndarray]]:
    """Earliest of each class of equal regions, in order of v; and the others."""
    o = np.lexsort((a["lo"], a["ord"], a["doc"], a["h"], a["v"]))
    a = {k: x[o] for k, x in a.items()}
    first = np.r_[True, (a["h"][1:] != a["h"][:-1]) | (a["v"][1:] != a["v"][:-1])] if len(o) else np.zeros(0, bool)
    head = np.flatnonzero(first)[np.cumsum(first) - 1] if len(o) else np.zeros(0, np.int64)
    same = (a["doc"] == a["doc"][head]) & (a["ord"] == a["ord"][head]) & (a["lo"] == a["lo"][head])
    return {k: x[first] for k, x in a.items()}, {k: x[~same] for k, x in a.items()}


def _ranges(a: dict[str, np.ndarray], width: int) -> np.ndarray:
    return np.stack([a["lo"], a["lo"] + a["span"].astype(np.int64) + width], axis=1)


def _repeats(docs: DataFrame, width: int) -> DataFrame:
    """doc, ord and ranges (pairs of byte offsets) of all repeated windows; docs: doc, ord, text."""
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column("text").to_pylist()
            for i, j in text_chunks(texts, 8_000_000):
                part = b.slice(i, j - i)
                a = anchors([(t or "").encode("utf-8", "surrogatepass") for t in texts[i:j]], width)
                row = a.pop("row")
                a["doc"], a["ord"] = (part.column(c).to_numpy(zero_copy_only=False)[row] for c in ("doc", "ord"))
                keep, gone = _collapse(a, width)
                bucket = (keep["v"] % np.uint64(parts)).astype(np.int64)
                o = np.argsort(bucket, kind="stable")
                cuts = np.flatnonzero(np.r_[True, bucket[o][1:] != bucket[o][:-1], True]) if len(o) else np.zeros(1, np.int64)
                groups = [o[x:y] for x, y in zip(cuts[:-1], cuts[1:], strict=True)]
                rows = [(int(bucket[g[0]]), _squeeze({k: x[g] for k, x in keep.items()}), None, None, None) for g in groups]
                rows += [(hash((d, r)) % parts, None, d, r, x) for d, r, x in _by_doc(gone["doc"], gone["ord"], _ranges(gone, width))]
                if rows:
                    yield records(_DEALT, **dict(zip(_DEALT.names, zip(*rows, strict=True), strict=True)))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict[str, np.ndarray]] = []
        for b in batches:
            blobs = b.column("blob").to_pylist()
            held += [_unsqueeze(x) for x in blobs if x is not None]
            done = [i for i, x in enumerate(blobs) if x is None]
            if done:
                t = b.take(pa.array(done))
                yield records(_DONE, doc=t.column("doc"), ord=t.column("ord"), ranges=t.column("ranges"), asked=pa.nulls(len(done), pa.binary()))
        if held:
            keep, gone = _collapse({k: np.concatenate([x[k] for x in held]) for k, _ in _ANCHORS}, width)
            held.clear()
            done_rows = [(d, r, x, None) for d, r, x in _by_doc(gone["doc"], gone["ord"], _ranges(gone, width))]
            # Windows that reach far behind their anchor go by the longer right key, the others by the left one.
            turn = width - ANCHOR - (width - ANCHOR + 1) // 2
            at = keep["lo"] + keep["off"]
            asked = []
            for side, lo, hi in (("right", np.maximum(keep["lo"], at - turn), keep["lo"] + keep["span"]), ("left", keep["lo"], np.minimum(keep["lo"] + keep["span"], at - turn - 1))):
                key = keep["v"] ^ mix(keep[side].astype(np.uint64))
                _, which, n = np.unique(key, return_inverse=True, return_counts=True)
                some = (keep[side] > 0) & (n[which] > 1) & (lo <= hi)
                rows = np.empty(int(some.sum()), _ASKED)
                rows["v"], rows["lo"], rows["span"] = key[some], lo[some], (hi - lo)[some]
                asked += [(d, r, None, x) for d, r, x in _by_doc(keep["doc"][some], keep["ord"][some], rows)]
            for rows in (done_rows, asked):
                if rows:
                    yield records(_DONE, **dict(zip(_DONE.names, zip(*rows, strict=True), strict=True)))

    met = cut(arrow_map(arrow_map(docs, find, _DEALT_DDL).repartition(parts, "bucket"), meet, _DONE_DDL))

    regions = pa.schema([("bucket", pa.int32()), ("v", pa.int64()), ("doc", pa.int64()), ("ord", pa.int32()), ("lo", pa.int64()), ("region", pa.binary())])

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for d, r, t, asked in zip(*(b.column(c).to_pylist() for c in ("doc", "ord", "text", "asked")), strict=True):
                raw = t.encode("utf-8", "surrogatepass")
                a = np.frombuffer(b"".join(asked), _ASKED)
                lo, end = a["lo"], a["lo"] + a["span"] + width
                yield records(regions, bucket=(a["v"] % np.uint64(parts)).astype(np.int32), v=a["v"].view(np.int64), doc=np.full(len(a), d), ord=np.full(len(a), r, np.int32), lo=lo, region=[raw[i:j] for i, j in zip(lo.tolist(), end.tolist(), strict=True)])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def out() -> Iterator[pa.RecordBatch]:
            order = np.array([x[1:4] for x in held], np.int64).reshape(-1, 3)
            starts = repeated_windows([x[4] for x in held], order, width)
            rows = []
            for (_, d, r, lo, _), s in zip(held, starts, strict=True):
                if len(s):
                    head = np.r_[True, s[1:] != s[:-1] + 1]
                    last = s[np.r_[np.flatnonzero(head)[1:], len(s)] - 1]
                    rows.append((d, r, (np.stack([s[head], last + width], axis=1) + lo).tobytes(), None))
            if rows:
                yield records(_DONE, **dict(zip(_DONE.names, zip(*rows, strict=True), strict=True)))

        size = 0
        for b in batches:  # sorted by anchor: a group of regions is whole when the anchor changes
            for x in zip(*(b.column(c).to_pylist() for c in ("v", "doc", "ord", "lo", "region")), strict=True):
                if size >= 1 << 18 and x[0] != held[-1][0]:
                    yield from out()
                    held.clear()
                    size = 0
                held.append(x)
                size += len(x[4])
        if held:
            yield from out()

    asked = met.where("asked is not null").groupBy("doc", "ord").agg(F.collect_list("asked").alias("asked"))
    wanted = arrow_map(docs.join(asked, ["doc", "ord"]).select("doc", "ord", "text", "asked"), fetch, "bucket int, v long, doc long, ord int, lo long, region binary")
    merged = cut(arrow_map(wanted.repartition(parts, "bucket").sortWithinPartitions("v").select("v", "doc", "ord", "lo", "region"), merge, _DONE_DDL))
    return met.where("ranges is not null").select("doc", "ord", "ranges").union(merged.select("doc", "ord", "ranges"))


def _numbered(docs: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """doc, ord, doc_id, text: ord tells rows apart that repeat a doc_id."""
    base = docs.select(F.coalesce("doc_id", F.lit(_NULL_ID)).alias("doc"), "doc_id", "text", *extra)
    twice = cut(base.groupBy("doc").agg(F.count("*").alias("n")).where("n > 1").select("doc"))
    if twice.isEmpty():
        return base.withColumn("ord", F.lit(0))
    from pyspark.sql import Window

    tag = F.xxhash64(F.coalesce("text", F.lit("")))
    rows = base.select("doc", tag.alias("tag")).join(twice, "doc").distinct().withColumn("ord", F.row_number().over(Window.partitionBy("doc").orderBy("tag")) - 1)
    return base.withColumn("tag", tag).join(rows, ["doc", "tag"], "left").withColumn("ord", F.coalesce("ord", F.lit(0))).drop("tag")


def covered(ranges: list[bytes] | None, n: int) -> np.ndarray:
    """Maximal removed runs (start, end) of a text of n bytes."""
    r = np.frombuffer(b"".join(ranges or []), np.int64).reshape(-1, 2)
    if not len(r):
        return r
    mark = np.zeros(n + 1, np.int32)
    np.add.at(mark, r[:, 0], 1)
    np.add.at(mark, r[:, 1], -1)
    on = np.r_[False, mark[:-1].cumsum() > 0, False]
    edge = np.flatnonzero(on[1:] != on[:-1])
    return np.stack([edge[::2], edge[1::2]], axis=1)


def kept_bytes(raw: bytes, runs: np.ndarray) -> bytes:
    at, out = 0, []
    for i, j in runs.tolist():
        out.append(raw[at:i])
        at = j
    return b"".join([*out, raw[at:]])


def with_ranges(docs: DataFrame, width: int = WIDTH, extra: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, text, extra columns and ranges (arrays of packed byte-offset pairs) of every row."""
    one = _numbered(docs, extra)
    ranges = _repeats(one.select("doc", "ord", "text"), width).groupBy("doc", "ord").agg(F.collect_list("ranges").alias("ranges"))
    return one.join(ranges, ["doc", "ord"], "left").select("doc_id", "text", *extra, "ranges")


_DIGEST = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for d, t, r in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "ranges")), strict=True):
            raw = (t or "").encode("utf-8", "surrogatepass")
            runs = covered(r, len(raw))
            rows.append((d, len(raw), int((runs[:, 1] - runs[:, 0]).sum()), len(runs), hashlib.sha256(kept_bytes(raw, runs)).hexdigest()))
        if rows:
            yield records(_DIGEST, **dict(zip(_DIGEST.names, zip(*rows, strict=True), strict=True)))


def op2_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return arrow_map(with_ranges(table(spark, sf_dir, "documents", "doc_id", "text")), _digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
