"""Sampled SentencePiece segmentations by forward filtering and backward sampling, and lossless decoding.

A text's piece lattice falls apart before every run of blanks, since no piece of the
vocabulary holds a blank behind another character. So lattices are built once for
each distinct stretch of a batch: the forward pass sums the weights of all paths to
each place, and every occurrence then draws its last piece, the one before it, and so
on, in proportion to those sums. The draws come from a hash of row key, stretch number
and step, so a row's segmentation depends on its key and text alone.

A piece's weight is (1 - score) ** -sharpness, a power law over the vocabulary's ranks.
Characters outside the vocabulary, and the blank mark itself where a text holds it
literally, are spelled as byte pieces; decoding gives back every text exactly.

Defined results: null and empty texts have no pieces and decode to the empty text.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from momentbuf.llm.common import CACHES, arrow_map, records, table, text_chunks
from momentbuf.llm.near_dup import _power, mix
from momentbuf.llm.tokens import vocabulary

MARK = "▁"
LONG = 64  # longer stretches take the rescaled pass, one by one
_SLOT_BITS = 18
_BLOCK = 1 << 16
_loaded: dict = CACHES.setdefault("pieces", {})


class Lattice:
    def __init__(self, path: str, sharpness: float = 1.0):
        import sentencepiece

        lib = sentencepiece.SentencePieceProcessor(model_file=path)
        n = lib.get_piece_size()
        self.text: list[str | None] = [None] * n
        self.bytes = np.full(256, -1, np.int32)
        self.byte_of = np.full(n, -1, np.int32)
        for i in range(n):
            p = lib.id_to_piece(i)
            if lib.is_byte(i):
                self.bytes[int(p[3:5], 16)] = i
                self.byte_of[i] = int(p[3:5], 16)
            elif not (lib.is_control(i) or lib.is_unknown(i) or lib.is_unused(i)):
                self.text[i] = p.replace(MARK, " ")
        self.ids = {p: i for i, p in enumerate(self.text) if p}
        self.most = max(map(len, self.ids))
        score = np.array([lib.get_score(i) for i in range(n)])
        weight = (1.0 - score) ** -sharpness
        usual = float(np.median(weight[[i for p, i in self.ids.items()]]))
        self.tilt = usual ** (-1 / 4)  # a factor a character leaves all proportions as they are and sums near one
        self.rare = usual  # of a character spelled as bytes
        every = np.array(list(self.ids.values()), np.int64)
        words = [self.text[i] for i in every]
        h = self._hashes("".join(words), np.array([len(w) for w in words]))
        # Open tables by the hash's slot; what collides goes to the next table.
        self.hash = np.zeros(n, np.uint64)
        self.hash[every] = h
        self.tables, left = [], every
        while len(left):
            slots = self._slot(self.hash[left])
            first = np.unique(slots, return_index=True)[1]
            table_ = np.full(1 << _SLOT_BITS, -1, np.int32)
            table_[slots[first]] = left[first]
            self.tables.append(table_)
            left = np.delete(left, first)
        self.plain = [chr(b) if 0 <= (b := int(self.byte_of[i])) < 128 else t for i, t in enumerate(self.text)]
        self.part_of_char = self.byte_of >= 128
        self.length = np.array([len(p) if p else 0 for p in self.text])
        self.weight = weight * self.tilt**self.length

    @staticmethod
    def _codes(text: str) -> np.ndarray:
        return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)

    @staticmethod
    def _slot(h: np.ndarray) -> np.ndarray:
        return (h * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)

    def _hashes(self, text: str, sizes: np.ndarray) -> np.ndarray:
        c = self._codes(text)
        up, down = _power(len(c) + 1)
        total = np.r_[np.uint64(0), ((c + np.uint64(1)) * up[: len(c)]).cumsum(dtype=np.uint64)]
        end = sizes.cumsum()
        start = end - sizes
        return (total[end] - total[start]) * down[start] + sizes.astype(np.uint64)

    def edges(self, text: str, inner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Weight and piece of the match of each length (column length - 1) that ends at each place of the joined stretches.

        inner: each place's number in its stretch, from 1. Piece -1: bytes; weight 0: no match.
        """
        c = self._codes(text)
        up, down = _power(len(c) + 1)
        total = np.r_[np.uint64(0), ((c + np.uint64(1)) * up[: len(c)]).cumsum(dtype=np.uint64)]
        weight, piece = np.zeros((len(c), self.most), np.float32), np.full((len(c), self.most), -1, np.int32)
        weight[:, 0] = self.rare * self.tilt
        for lo in range(0, len(c), _BLOCK):  # blocks of places that stay in the cache
            hi = min(lo + _BLOCK, len(c))
            own = inner[lo:hi]
            for n in range(1, self.most + 1):
                if n <= 8:
                    first = max(lo, n - 1)
                    if first >= hi:
                        break
                    h = (total[first + 1 : hi + 1] - total[first + 1 - n : hi + 1 - n]) * down[first + 1 - n : hi + 1 - n] + np.uint64(n)
                    at = None
                else:  # few stretches are this long
                    at = np.flatnonzero(own >= n) + lo if n == 9 else at[inner[at] >= n]
                    if not len(at):
                        break
                    h = (total[at + 1] - total[at + 1 - n]) * down[at + 1 - n] + np.uint64(n)
                slot = self._slot(h)
                for t in self.tables:
                    p = t[slot]
                    may = np.flatnonzero(p >= 0)
                    p = p[may]
                    hit = self.hash[p] == h[may]
                    p, e = p[hit], may[hit]
                    if at is not None:
                        e = at[e]
                    else:
                        e = e + first
                        if n > 1:
                            inside = inner[e] >= n
                            p, e = p[inside], e[inside]
                    weight[e, n - 1], piece[e, n - 1] = self.weight[p], p
        return weight, piece

    def sample(self, stretches: list[str], which: np.ndarray, seed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pieces of every occurrence `which` (numbers of distinct stretches), and how many each has; piece -1 - code: a character spelled as bytes."""
        sizes = np.array([len(s) for s in stretches], np.int64)
        text = "".join(stretches)
        begin = sizes.cumsum() - sizes
        inner = np.arange(len(text)) - np.repeat(begin, sizes) + 1
        weight, piece = self.edges(text, inner)
        # Forward: all stretches advance together, a place of each at a time.
        by_level = np.argsort(np.minimum(inner, 65535).astype(np.uint16), kind="stable") if not len(inner) or inner.max() < 65536 else np.argsort(inner, kind="stable")
        level = np.searchsorted(inner[by_level], np.arange(1, (int(inner.max()) if len(inner) else 0) + 2))
        sums = np.ones(len(text) + len(stretches))  # stretch j's start lies at begin[j] + j
        to = np.arange(1, len(text) + 1) + np.repeat(np.arange(len(stretches)), sizes)
        for p in range(len(level) - 1):
            place = by_level[level[p] : level[p + 1]]
            spot, reach = to[place], min(p + 1, self.most)
            part = weight[place, :reach] * sums[spot[:, None] - np.arange(1, reach + 1)]
            run = part.cumsum(axis=1)
            total = run[:, -1].copy()
            if p >= LONG:  # keep long stretches in range: what counts is the proportion within a place
                for i in np.flatnonzero((total > 1e100) | (total < 1e-100)).tolist():
                    sums[spot[i] - reach : spot[i]] /= total[i]
                    total[i] = 1.0
            sums[spot] = total
            weight[place, :reach] = run / run[:, -1:]
            weight[place, reach:] = 1.0
        # Backward: a place's row now holds the running shares of the lengths of its last piece.
        live = np.flatnonzero(sizes[which] > 0)
        at = (begin + sizes - 1)[which[live]]
        steps = []
        while len(live):
            u = (mix(seed[live] + np.uint64(len(steps) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) >> np.uint64(40)).astype(np.float32) * np.float32(2.0**-24)
            n = np.minimum((weight[at] <= u[:, None]).sum(axis=1, dtype=np.int64), np.minimum(inner[at], self.most) - 1)
            p = piece[at, n]
            steps.append((live, np.where(p >= 0, p, -1 - at)))
            go = np.flatnonzero(n + 1 < inner[at])
            live, at = live[go], at[go] - n[go] - 1
        count = np.zeros(len(which), np.int64)
        for live, _ in steps:
            count[live] += 1
        stop = count.cumsum()
        out = np.empty(int(stop[-1]) if len(stop) else 0, np.int64)
        for k, (live, p) in enumerate(steps):
            out[stop[live] - 1 - k] = p
        odd = np.flatnonzero(out < 0)
        if len(odd):
            code = self._codes(text)[-1 - out[odd]].astype(np.int64)
            out[odd] = np.where(code < 128, self.bytes[np.minimum(code, 127)], -1 - code)
        return out, count

    def encode(self, keys: list, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of each text, drawn from its key."""
        known: dict[str, int] = {}
        which, counts = [], []
        for t in texts:
            segs = _stretches(t or "")
            which += [known.setdefault(s, len(known)) for s in segs]
            counts.append(len(segs))
        n = np.array(counts)
        seed = mix(np.array([zlib.crc32(repr(k).encode()) | (zlib.crc32(repr(k).encode(), 77) << 32) for k in keys], np.uint64))
        number = np.arange(len(which)) - np.repeat(n.cumsum() - n, n)
        seed = mix(np.repeat(seed, n) + number.astype(np.uint64) * np.uint64(0xD1342543DE82EF95))
        pieces, count = self.sample(list(known), np.array(which, np.int64), seed)
        per = np.r_[0, count.cumsum()][np.r_[0, n.cumsum()]]
        return [self._spelled(pieces[i:j]) for i, j in zip(per[:-1].tolist(), per[1:].tolist(), strict=True)]

    def _spelled(self, ids: np.ndarray) -> np.ndarray:
        if not len(ids) or ids.min() >= 0:
            return ids.astype(np.uint32)
        out: list[int] = []
        for i in ids.tolist():
            out += [i] if i >= 0 else self.bytes[list(chr(-1 - i).encode("utf-8", "surrogatepass"))].tolist()
        return np.array(out, np.uint32)

    def decode(self, ids: np.ndarray) -> str:
        """The text whose pieces these are, without the blank that encoding puts in front."""
        if not len(ids):
            return ""
        if not self.part_of_char[ids].any():
            return "".join(map(self.plain.__getitem__, ids.tolist()))[1:]
        return b"".join(bytes([self.byte_of[i]]) if self.byte_of[i] >= 0 else self.text[i].encode("utf-8", "surrogatepass") for i in ids.tolist()).decode("utf-8", "surrogatepass")[1:]


def _stretches(text: str) -> list[str]:
    """Runs of blanks with what follows them, one blank put in front of the text; nothing for an empty text."""
    if not text:
        return []
    words = text.split(" ")
    if "" not in words:
        return [" " + w for w in words]
    out, blanks = [], ""
    for w in words:
        blanks += " "
        if w:
            out.append(blanks + w)
            blanks = ""
    return [*out, blanks] if blanks else out


def lattice(path: str, sharpness: float) -> Lattice:
    key = (path, sharpness)
    if key not in _loaded:
        _loaded[key] = Lattice(path, sharpness)
    return _loaded[key]


_OUT = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))])
_DIGEST = pa.schema([("doc_id", pa.int64()), ("n_pieces", pa.int64()), ("ids_crc32", pa.int64()), ("lossless", pa.bool_())])


def _encoded(batches: Iterator[pa.RecordBatch], path: str, sharpness: float) -> Iterator[tuple[list, list, list[np.ndarray], Lattice]]:
    model = lattice(path, sharpness)
    for b in batches:
        ids, texts = b.column("doc_id").to_pylist(), b.column("text").to_pylist()
        for i, j in text_chunks(texts, 4_000_000):
            yield ids[i:j], texts[i:j], model.encode(ids[i:j], texts[i:j]), model


def encode(docs: DataFrame, path: str, sharpness: float = 1.0) -> DataFrame:
    """doc_id and ids of a sampled segmentation of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for d, _, ids, _ in _encoded(batches, path, sharpness):
            yield records(_OUT, doc_id=d, ids=[x.astype(np.int32) for x in ids])

    return arrow_map(docs.select("doc_id", "text"), run, "doc_id long, ids array<int>", uses="pieces")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and text of every row of ids."""
    out = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = lattice(path, 1.0)
        for b in batches:
            yield records(out, doc_id=b.column("doc_id"), text=[model.decode(np.array(x or [], np.int64)) for x in b.column("ids").to_pylist()])

    return arrow_map(encoded.select("doc_id", "ids"), run, "doc_id long, text string", uses="pieces")


def op3_sampled_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of the sampled ids of every document, and whether decoding them gave the text back."""
    path = vocabulary("piece_bpe_32k.model")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for d, texts, ids, model in _encoded(batches, path, 1.0):
            yield records(_DIGEST, doc_id=d, n_pieces=[len(x) for x in ids], ids_crc32=[zlib.crc32(x.astype("<u4").tobytes()) for x in ids], lossless=[model.decode(x) == (t or "") for x, t in zip(ids, texts, strict=True)])

    return arrow_map(table(spark, sf_dir, "documents", "doc_id", "text"), run, "doc_id long, n_pieces long, ids_crc32 long, lossless boolean", uses="pieces")
