"""Operators against plain versions: nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns."""

import io
import math
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from momentbuf.llm import common, embeddings, html, near_dup, packing, pieces, secrets, sstable, suffix_dedup, tokens, topk, toxicity
from momentbuf.llm.common import arrow_map, components, cut, shared_dir
from tests.llm import brute
from tests.llm.conftest import corpus, frame


# --- components


def test_components_by_rounds_and_in_one_partition(spark, monkeypatch):
    r = random.Random(1)
    e = [(r.randrange(300), r.randrange(300)) for _ in range(170)] + [(500 + i, 501 + i) for i in range(40)]
    parent = {}
    for a, b in e:
        for x in (a, b):
            parent.setdefault(x, x)
        p, q = brute.find(parent, a), brute.find(parent, b)
        parent[max(p, q)] = min(p, q)
    want = {x: brute.find(parent, x) for a, b in e for x in (a, b) if a != b}
    df = spark.createDataFrame(e, "a long, b long")
    for most in (1_000_000, 50):
        monkeypatch.setattr("momentbuf.llm.common.FOREST", most)
        got = {x["id"]: x["component"] for x in components(df).collect()}
        assert got == want


# --- 1 embeddings


def vectors(n=400, dim=16, seed=5):
    r = np.random.default_rng(seed)
    base = r.normal(size=(12, dim))
    out = []
    for i in range(n):
        v = base[i % 12] + r.normal(size=dim) * (0.12 if i % 3 else 1.0)
        out.append((i, [float(x) for x in np.float32(v)]))
    out += [(n, out[0][1]), (n + 1, out[0][1]), (n + 2, None), (n + 3, [0.0] * dim), (n + 4, [float("nan")] + [1.0] * (dim - 1)), (n + 5, [float("inf")] + [1.0] * (dim - 1)), (n + 6, [None] + [1.0] * (dim - 1))]
    return out


def test_links(spark):
    rows = vectors()
    df = spark.createDataFrame([(i, v, 1, 2, 3) for i, v in rows], "vec_id long, embedding array<float>, links long, x int, component int")
    got = {x["vec_id"]: (x["n_links"], x["component_id"], x["kept"]) for x in embeddings.link(df).collect()}
    want = brute.links(rows)
    assert len(got) == len(rows)
    found, there = sum(v[0] for v in got.values()), sum(v[0] for v in want.values())
    assert there > 500 and 0.98 * there <= found <= there
    if found == there:
        assert got == {i: (n, c, c == i) for i, (n, c) in want.items()}


def test_links_crowded_cell_is_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(embeddings, "BLOCK", 16)
    rows = [(i, [float(x) for x in np.float32(np.r_[1.0, np.random.default_rng(i).normal(size=7) * 0.08])]) for i in range(150)]
    got = {x["vec_id"]: (x["n_links"], x["component_id"]) for x in embeddings.link(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()}
    want = brute.links(rows)
    assert sum(v[0] for v in got.values()) >= 0.98 * sum(v[0] for v in want.values())
    assert {i: c for i, (_, c) in got.items()} == {i: c for i, (_, c) in want.items()}


def test_links_of_nothing(spark):
    empty = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert embeddings.link(empty).count() == 0
    one = spark.createDataFrame([(3, None), (None, [1.0])], "vec_id long, embedding array<float>")
    assert {tuple(x) for x in embeddings.link(one).collect()} == {(3, 0, 3, True), (None, 0, None, True)}


def test_multi_sequence_goes_in_order():
    r = np.random.default_rng(0)
    a, b = r.random(6), r.random(5)
    got = list(embeddings.multi_sequence(a, b))
    assert len(got) == 30 and [s for s, _, _ in got] == sorted(s for s, _, _ in got)
    many = r.random((40, 6)), r.random((40, 5))
    for radius in (0.3, 0.8, 9.0):
        row, cell = embeddings.traverse(*many, radius)
        for x in range(40):
            want = [(i, j) for s, i, j in embeddings.multi_sequence(many[0][x], many[1][x]) if s <= radius]
            assert [(c // 5, c % 5) for c in cell[row == x].tolist()] == want


def test_links_of_equal_ids_and_recall(spark):
    r = np.random.default_rng(3)
    base = r.normal(size=(300, 64))
    turned = base + 0.31 * np.linalg.norm(base, axis=1)[:, None] * (lambda n: n / np.linalg.norm(n, axis=1)[:, None])(r.normal(size=base.shape))
    rows = [(i, [float(x) for x in np.float32(v)]) for i, v in enumerate(np.r_[base, turned])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {x["vec_id"]: x["n_links"] for x in embeddings.link(df).collect()}
    want = brute.links(rows)
    there = sum(v[0] for v in want.values())
    assert there > 200 and 0.99 * there <= sum(got.values()) <= there
    again = spark.createDataFrame([(7, rows[0][1]), (7, rows[1][1]), (8, rows[0][1])], "vec_id long, embedding array<float>")
    out = [(x["vec_id"], x["component_id"]) for x in embeddings.link(again).collect()]
    assert sorted(out) == [(7, 7), (7, 7), (8, 7)]


# --- 2 repeated strings


def test_repeated_strings(spark, rows):
    got = {x["doc_id"]: (x["n_bytes"], x["n_removed"], x["n_spans"], x["kept_sha256"]) for x in arrow_map(suffix_dedup.with_ranges(frame(spark, rows)), suffix_dedup._digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string").collect()}
    want = brute.repeated(rows)
    assert got == {i: v[:4] for i, v in want.items()}
    assert sum(v[1] for v in got.values()) > 1000


def test_repeated_rows_and_ids(spark):
    t = "abcdefghij" * 5 + "".join(chr(97 + i * 7 % 26) for i in range(90))
    rows = [(1, t), (1, t), (2, "x" + t), (3, "short"), (None, None)]
    got = [(x["doc_id"], x["n_removed"]) for x in arrow_map(suffix_dedup.with_ranges(frame(spark, rows)), suffix_dedup._digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string").collect()]
    assert sorted(got, key=str) == sorted([(1, 0), (1, 0), (2, len(t)), (3, 0), (None, 0)], key=str)
    assert suffix_dedup.with_ranges(frame(spark, rows).where("false")).count() == 0


def test_segments_of_long_texts(monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SEGMENT", 64)
    r = random.Random(4)
    raw = bytes(r.randrange(97, 101) for _ in range(400))
    for cut_at in (64, 1000):
        monkeypatch.setattr(suffix_dedup, "SEGMENT", cut_at)
        a = suffix_dedup.anchors([raw, b"", raw[:50]], 30, 8)
        windows = [w for lo, s in zip(a["lo"].tolist(), a["span"].tolist()) for w in range(lo, lo + s + 1)]
        assert windows == list(range(400 - 30 + 1)) + list(range(21))
        for lo, off, v in zip(a["lo"].tolist(), a["off"].tolist(), a["v"].tolist()):
            assert off >= 0


def test_merged_transforms_give_repeated_intervals():
    r = random.Random(2)
    texts = [bytes(r.choice(b"ab") for _ in range(r.randrange(12, 40))) for _ in range(30)]
    shards = [np.concatenate([np.r_[np.frombuffer(t, np.uint8).astype(np.uint16) + 1, np.uint16(0)] for t in texts[i::3]]) for i in range(3)]
    blocks = suffix_dedup.merged_intervals(shards, 9)
    names, seen = {}, {}
    for part, t in zip(blocks, shards):
        for i in range(len(t)):
            w = tuple(t[i : i + 9].tolist())
            if len(w) == 9 and 0 not in w:
                seen[w] = seen.get(w, 0) + 1
                assert names.setdefault(w, part[i]) == part[i]
    assert all((names[w] >= 0) == (n > 1) for w, n in seen.items())
    shared = [x for x in names.values() if x >= 0]
    assert len(set(shared)) == len(shared) > 50


# --- 3 pieces


def test_pieces_are_lossless_and_reproducible(spark, rows):
    path = tokens.vocabulary("piece_bpe_32k.model")
    df = frame(spark, [*rows, (900, "a▁b  c ⁇ <s> \u0000")])
    enc = cut(pieces.encode(df, path))
    back = {x["doc_id"]: x["text"] for x in pieces.decode(enc, path).collect()}
    assert back == {i: t or "" for i, t in [*rows, (900, "a▁b  c ⁇ <s> \u0000")]}
    again = {x["doc_id"]: x["ids"] for x in pieces.encode(df.repartition(7), path).collect()}
    assert again == {x["doc_id"]: x["ids"] for x in enc.collect()}
    assert pieces.encode(df.where("false"), path).count() == 0


def test_piece_frequencies_follow_the_lattice():
    m = pieces.lattice(tokens.vocabulary("piece_bpe_32k.model"), 0.5)

    def paths(s):
        return [((), 1.0)] if not s else [((m.ids[s[:n]], *p), m.weight[m.ids[s[:n]]] * q) for n in range(1, len(s) + 1) if s[:n] in m.ids for p, q in paths(s[n:])]

    want = dict(paths(" lower"))
    total = sum(want.values())
    got = {}
    for x in m.encode(list(range(20_000)), ["lower"] * 20_000):
        got[tuple(x.tolist())] = got.get(tuple(x.tolist()), 0) + 1
    assert set(got) <= set(want)
    assert all(abs(got.get(p, 0) / 20_000 - q / total) < 0.015 for p, q in want.items())


# --- 4 top k


def test_top_k(spark):
    r = np.random.default_rng(8)
    rows = [(i, [float(x) for x in np.float32(r.normal(size=8).round(1))]) for i in range(700)]
    extra = [(701, None), (702, [float("nan")] * 8), (703, [1.0])]
    df = spark.createDataFrame([(i, v, 0, 0) for i, v in rows + extra], "vec_id long, embedding array<float>, shard int, v int")
    want = brute.top_k(rows)
    for most in (4096, 100):
        topk.SHARD, keep = most, topk.SHARD
        try:
            got = {}
            for x in topk.search(topk.whole(df)).orderBy("query_id", "rank").collect():
                got.setdefault(x["query_id"], []).append((x["vec_id"], x["score"]))
        finally:
            topk.SHARD = keep
        assert got == {q: [(i, -s) for i, s in v] for q, v in want.items()}
    odd = [(0, [2.0, 1.0]), (0, [1.0, 3.0]), (20, [2.0, 1.0]), (20, [2.0, 1.0]), (3, [2.0, 1.0]), (4, None), (40, [float(1 << 20), 1.0]), (60, [float(1 << 23), 0.0])]
    num = [(i, i_d, np.floor(64 * np.array(v)).astype(int)) for i, (i_d, v) in enumerate(odd) if v is not None and max(v) < 1 << 22]
    want_odd = sorted((a_id, rank + 1, b_id, -s) for i, a_id, a in num if a_id % 20 == 0 for rank, (s, b_id) in enumerate(sorted((-int(a @ b), b_id) for j, b_id, b in num if j != i)[:20]))
    got_odd = sorted(tuple(x) for x in topk.search(topk.whole(spark.createDataFrame(odd, "vec_id long, embedding array<double>"))).collect())
    assert got_odd == want_odd
    topk.SHARD, topk.ASKED, keep = 16, 3, (topk.SHARD, topk.ASKED)
    try:  # a vector that most rows hold, boxes that close shards, and shards that answer in lots
        r2 = np.random.default_rng(4)
        many = [(i, [1.0] * 4 if i % 3 else [float(x) for x in (r2.normal(size=4) + 20 * (i % 2)).round(2)]) for i in range(300)]
        got_many = {}
        for x in topk.search(topk.whole(spark.createDataFrame(many, "vec_id long, embedding array<double>"))).orderBy("query_id", "rank").collect():
            got_many.setdefault(x["query_id"], []).append((x["vec_id"], -x["score"]))
        assert got_many == brute.top_k(many)
    finally:
        topk.SHARD, topk.ASKED = keep
    few = topk.search(topk.whole(df.where("vec_id < 4"))).collect()
    assert [x["rank"] for x in few] == [1, 2, 3]
    assert topk.search(topk.whole(df.where("false"))).count() == 0


# --- 5 toxicity


def test_toxicity(spark):
    r = random.Random(6)
    words = ["".join(r.choice("abcdeiostn") for _ in range(5)) for _ in range(400)]
    docs, labels = [], []
    for i in range(600):
        w = [r.choice(words) for _ in range(25)]
        bad = i % 3 == 0
        if bad:
            w[3] = r.choice(["vileword", "nastyish", "rottenly"])
        docs.append((i, " ".join(w)))
        labels.append((i, int(bad)))
    df = frame(spark, [*docs, (1000, None), (1001, "")])
    lab = spark.createDataFrame([*labels, (None, 1), (5, None)], "doc_id long, toxic int")
    model = toxicity.train(df, lab)
    got = {x["doc_id"]: x for x in toxicity.score(df, model).collect()}
    assert len(got) == 602 and all(0 <= x["score"] <= 1 for x in got.values())
    held = [i for i, _ in labels if zlib.crc32(str(i).encode()) % 3 == 1]
    assert all(got[i]["held_out"] for i in held) and not any(got[i]["held_out"] for i, _ in labels if i not in held)
    assert sum(got[i]["predicted"] == y for i, y in labels if i in held) >= 0.98 * len(held)
    assert toxicity.without_toxic(df, model).count() == sum(1 - x["predicted"] for x in got.values())
    assert toxicity.score(df, toxicity.train(df, lab.where("false"))).agg(F.max("score")).first()[0] == 0.0
    assert toxicity.score(df.where("false"), model).count() == 0


def test_counterfactuals_lower_the_weight_of_groups():
    r = random.Random(9)
    words = ["".join(r.choice("abcdeiostn") for _ in range(5)) for _ in range(200)]
    texts, y = [], []
    for i in range(400):
        w = {r.choice(words) for _ in range(12)}
        bad = i % 2
        if bad and r.random() < 0.6:
            w.add("vileword" if i % 4 == 1 else "nastyish")
        if r.random() < (0.7 if bad else 0.1):
            w.add("muslim")
        texts.append("\n".join(sorted(w)))
        y.append(bad)
    plain, fair = (toxicity.fit(texts, np.array(y), fairness=f, l1=1e-4) for f in (0.0, 5.0))
    move = lambda m: abs(sum(m.weights.get(x, 0.0) for x in toxicity.features_of({"muslim"})))
    assert move(fair) < 0.3 * move(plain)
    assert fair.score("my muslim friend reads") < toxicity.THRESHOLD


# --- 6 token tables


def test_token_tables(spark, rows):
    path = tokens.vocabulary("word_bpe_49k.json")
    enc = tokens.encoder(path, False)
    docs = [*rows, (5, "again five"), (None, "no id")]
    folder = f"{shared_dir(spark)}/t"
    manifest = cut(sstable.write_shards(frame(spark, docs), folder, path, partitions=3))
    got = [(x["doc_id"], x["start"], x["n_tokens"], x["ids_crc32"]) for x in sstable.read_shards(manifest).collect()]
    want, at = [], 0
    for i, ids in sorted(((i, [*enc.lib.encode(t or "", add_special_tokens=False).ids, 1]) for i, t in docs), key=lambda x: (x[0] is not None, x[0] or 0, np.array(x[1], "<u4").tobytes())):
        want.append((i, at, len(ids), brute.crc(ids)))
        at += len(ids)
    assert sorted(got, key=lambda x: x[1]) == want
    assert sstable.read_shards(cut(sstable.write_shards(frame(spark, docs).where("false"), folder, path))).count() == 0


def test_shard_lookup():
    sink = io.BytesIO()
    w = sstable.ShardWriter(sink, block_bytes=400)
    r = random.Random(3)
    data = {i: np.array([r.randrange(70_000 if i % 2 else 900) for _ in range(r.randrange(9))], "<u4").tobytes() for i in range(-500, 3000, 7)}
    for i in sorted(data):
        w.add(sstable.key_of(i), data[i])
    w.add(sstable.key_of(max(data)), b"")
    assert w.close()[0] == len(data) + 1
    s = sstable.ShardReader(sink, sink.tell())
    assert all(s.get(i)[0] == data[i] for i in data) and len(s.get(max(data))) == 2
    missing = [i for i in range(-600, 3100) if i not in data]
    assert all(s.get(i) == [] for i in missing)
    assert sum(s.may_have(sstable.key_of(i)) for i in missing) < 0.05 * len(missing)
    assert [sstable.id_of(k) for k, _ in s] == [*sorted(data), max(data)]
    with pytest.raises(ValueError):
        w2 = sstable.ShardWriter(io.BytesIO())
        w2.add(sstable.key_of(5), b"")
        w2.add(sstable.key_of(4), b"")


# --- 7 near duplicates


@pytest.mark.parametrize("percent", [85, 80])
def test_near_duplicates(spark, rows, percent):
    docs = [*rows, *[(2000 + i, t) for i, t in corpus(90, 11)]]
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"], x["kept"]) for x in near_dup.join_components(frame(spark, docs), percent).collect()}
    want = brute.near_duplicates(docs, percent)
    assert got == {i: (n, c, c == i) for i, (n, c) in want.items()}


def test_near_duplicate_cloud_and_passages(spark, monkeypatch):
    r = random.Random(12)
    words = ["".join(r.choice("abcdeiostn") for _ in range(6)) for _ in range(3000)]
    base = [r.choice(words) for _ in range(130)]
    passage = [r.choice(words) for _ in range(60)]
    docs = []
    for i in range(260):
        if i % 2:
            w = list(base)
            for _ in range(r.choice([1, 2, 3, 4])):
                w[r.randrange(len(w))] = r.choice(words)
        else:
            w = [r.choice(words) for _ in range(60)] + passage
        docs.append((i, " ".join(w)))
    got = {x["doc_id"]: x["component_id"] for x in near_dup.join_components(frame(spark, docs), 85, small=64, dense=0.5).collect()}
    assert got == {i: c for i, (_, c) in brute.near_duplicates(docs, 85).items()}


def test_near_duplicates_of_odd_rows(spark):
    docs = [(4, "a b c d e f"), (4, "a b c d e f"), (9, "A B C D E F"), (None, "a b c d e f"), (None, None), (11, "")]
    got = sorted(((x["doc_id"], x["n_shingles"], x["component_id"], x["kept"]) for x in near_dup.join_components(frame(spark, docs)).collect()), key=str)
    assert got == sorted([(4, 2, 4, True), (4, 2, 4, True), (9, 2, 4, False), (None, 2, None, True), (None, 0, None, True), (11, 0, 11, True)], key=str)
    assert near_dup.join_components(frame(spark, docs).where("false")).count() == 0


# --- 8 secrets


def test_secrets(spark):
    key, rare = "AKIA" + "B7" * 8, "0123456789abcdef" * 2
    texts = ["", None, f'api_key = "{rare}" and token: short', f"x{key}y {rare}", "PASSWORD:abcdefghijklm token=secret=abcdefghijklmnop", "ſecret=abcdefghijklmnop", f"ghp_{'a1B2' * 6}", "é" * 20 + f" secret: {rare}", f"copied {'feedface' * 3}"] + [f"copied {'feedface' * 3}"] * 5
    docs = list(enumerate(texts)) + [(2, texts[2])]
    got = secrets.digest(secrets.scan(frame(spark, docs))).collect()
    assert len(got) == len(docs)
    import hashlib

    for x in got:
        want = brute.base_secrets(dict(docs)[x["doc_id"]])
        assert (x["n_assign"], x["n_access"], x["n_hex"]) == tuple(sum(k == kind for k, _, _ in want) for kind in ("assign", "access", "hex"))
        line = ",".join(f"{k}:{s}:{e}" for k, s, e in want)
        assert x["base_sha256"] == hashlib.sha256(line.encode()).hexdigest()
        assert set(filter(None, line.split(","))) <= set(x["spans"].split(","))
    by = {x["doc_id"]: x for x in got}
    assert by[6]["spans"].startswith("vendor:0:") and by[8]["n_copied"] == 1 and by[8]["n_live"] == 0 and by[3]["n_live"] >= 1
    assert secrets.digest(secrets.scan(frame(spark, docs).where("false"))).count() == 0


# --- 9 packing


def test_packing(spark, rows):
    path = tokens.vocabulary("byte_bpe_50k.json")
    enc = tokens.encoder(path, True)
    docs = [*rows, (5, rows[5][1]), (None, "x")]
    for cap, block, salts in ((64, 1 << 16, None), (64, 40, 3)):
        out = packing.pack(cut(packing.tokenized(frame(spark, docs), path, capacity=cap)), cap, block, salts).collect()
        seqs, by = {}, {}
        for x in out:
            seqs.setdefault(x["sequence_id"], []).append((x["offset"], x["length"]))
            by.setdefault(x["doc_id"], []).append(x)
        for parts in seqs.values():
            at = 0
            for o, n in sorted(parts):
                assert o == at
                at += n
            assert at <= cap
        for i, t in rows:
            ids = [*enc.lib.encode(t or "", add_special_tokens=False).ids, 2]
            part = sorted(by[i], key=lambda x: x["piece"])[:: 2 if i == 5 else 1]
            assert sum(x["length"] for x in part) == len(ids)
            for x in part:
                assert x["ids_crc32"] == brute.crc(ids[x["start"] : x["start"] + x["length"]])
        total = sum(x["length"] for x in out)
        if block > 40:
            assert len(seqs) <= math.ceil(total / cap) * 1.05 + 1
    assert packing.pack(cut(packing.tokenized(frame(spark, docs).where("false"), path))).count() == 0


def test_sum_of_squares_is_tight():
    s = np.sort(np.random.default_rng(2).integers(1, 1024, 20_000))[::-1]
    bins, off, n = packing.sum_of_squares(s)
    fill = np.bincount(bins, s)
    assert fill.max() <= 1024 and n <= 1.005 * s.sum() / 1024 + 1
    levels = packing.plan(np.bincount(s, minlength=1025), block=4096)
    assert sum(int((x["taken"] * x["times"] * np.arange(1025)).sum()) for x in levels) == s.sum()
    assert sum(x["bins"] * x["times"] for x in levels) <= 1.02 * s.sum() / 1024


def test_cached_ids_are_the_librarys(rows):
    odd = ["a   b", "  a", "a  ", "a\t \tb", "x \n y", "it's  'll é ́b <|endoftext|> q", "\n\n a", " ", "ΣΑΣ σας İstanbul ﬁ", "a b c  d"]
    for name, blanks in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        enc = tokens.CachedEncoder(tokens.vocabulary(name), blanks, entries=200)
        texts = [t or "" for _, t in rows] + odd
        for t, ids in zip(texts, enc.encode(texts)):
            assert np.frombuffer(ids, "<u4").tolist() == enc.lib.encode(t, add_special_tokens=False).ids, t[:50]


def test_special_tokens_spelt_out_have_their_one_id(spark):
    from tokenizers import Tokenizer

    parts = ["<|endoftext|>", "<|startoftext|>", "<|endoftext|><|endoftext|>", "a<|endoftext|>b", "<|ENDOFTEXT|>", "<|endoftext", "word", "it's", "", "\t", "\n", "Zwei", "x1"]
    r = random.Random(14)
    texts = [" ".join(r.choice(parts) for _ in range(r.randint(1, 9))) for _ in range(400)] + ["<|endoftext|>", "  <|endoftext|>  b", "a\n<|endoftext|>\nb"]
    for name, blanks, special in (("byte_bpe_50k.json", True, 50256), ("word_bpe_49k.json", False, 49407)):
        lib = Tokenizer.from_file(tokens.vocabulary(name))
        assert lib.encode("<|endoftext|>", add_special_tokens=False).ids == [special]
        for entries in (0, 600_000):
            enc = tokens.CachedEncoder(tokens.vocabulary(name), blanks, entries=entries)
            for t, ids in zip(texts, enc.encode(texts)):
                assert np.frombuffer(ids, "<u4").tolist() == lib.encode(t, add_special_tokens=False).ids, t
    manifest = cut(sstable.write_shards(frame(spark, [(1, "a <|endoftext|>")]), f"{shared_dir(spark)}/t", tokens.vocabulary("word_bpe_49k.json"), partitions=1))
    assert [x["n_tokens"] for x in sstable.read_shards(manifest).collect()] == [3]


# --- 10 pages


def test_pages(spark):
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style></head><body><nav><a href=/>Home</a></nav><header>Site</header><div class="cookie-notice">We use cookies</div>
    <article><h1>The &amp; title</h1><p>First   paragraph\n of the text &copy; 2020.<p>Second <b>one<br>goes on</p><ul><li>item</ul><div class="comments"><p>I think so too, and this comment is long enough.</p></div></article>
    <aside>Side</aside><form>Mail <input></form><script>var x="</p>";</script><footer>Foot</footer></body></html>"""
    want = "The & title\nFirst paragraph of the text © 2020.\nSecond one goes on\nitem"
    rows = [(1, "u", page), (2, "u", None), (3, None, ""), (4, "u", "<p>unclosed <b>text"), (5, "u", "plain"), (5, "u", page), (6, "u", "<article></article>"), (7, "u", "<div class=ad>x</div>")]
    df = spark.createDataFrame([(*r, "t", 0) for r in rows], "page_id long, url string, html string, text string, n_chars int")
    got = sorted(((x["page_id"], x["text"], x["n_chars"]) for x in html.extract(df).collect()))
    texts = [(1, want), (2, ""), (3, ""), (4, "unclosed text"), (5, "plain"), (5, want), (6, ""), (7, "")]
    assert got == sorted((i, t, len(t)) for i, t in texts)
    assert html.extract(df.where("false")).count() == 0


def test_page_without_article_keeps_the_dense_region():
    text = "This is a paragraph with quite a few words in it, so that its ratio of text to tags is high."
    page = "<div><a>Home</a><a>News</a></div><div>" + f"<p>{text}</p>" * 5 + "</div><div><a>More</a> <a>Links</a> <a>Here</a></div>"
    assert html.main_text(page) == "\n".join([text] * 5)


def test_page_without_article_keeps_every_block_of_its_region():
    para = ("This is a long paragraph of plain words that goes on for quite a while. " * 6).strip()
    menu = "<div><a>Home</a> <a>News</a> <a>About us</a></div>"
    foot = "<div><ul><li><a>More</a></li><li><a>Links</a></li><li><a>Here</a></li></ul></div>"
    title, byline = "<h1>A title</h1>", "<div>By <a>J. Doe</a>, May 2</div>"
    items = "<ul>" + "".join(f"<li>item {i}</li>" for i in range(6)) + "</ul>"
    linked = "<ul><li><a>One source</a></li><li><a>Another</a></li></ul>"
    lines = ["A title", "By J. Doe, May 2", *[f"item {i}" for i in range(6)], *[para] * 4, "One source", "Another", para, *[f"item {i}" for i in range(6)], "The end."]
    body = byline + items + f"<p>{para}</p>" * 4 + linked + f"<p>{para}</p>" + items + "<p>The end.</p>"
    for page in (
        f"<body>{menu}<div>{title}{body}</div>{foot}</body>",
        f"<body>{menu}<div>{title}<div>{body}</div></div>{foot}</body>",
        f"<body>{menu}{title}{body}{foot}</body>",
        f"<body><div>{menu}<div>{title}{menu}<div>{body}</div></div>{foot}</div></body>",
        f"<div>{title}{body}</div>",
    ):
        assert html.main_text(page) == "\n".join(lines), page
    short = f"<body>{menu}<div><h1><a>T</a></h1><p>by me</p>" + f"<p>{para[:400]}</p>" * 5 + f"<p>Bye.</p></div>{foot}</body>"
    assert html.main_text(short) == "\n".join(["T", "by me", *[para[:400].strip()] * 5, "Bye."])
    one = f"<body>{menu}<h1>T</h1><p>{para * 3}</p><p>Bye.</p>{foot}</body>"
    assert html.main_text(one) == f"T\n{para * 3}\nBye."


def test_pages_are_decided_by_the_clusters(spark, monkeypatch):
    para = ("Plain words of an article that goes on for quite a while, so that there is far more text than markup. " * 3).strip()
    menu = "".join(f"<div><span><b>Part {i}</b></span></div>" for i in range(8))  # a menu that nothing marks as one
    teaser = "<article><h3>Other</h3><p>See</p></article>"
    body = "<h1>A title</h1><p>by</p>" + f"<p>{para}</p>" * 4 + "<p>End.</p>"
    pages = {
        "div": f"<body><div>{menu}</div><div><a>x</a> <a>y</a></div><div>{body}</div><div><a>q</a> <a>r</a></div><div>{menu}</div></body>",
        "teaser": f"<body><div>{teaser * 3}</div><div><a>x</a> <a>y</a></div><div>{body}</div><div><a>q</a> <a>r</a></div></body>",
        "within": f"<body><article>{body}<div class='comments'><p>ok</p><p>{para[:60]}</p></div></article></body>",
    }
    want = "\n".join(["A title", "by", *[para] * 4, "End."])
    assert {k: html.main_text(v) for k, v in pages.items()} == dict.fromkeys(pages, want)
    monkeypatch.setattr(html, "two_clusters", lambda x: -1.0)
    assert all(html.main_text(v) != want for v in pages.values())


def test_very_long_pages_and_texts(spark):
    page = "<article>" + "<p>word " * 60_000 + "</article>"
    assert html.main_text(page) == "\n".join(["word"] * 60_000)
    r = random.Random(5)
    long = " ".join(str(r.randrange(10**6)) for _ in range(120_000))
    docs = [(1, long), (2, long + " tail"), (3, "x " * 200_000), (4, "short")]
    got = {x["doc_id"]: x["component_id"] for x in near_dup.join_components(frame(spark, docs)).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 4}
    out = {x["doc_id"]: x["n_removed"] for x in arrow_map(suffix_dedup.with_ranges(frame(spark, docs)), suffix_dedup._digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string").collect()}
    assert out[1] == 0 and out[2] == len(long) and out[3] >= 399_000 and out[4] == 0


def test_trees_follow_from_the_recall():
    r = np.random.default_rng(1)
    for s in (0.85, 0.8):
        trees = near_dup.trees_for(s)
        values = r.integers(0, 1 << 32, (2, 300, near_dup.SKETCH), dtype=np.uint64).astype(np.uint32)
        same = r.random((300, near_dup.SKETCH)) < s
        values[1][same] = values[0][same]
        met = 0
        for i in range(300):
            both = []
            for side in (0, 1):
                node, row = near_dup.descend(np.repeat(near_dup.mix(np.arange(1, trees + 1, dtype=np.uint64)), 1), np.zeros(trees, np.int64), values[side][i : i + 1], s, 2)
                both.append(set(node.tolist()))
            met += len(both[0] & both[1]) >= 2
        assert met >= 298
        assert near_dup.roots_for(s, trees, []) <= near_dup.roots_for(s, trees, [1, 1, 1]) <= 64
        assert near_dup.parted(s, 2) ** trees < 1e-4


def test_sketches_are_packed_by_planes():
    values = np.random.default_rng(4).integers(0, 1 << 32, (7, near_dup.SKETCH), dtype=np.uint64).astype(np.uint32)
    packed = [near_dup.planes(v) for v in values]
    assert (near_dup.unplaned(pa.array(packed)) == values).all()
    assert (near_dup.lows(pa.array([p[: near_dup.SKETCH] for p in packed])) == values.astype(np.uint8)).all()


def test_salts_follow_the_rows_of_a_key(spark, monkeypatch):
    monkeypatch.setattr(common, "HOT", 5)
    rows = spark.createDataFrame([(k, i) for k, n in ((1, 40), (2, 6), (3, 5)) for i in range(n)], "k long, i long").cache()
    hot = common.hot_keys(rows.groupBy("k").count(), "k", "count")
    assert hot == {8: [1], 2: [2]}
    names = spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "k long, name string")
    got = common.salted_join(rows, names, "k", "i", hot)
    assert sorted(map(tuple, got.select("k", "i", "name").collect())) == sorted((r.k, r.i, "abc"[r.k - 1]) for r in rows.collect())


def test_cloud_with_one_odd_document_costs_its_own_size(spark, monkeypatch):
    r = random.Random(2)
    words = [f"w{i}" for i in range(4000)]
    base = [r.choice(words) for _ in range(120)]
    docs = []
    for i in range(400):
        docs.append((i, " ".join([*base[:-1], f"end{i}"])))
    odd = list(base)
    for i in (20, 50, 80, 100):
        odd[i] = "odd"
    docs.append((1000, " ".join(odd)))
    seen = spark.sparkContext.accumulator(0)
    plain = near_dup._exhaust

    def counted(cluster, *args, **kw):
        n, k = cluster.count(), cluster.where("odd").count()
        seen.add(n * k)
        return plain(cluster, *args, **kw)

    monkeypatch.setattr(near_dup, "_exhaust", counted)
    got = {x["doc_id"]: x["component_id"] for x in near_dup.join_components(frame(spark, docs), 85, small=64, dense=0.5).collect()}
    assert got == {i: c for i, (_, c) in brute.near_duplicates(docs, 85).items()}
    assert seen.value <= 3 * len(docs)


def test_random_runs_and_hot_values(spark, monkeypatch):

    monkeypatch.setattr(common, "HOT", 5)
    rare, copied = "q7Zr2LmX9cTbV4nKs8HdWy3P", "mN5vB8xC2zL7kJ4hG9fD3sA6"
    docs = [(i, f"id {copied} here") for i in range(40)] + [(50, f"key {rare}."), (51, "a" * 40), (52, f"token={rare}x")]
    got = {x["doc_id"]: x for x in secrets.digest(secrets.scan(frame(spark, docs))).collect()}
    assert got[50]["spans"] == f"random:4:{4 + len(rare)}" and got[3]["spans"] == "" and got[3]["n_copied"] == 1 and got[51]["spans"] == "hex:0:40"
    assert got[52]["spans"].startswith("assign:0:") and "random" not in got[52]["spans"]


def test_identity_terms_of_every_language_are_swapped():
    for words in ({"muslime", "lesen"}, {"musulmans", "lisent"}, {"musulmanes", "leen"}, {"muslims", "read"}):
        assert toxicity._swaps(words)


def test_repeated_labels_and_rows(spark):
    docs = [(i, f"w{i} " + ("vile" if i % 2 else "fine") + f" x{i % 5}") for i in range(0, 60)]
    lab = [(i, i % 2) for i in range(60)] * 2 + [(0, 1)]
    model = toxicity.train(frame(spark, docs + docs[:9] + [(0, "other")]), spark.createDataFrame(lab, "doc_id long, toxic int"), most=50)
    assert model.score("vile words") > model.score("fine words")
