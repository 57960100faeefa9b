"""The pipeline's stages against plain versions, and its queries."""

import zlib

import corpus_pipeline as C
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from momentbuf.llm import tokens, toxicity
from tests.llm import brute
from tests.llm.conftest import frame


def test_registered():
    names = entry.queries()
    assert all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11)) and "pipeline" in names
    assert [n for n, _ in C.STAGES] == ["toxicity", "near_duplicates", "repeated_strings", "secret_scans", "packing"]


def test_stages(spark, sf, rows):
    docs = frame(spark, [*rows, (1, rows[1][1])]).select(*C.COLUMNS)
    kept = C.near_duplicates(spark, docs, sf)
    assert kept.columns == list(C.COLUMNS)
    want = sorted(i for i, (_, c) in brute.near_duplicates(rows, 80).items() if c == i)
    assert sorted(x["doc_id"] for x in kept.collect()) == want
    cleaned = C.repeated_strings(spark, frame(spark, rows).select(*C.COLUMNS), sf)
    assert {x["doc_id"]: x["text"] or "" for x in cleaned.collect()} == {i: v[4].decode("utf-8", "ignore") for i, v in brute.repeated(rows).items()}
    secret = "password: hunter2hunter2"
    masked = C.secret_scans(spark, frame(spark, [(1, f"a {secret} b"), (2, None), (3, "clean text")]).select(*C.COLUMNS), sf)
    assert {x["doc_id"]: (x["text"], x["n_chars"]) for x in masked.collect()} == {1: ("a [assign] b", 12), 2: (None, None), 3: ("clean text", 10)}


def test_rows_that_share_an_id_are_documents_of_their_own(spark, sf):
    a, b, c = (" ".join(f"{x}{i}" for i in range(60)) for x in "abc")
    near = lambda t: f"{t} more"
    docs = [(5, a), (5, b), (5, b), (7, near(b)), (4, c), (4, near(c)), (9, near(a)), (9, "short one"), (8, ""), (8, ""), (8, "\n"), (None, a), (None, a)]
    got = C.near_duplicates(spark, frame(spark, docs).select(*C.COLUMNS), sf).collect()
    texts = sorted((x["doc_id"] or 0, x["text"]) for x in got if x["doc_id"] != 4)
    assert texts == sorted([(5, a), (5, b), (9, "short one"), (8, ""), (8, "\n"), (0, a), (0, a)])
    assert [x["text"] in (c, near(c)) for x in got if x["doc_id"] == 4] == [True]


@pytest.mark.parametrize("stage", range(5))
def test_stages_of_nothing(spark, sf, stage):
    empty = frame(spark, [(1, "a")]).select(*C.COLUMNS).where("false")
    assert C.STAGES[stage][1](spark, empty, sf).count() == 0


def packed_of(rows):
    """{(doc_id, piece): (start, length, checksum)} of (doc_id, text) rows, by the library's plain call."""
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(tokens.vocabulary("byte_bpe_50k.json"))
    out = {}
    for i, t in rows:
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 2]
        first = len(ids) % 1024 or 1024
        for n, (a, b) in enumerate(zip([0, *range(first, len(ids), 1024)], range(first, len(ids) + 1, 1024))):
            out[i, n] = (a, b - a, brute.crc(ids[a:b]))
    return out


def masked_of(text):
    """A text with its base secrets masked, for texts without further ones."""
    out, at = [], 0
    for k, s, e in sorted(brute.base_secrets(text), key=lambda x: (x[1], -x[2])):
        if s >= at:
            out += [text[at:s], f"[{k}]"]
        at = max(at, e)
    return "".join([*out, text[at:]]) if out else text


def test_toxicity_and_packing_stages(spark, sf, rows):
    docs = frame(spark, [*rows, (1, rows[1][1])]).select(*C.COLUMNS)
    model = toxicity.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    kept = sorted((x["doc_id"], x["text"] or "") for x in C.toxicity(spark, docs, sf).collect())
    assert kept == sorted((i, t or "") for i, t in [*rows, (1, rows[1][1])] if model.score(t) < toxicity.THRESHOLD)
    got = C.packing(spark, frame(spark, rows).select(*C.COLUMNS), sf).collect()
    assert {(x["doc_id"], x["piece"]): (x["start"], x["length"], x["ids_crc32"]) for x in got} == packed_of(rows)


def test_run_against_the_plain_versions_chained(spark, sf, rows, tmp_path):
    docs = [(i, t) for i, t in rows if i < 60 or i in (60, 62, 66)] + [(100, "note password: hunter2hunter2 end"), (101, "AKIA" + "Q" * 16)]
    docs += [(200 + i, f"vileword{i % 3} and " + " ".join(f"t{i}x{j}" for j in range(20))) for i in range(30)] + [(300 + i, " ".join(f"c{i}x{j}" for j in range(20))) for i in range(30)]
    labels = [(200 + i, 1) for i in range(30)] + [(300 + i, 0) for i in range(30)]
    frame(spark, docs).select(*C.COLUMNS).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    model = toxicity.train(frame(spark, docs), spark.createDataFrame(labels, "doc_id long, toxic int"))
    left = [(i, t) for i, t in docs if model.score(t) < toxicity.THRESHOLD]
    assert {i for i, _ in docs if 300 <= i < 330} <= {i for i, _ in left} and len(left) < len(docs)
    first = {i for i, (_, c) in brute.near_duplicates(left, 80).items() if i == c}
    left = [(i, t) for i, t in left if i in first]
    cleaned = brute.repeated(left)
    left = [(i, masked_of(cleaned[i][4].decode("utf-8", "ignore"))) for i, _ in left]
    got = {(x["doc_id"], x["piece"]): (x["start"], x["length"], x["ids_crc32"]) for x in C.run(spark, str(tmp_path)).collect()}
    assert got == packed_of(left)


def test_run(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = C.run(spark, sf)
    assert set(out.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"}
    fill = out.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.max(F.col("offset") + F.col("length")).alias("end")).collect()
    assert all(x["n"] == x["end"] <= 1024 for x in fill)
    assert out.select("doc_id").distinct().count() <= docs.count()
    assert tokens.vocabulary("byte_bpe_50k.json").endswith(".json") and zlib.crc32(b"") == 0
