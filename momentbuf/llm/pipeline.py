"""The corpus pipeline: toxicity, near-duplicates, repeated strings, secrets, packing.

Each stage takes (spark, docs, sf_dir) and returns a frame that is written as Parquet
and read again as the next one's docs. All but the last return the columns of documents.

Defined results, for every stage: null and empty texts pass (packed: the end id alone);
further columns of docs are left behind; an empty table gives no rows; rows that repeat a
doc_id are documents of their own, except that equal ones collapse as near duplicates.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, ship, table
from momentbuf.llm.near_dup import join_components
from momentbuf.llm.packing import pack, tokenized
from momentbuf.llm.secrets import KINDS, scan
from momentbuf.llm.suffix_dedup import covered, kept_bytes, with_ranges
from momentbuf.llm.tokens import vocabulary
from momentbuf.llm.toxicity import train, without_toxic

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score stays below the threshold, as they are: null and empty texts, repeated rows and rows without an id too. Without labels of both classes all stay."""
    ship(spark)
    model = train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return without_toxic(docs.select(*COLUMNS), model)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row, of the smallest doc_id, of each group of rows linked at a similarity of 0.8. Rows without a doc_id stay.

    Rows that share a doc_id are documents of their own: only equal ones and linked ones collapse.
    """
    ship(spark)
    docs = docs.select(*COLUMNS)
    twice = cut(docs.groupBy("doc_id").count().where("count > 1 and doc_id is not null").select("doc_id"))
    if twice.isEmpty():
        gone = join_components(docs.select("doc_id", "text"), percent=80).where(~F.col("kept")).select("doc_id").distinct()
        return docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)
    again = docs.join(twice, "doc_id", "left_semi").select(*COLUMNS).distinct()
    rows = cut(docs.join(twice, "doc_id", "left_anti").select(*COLUMNS).union(again).withColumn("row", F.monotonically_increasing_id()))
    named = rows.where("doc_id is not null")
    part = cut(join_components(named.select(F.col("row").alias("doc_id"), "text"), percent=80).select(F.col("doc_id").alias("row"), "component_id"))
    order = named.select("row", "doc_id", F.xxhash64(*COLUMNS[1:]).alias("hash"))
    first = part.join(order, "row").groupBy("component_id").agg(F.min(F.struct("doc_id", "hash", "row")).alias("first")).select("first.row")
    return named.join(first, "row", "left_semi").select(*COLUMNS).union(rows.where("doc_id is null").select(*COLUMNS))


def repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes that a string of 100 bytes repeats from earlier; characters that a cut splits go with it."""
    ship(spark)
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = []
            for t, r in zip(b.column("text").to_pylist(), b.column("ranges").to_pylist(), strict=True):
                raw = (t or "").encode("utf-8", "surrogatepass")
                texts.append(t if not r else kept_bytes(raw, covered(r, len(raw))).decode("utf-8", "ignore"))
            yield b.set_column(b.schema.get_field_index("text"), "text", pa.array(texts, pa.string())).drop_columns(["ranges"])

    kept = with_ranges(docs.select(*COLUMNS), extra=("lang", "source"))
    cleaned = arrow_map(kept.select("doc_id", "text", "lang", "source", "ranges"), run, "doc_id long, text string, lang string, source string")
    return cleaned.select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def secret_scans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with every base secret, and every further one that isn't widely copied, replaced by its kind in brackets."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    found = scan(docs, keep=("text", "lang", "source"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = []
            for t, spans in zip(b.column("text").to_pylist(), b.column("spans").to_pylist(), strict=True):
                out, at = [], 0
                for s in sorted((x for x in spans or () if x["kind"] in KINDS or not x["widely"]), key=lambda x: (x["start"], -x["end"])):
                    if s["start"] >= at:
                        out += [t[at : s["start"]], f"[{s['kind']}]"]
                    at = max(at, s["end"])
                texts.append(t if not out else "".join([*out, t[at:]]))
            yield b.set_column(b.schema.get_field_index("text"), "text", pa.array(texts, pa.string())).drop_columns(["spans"])

    masked = arrow_map(found.select("doc_id", "text", "lang", "source", "spans"), run, "doc_id long, text string, lang string, source string")
    return masked.select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 1024 tokens and their places in sequences; each row is packed, equal rows each on their own."""
    ship(spark)
    return pack(cut(tokenized(docs.select("doc_id", "text"), vocabulary("byte_bpe_50k.json"))))


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
STAGES: list[tuple[str, Stage]] = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("repeated_strings", repeated_strings),
    ("secret_scans", secret_scans),
    ("packing", packing),
]
#: A trained classifier, minwise trees, merged transforms and a tokenizer can't be stated in SQL; a test holds run() against the plain versions, chained.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = cut(docs)
    return docs
