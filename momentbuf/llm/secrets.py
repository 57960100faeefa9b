"""Secret scans with corpus-wide ownership frequency.

Base findings come from three patterns. The method then aggregates the hash of
every candidate value over all documents by distinct repositories (source and
language) and owners (source): a value that many owners hold is an example that
was copied about, one that few hold looks live. Further detectors (vendor
tokens, signed tokens, private keys, credentials in addresses) are wide, so
their spans are added only where the value is owner-specific.

Defined results: null and empty texts have no spans; a value repeated in one
document counts once for its owner; a null owner counts as one owner of its own.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from math import log2

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, hot_keys, records, salted_join, table

#: Base patterns, with the least length of the part that counts.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
KINDS = ("assign", "access", "hex")
#: Public formats of further credentials.
MORE = (
    ("vendor", re.compile(r"(?<![A-Za-z0-9_])(?:gh[pousr]_[A-Za-z0-9]{20,}|github_pat_[A-Za-z0-9_]{22,}|xox[abprs]-[A-Za-z0-9-]{10,}|sk_live_[A-Za-z0-9]{16,}|AIza[A-Za-z0-9_-]{30,}|glpat-[A-Za-z0-9_-]{20,})")),
    ("signed", re.compile(r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}")),
    ("private", re.compile(r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----[^-]*-----END (?:[A-Z]+ )*PRIVATE KEY-----")),
    ("address", re.compile(r"[a-z][a-z0-9+.-]{1,20}://[^\s:/@]{1,64}:[^\s:/@]{6,128}@[A-Za-z0-9.-]+")),
)
#: A run that looks drawn at random: so long, of small and capital letters and digits, of so many bits a character.
RANDOM = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9_-]{24,512}(?![A-Za-z0-9+/_=-])")
RANDOM_BITS = 4.0
_DIGIT, _SMALL, _BIG = (re.compile(x) for x in ("[0-9]", "[a-z]", "[A-Z]"))
_ORDER = {k: i for i, k in enumerate([*KINDS, *(k for k, _ in MORE), "random"])}
_HINTS = ("_", "-", "eyJ", "://", "AIza")
_SCHEMA = pa.schema([("rid", pa.int64()), ("doc_id", pa.int64()), ("owner", pa.string()), ("repo", pa.string()), ("found", pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value", pa.string())])))])
_DDL = "rid long, doc_id long, owner string, repo string, found array<struct<kind:string,start:long,end:long,value:string>>"


def base_spans(text: str) -> list[tuple[str, int, int, str]]:
    """(kind, start, end, value) of the base patterns; each pattern is leftmost and without overlaps, short matches drop out after that."""
    out = [("assign", m.start(), m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    out += [("access", m.start(), m.end(), m[0]) for m in ACCESS.finditer(text)]
    return out + [("hex", m.start(), m.end(), m[0]) for m in HEX.finditer(text)]


def bits(value: str) -> float:
    """Bits a character, by the value's own frequencies."""
    n = len(value)
    return -sum(c / n * log2(c / n) for c in Counter(value).values())


def further_spans(text: str) -> list[tuple[str, int, int, str]]:
    out = [(k, m.start(), m.end(), m[0]) for k, p in MORE for m in p.finditer(text)] if any(h in text for h in _HINTS) else []
    for m in RANDOM.finditer(text):
        v = m[0]
        if _DIGIT.search(v) and _SMALL.search(v) and _BIG.search(v) and bits(v) >= RANDOM_BITS and not any(s < m.end() and m.start() < e for _, s, e, _ in out):
            out.append(("random", m.start(), m.end(), v))
    return out


def _ordered(found: list) -> list:
    return sorted(found, key=lambda x: (x[1], _ORDER[x[0]], x[2]))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        found = []
        for t in b.column("text").to_pylist():
            t = t or ""
            hits = base_spans(t)
            base = [(s, e) for _, s, e, _ in hits]
            hits += [x for x in further_spans(t) if x[0] != "random" or not any(s < x[2] and x[1] < e for s, e in base)]
            found.append([{"kind": k, "start": s, "end": e, "value": hashlib.blake2b(v.encode("utf-8", "surrogatepass"), digest_size=16).hexdigest()} for k, s, e, v in _ordered(hits)])
        yield records(_SCHEMA, rid=b.column("rid"), doc_id=b.column("doc_id"), owner=b.column("owner"), repo=b.column("repo"), found=found)


def candidates(docs: DataFrame, numbered: bool = False) -> DataFrame:
    """rid, doc_id, owner, repo and found: every candidate span of the whole text with its value's hash (values themselves don't leave the scan)."""
    owner = F.coalesce(F.col("source"), F.lit("?"))
    rid = F.col("rid") if numbered else F.monotonically_increasing_id()
    return arrow_map(docs.select(rid.alias("rid"), "doc_id", owner.alias("owner"), F.concat_ws("/", owner, F.coalesce("lang", F.lit("?"))).alias("repo"), "text"), _scan, _DDL)


def ownership(found: DataFrame, widespread: int = 3) -> DataFrame:
    """value, owners, repos, docs and widely: how many distinct owners and repositories hold each candidate value.

    Distinct (value, owner, repository) triples are combined before the exchange,
    so a value that a third of all documents hold moves a few rows a task.
    """
    one = found.select("owner", "repo", F.explode("found").alias("f")).groupBy(F.col("f.value").alias("value"), "owner", "repo").agg(F.count("*").alias("n"))
    return one.groupBy("value").agg(F.countDistinct("owner").alias("owners"), F.countDistinct("repo").alias("repos"), F.sum("n").alias("uses")).withColumn("widely", F.col("owners") >= widespread)


def scan(docs: DataFrame, widespread: int = 3, keep: tuple[str, ...] = ()) -> DataFrame:
    """Every row's doc_id, the columns to keep, and spans (start, kind, end, value, owners, repos, widely).

    Rows are told apart by the number they get when they are first written, so ids may
    repeat. Texts to keep are written with the number and joined once; else they stay behind.
    """
    if keep:
        docs = cut(docs.select(*dict.fromkeys(("doc_id", "text", "lang", "source", *keep)), F.monotonically_increasing_id().alias("rid")))
    found = cut(candidates(docs, bool(keep)))
    own = cut(ownership(found, widespread))
    hot = hot_keys(own, "value", "uses")
    flat = found.select("rid", F.explode("found").alias("f")).select("rid", "f.*")
    spans = salted_join(flat, own, "value", "rid", hot).groupBy("rid").agg(F.collect_list(F.struct("start", "kind", "end", "value", "owners", "repos", "widely")).alias("spans"))
    rows = docs.select("rid", "doc_id", *keep) if keep else found.select("rid", "doc_id")
    return rows.join(spans, "rid", "left").drop("rid")


def _rank(x):
    return F.element_at(F.create_map(*[F.lit(v) for kv in _ORDER.items() for v in kv]), x)


def digest(scanned: DataFrame) -> DataFrame:
    """The contract's columns, and how many spans look live or widely copied."""
    in_order = F.array_sort(F.transform(F.coalesce("spans", F.array().cast("array<struct<start:long,kind:string,end:long,value:string,owners:long,repos:long,widely:boolean>>")), lambda x: F.struct(x["start"].alias("start"), _rank(x["kind"]).alias("rank"), x["end"].alias("end"), x["kind"].alias("kind"), x["widely"].alias("widely"))))
    df = scanned.select("doc_id", in_order.alias("s"))
    line = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    base = F.filter("s", lambda x: x["rank"] < len(KINDS))
    count = lambda k: F.size(F.filter("s", lambda x: x["kind"] == k)).cast("long")
    kept = F.filter("s", lambda x: (x["rank"] < len(KINDS)) | ~x["widely"])
    return df.select(
        "doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"),
        F.sha2(line(base), 256).alias("base_sha256"), line(kept).alias("spans"),
        F.size(F.filter("s", lambda x: ~x["widely"])).cast("long").alias("n_live"), F.size(F.filter("s", lambda x: x["widely"])).cast("long").alias("n_copied"),
    )


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(scan(table(spark, sf_dir, "documents", "doc_id", "text", "source", "lang")))
