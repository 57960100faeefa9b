"""Counterfactual-regularised toxicity classifier.

A sparse logistic model on the presence of words and of word beginnings (inflected
forms share these). Sentences that name an identity
group are swapped to each other group's term and to a neutral word; the squared
change of the score over all swaps is added to the loss, so that a mention of a
group moves no score and neutral mentions aren't taken for toxic ones.

Training takes at most `most` labelled documents (those with the smallest hashes of
their ids; of rows that repeat an id one stands for it, and of repeated labels the
largest counts); near copies in it share one weight. Scores read the text only.
Defined results: null and empty texts get the intercept's score; without
labelled rows of both classes every score is 0.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, records, table

THRESHOLD = 0.7
#: Terms for identity groups, by the kind of group, in the corpus' four languages; a term is swapped for others of its own list.
IDENTITY = (
    "women men woman man girls boys female male transgender nonbinary".split(),
    "gay lesbian bisexual straight queer heterosexual homosexual".split(),
    "muslim muslims christian christians jewish jews hindu hindus buddhist atheist catholic".split(),
    "black white asian latino hispanic african arab european american mexican chinese indian".split(),
    "immigrant immigrants refugee refugees foreigner foreigners".split(),
    "disabled deaf blind autistic elderly old young".split(),
    "frauen männer frau mann mädchen jungen weiblich männlich".split(),
    "schwule lesben bisexuelle heterosexuelle homosexuelle".split(),
    "muslime muslim christen christ juden jude hindus buddhisten atheisten katholiken".split(),
    "schwarze weiße asiaten araber afrikaner europäer amerikaner türken chinesen inder".split(),
    "einwanderer flüchtlinge flüchtling ausländer migranten".split(),
    "behinderte gehörlose blinde alte junge".split(),
    "femmes hommes femme homme filles garçons féminin masculin".split(),
    "gays lesbiennes bisexuels hétérosexuels homosexuels".split(),
    "musulmans musulman chrétiens chrétien juifs juif hindous bouddhistes athées catholiques".split(),
    "noirs blancs asiatiques arabes africains européens américains mexicains chinois indiens".split(),
    "immigrés immigré réfugiés réfugié étrangers migrants".split(),
    "handicapés sourds aveugles vieux jeunes".split(),
    "mujeres hombres mujer hombre niñas niños femenino masculino".split(),
    "lesbianas bisexuales heterosexuales homosexuales".split(),
    "musulmanes musulmán cristianos cristiano judíos judío hindúes budistas ateos católicos".split(),
    "negros blancos asiáticos árabes africanos europeos americanos mexicanos chinos indios".split(),
    "inmigrantes inmigrante refugiados refugiado extranjeros".split(),
    "discapacitados sordos ciegos ancianos jóvenes".split(),
)
NEUTRAL = ("people", "person", "menschen", "personen", "personnes", "gens", "personas", "gente")
_TERMS = frozenset(x for g in IDENTITY for x in g)
_WORD = re.compile(r"\w+")


#: Lengths of word beginnings that are features of their own, marked by a star.
BEGINNINGS = (4, 5, 6)


def words_of(text: str | None) -> set[str]:
    return set(_WORD.findall((text or "").lower()))


def features_of(words: set[str], lengths: tuple[int, ...] = BEGINNINGS) -> set[str]:
    """The words, and the beginnings of longer ones."""
    return words.union(*({w[:n] + "*" for w in words if len(w) > n} for n in lengths))


@dataclass
class Model:
    weights: dict[str, float] = field(default_factory=dict)
    intercept: float = -50.0

    def __post_init__(self) -> None:
        self.lengths = tuple(n for n in BEGINNINGS if any(len(w) == n + 1 and w[-1] == "*" for w in self.weights))

    def score(self, text: str | None) -> float:
        z = self.intercept + sum(self.weights[w] for w in self.weights.keys() & features_of(words_of(text), self.lengths))
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40)))) if z > -40 else 0.0


def _swaps(words: set[str]) -> list[tuple[str, str]]:
    """(term, replacement) pairs for the counterfactuals of one text."""
    return [(t, x) for g in IDENTITY for t in g if t in words for x in (*g, *NEUTRAL) if x != t and x not in words]


_BUCKETS = 1 << 21


def _bucket(feature: str) -> int:
    return zlib.crc32(feature.encode("utf-8", "surrogatepass")) & (_BUCKETS - 1)


def fit(texts: list[str], labels: np.ndarray, fairness: float = 1.0, l1: float = 2e-3, features: int = 4096, steps: int = 300) -> Model:
    """Select features by weighted log-odds, fit with an l1 penalty, then refit those that stay with a small l2 penalty.

    texts: each one's distinct words, joined by line ends. Features are counted in hashed
    buckets first, so that memory holds the words and the promising features alone.
    """
    y = np.asarray(labels, float)
    if not len(y) or y.min() == y.max():
        return Model()
    words = lambda t: set(t.split("\n")) - {""}
    sign = [tuple(sorted(zlib.crc32(w.encode("utf-8", "surrogatepass")) for w in features_of(words(t)))[:4]) for t in texts]
    copies = Counter(sign)
    weight = np.array([1 / copies[s] for s in sign])
    for k in (0.0, 1.0):
        weight[y == k] /= weight[y == k].sum()
    eps = 1 / len(y)

    def gain(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.where(a + b > 4 * eps, np.abs(a - b) * np.abs(np.log((a + eps) / (b + eps))), 0.0)

    bucket = np.zeros((2, _BUCKETS), np.float32)
    for t, k, w in zip(texts, y.astype(int).tolist(), weight.tolist(), strict=True):
        bucket[k, list({_bucket(x) for x in features_of(words(t))})] += w
    most = gain(bucket[1], bucket[0])
    promising = most >= np.sort(most)[-min(len(most), 4 * features)]
    promising &= most > 0
    share: tuple[dict, dict] = ({}, {})
    for t, k, w in zip(texts, y.astype(int).tolist(), weight.tolist(), strict=True):
        d = share[k]
        for x in features_of(words(t)):
            if promising[_bucket(x)]:
                d[x] = d.get(x, 0.0) + w
    names = sorted(share[0].keys() | share[1].keys())
    exact = gain(*(np.array([share[k].get(x, 0.0) for x in names]) for k in (1, 0)))
    chosen = [names[i] for i in np.argsort(-exact, kind="stable")[:features] if exact[i] > 0]
    seen = set().union(*(words(t) & _TERMS for t in texts))
    chosen = list(dict.fromkeys([*chosen, *sorted(seen)]))
    at = {x: i for i, x in enumerate(chosen)}
    lists = [sorted(at[x] for x in features_of(words(t)) if x in at) for t in texts]
    cols = np.fromiter((c for r in lists for c in r), np.int64)
    rows = np.repeat(np.arange(len(texts)), [len(r) for r in lists])
    pairs = Counter(p for t in texts for p in _swaps(words(t)))
    # A swap takes the term's features away and puts the other's in.
    moved = [(i, at[x], sign) for i, (a, b) in enumerate(pairs) for w, sign in ((a, 1.0), (b, -1.0)) for x in features_of({w}) if x in at]
    pr, pc = (np.array([m[k] for m in moved], np.int64) for k in (0, 1))
    ps = np.array([m[2] for m in moved])
    pn = np.array(list(pairs.values()), float)
    pn = pn / max(1.0, pn.sum())

    def solve(on: np.ndarray, l1: float, l2: float, steps: int) -> np.ndarray:
        keep = on[cols] if len(cols) else np.zeros(0, bool)
        r, c = rows[keep], cols[keep]
        m, n = len(chosen), len(texts)

        def grad(w: np.ndarray) -> np.ndarray:
            z = np.bincount(r, w[c], n) + w[m]
            e = weight * (1 / (1 + np.exp(-z)) - y)
            g = np.r_[np.bincount(c, e[r], m), e.sum()]
            if len(moved):
                d = np.bincount(pr, ps * w[pc], len(pn))
                g[:m] += np.bincount(pc, 2 * fairness * pn[pr] * d[pr] * ps, m)
            g[:m] += l2 * w[:m]
            return g

        v = np.ones(m + 1)
        for _ in range(12):  # largest eigenvalue of the bound on the curvature
            u = np.bincount(r, v[c], n) + v[m]
            v2 = np.r_[np.bincount(c, (weight * u)[r], m), (weight * u).sum()] / 4
            size = float(np.linalg.norm(v2)) or 1.0
            v = v2 / size
        rate = 1 / (1.1 * size + (16 * fairness if moved else 0.0) + l2)
        w = q = np.zeros(m + 1)
        t = 1.0
        for _ in range(steps):
            new = q - rate * grad(q)
            new[:m] = np.where(on, np.sign(new[:m]) * np.maximum(0, np.abs(new[:m]) - rate * l1), 0)
            t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
            q = new + (t - 1) / t2 * (new - w)
            w, t = new, t2
        return w

    first = solve(np.ones(len(chosen), bool), l1, 0.0, steps)
    on = np.abs(first[:-1]) > 0.02 * max(1e-9, np.abs(first[:-1]).max())
    w = solve(on, 0.0, 2e-5, 2 * steps)
    # The threshold's score goes to the cut that separates the classes best; in its gap it lies nearer to the class that spreads less.
    z = np.bincount(rows, w[cols], len(texts)) + w[-1]
    order = np.argsort(z, kind="stable")
    lost = np.r_[0, np.cumsum(np.where(y[order] == 1, weight[order], 0))] + np.r_[0, np.cumsum(np.where(y[order] == 0, weight[order], 0))][-1] - np.r_[0, np.cumsum(np.where(y[order] == 0, weight[order], 0))]
    sides = [float(np.sqrt(np.average((z[y == k] - np.average(z[y == k], weights=weight[y == k])) ** 2, weights=weight[y == k]))) for k in (0, 1)]
    part = float(np.clip(sides[0] / max(1e-9, sum(sides)), 0.25, 0.75))
    edge = np.r_[z[order[0]] - 1, z[order][:-1] + part * (z[order][1:] - z[order][:-1]), z[order[-1]] + 1]
    edge_width = np.r_[1, z[order][1:] - z[order][:-1], 1]
    best = np.flatnonzero(lost <= lost.min() + 1e-12)
    cut = edge[best[edge_width[best].argmax()]]
    return Model({x: float(w[i]) for x, i in at.items() if w[i]}, float(w[-1] - cut + np.log(THRESHOLD / (1 - THRESHOLD))))


def held_out(doc_id) -> F.Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1


_WORDS = pa.schema([("words", pa.string()), ("toxic", pa.int32())])


def _distinct_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield records(_WORDS, words=["\n".join(sorted(words_of(t))) for t in b.column("text").to_pylist()], toxic=b.column("toxic"))


def train(docs: DataFrame, labels: DataFrame, most: int = 8_000, **options: float) -> Model:
    """Fit on at most `most` labelled rows that aren't held out; only their distinct words reach the driver."""
    rows = labels.where("doc_id is not null and toxic is not null").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    some = rows.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    # Of rows that repeat an id the one with the smallest hash stands for it, so there are at most `most`.
    texts = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id").groupBy("doc_id", "toxic").agg(F.min_by("text", F.struct(F.xxhash64("text"), "text")).alias("text"))
    got = arrow_map(texts.select("text", "toxic"), _distinct_words, "words string, toxic int").collect()
    got = sorted(got)  # whatever order tasks end in, sums are taken in the same one
    return fit([r["words"] for r in got], np.array([r["toxic"] for r in got]), **options)


_SCORES = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score and predicted of every document; a map without exchange."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield records(_SCORES, doc_id=b.column("doc_id"), score=[model.score(t) for t in b.column("text").to_pylist()])

    out = arrow_map(docs.select("doc_id", "text"), run, "doc_id long, score double")
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def without_toxic(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs, all columns, whose score is below the threshold."""
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array([model.score(t) < THRESHOLD for t in b.column("text").to_pylist()], pa.bool_()))

    return arrow_map(docs, run, schema)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return score(docs, train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))
