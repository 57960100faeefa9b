"""Interpolation weights: what a cell at offset r of a bin gives to the cells around the bin.

For the stencil K = {1-M', .., M} the weight for cell k is the basis polynomial of node k
on the nodes K at t = r / b. Whole-number weights are the same times b^(N-1) (N-1)!.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from math import factorial, prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG


@dataclass(frozen=True)
class Stencil:
    """N = M + M' nodes around a bin."""

    M: int
    Mp: int

    def __post_init__(self) -> None:
        if self.M < 0 or self.Mp < 1:
            raise ValueError("a stencil needs M' >= 1: without node 0 cells on bin edges would not keep their own weight")

    @classmethod
    def of(cls, n: int) -> Stencil:
        return cls(n // 2, n - n // 2)

    @property
    def n(self) -> int:
        return self.M + self.Mp

    @property
    def nodes(self) -> range:
        return range(1 - self.Mp, self.M + 1)

    def scale(self, b: int) -> int:
        """What whole-number weights are multiples of."""
        return b ** (self.n - 1) * factorial(self.n - 1)

    def coefficient(self, k: int) -> Fraction:
        return Fraction(1, prod(k - j for j in self.nodes if j != k))

    def polynomial(self, k: int) -> list[Fraction]:
        """The weight for cell k as a polynomial in t = r / b, lowest power first."""
        out = [self.coefficient(k)]
        for j in self.nodes:
            if j != k:
                out = [(out[i - 1] if i else 0) - (j * out[i] if i < len(out) else 0) for i in range(len(out) + 1)]
        return out

    def exact(self, k: int, r: int, b: int) -> Fraction:
        return self.coefficient(k) * prod(Fraction(r, b) - j for j in self.nodes if j != k)

    def weight(self, k: int, r: str, b: int) -> str:
        """SQL of the weight in double precision at the offset that the text r gives."""
        t = f"(CAST({r} AS DOUBLE) / {float(b)!r}D)"
        return "*".join([f"({float(self.coefficient(k))!r}D)", *(f"({t} - {float(j)!r}D)" for j in self.nodes if j != k)])

    def whole(self, k: int, r: str, b: int) -> str:
        """SQL of the weight times scale(b), a whole number."""
        kind = BIG if self.scale(b) * (self.n + 1) ** self.n >= 1 << 62 else "BIGINT"
        c = int(self.coefficient(k) * factorial(self.n - 1))
        return "*".join([f"CAST({c} AS {kind})", *(f"(CAST({r} AS {kind}) - CAST({j * b} AS {kind}))" for j in self.nodes if j != k)])


def lagrange_eval(samples: dict[int, Fraction], x: Fraction) -> Fraction:
    """Value at x of the polynomial through the samples."""
    return sum((v * prod((x - j) / Fraction(k - j) for j in samples if j != k) for k, v in samples.items()), Fraction(0))


def weight_table(spark: SparkSession, b: int, stencil: Stencil) -> DataFrame:
    """r, k, w of all weights of a bin; N * b rows, for small b."""
    r = spark.range(b).select(F.col("id").alias("r"))
    return r.select("r", F.inline(F.array(*[F.struct(F.lit(k).alias("k"), F.expr(stencil.weight(k, "r", b)).alias("w")) for k in stencil.nodes])))


def hat_weight(offset: Column, b: int) -> Column:
    """Weight 1 - |i|/b, the stencil M = M' = 1."""
    return F.lit(1.0) - F.abs(offset).cast("double") / F.lit(float(b))


def box_weight(offset: Column, b: int) -> Column:
    """Weight one: disjoint bins."""
    return F.lit(1.0)


def num_levels(n: int, b: int, order: int) -> int:
    """Largest number of scales with at least `order` cells at the top; one at least."""
    t = 0
    while n // b ** (t + 1) >= order:
        t += 1
    return max(1, t)
