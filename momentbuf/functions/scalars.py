"""Scalar expressions shared by the operators; all of them stay in generated code."""

from __future__ import annotations

from fractions import Fraction
from math import comb, lcm

from pyspark.sql import Column
from pyspark.sql import functions as F

BIG = "decimal(38,0)"


def power(x: Column, k: int) -> Column:
    """x to a small whole power by multiplication, so whole numbers stay whole."""
    if k == 0:
        return F.lit(1).cast("long")
    out = x
    for _ in range(k - 1):
        out = out * x
    return out


def poly_eval(coef: Column, x: Column) -> Column:
    """Value of the polynomial whose coefficients (lowest first) an array column holds, by Horner's rule."""
    return F.aggregate(F.reverse(coef), F.lit(0.0), lambda acc, c: acc * x + c)


def binomial_shift(moments: list[Column], distance: Column) -> list[Column]:
    """Moments about an origin that lies `distance` before the old one: M_k = sum_j C(k,j) distance^(k-j) m_j."""
    return [sum((F.lit(comb(k, j)) * power(distance, k - j) * moments[j] for j in range(k)), F.lit(0).cast("long")) + moments[k] for k in range(len(moments))]


def index_of_ts(ts: str, origin: str, unit: str = "MINUTE") -> Column:
    """Number of whole units between an origin and a column of timestamps without zone."""
    return F.expr(f"timestampdiff({unit}, TIMESTAMP_NTZ'{origin}', {ts})")


def ts_of_index(index: str, origin: str, unit: str = "MINUTE") -> Column:
    return F.expr(f"timestampadd({unit}, {index}, TIMESTAMP_NTZ'{origin}')")


def word_count(text: Column) -> Column:
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != ""))


def strip_html(html: Column) -> Column:
    return F.regexp_replace(html, "<[^>]*>", " ")


def json_number(column: Column, path: str) -> Column:
    return F.get_json_object(column, path).cast("long")


def array_moment(array: Column, p: int, q: int, c: int, k: int) -> Column:
    """Local moment of an in-row array (positions from 0)."""
    part = F.slice(array, p + 1, q - p + 1)
    terms = F.transform(part, lambda x, i: power((i + p - c).cast("double"), k).cast("double") * x.cast("double") if k else x.cast("double"))
    return F.aggregate(terms, F.lit(0.0), lambda a, x: a + x)


def bernoulli_sums(k: int) -> list[Fraction]:
    """Coefficients (lowest first) of the polynomial S with S(m) = sum of i^k for i < m, solved from its own differences."""
    coef = [Fraction(0)] * (k + 2)
    # S(m+1) - S(m) = m^k: match powers from the top down.
    for d in range(k, -1, -1):
        have = sum(coef[j] * comb(j, d) for j in range(d + 2, k + 2))
        coef[d + 1] = (Fraction(int(d == k)) - have) / (d + 1)
    return coef


def power_sum(k: int, p: Column, q: Column) -> Column:
    """Sum of i^k for p <= i <= q in constant time, exact in whole numbers."""
    coef = bernoulli_sums(k)
    base = lcm(*(c.denominator for c in coef))

    def at(m: Column) -> Column:
        m = m.cast(BIG)
        out = F.lit(0).cast(BIG)
        for c in reversed(coef):
            out = (out * m + F.lit(int(c * base)).cast(BIG)).cast(BIG)
        return out

    return ((at(q + 1) - at(p)) / F.lit(base).cast(BIG)).cast("long")
