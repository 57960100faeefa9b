"""Lagrange moment buffers in whole numbers modulo a few primes.

Interpolation weights are fractions whose denominators divide b^(N-1) (N-1)!, hence
numbers modulo any prime that divides neither. A cell held as its remainders modulo four
primes of 31 bits (16 bytes, as wide as a long decimal) doesn't grow with levels or with
b, all arithmetic stays in longs, and the answer, a whole number of less than half the
primes' product (about 2^124), is had back from its remainders exactly. So buffers of
any length are exact, where scaled decimals would overflow.

Weights are polynomials in a cell's offset r, so a bin is summed up by its remainders of
r^d times cell, d below N; the weights are applied to these sums, once a bin.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momentbuf.functions.scalars import BIG
from momentbuf.functions.weights import Stencil

#: The four largest primes below 2^31.
PRIMES = (2147483647, 2147483629, 2147483587, 2147483579)
COLUMNS = tuple(f"r{j}" for j in range(len(PRIMES)))


def coefficients(st: Stencil, b: int, m: int) -> dict[int, list[int]]:
    """For each node the weight's coefficients of r^d modulo a prime."""
    inverse = pow(b, -1, m)
    return {k: [c.numerator * pow(c.denominator, -1, m) * pow(inverse, d, m) % m for d, c in enumerate(st.polynomial(k))] for k in st.nodes}


def _powers(r: str, b: int, count: int, m: int) -> list[str]:
    out, size = ["1L"], 1
    for d in range(1, count):
        size *= b
        x = "*".join([r] * d) if size < m else f"({out[-1]} * {r} % {m}L)"
        out.append(f"({x})")
    return out


def _moment_sums(values: list[str], r: str, b: int, count: int) -> list[Column]:
    """Sums of r^d times each prime's remainder, reduced term by term so that no sum overflows."""
    return [F.expr(f"sum({v} * {p} % {m}L) % {m}L AS m{j}_{d}") for j, (v, m) in enumerate(zip(values, PRIMES, strict=True)) for d, p in enumerate(_powers(r, b, count, m))]


def _weighted(j: int, coef: list[int]) -> str:
    """A node's weighted sum of a bin modulo prime j; two products of 62 bits at most stand in one sum."""
    m = PRIMES[j]
    return "(" + " + ".join(f"m{j}_{d} * {c}L % {m}L" for d, c in enumerate(coef) if c) + f") % {m}L"


def spread(df: DataFrame, b: int, st: Stencil, limit: int, keys: tuple[str, ...], first: bool) -> DataFrame:
    """(keys,) pos and remainders of the next level's cells. first: df has whole numbers v, else remainders."""
    values = [f"pmod(v, {m}L)" for m in PRIMES] if first else list(COLUMNS)
    sums = df.groupBy(*keys, F.expr(f"pos div {b} AS bin")).agg(*_moment_sums(values, f"(pos % {b})", b, st.n))
    tables = [coefficients(st, b, m) for m in PRIMES]
    cells = ", ".join("struct(" + ", ".join([f"bin + {k} AS pos", *(f"{_weighted(j, t[k])} AS {c}" for j, (c, t) in enumerate(zip(COLUMNS, tables, strict=True)))]) + ")" for k in st.nodes)
    return sums.select(*keys, F.expr(f"inline(array({cells}))")).where(f"pos >= 0 AND pos < {limit}").groupBy(*keys, "pos").agg(*[F.expr(f"sum({c}) % {m}L AS {c}") for c, m in zip(COLUMNS, PRIMES, strict=True)])


def names(f: str) -> list[str]:
    """Columns of a function's remainders."""
    return [f"{f}_{j}" for j in range(len(PRIMES))]


def _mod(f, x: str, m: int) -> str:
    """f at x modulo a prime."""
    if not hasattr(f, "mod"):
        raise ValueError("residue mode takes functions with a modular form, as moment_poly gives; use mode 'exact' or 'double' for others")
    return f.mod(x, m)


def top_sums(fs: Mapping, pos: str) -> list[Column]:
    return [F.expr(f"sum({_mod(f, pos, m)} * ({c} % {m}L) % {m}L) AS {to}") for k, f in fs.items() for to, c, m in zip(names(k), COLUMNS, PRIMES, strict=True)]


def near_sums(near: DataFrame, by: list[str], asked: list[str], fs: Mapping, level: int, b: int, st: Stencil, counts: list[Column]) -> DataFrame:
    """(keys,) qid, remainders for each f, and counts: what a level's interpolant misses.

    near: (keys,) pos, bin, values and the ranges' columns `asked`. A bin gives the range's
    own share of f times cell, and its sums of r^d times cell, from which the samples of f
    times the weights are taken off.
    """
    g = b**level
    values = [f"pmod(v, {m}L)" for m in PRIMES] if level == 0 else [f"({c} % {m}L)" for c, m in zip(COLUMNS, PRIMES, strict=True)]
    own = [F.expr(f"sum(CASE WHEN pos * {g} BETWEEN p AND q THEN {_mod(f, f'(pos * {g})', m)} * {v} % {m}L ELSE 0L END) % {m}L AS own_{to}") for k, f in fs.items() for to, v, m in zip(names(k), values, PRIMES, strict=True)]
    rest = [F.expr(f"first({c}) AS {c}") for c in asked if c != "qid"]
    bins = near.groupBy(*by, "bin").agg(*rest, *own, *_moment_sums(values, f"(pos - bin * {b})", b, st.n), F.expr("count(*) AS rows_"))
    # Weighted sums of each node first, so that the functions only multiply them.
    tables = [coefficients(st, b, m) for m in PRIMES]
    bins = bins.selectExpr("*", *[f"{_weighted(j, t[k])} AS w{j}_{i}" for j, t in enumerate(tables) for i, k in enumerate(st.nodes)])
    sums = []
    for name, f in fs.items():
        for j, (to, m) in enumerate(zip(names(name), PRIMES, strict=True)):
            off = "".join(f" + ({m}L - CASE WHEN (bin + {k}) * {g * b} BETWEEN p AND q THEN {_mod(f, f'((bin + {k}) * {g * b})', m)} * w{j}_{i} % {m}L ELSE 0L END)" for i, k in enumerate(st.nodes))
            sums.append(F.expr(f"sum((own_{to}{off}) % {m}L) AS {to}"))
    return bins.groupBy(*by).agg(*sums, *counts)


def whole(sums: DataFrame, by: list[str], fs: list[str], wide: bool, more: list[str]) -> DataFrame:
    """by, one whole number for each f, and more: the number of least absolute value with these (unreduced) remainders, from its digits in a mixed radix."""
    big = lambda x: f"CAST('{x}' AS {BIG})"
    rows = sums
    for j, m in enumerate(PRIMES):  # digit j needs the digits before it
        cols = []
        for k in fs:
            x = f"{names(k)[j]} % {m}L"
            for i, p in enumerate(PRIMES[:j]):
                x = f"pmod({x} - d{i}_{k}, {m}L) * {pow(p, -1, m)}L % {m}L"
            cols.append(F.expr(f"{x} AS d{j}_{k}"))
        rows = rows.select("*", *cols)
    sizes = [1]
    for m in PRIMES:
        sizes.append(sizes[-1] * m)
    add = lambda k: "(" + " + ".join(f"CAST(CAST(d{j}_{k} AS {BIG}) * {big(sizes[j])} AS {BIG})" for j in range(len(PRIMES))) + ")"
    rows = rows.select(*by, *more, *[F.expr(f"CAST({add(k)} AS {BIG}) AS {k}") for k in fs])
    signed = [f"CASE WHEN {k} > {big(sizes[-1] // 2)} THEN CAST({k} - {big(sizes[-1])} AS {BIG}) ELSE {k} END" for k in fs]
    return rows.selectExpr(*by, *more, *[f"CAST({x} AS {BIG if wide else 'BIGINT'}) AS {k}" for x, k in zip(signed, fs, strict=True)])
