"""Choice of a method for a range aggregate, and the frames that carry it out."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from momentbuf.functions.algebra import AggSpec
from momentbuf.operators.baselines import query_prefix, scan_ranges
from momentbuf.operators.binbuf import BinBuffer, query_bins
from momentbuf.operators.lagrange_buffer import LagrangeBuffer, moment_poly, query_lagrange
from momentbuf.operators.pyramid import PyramidBuffer, query_pyramid
from momentbuf.plans.cost import expected_cells
from momentbuf.sources.arrays import IndexedArray


@dataclass
class Available:
    """Buffers there are for an array."""

    bins: BinBuffer | None = None
    pyramid: PyramidBuffer | None = None
    lagrange: LagrangeBuffer | None = None
    prefix: DataFrame | None = None


def choose_plan(spec: AggSpec, have: Available, n: int, length: int) -> str:
    """The method that reads fewest cells among those that can answer: linear moments below N from the Lagrange buffer, any spec from its own bins or pyramid, sums from prefixes, anything by a scan."""
    cost = {"scan": float(length)}
    if have.bins is not None and have.bins.spec.name == spec.name:
        cost["bins"] = expected_cells(n, have.bins.b, 1, 1, length)["bins"]
    if have.pyramid is not None and have.pyramid.spec.name == spec.name:
        cost["pyramid"] = expected_cells(n, have.pyramid.b, 1, have.pyramid.levels, length)["pyramid"]
    order = 0 if spec.name == "sum" else spec.order
    if have.lagrange is not None and 0 <= order < have.lagrange.stencil.n and spec.name in ("sum", f"moment{order}"):
        lag = have.lagrange
        cost["lagrange"] = expected_cells(n, lag.b, lag.stencil.n, lag.levels, length)["lagrange"]
    if have.prefix is not None and spec.name == "sum":
        cost["prefix"] = 2.0
    return min(cost, key=lambda k: (cost[k], k))


def answer(spec: AggSpec, arr: IndexedArray, have: Available, ranges: DataFrame, length: int | None = None) -> DataFrame:
    """qid, result by the chosen method (length: typical length of the ranges)."""
    how = choose_plan(spec, have, arr.n, length or arr.n // 3)
    if how == "bins":
        return query_bins(arr, have.bins, ranges)
    if how == "pyramid":
        return query_pyramid(arr, have.pyramid, ranges)
    if how == "lagrange":
        return query_lagrange(arr, have.lagrange, ranges, moment_poly(max(0, spec.order), "p"))
    if how == "prefix":
        return query_prefix(have.prefix, ranges)
    return scan_ranges(arr, ranges, spec)
