"""The published size, plans that prune, updates that move nothing, and joins by equality."""

import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from momentbuf.functions import algebra as A
from momentbuf.functions.weights import Stencil, hat_weight
from momentbuf.operators import baselines as D
from momentbuf.operators import binbuf as B
from momentbuf.operators import lagrange_buffer as L
from momentbuf.operators import overlap as O
from momentbuf.operators import pyramid as P
from momentbuf.operators import residues as R
from momentbuf.operators.ranges import match, merged
from momentbuf.plans.cost import scan_metrics
from momentbuf.sources.arrays import from_rows, virtual_array
from momentbuf.sources.store import held, hold_bins, hold_lagrange, read_array, read_lagrange, write_array, write_lagrange


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("b", [128, 32])
def test_default_mode_at_the_published_length(spark, b):
    n, r = 1 << 30, random.Random(b)
    cells = {r.randrange(n): r.randrange(-900, 1000) for _ in range(1500)} | {0: 7, n - 1: 11, b: 3, b**4: -5}
    arr = from_rows(spark, sorted(cells.items()), n)
    buf = L.build_lagrange(arr, b)
    assert buf.mode == "residue" and buf.levels == (4 if b == 128 else 5)
    spans = [(0, n - 1), (0, 0), (n - 1, n - 1), (b, b**4), *(tuple(sorted((r.randrange(n), r.randrange(n)))) for _ in range(12))]
    spans += [(max(0, i - r.randrange(2 * b)), min(n - 1, i + r.randrange(b**2))) for i in list(cells)[:12]]
    ranges = spark.createDataFrame([(i, p, q) for i, (p, q) in enumerate(spans)], "qid long, p long, q long")
    got = {x["qid"]: x for x in L.query_many(arr, buf, ranges, {f"m{k}": L.moment_poly(k, "p") for k in range(4)}, wide=True).collect()}
    for i, (p, q) in enumerate(spans):
        for k in range(4):
            assert int(got[i][f"m{k}"]) == sum((x - p) ** k * v for x, v in cells.items() if p <= x <= q), (p, q, k)
    sums = {x["qid"]: x["result"] for x in L.query_lagrange(arr, buf, ranges).collect()}
    assert sums == {i: sum(v for x, v in cells.items() if p <= x <= q) for i, (p, q) in enumerate(spans)}
    with pytest.raises(Exception, match="OVERFLOW"):
        L.query_lagrange(arr, buf, ranges.where("qid = 0"), L.moment_poly(3, "p")).collect()
    with pytest.raises(ValueError):
        L.build_lagrange(arr, b, 8, mode="exact")


def test_residues_of_all_ranges_and_updates(spark):
    n = 37
    vals = [((i * 7919) % 41) - 17 for i in range(n)]
    arr = from_rows(spark, list(enumerate(vals)), n)
    buf = L.build_lagrange(arr, 3, 4, 2, mode="residue")
    r = spark.range(n).select(F.col("id").alias("p")).join(spark.range(n).select(F.col("id").alias("q")), F.col("p") <= F.col("q")).select((F.col("p") * n + F.col("q")).alias("qid"), "p", "q")
    up = spark.createDataFrame([(3, 5), (36, -4), (3, 1)], "idx long, delta long")
    new = [v + (6 if i == 3 else -4 if i == 36 else 0) for i, v in enumerate(vals)]
    for how in ("merge", "append"):
        b2 = L.update_lagrange(buf, up, how)
        for x in L.query_lagrange(B.updated(arr, up), b2, r, L.moment_poly(1, -2)).collect():
            p, q = divmod(x["qid"], n)
            assert x["result"] == sum((i + 2) * new[i] for i in range(p, q + 1))
    assert L.compacted(b2).df.count() == buf.df.count()
    assert all(p % d for p in R.PRIMES for d in range(2, 50_000))
    with pytest.raises(ValueError):
        L.query_lagrange(arr, buf, r, lambda x: F.lit(1))


def test_queries_over_files_read_only_the_ends(spark, tmp_path):
    n, b = 1 << 16, 64
    vals = spark.range(n).select(F.col("id").alias("idx"), ((F.col("id") * 7919) % 41 - 17).alias("val"))
    write_array(virtual_array(spark, n).with_df(vals), str(tmp_path / "a"), chunk=n // 16)
    arr = read_array(spark, str(tmp_path / "a"))
    ranges = spark.createDataFrame([(0, 5000, 5200), (1, 5001, 60_000)], "qid long, p long, q long")
    want = {q: sum((i * 7919) % 41 - 17 for i in range(lo, hi + 1)) for q, lo, hi in ((0, 5000, 5200), (1, 5001, 60_000))}
    lag = hold_lagrange(L.build_lagrange(arr, b, 4, 2))
    bins, pyr = hold_bins(B.build_bins(arr, A.sum_spec(), b)), P.build_pyramid(arr, A.sum_spec(), b, 2)
    pyr = replace(pyr, df=held(pyr.df))
    whole = scan_metrics(arr.df, "val")
    assert whole["files"] >= 16 and whole["rows"] == n
    for df in (L.query_lagrange(arr, lag, ranges), B.query_bins(arr, bins, ranges), P.query_pyramid(arr, pyr, ranges)):
        assert {x["qid"]: x["result"] for x in df.collect()} == want
        text = df._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
        scan = next(x for x in text.split("\n\n") if "PartitionFilters" in x and "chunk#" in x)
        assert "GreaterThanOrEqual(idx," in scan and "chunk#" in scan.split("PartitionFilters:")[1].split("\n")[0]
        read = scan_metrics(df, "val")
        assert 0 < read["files"] <= 3 and read["rows"] < n // 4
    write_lagrange(lag, str(tmp_path / "buf"))
    again = read_lagrange(spark, str(tmp_path / "buf"))
    assert (again.b, again.n, again.levels, again.mode, again.stencil) == (lag.b, lag.n, lag.levels, lag.mode, lag.stencil)
    assert {x["qid"]: x["result"] for x in L.query_lagrange(arr, again, ranges).collect()} == want


def test_updates_leave_the_buffer_where_it_lies(spark, tmp_path):
    n = 1 << 14
    arr = virtual_array(spark, n)
    lag = hold_lagrange(L.build_lagrange(arr, 16, 4, 2, "double"))
    up = spark.range(50).select((F.col("id") * 311 % n).alias("idx"), F.col("id").cast("double").alias("delta"))
    def exchanged(node, inside=False):
        """Names of scans of files below an exchange by hash."""
        name = node.nodeName()
        if name == "AdaptiveSparkPlan":
            return exchanged(node.executedPlan(), inside)
        inside = inside or (name == "Exchange" and "hashpartitioning" in node.simpleString(200))
        if name.startswith("Scan parquet"):
            return [(inside, node.output().size())]
        return [x for i in range(node.children().size()) for x in exchanged(node.children().apply(i), inside)]

    for how in ("merge", "append"):
        scans = exchanged(L.update_lagrange(lag, up, how).df._jdf.queryExecution().executedPlan())
        # A scan with values is the buffer's own; what is exchanged at most are the keys that meet the few deltas.
        assert scans and not any(inside for inside, columns in scans if columns >= 3), scans
    scans = exchanged(B.apply_updates(hold_bins(B.build_bins(arr, A.sum_spec(), 16)), up).df._jdf.queryExecution().executedPlan())
    assert scans and not any(inside for inside, columns in scans if columns >= 2), scans


def test_no_nested_loops(spark):
    n = 4096
    arr = from_rows(spark, [(i, i % 13) for i in range(0, n, 3)], n)
    r = spark.createDataFrame([(0, 5, 4000), (1, 7, 9)], "qid long, p long, q long")
    hat = lambda x: F.lit(1.0)
    over = O.build_overlap(arr, 16, 1, 1, hat_weight)
    coefs, levels = D.haar_transform(arr)
    frames = [
        B.query_bins(arr, B.build_bins(arr, A.topn_spec(3), 16), r), P.query_pyramid(arr, P.build_pyramid(arr, A.sum_spec(), 8, 2, True), r), L.query_lagrange(arr, L.build_lagrange(arr, 8), r),
        O.query_overlap(arr, over, 16, 1, 1, hat_weight, hat, r), O.query_overlap(arr, over, 16, 1, 1, hat_weight, hat, r, "candidates"), D.scan_ranges(arr, r, A.sum_spec()), D.query_haar(coefs, levels, r),
    ]
    for df in frames:
        assert "NestedLoop" not in plan_of(df) and "Cartesian" not in plan_of(df)
    a, b = ({x["qid"]: round(x["result"], 6) for x in df.collect()} for df in frames[3:5])
    assert a == b == {0: sum(i % 13 for i in range(0, n, 3) if 5 <= i <= 4000), 1: 9.0}


def test_match_and_merged(spark):
    cells = spark.range(3000).select(F.col("id").alias("at"))
    runs = [(0, 0, 2999), (1, 5, 5), (2, 100, 900), (3, 2990, 3100), (4, 64, 127)]
    df = spark.createDataFrame(runs, "qid long, lo long, hi long")
    for span, known, lengths in ((3000, None, None), (1 << 40, None, None), (3000, [1], [3000, 1, 801, 111, 64])):
        got = {x["qid"]: x["n"] for x in match(cells, "at", df, "lo", "hi", span, known, lengths).groupBy("qid").agg(F.count("*").alias("n")).collect()}
        assert got == {q: len(range(lo, min(hi, 2999) + 1)) for q, lo, hi in runs}
    import numpy as np

    assert merged(np.array([5, 1, 20, 9]), np.array([8, 3, 25, 9]), 32) == [(1, 3), (5, 9), (20, 25)]
    assert merged(np.array([0, 10, 30]), np.array([1, 11, 31]), 2) == [(0, 11), (30, 31)]


def test_large_batches_are_joined_by_exchange(spark, monkeypatch):
    from momentbuf.operators import ranges as X

    monkeypatch.setattr(X, "BATCH", 5)
    monkeypatch.setattr(B, "BATCH", 5)
    n = 300
    arr = from_rows(spark, [(i, i % 7) for i in range(n)], n)
    r = spark.range(40).select(F.col("id").alias("qid"), F.col("id").alias("p"), (F.col("id") * 6 + 20).alias("q"))
    want = {i: sum(x % 7 for x in range(i, i * 6 + 21)) for i in range(40)}
    for df in (L.query_lagrange(arr, L.build_lagrange(arr, 4), r), B.query_bins(arr, B.build_bins(arr, A.sum_spec(), 8), r), P.query_pyramid(arr, P.build_pyramid(arr, A.sum_spec(), 4, 2, True), r), D.scan_ranges(arr, r, A.sum_spec())):
        assert {x["qid"]: x["result"] for x in df.collect()} == want
    up = spark.range(20).select((F.col("id") * 7).alias("idx"), F.lit(2).cast("long").alias("delta"))
    new = L.update_lagrange(L.build_lagrange(arr, 4), up)
    assert {x["qid"]: x["result"] for x in L.query_lagrange(B.updated(arr, up), new, r).collect()} == {i: want[i] + 2 * sum(7 * j in range(i, i * 6 + 21) for j in range(20)) for i in want}


def test_stencil_polynomials():
    from fractions import Fraction

    for n in (2, 3, 4, 8):
        st = Stencil.of(n)
        for k in st.nodes:
            for r in range(5):
                assert sum(c * Fraction(r, 5) ** d for d, c in enumerate(st.polynomial(k))) == st.exact(k, r, 5)
