"""Brute force over every range of small arrays, invariants of weights, updates, worked examples, plans."""

from decimal import Decimal
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from momentbuf import workloads as W
from momentbuf.functions import algebra as A
from momentbuf.functions.weights import Stencil, lagrange_eval, num_levels
from momentbuf.operators import binbuf as B
from momentbuf.operators import lagrange_buffer as L
from momentbuf.operators import moments as M
from momentbuf.operators import overlap as O
from momentbuf.operators import progressive as G
from momentbuf.operators import pyramid as P
from momentbuf.operators.ranges import split_to_bins, validate_ranges
from momentbuf.plans.cost import array_free_ranges, fit_shape
from momentbuf.plans.planner import Available, choose_plan
from momentbuf.sources.arrays import from_rows, make_array, validate, virtual_array
from momentbuf.sources.store import append_delta, assert_clustered, compact, read_array, read_buffer, read_deltas, write_array, write_buffer


def values(n):
    return [((i * 7919) % 41) - 17 for i in range(n)]


def small(spark, n, skip=lambda i: False):
    return from_rows(spark, [(i, v) for i, v in enumerate(values(n)) if not skip(i)], n), [0 if skip(i) else v for i, v in enumerate(values(n))]


def every_range(spark, n):
    return spark.range(n).select(F.col("id").alias("p")).join(spark.range(n).select(F.col("id").alias("q")), F.col("p") <= F.col("q")).select((F.col("p") * n + F.col("q")).alias("qid"), "p", "q")


def check_all(df, n, f):
    got = {r["qid"]: r["result"] for r in df.collect()}
    assert len(got) == n * (n + 1) // 2
    bad = [(p, q) for p in range(n) for q in range(p, n) if got[p * n + q] != f(p, q)]
    assert not bad, bad[:5]


@pytest.mark.parametrize("n,b,order,levels", [(37, 4, 4, 1), (40, 2, 4, 3), (41, 3, 2, 2), (33, 4, 3, 2), (40, 4, 6, 1), (9, 16, 4, 1), (36, 2, 2, 4), (32, 4, 4, 3)])
def test_lagrange_all_ranges(spark, n, b, order, levels):
    arr, a = small(spark, n, lambda i: i % 5 == 2)
    buf = L.build_lagrange(arr, b, order, levels)
    r = every_range(spark, n)
    k = min(order - 1, 2)
    check_all(L.query_lagrange(arr, buf, r, L.moment_poly(k, "p")), n, lambda p, q: sum((i - p) ** k * a[i] for i in range(p, q + 1)))


@pytest.mark.parametrize("M,Mp", [(2, 1), (1, 2), (0, 1), (0, 2), (3, 1)])
def test_uneven_stencils(spark, M, Mp):
    n = 29
    arr, a = small(spark, n)
    buf = L.build_lagrange(arr, 4, levels=2, stencil=Stencil(M, Mp))
    check_all(L.query_lagrange(arr, buf, every_range(spark, n)), n, lambda p, q: sum(a[p : q + 1]))


def test_stencil_without_node_zero_is_rejected():
    with pytest.raises(ValueError):
        Stencil(2, 0)


@pytest.mark.parametrize("n,b,levels,inplace", [(37, 3, 2, False), (37, 3, 2, True), (40, 2, 4, True), (16, 4, 1, False)])
def test_pyramid_all_ranges(spark, n, b, levels, inplace):
    arr, a = small(spark, n)
    pyr = P.build_pyramid(arr, A.moment_spec(1), b, levels, inplace)
    check_all(P.query_pyramid(arr, pyr, every_range(spark, n)), n, lambda p, q: sum((i - p) * a[i] for i in range(p, q + 1)))


@pytest.mark.parametrize("b", [1, 4, 7, 64])
def test_bins_all_ranges(spark, b):
    n = 33
    arr, a = small(spark, n)
    check_all(B.query_bins(arr, B.build_bins(arr, A.max_spec(), b), every_range(spark, n)), n, lambda p, q: max(a[p : q + 1]))


@pytest.mark.parametrize("order", [2, 3, 4, 5, 8])
def test_weights(order):
    st = Stencil.of(order)
    for b in (3, 8):
        for r in range(b):
            w = {k: st.exact(k, r, b) for k in st.nodes}
            assert sum(w.values()) == 1
            for d in range(order):
                assert sum(w[k] * k**d for k in st.nodes) == Fraction(r, b) ** d
            if r == 0:
                assert [k for k in st.nodes if w[k]] == [0]
            assert all((w[k] * st.scale(b)).denominator == 1 for k in st.nodes)
    assert sum(st.exact(k, 1, 3) * k**order for k in st.nodes) != Fraction(1, 3) ** order
    assert lagrange_eval({k: Fraction(k) for k in st.nodes}, Fraction(1, 3)) == Fraction(1, 3) or order < 2


def test_hierarchy_needs_no_cells_outside_and_extra_levels_agree(spark):
    n = 50
    arr, a = small(spark, n)
    r = every_range(spark, n).where("qid % 7 = 0")
    want = {p * n + q: sum(a[p : q + 1]) for p in range(n) for q in range(p, n)}
    for levels in (1, 2, 3, 4):
        got = L.query_lagrange(arr, L.build_lagrange(arr, 3, 4, levels), r).collect()
        assert all(want[x["qid"]] == x["result"] for x in got)


def test_update_equals_rebuild_and_touches_few_cells(spark):
    n = 96
    arr, _ = small(spark, n)
    u = spark.createDataFrame([(0, 5), (95, -3), (8, 2), (8, 2), (31, 7), (32, 9)], "idx long, delta long")
    buf = L.update_lagrange(L.build_lagrange(arr, 4, 4, 2), u)
    new = L.build_lagrange(B.updated(arr, u), 4, 4, 2)
    assert buf.df.exceptAll(new.df).isEmpty() and new.df.exceptAll(buf.df).isEmpty()
    for j in range(0, 96, 5):
        cells = {(x["level"], x["parent"]) for x in L.update_dag(spark, j, 2, Stencil.of(4), 3, n).collect()}
        assert all(sum(lv == x for x, _ in cells) <= 8 for lv in (1, 2, 3))


def test_inplace_refuses_max_and_parts(spark):
    arr, _ = small(spark, 20)
    with pytest.raises(ValueError):
        P.build_pyramid(arr, A.max_spec(), 2, 2, inplace=True)
    with pytest.raises(ValueError):
        A.max_spec().unit(F.lit(0))


def test_residual_identity_for_any_function(spark):
    n = 40
    arr, a = small(spark, n)
    f = lambda x: F.pow(F.lit(1.1), x) + F.when(F.pmod(x, F.lit(3)) == 0, 2.0).otherwise(0.0)
    from momentbuf.functions.weights import hat_weight

    r = every_range(spark, n).where("qid % 11 = 0")
    got = O.query_overlap(arr, O.build_overlap(arr, 4, 1, 1, hat_weight), 4, 1, 1, hat_weight, f, r).collect()
    g = lambda i: 1.1**i + (2.0 if i % 3 == 0 else 0.0)
    for x in got:
        p, q = divmod(x["qid"], n)
        assert x["result"] == pytest.approx(sum(g(i) * a[i] for i in range(p, q + 1)), abs=1e-6)
    assert O.check_edge_condition(4, 1, 1, lambda i: max(0.0, 1 - abs(i) / 4))
    assert not O.check_edge_condition(4, 1, 1, lambda i: 1.0)


def test_guard_cells_keep_the_sum(spark):
    from momentbuf.functions.weights import hat_weight

    arr, a = small(spark, 30)
    assert O.build_overlap(arr, 4, 1, 1, hat_weight, guard=True).agg(F.sum("v")).first()[0] == pytest.approx(sum(a))


def test_progressive_is_exact_with_all_bins_and_within_its_bound(spark):
    n = 64
    arr, a = small(spark, n)
    buf = L.build_lagrange(arr, 8, 4, 1, "double")
    r = every_range(spark, n).where("qid % 29 = 0")
    for x in G.progressive(arr, buf, r, kappa=25.0).collect():
        p, q = divmod(x["qid"], n)
        want = sum(a[p : q + 1])
        assert abs(x["estimate"] - want) <= (x["bound"] if x["ring"] < 4 else 1e-6)


def test_reported_shares_and_levels():
    s = G.error_share(4, 1024, 1)
    assert s["energy"] > 0.94 and 0.85 < s["sup"] < 0.9
    assert 0.96 < G.error_share(16, 64, 5)["sup"] < 0.98
    assert [num_levels(1 << 30, b, 4) for b in (32, 128, 1024, 1 << 15, 1 << 20)] == [5, 4, 2, 1, 1]
    assert array_free_ranges(64, 2) == (528, 496)
    a, b = fit_shape([2, 4, 8, 16], [268 * x + 450 for x in (2, 4, 8, 16)], [lambda x: x, lambda x: 1.0])
    assert (round(a), round(b)) == (268, 450)


def test_split_and_validation(spark):
    r = spark.createDataFrame([(0, 0, 7), (1, 3, 3), (2, 4, 7), (3, 2, 9), (4, 3, 4)], "qid long, p long, q long")
    frags, mid = split_to_bins(r, 4)
    f = {(x["qid"], x["lo"], x["hi"]) for x in frags.collect()}
    assert f == {(1, 3, 3), (3, 2, 3), (3, 8, 9), (4, 3, 3), (4, 4, 4)}
    assert {(x["qid"], x["first"], x["last"]) for x in mid.collect()} == {(0, 0, 1), (2, 1, 1), (3, 1, 1)}
    e = validate_ranges(spark.createDataFrame([(0, -5, 3), (1, 9, 4)], "qid long, p long, q long"), 8).collect()
    assert [(x["p"], x["q"], x["empty"]) for x in e] == [(0, 3, False), (9, 4, True)]


def test_empty_zero_and_bad_arrays(spark):
    r = spark.createDataFrame([(0, 0, 4)], "qid long, p long, q long")
    none = from_rows(spark, [], 5)
    assert L.query_lagrange(none, L.build_lagrange(none, 2, 4, 1), r).first()["result"] == 0
    assert B.query_bins(none, B.build_bins(none, A.sum_spec(), 2), r).first()["result"] == 0
    for rows in ([(0, 1), (0, 2)], [(9, 1)], [(-1, 1)]):
        with pytest.raises(ValueError):
            validate(from_rows(spark, rows, 5))
    df = spark.createDataFrame([(None, 3), (1, None), (1, 4), (1, 5)], "i long, v long")
    assert [tuple(x) for x in make_array(df, F.col("i"), F.col("v")).df.collect()] == [(1, 9)]


def test_store_round_trips(spark, tmp_path):
    arr, _ = small(spark, 200)
    write_array(arr, f"{tmp_path}/a", 64)
    back = read_array(spark, f"{tmp_path}/a")
    assert back.n == 200 and back.df.exceptAll(arr.df.select("idx", "val")).isEmpty()
    part = read_array(spark, f"{tmp_path}/a", 70, 90).df
    assert part.count() == 21
    plan = part._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(chunk" in plan and "GreaterThanOrEqual(idx,70)" in plan
    assert assert_clustered(spark.read.parquet(f"{tmp_path}/a/cells")).isEmpty()
    buf = L.build_lagrange(arr, 8, 4, 1)
    write_buffer(buf.df, f"{tmp_path}/b", n=200, b=8)
    df, meta = read_buffer(spark, f"{tmp_path}/b")
    assert meta["b"] == "8" and df.count() == buf.df.count()
    for batch in (1, 1, 2):
        append_delta(spark.createDataFrame([(0, 1)], "cell long, v long"), f"{tmp_path}/log", batch)
    assert compact(None, read_deltas(spark, f"{tmp_path}/log"), ["cell"], "v").first()["v"] == 2


def test_plans(spark):
    arr, r = virtual_array(spark, 4096), spark.createDataFrame([(0, 5, 4000)], "qid long, p long, q long")
    plan = L.query_lagrange(arr, L.build_lagrange(arr, 16, 4, 1, "double"), r)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan and "NestedLoop" not in plan and "EvalPython" not in plan
    have = Available(bins=B.BinBuffer(arr.df, 64, 4096, A.sum_spec()))
    assert choose_plan(A.sum_spec(), have, 4096, 2000) == "bins" and choose_plan(A.sum_spec(), have, 4096, 50) == "scan" and choose_plan(A.max_spec(), have, 4096, 2000) == "scan"


def test_virtual_source_pushes_bounds(spark):
    from momentbuf.sources.virtual import register

    register(spark)
    df = spark.read.format("virtual_array").option("n", 1000).option("partitions", 4).load().where("idx >= 100 and idx < 300")
    assert df.count() == 200 and df.agg(F.min("idx")).first()[0] == 100


def test_exact_answers_beyond_longs(spark):
    n, top = 40, 3 * 10**18
    arr = make_array(spark.range(n).selectExpr("id", f"CAST({top} + id AS DECIMAL(38,0)) AS v"), F.col("id"), F.col("v"), n, unique=True)
    r = spark.createDataFrame([(0, 0, n - 1), (1, 7, 8)], "qid long, p long, q long")
    buf = L.build_lagrange(arr, 4, 4, 2, "exact")
    want = {0: sum(top + i for i in range(n)), 1: 2 * top + 15}
    assert {x["qid"]: int(x["result"]) for x in L.query_lagrange(arr, buf, r, wide=True).collect()} == want
    with pytest.raises(Exception, match="CAST_OVERFLOW|out of range|OVERFLOW"):
        L.query_lagrange(arr, buf, r).collect()


def test_segments_of_values_whose_squares_outgrow_longs(spark):
    level = [10**10 * (1 if i < 20 else 5) for i in range(48)]
    arr = from_rows(spark, list(enumerate(level)), 48)
    sq = W._squares(arr)
    got = M.segment(arr, L.build_lagrange(arr, 8, 4, 1), L.build_lagrange(sq, 8, 4, 1), sq, 2, tries=2)
    assert [x[:2] for x in got] == [(0, 19), (20, 47)] and all(x[2] < 1e-9 * sum(v * v for v in level) for x in got)


def test_line_through_moments_near_the_end_of_longs(spark):
    m = spark.createDataFrame([(0, 0, 2499, 10**16, 5 * 10**18), (1, 3, 6, 10, 20), (2, 5, 5, 7, 0)], "qid long, p long, q long, m0 long, m1 long")
    got = {x["qid"]: (x["intercept"], x["slope"]) for x in M.fit_line(m).collect()}
    for qid, n, m0, m1 in ((0, 2500, 10**16, 5 * 10**18), (1, 4, 10, 20)):
        s1, s2 = sum(range(n)), sum(i * i for i in range(n))
        det = n * s2 - s1 * s1
        assert got[qid] == pytest.approx((float(Fraction(s2 * m0 - s1 * m1, det)), float(Fraction(n * m1 - s1 * m0, det))), rel=1e-14)
    assert got[2][1] is None


def test_tabulated_ends_beyond_doubles(spark):
    n, top = 20, 2**54
    a = [top + 1 + i % 3 for i in range(n)]
    arr = from_rows(spark, list(enumerate(a)), n)
    r = every_range(spark, n).selectExpr("*", "0 AS c0", "4 AS c1")
    arr = arr.with_df(arr.df.withColumn("val", F.col("val").cast("decimal(38,0)")))
    got = L.query_tabulated(arr, L.build_lagrange(arr, 4, 4, 1, "exact"), r, L.endpoint_table(spark, 4, Stencil.of(4), "exact"), ["c0", "c1"])
    check_all(got, n, lambda p, q: sum((i - p) * a[i] for i in range(p, q + 1)))


@pytest.mark.parametrize("scan", ["full", "candidates"])
def test_hats_beyond_doubles(spark, scan):
    from momentbuf.functions.weights import hat_weight

    n, top = 20, 2**54
    a = [top + 1 + i % 3 for i in range(n)]
    arr = from_rows(spark, list(enumerate(a)), n)
    buf = O.build_overlap(arr, 4, 1, 1, hat_weight, scale=4)
    got = O.query_overlap(arr, buf, 4, 1, 1, hat_weight, lambda x: x - F.col("p"), every_range(spark, n), scan, scale=4)
    check_all(got, n, lambda p, q: sum((i - p) * a[i] for i in range(p, q + 1)))


def test_rectangles_beyond_doubles(spark):
    a = {(i, j): 2**53 + 1 + (3 * i + j) % 5 for i in range(13) for j in range(9)}
    cells = spark.createDataFrame([(*k, v) for k, v in a.items()], "i0 long, i1 long, val long")
    rects = [(0, 0, 12, 0, 8), (1, 2, 11, 1, 6), (2, 4, 4, 4, 4), (3, 0, 3, 5, 8)]
    got = {x["qid"]: (x["total"], x["m1"]) for x in M.rect_moments(cells, spark.createDataFrame(rects, "qid long, p0 long, q0 long, p1 long, q1 long"), 4).collect()}
    for qid, p0, q0, p1, q1 in rects:
        held = [(i, v) for (i, j), v in a.items() if p0 <= i <= q0 and p1 <= j <= q1]
        assert got[qid] == (sum(v for _, v in held), sum(i * v for i, v in held))


def test_quadratic_far_above_its_noise(spark):
    """Exact moments of a parabola on a base of 10^12 over 43,200 cells give its coefficients and its whole energy."""
    n, c = 43_200, (10**12, 3, -2)
    y = [c[0] + c[1] * i + c[2] * i * i for i in range(n)]
    ms = [sum(v * i**k for i, v in enumerate(y)) for k in range(3)]
    m = spark.createDataFrame([(0, 0, n - 1, *map(Decimal, ms))], "qid long, p long, q long, m0 decimal(38,0), m1 decimal(38,0), m2 decimal(38,0)")
    got = M.fit_poly(m, 2).first()
    want = [c[0], c[1] * n, c[2] * n * n]
    assert all(abs(g - w) < 0.004 for g, w in zip(got["coef"], want)), got["coef"]
    assert got["explained"] == pytest.approx(float(sum(v * v for v in y)), rel=1e-15)


def test_fit_whose_second_moment_outgrows_longs(spark):
    arr = make_array(spark.range(4000).selectExpr("id", "CAST(1000000000 + 7 * id AS BIGINT) AS v"), F.col("id"), F.col("v"), 4000, unique=True)
    r = spark.createDataFrame([(0, 0, 3999)], "qid long, p long, q long")
    m = M.moments_of_ranges(arr, L.build_lagrange(arr, 32, 4, 2), r, 2, wide=True).join(r, "qid")
    assert m.first()["m2"] > 2**63
    assert M.fit_poly(m, 2).first()["coef"] == pytest.approx([1e9, 28_000.0, 0.0], abs=1e-3)


def test_edges_of_many_updates_are_those_of_each(spark):
    js, st = [0, 7, 16, 41, 63], Stencil.of(4)
    got = [tuple(x) for x in L.update_edges(spark.createDataFrame([(j,) for j in js], "j long"), 2, st, 3, 64).collect()]
    assert len(got) == len(set(got)) and set(got) == {tuple(x) for j in js for x in L.update_dag(spark, j, 2, st, 3, 64).collect()}
