from collections import defaultdict

from momentbuf import experiments as E


def test_files_opened_by_a_plain_query(spark, sf):
    for x in E.disk_array(spark, sf).collect():
        assert x["equal"] and 0 < x["files_read"] <= 3 < x["files_all"] and x["rows_read"] <= (1 << 16) // 4


def test_every_update_stays_within_its_bound(spark, sf):
    rows = {(x["b"], x["N"]): x for x in E.updates_over_grid(spark, sf, n=1 << 14, count=300).collect()}
    assert all(0 < x["touched_mean"] <= x["touched_most"] <= x["bound"] for x in rows.values())
    assert rows[128, 2]["touched_mean"] < rows[128, 4]["touched_mean"] < rows[128, 8]["touched_mean"]


def test_updates_pay_for_sparse_arrays_alone(spark, sf):
    rows = {x["array"]: x for x in E.sparse_and_dense(spark, sf).collect()}
    assert rows["event_second"]["density"] < 0.01 and rows["event_second"]["updates_pay"]
    assert rows["event_value"]["density"] > 0.9 and not rows["event_value"]["updates_pay"]


def test_cells_are_the_same_for_sums_and_first_moments(spark, sf):
    cells = defaultdict(dict)
    for x in E.query_over_bin_size(spark, sf, count=40).collect():
        cells[x["b"]][x["moment"]] = (x["cells_array"], x["cells_buffer"])
    assert all(x[0] == x[1] for x in cells.values())


def test_cells_grow_with_the_order(spark, sf):
    by = defaultdict(list)
    for x in E.query_over_order(spark, sf, orders=(2, 4, 8), count=40).orderBy("levels", "N").collect():
        by[x["levels"]].append(x["cells_array"] + x["cells_buffer"])
    assert all(x == sorted(x) for x in by.values())


def test_the_last_ring_is_exact(spark, sf):
    by = defaultdict(dict)
    for x in E.progressive_errors(spark, sf).collect():
        by[x["N"]][x["ring"]] = x["mean_error"]
    for rings in by.values():
        assert rings[max(rings)] < 1e-6 * max(rings.values()) and rings[min(rings)] > 0
