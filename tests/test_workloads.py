import re

import duckdb
import pytest

from momentbuf import workloads as W
from tests.oracle import connect, rows


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(W.QUERIES))
def test_query(spark, sf, con, name):
    got = W.QUERIES[name](spark, sf).toPandas()
    assert len(got.columns) == len(set(got.columns))
    if name in W.ORACLES:
        want = con.sql(W.ORACLES[name]).df()
        assert sorted(got.columns) == sorted(want.columns)
        assert rows(got) == rows(want)
    else:
        assert len(got)


def test_flagship(spark, sf):
    assert W.flagship(spark, sf).count() > 100


def test_text_measures_of_every_document(spark, sf, tmp_path):
    texts = ["ein Wort", "two  words", "", None, " \t\n ", "a\x0bb\x0cc\r\nd", "a\u00a0b \u3000 c", "\U0001f600 é ", "x"]
    docs = [(i - 2, t, lang) for i, (t, lang) in enumerate(zip(texts, ["de", "en", "fr", None, "es", None, "en", "de", "fr"]))]
    spark.createDataFrame(docs, "doc_id long, text string, lang string").write.parquet(str(tmp_path / "documents.parquet"))
    given = [tuple(x) for x in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    for d, rows_in in ((str(tmp_path), [x[:2] for x in docs]), (sf, given)):
        got = [tuple(x) for x in W.QUERIES["text_measures"](spark, d).select("doc_id", "chars", "words").collect()]
        want = [(i, None, None) if t is None else (i, len(t), len(re.findall(r"[^ \t\n\x0b\x0c\r]+", t))) for i, t in rows_in]
        assert sorted(got) == sorted(want)


@pytest.mark.parametrize("name", ["stream_session", "stream_tumbling", "stream_stateful_buffer"])
def test_streams_leave_files_not_driver_memory(spark, sf, name):
    assert W.QUERIES[name](spark, sf).inputFiles()


def test_second_moments_whose_parts_leave_bigint(spark, tmp_path):
    """Terms of a whole bin and of a fragment lie beyond 2^63, their sum doesn't; one that does raises, and is had in full from the bins."""
    from momentbuf.functions import algebra as A
    from momentbuf.operators import binbuf as B
    from momentbuf.sources.fixtures import fixture

    at = 2_900_000_000
    for name, back in (("fits", -0.02), ("beyond", 0.0)):
        (tmp_path / name).mkdir()
        spark.createDataFrame([(0, 0.0), (at, back), (at + 1000, 0.03)], "event_id long, value double").write.parquet(str(tmp_path / name / "events.parquet"))
    d = str(tmp_path / "fits")
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{d}/events.parquet/*.parquet'")
    got = W.QUERIES["bin_query_moment2"](spark, d).toPandas()
    assert rows(got) == rows(con.sql(W.ORACLES["bin_query_moment2"]).df())
    assert got.set_index("qid")["result"][W.COUNT] == 3 * (at + 1000) ** 2 - 2 * at**2
    d = str(tmp_path / "beyond")
    with pytest.raises(Exception, match="OVERFLOW"):
        W.QUERIES["bin_query_moment2"](spark, d).collect()
    arr = fixture(spark, d, "event_value")
    whole = spark.createDataFrame([(0, 0, arr.n - 1)], "qid long, p long, q long")
    assert int(B.query_bins(arr, B.build_bins(arr, A.moment_spec(2, exact=True), 32), whole).first()["result"]) == 3 * (at + 1000) ** 2
