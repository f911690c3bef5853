"""Queries against DuckDB on the smallest tables, and files read with a schema."""

from collections import Counter

import duckdb
import pytest
from pyspark.sql import functions as F

from pairdict import queries, sources
from tests.conftest import SF

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SQL = queries.oracle_sql()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def plain(v):
    return f"{v:.9g}" if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, duck, name):
    got = queries.queries()[name](spark, SF)
    want = duck.sql(SQL[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    a = Counter(tuple(plain(r[c]) for c in columns) for r in got.collect())
    at = [want.columns.index(c) for c in columns]
    assert a == Counter(tuple(plain(r[i]) for i in at) for r in want.fetchall())


def test_every_query_has_a_name_once():
    assert set(SQL) <= set(queries.queries()) and len(queries.queries()) > 100


def test_files(spark, tmp_path):
    (tmp_path / "a.csv").write_text("k,v\n1,x\nbad,y\n")
    (tmp_path / "a.json").write_text('{"k": 1, "v": "x"}\n{"k": \n')
    csv = sources.read_delimited(spark, str(tmp_path / "a.csv"), "k int, v string").cache()
    assert csv.where(F.col("_malformed").isNotNull()).count() == 1 and csv.where("k = 1").first().v == "x"
    assert sources.read_json(spark, str(tmp_path / "a.json"), "k int, v string").cache().where(F.col("_malformed").isNotNull()).count() == 1
    assert sources.read_text(spark, str(tmp_path / "a.csv")).count() == 3
    df = spark.range(1000).select(F.col("id"), F.lit("the same text").alias("v"))
    assert sources.parquet_bytes(df, str(tmp_path / "z"), "zstd") <= sources.parquet_bytes(df, str(tmp_path / "n"), "uncompressed")


def test_whole_results_of_streams_do_not_pass_the_driver(spark):
    """Spark's memory sink holds all rows of a stream's result in the driver."""
    for name in ("stream_sessions", "stream_ratio_tumbling", "stream_ratio_sliding"):
        got = queries.queries()[name](spark, SF)
        assert got.inputFiles() and got.count() > 0


@pytest.mark.parametrize("name", ["o13_grid", "o30_recursion"])
def test_reads_a_given_table(spark, name):
    assert "parquet" in queries.queries()[name](spark, SF)._jdf.queryExecution().toString()
