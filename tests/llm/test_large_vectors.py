"""Vectors with large components."""

import pytest

from pairdict.llm import topk


def test_large_components(spark):
    big = float(2**41)
    rows = [(0, [1.0, 2.0]), (1, [big, 0.0]), (2, [3.0, 1.0]), (20, [0.5, 5.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = []
    for q, x in rows:
        if q % 20 == 0:
            best = sorted((-sum(int(64 * a) * int(64 * b) for a, b in zip(x, y, strict=True)), c) for c, y in rows if c != q)
            want += [(q, rank, c, -s) for rank, (s, c) in enumerate(best, 1)]
    assert sorted(map(tuple, topk.top_k(df).select("query_id", "rank", "vec_id", "score").collect())) == sorted(want)


def test_overflow_is_an_error(spark):
    for x in (float(2**27), 1e300):
        df = spark.createDataFrame([(0, [x]), (1, [x])], "vec_id long, embedding array<double>")
        with pytest.raises(ValueError):
            topk.top_k(df)
