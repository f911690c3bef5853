"""Offsets past the first 2,000 blocks keep their rows."""

from pairdict import queries
from tests.conftest import SF


def test_far_offsets(spark, monkeypatch):
    starts = spark.createDataFrame([(1, 0), (2, 65_536), (3, 131_072_000), (4, 500_000_000)], "key long, start long")
    monkeypatch.setattr(queries.blocks, "layout", lambda df: starts)
    got = sorted(map(tuple, queries.range_join(spark, SF).select("key", "block_id").collect()))
    assert got == [(1, 0), (2, 1), (3, 2000), (4, 500_000_000 // 65_536)]
    monkeypatch.setattr(queries.blocks, "layout", lambda df: starts.where("false"))
    assert queries.range_join(spark, SF).count() == 0
