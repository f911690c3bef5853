"""Benchmark items without an id."""

from pairdict.llm import decontaminate


def test_item_without_id(spark):
    docs = spark.createDataFrame([(1, "before one two three after"), (2, "nothing")], "doc_id long, text string")
    bench = spark.createDataFrame([(None, "one two three"), (None, "four"), (7, "three")], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.scan(docs, bench, block_bytes=5).collect()}
    assert got[1].n_hit == 3 and got[1]["items"] == ["7"] and "two" not in got[1].text
    assert got[2].n_hit == 0 and got[2]["items"] == []
