"""Corpora: DataFrames of (key long, value string) over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _plain(name: str, key: str, value: str):
    return lambda spark, d: table(spark, d, name).select(F.expr(key).cast("long").alias("key"), F.expr(value).alias("value"))


def _pieces(name: str, key: str, parts: str):
    def load(spark: SparkSession, d: str) -> DataFrame:
        rows = table(spark, d, name).select(F.expr(key).alias("base"), F.posexplode(F.split("text", parts)).alias("pos", "value"))
        return rows.where("value <> ''").select((F.col("base") + F.col("pos")).cast("long").alias("key"), "value")

    return load


CORPORA = {
    "reviews": _plain("conversations", "conv_id * 1000 + turn", "text"),
    "reviews_xl": _plain("documents", "doc_id", "text"),
    "titles": _plain("part", "p_partkey", "concat_ws(' ', p_brand, p_type, p_name, 'size', p_size)"),
    "headlines": _pieces("documents", "doc_id * 1048576", "[.,\n]+"),
    "tweets": _pieces("conversations", "(conv_id * 1000 + turn) * 4096", r"\. "),
    "urls": _plain("pages", "page_id", "url"),
    "ids": _plain("customer", "c_custkey", "c_name"),
    "html": _plain("pages", "page_id", "html"),
    "props": _plain("events", "event_id", "props"),
    "nations": _plain("nation", "n_nationkey", "n_name"),
    "enums": _plain("orders", "o_orderkey", "o_orderpriority"),
}

#: Bits of an entry number by corpus at sf0.01 and below; larger inputs take `suggest_bits`.
BITS = {"nations": 9, "titles": 10, "reviews": 11, "reviews_xl": 13, "headlines": 13, "tweets": 11, "urls": 9, "ids": 9, "html": 12, "props": 9, "enums": 9}
FIVE = ("reviews", "titles", "headlines", "tweets", "urls")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(key, value) of a corpus; only the columns it needs are scanned."""
    return CORPORA[name](spark, sf_dir)


def size_bytes(corpus: DataFrame) -> int:
    return int(corpus.agg(F.sum(F.octet_length("value"))).first()[0] or 0)


def summary(spark: SparkSession, sf_dir: str, names=tuple(CORPORA)) -> DataFrame:
    """Rows, bytes and mean length of each corpus."""
    parts = [
        load(spark, sf_dir, n).agg(F.lit(n).alias("corpus"), F.count("value").alias("n_rows"), F.coalesce(F.sum(F.octet_length("value")), F.lit(0)).alias("n_bytes"), F.round(F.avg(F.octet_length("value")), 6).alias("avg_bytes"))
        for n in names
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
