"""Lightweight schemes: ordered domain codes, run lengths, differences, frames of reference and suppressed zeros."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


class DomainCodec:
    """Order-preserving codes of a column's distinct values: ranges of values are ranges of codes."""

    def __init__(self, domain: DataFrame):
        self.domain = domain

    @staticmethod
    def fit(df: DataFrame, column: str = "value", most: int = 1 << 20) -> DomainCodec:
        """Rank the distinct values in byte order. Refuses more than `most`: the ranking and the joins' broadcast side are bounded."""
        distinct = df.where(F.col(column).isNotNull()).select(F.col(column).alias("value")).distinct()
        if distinct.limit(most + 1).count() > most:
            raise ValueError(f"more than {most} distinct values: use a string codec")
        return DomainCodec(distinct.select("value", (F.dense_rank().over(Window.orderBy("value")) - 1).alias("code")))

    def encode(self, df: DataFrame, column: str = "value") -> DataFrame:
        return df.join(F.broadcast(self.domain.withColumnRenamed("value", column)), column, "left").drop(column)

    def decode(self, df: DataFrame, code: str = "code", out: str = "value") -> DataFrame:
        return df.join(F.broadcast(self.domain.select(F.col("code").alias(code), F.col("value").alias(out))), code, "left").drop(code)

    def range_filter(self, encoded: DataFrame, low: str, high: str, code: str = "code") -> DataFrame:
        """Rows whose value lies in [low, high], found on the codes: two integers from the driver."""
        a, b = self.domain.where(F.col("value").between(low, high)).agg(F.min("code"), F.max("code")).first()
        return encoded.where(F.lit(False)) if a is None else encoded.where(F.col(code).between(a, b))

    def compressed(self, dictionary) -> DataFrame:
        """The domain with its strings encoded by a dictionary: code, payload, n_tokens, dict_version."""
        from ..codec import encode

        return encode(self.domain.select("code", "value"), "value", dictionary)


def rle_encode(df: DataFrame, order: str, column: str, by: list[str] = ()) -> DataFrame:
    """Runs of equal neighbours: by, value, first (order of the run's first row), n."""
    w = Window.partitionBy(*by).orderBy(order)
    starts = df.withColumn("_new", F.when(F.lag(column).over(w).eqNullSafe(F.col(column)) & (F.row_number().over(w) > 1), 0).otherwise(1))
    runs = starts.withColumn("_run", F.sum("_new").over(w))
    return runs.groupBy(*by, "_run").agg(F.first(column).alias("value"), F.min(order).alias("first"), F.count(F.lit(1)).alias("n")).drop("_run")


def delta_encode(df: DataFrame, order: str, column: str, by: list[str] = ()) -> DataFrame:
    """by, order, delta: the difference to the row before; the first row keeps its value."""
    w = Window.partitionBy(*by).orderBy(order)
    return df.select(*by, order, (F.col(column) - F.coalesce(F.lag(column).over(w), F.lit(0))).alias("delta"))


def delta_decode(df: DataFrame, order: str, by: list[str] = (), out: str = "value") -> DataFrame:
    return df.select(*by, order, F.sum("delta").over(Window.partitionBy(*by).orderBy(order)).alias(out))


def frame_of_reference(df: DataFrame, frame: Column, column: str, keep: list[str]) -> DataFrame:
    """keep, frame, base (the frame's least value), offset and bits (what the frame's widest offset needs)."""
    w = Window.partitionBy("frame")
    rows = df.withColumn("frame", frame).withColumn("base", F.min(column).over(w))
    rows = rows.withColumn("offset", F.col(column) - F.col("base")).withColumn("_top", F.max("offset").over(w))
    return rows.select(*keep, "frame", "base", "offset", F.length(F.bin(F.greatest(F.col("_top").cast("long"), F.lit(1)))).alias("bits"))


def null_suppress(value: Column) -> tuple[Column, Column]:
    """(significant bytes, their hex) of a non-negative integer without leading zero bytes."""
    h = F.hex(value.cast("long"))
    even = F.when(F.length(h) % 2 == 1, F.concat(F.lit("0"), h)).otherwise(h)
    return (F.length(even) / 2).cast("int"), even
