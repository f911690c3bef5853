"""A compressed column at rest: payloads sorted by key in Parquet, the dictionary beside them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..dictionary import Dictionary
from . import decode, encode, encode_column


@dataclass
class CompressedStore:
    rows: DataFrame
    dictionary: Dictionary
    key: str = "key"

    @staticmethod
    def write(df: DataFrame, path: str, dictionary: Dictionary, key: str = "key", value: str = "value", partition_by: list[str] | None = None, files: int | None = None) -> None:
        """Encode and write, sorted by key, so that row groups have narrow key ranges and point reads skip the rest."""
        coded = encode(df, value, dictionary)
        coded = coded.repartitionByRange(*([files] if files else []), *(partition_by or []), key).sortWithinPartitions(*(partition_by or []), key)
        out = coded.write.mode("overwrite")
        (out.partitionBy(*partition_by) if partition_by else out).parquet(f"{path}/rows")
        dictionary.save(df.sparkSession, f"{path}/dictionary")

    @staticmethod
    def read(spark: SparkSession, path: str, key: str = "key") -> CompressedStore:
        return CompressedStore(spark.read.parquet(f"{path}/rows"), Dictionary.load(spark, f"{path}/dictionary"), key)

    def values(self, rows: DataFrame | None = None) -> DataFrame:
        """Decode: everything, or the rows of a plan over `rows` of this store. The dictionary's version is checked."""
        rows = self.rows if rows is None else rows
        version = self.dictionary.version
        safe = rows.withColumn("payload", F.when(F.col("dict_version") == version, F.col("payload")).otherwise(F.raise_error(F.lit("payload of another dictionary")).cast("binary")))
        return decode(safe.drop("n_tokens", "dict_version"), "payload", self.dictionary)

    def lookup(self, keys: DataFrame) -> DataFrame:
        """key, value for the keys asked; repeats stay. Only the rows found are decoded, after the join."""
        return self.values(keys.select(self.key).join(self.rows, self.key))

    def where_equal(self, literals: list[str], column: str = "payload") -> DataFrame:
        """Rows whose value is one of `literals`: each is encoded once and compared as bytes, which Parquet can skip by."""
        return self.rows.where(F.col(column).isin([F.lit(bytearray(b)) for b in payloads(literals, self.dictionary)]))


def payloads(literals: list[str], dictionary: Dictionary) -> list[bytes]:
    import numpy as np
    import pyarrow as pa

    ids, count, _ = encode_column(pa.array(literals, pa.string()), dictionary)
    wide = "<u2" if dictionary.bits <= 16 else "<u4"
    cut = np.concatenate([[0], np.cumsum(count)])
    return [ids[a:b].astype(wide).tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]


def rewrite_equality(df: DataFrame, column: str, literal: str, dictionary: Dictionary) -> DataFrame:
    """Filter an encoded table by an equality on the value it stands for; rows of other dictionaries never match."""
    return df.where((F.col(column) == F.lit(bytearray(payloads([literal], dictionary)[0]))) & (F.col("dict_version") == dictionary.version))


def uniform_keys(spark: SparkSession, keys: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """n keys drawn uniformly with repeats. Places are dealt by hash; a key's place is its rank inside hash parts (no global sort)."""
    total = keys.count()
    from pyspark.sql import Window

    parts = 64
    placed = keys.select("key").withColumn("_p", F.pmod(F.xxhash64("key"), F.lit(parts)))
    base = placed.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"))  # 64 rows
    base = base.select("_p", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    placed = placed.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy("key")) - 1).join(F.broadcast(base), "_p")
    placed = placed.select("key", (F.col("_b") + F.col("_r")).alias("_at"))
    asked = spark.range(n).select(F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(max(1, total))).alias("_at"))
    return asked.join(placed, "_at").select("key")
