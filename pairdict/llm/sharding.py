"""Jump consistent hashing: shard numbers from a stable key and the number of shards alone."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import shared

_STEP = np.uint64(2862933555777941757)  # the generator's fixed multiplier


def jump(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each 64-bit key. Each round moves only the keys whose next jump still lands below `shards`."""
    if shards < 1:
        raise ValueError("at least one shard is needed")
    state = np.asarray(keys).astype(np.int64).view(np.uint64).copy()
    home = np.zeros(len(state), np.int64)
    left = np.arange(len(state))
    with np.errstate(over="ignore"):
        while len(left):
            state[left] = state[left] * _STEP + np.uint64(1)
            share = ((state[left] >> np.uint64(33)) + np.uint64(1)).astype(np.float64)
            to = np.floor((home[left] + 1) * (2.0**31 / share)).astype(np.int64)
            stays = to < shards
            left = left[stays]
            home[left] = to[stays]
    return home.astype(np.int32)


def shard_of(key: Column, shards: int) -> Column:
    """The shard as a column; key: a long."""

    @F.pandas_udf("int")
    def f(k: pd.Series) -> pd.Series:
        return pd.Series(jump(k.to_numpy(), shards))

    return f(key)


def stable_key(id_col: str) -> Column:
    """A well-mixed long from an id of any type: 60 bits of the md5 of its text. Null has the key 0."""
    return F.coalesce(F.conv(F.substring(F.md5(F.col(id_col).cast("string").cast("binary")), 1, 15), 16, 10).cast("long"), F.lit(0).cast("long"))


def assign(docs: DataFrame, shards: int = 16, id_col: str = "doc_id", text_col: str = "text", spread: int = 64) -> DataFrame:
    """Put every row into a shard, with its place inside.

    Returns id, size (UTF-8 bytes + 1; null text: 1), text_crc32 (null text: of nothing, 0), law = 'key', shard, slot and
    grown_shard (the shard if there were one more). slot runs from 0 without a gap in each shard: rows are counted by
    (shard, part of `spread`), the counts are summed up front, and rows are numbered inside their part only, so no task
    sorts a whole shard. Repeated rows get slots of their own; rows with a null id share one shard. Empty input: empty output.
    """
    key, bytes_ = stable_key(id_col), F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    rows = docs.select(F.col(id_col), (F.octet_length(bytes_).cast("long") + 1).alias("size"), F.crc32(bytes_).cast("long").alias("text_crc32"), key.alias("_k"))
    rows = rows.withColumn("shard", shard_of(F.col("_k"), shards)).withColumn("grown_shard", shard_of(F.col("_k"), shards + 1))
    rows = shared.keep(rows.withColumn("_part", F.pmod(F.xxhash64("_k", "text_crc32"), F.lit(spread)).cast("int")).drop("_k"))
    before = Window.partitionBy("shard").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = rows.groupBy("shard", "_part").agg(F.count(F.lit(1)).alias("_n"))  # shards x spread rows at most
    starts = starts.select("shard", "_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_at"))
    inside = Window.partitionBy("shard", "_part").orderBy(id_col, "text_crc32", "size")
    rows = rows.withColumn("_in", F.row_number().over(inside) - 1).join(F.broadcast(starts), ["shard", "_part"])
    return rows.select(id_col, "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("_at") + F.col("_in")).cast("long").alias("slot"), "grown_shard")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(shared.documents(spark, sf_dir), 16)
