"""Block codecs: neighbouring strings in blocks of 64 KiB through a general compressor."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..corpora import size_bytes
from ..scratch import keep

CODECS = ("lz4_raw", "zstd", "gzip")
BLOCK_BYTES = 65536


def layout(corpus: DataFrame, block_bytes: int = BLOCK_BYTES, part_bytes: int = 64 << 20) -> DataFrame:
    """key, value, block_id, start: where each string lies when the corpus is written end to end in key order.

    Offsets come in two levels: running sums inside ranges of keys that hold about `part_bytes` each, and the ranges' totals (a row
    each) summed up front, so no window sees the whole corpus. A block is what begins inside one stretch of `block_bytes`.
    Nulls are left out. The ranges are written to the shared folder: both passes must see the same ones.
    """
    spark = corpus.sparkSession
    rows = corpus.where(F.col("value").isNotNull()).select(F.col("key").cast("long").alias("key"), "value")
    parts = max(8, -(-size_bytes(rows) // part_bytes))

    def run(batches):
        part, at = TaskContext.get().partitionId(), 0
        for batch in batches:
            n = pc.binary_length(batch.column(1)).to_numpy().astype(np.int64)
            start = at + np.cumsum(n) - n
            at += int(n.sum())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(n), part, np.int32)), pa.array(start), pa.array(start + n)], ["key", "value", "part", "inside", "upto"])

    placed = rows.repartitionByRange(parts, "key").sortWithinPartitions("key").mapInArrow(run, "key long, value string, part int, inside long, upto long")
    placed = keep(placed)
    totals = placed.groupBy("part").agg(F.max("upto").alias("size"))
    before = totals.select("part", F.coalesce(F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    start = F.col("base") + F.col("inside")
    return placed.join(F.broadcast(before), "part").select("key", "value", F.floor(start / block_bytes).cast("long").alias("block_id"), start.cast("long").alias("start"))


def compress(corpus: DataFrame, codec: str = "zstd", block_bytes: int = BLOCK_BYTES) -> tuple[DataFrame, DataFrame]:
    """(blocks, locator): block_id, payload, n_strings, raw_bytes; and key, block_id, at, len inside the block's raw bytes."""
    if codec not in CODECS:
        raise ValueError(f"codec is one of {CODECS}")
    placed = layout(corpus, block_bytes)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches)).sort_by("start")
        raw = b"".join(v.encode() for v in t["value"].to_pylist())
        body = pa.Codec(codec).compress(raw, asbytes=True) if raw else b""
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()]), pa.array([body], pa.binary()), pa.array([t.num_rows], pa.int32()), pa.array([len(raw)], pa.int32())], ["block_id", "payload", "n_strings", "raw_bytes"])

    blocks = placed.groupBy("block_id").applyInArrow(run, "block_id long, payload binary, n_strings int, raw_bytes int")
    first = placed.groupBy("block_id").agg(F.min("start").alias("first"))
    locator = placed.select("key", "block_id", "start", F.octet_length("value").alias("len")).join(first, "block_id")
    return blocks, locator.select("key", "block_id", (F.col("start") - F.col("first")).cast("int").alias("at"), "len")


def lookup(blocks: DataFrame, locator: DataFrame, keys: DataFrame | None, codec: str = "zstd", cache: bool = True) -> DataFrame:
    """key, value for the keys asked (repeats stay; None: all). Blocks and the places asked of them meet by block, so a block moves
    once however many strings it holds. With `cache` it is opened once for all its keys; without, once a key."""
    asked = locator if keys is None else keys.select("key").join(locator, "key")
    wanted = blocks if keys is None else blocks.join(asked.select("block_id").distinct(), "block_id", "left_semi")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        body, size = (left[c][0].as_py() for c in ("payload", "raw_bytes"))
        unpack = lambda: pa.Codec(codec).decompress(body, size, asbytes=True) if size else b""
        opened, out = unpack() if cache else None, []
        for at, n in zip(right["at"].to_pylist(), right["len"].to_pylist(), strict=True):
            out.append((opened if cache else unpack())[at : at + n].decode())
        return pa.table({"key": right["key"], "value": pa.array(out, pa.string())})

    grouped = wanted.select("block_id", "payload", "raw_bytes").groupBy("block_id").cogroup(asked.select("key", "block_id", "at", "len").groupBy("block_id"))
    return grouped.applyInArrow(run, "key long, value string")


def decompress(blocks: DataFrame, locator: DataFrame, codec: str = "zstd") -> DataFrame:
    """key, value of everything."""
    return lookup(blocks, locator, None, codec)


def bytes_touched(locator: DataFrame, blocks: DataFrame, keys: DataFrame, cache: bool) -> DataFrame:
    """queries, raw bytes decompressed for them: a block a query without a cache, each block once with it."""
    hit = keys.select("key").join(locator.select("key", "block_id"), "key").join(blocks.select("block_id", "raw_bytes"), "block_id")
    if not cache:
        return hit.agg(F.count(F.lit(1)).alias("queries"), F.sum("raw_bytes").alias("bytes_touched"))
    each = hit.groupBy("block_id").agg(F.count(F.lit(1)).alias("n"), F.max("raw_bytes").alias("b"))
    return each.agg(F.sum("n").alias("queries"), F.sum("b").alias("bytes_touched"))


def write_store(corpus: DataFrame, path: str, codec: str = "zstd", block_bytes: int = BLOCK_BYTES) -> None:
    """Blocks and locator as Parquet, each sorted by what it is read by."""
    b, where = compress(corpus, codec, block_bytes)
    b.repartitionByRange("block_id").sortWithinPartitions("block_id").write.mode("overwrite").parquet(f"{path}/blocks")
    where.repartitionByRange("key").sortWithinPartitions("key").write.mode("overwrite").parquet(f"{path}/locator")


def read_store(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    return spark.read.parquet(f"{path}/blocks"), spark.read.parquet(f"{path}/locator")


def sizes(lengths: np.ndarray, block_bytes: int = BLOCK_BYTES) -> np.ndarray:
    """Block of each string from the lengths alone."""
    return (np.cumsum(lengths) - lengths) // block_bytes
