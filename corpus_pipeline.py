"""From raw documents to sampled subword ids: five stages, each written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairdict.llm import decontaminate, language, line_dedup, near_copies, shared, simhash, subwords

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _documents(df: DataFrame) -> DataFrame:
    return df.withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language cannot be told (null texts and texts without a letter) go; a missing lang is filled in."""
    got = language.identify(docs.select(*COLUMNS), language.train(docs), keep=list(COLUMNS))
    return got.where(F.col("lang_pred") != "und").withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shared lines go from all documents but the one with the largest id."""
    return _documents(line_dedup.dedup_lines(docs, extra=["lang", "source"]))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8 or more) one document stays: of the rows with the
    least id that with the least hash of its text, once. Rows without an id are not judged."""
    named = docs.where(F.col("doc_id").isNotNull())
    found = shared.keep(simhash.near_duplicates(named, width=5, similarity=(4, 5)).select("doc_id", "text_hash", "class_key"), "found")
    stays = found.groupBy("class_key").agg(F.min(F.struct("doc_id", "text_hash")).alias("s"), F.count(F.lit(1)).alias("rows"))
    goes = found.join(stays.where("rows > 1").select("class_key", "s"), "class_key").where(F.struct("doc_id", "text_hash") != F.col("s"))
    goes = shared.keep(goes.select("doc_id", "text_hash").distinct(), "goes")
    twice = found.groupBy("doc_id", "text_hash").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id", "text_hash")
    row = F.xxhash64("doc_id", "text_hash").alias("th")
    marked = docs.select(*COLUMNS, F.xxhash64("text").alias("text_hash")).select(row, "text_hash", *COLUMNS)
    # rows that no decision touches do not move: a filter of fixed size tells most of them
    free, others = near_copies.parted(marked, goes.union(twice).select(row))
    left = others.join(goes, ["doc_id", "text_hash"], "left_anti").where(F.col("doc_id").isNotNull()).dropDuplicates(["doc_id", "text_hash"])
    return free.select(*COLUMNS).union(left.select(*COLUMNS)).union(others.where(F.col("doc_id").isNull()).select(*COLUMNS))


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of the benchmark are cut out of the documents."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return _documents(decontaminate.scan(docs, items, extra=["lang", "source"]))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Two sampled segmentations of every text, without replacement."""
    return subwords.encode(docs, k=2, keep=["doc_id", "lang", "source"], lean=True)


STAGES = [
    ("language", language_id),
    ("lines", lines),
    ("near_duplicates", near_duplicates),
    ("benchmark", benchmark),
    ("subwords", encode),
]
#: No SQL for the whole: fingerprints, components and sampled segmentations are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = shared.documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = shared.keep(stage(spark, docs, sf_dir), name)
    return docs
