"""Removal of lines that many documents share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_SPACE = " \t\n\x0b\f\r"


def _key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(_SPACE)), _UPPER, _UPPER.lower())


def dedup_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3, id_col: str = "doc_id", text_col: str = "text", extra: list[str] | None = None) -> DataFrame:
    """Drop the lines whose key at least `min_docs` documents hold, but in the largest id that holds it.

    A key is the line without white space at its ends and with A-Z lower-cased; keys under `min_chars` code points stay.
    Returns id, n_lines, n_dropped, text (the lines left, joined by newlines) and the columns named in `extra`.
    Null and empty texts are one empty line. A document is what has one id: rows that repeat an id count once and lose
    the same keys. Rows with a null id keep all lines and count for nothing. Keys are compared by 128 bits of hash.
    """
    own = F.xxhash64(F.coalesce(text_col, F.lit(""))).alias("_own")  # tells texts apart where an id is repeated
    split = F.split(F.coalesce(text_col, F.lit("")), "\n", -1).alias("_lines")
    rows = docs.where(F.col(id_col).isNotNull()).select(id_col, own, F.posexplode(F.transform(split, _key)).alias("_pos", "_key")).where(F.char_length("_key") >= min_chars)
    lines = shared.keep(rows.select(id_col, "_own", "_pos", F.xxhash64("_key").alias("_h"), F.xxhash64(F.lit(1), F.col("_key")).alias("_g")), "lines")
    # one row for each key and document first, so that a key found everywhere is counted in many tasks
    common = lines.groupBy("_h", "_g").agg(F.count_distinct(id_col).alias("_n"), F.max(id_col).alias("_last")).where(F.col("_n") >= min_docs)
    gone = lines.join(common, ["_h", "_g"]).where(F.col(id_col) < F.col("_last")).groupBy(id_col, "_own").agg(F.collect_set("_pos").alias("_gone"))
    out = docs.select(id_col, *(extra or []), own, split).join(gone, [id_col, "_own"], "left")
    n, whole = F.size("_lines"), F.col("_gone").isNull()
    left = F.when(whole, F.col("_lines")).otherwise(F.transform(F.array_except(F.sequence(F.lit(0), n - 1), "_gone"), lambda i: F.get("_lines", i)))
    dropped = F.when(whole, F.lit(0)).otherwise(F.size("_gone"))
    return out.select(id_col, *(extra or []), n.cast("long").alias("n_lines"), dropped.cast("long").alias("n_dropped"), F.array_join(left, "\n").alias(text_col))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_lines(shared.documents(spark, sf_dir))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))
