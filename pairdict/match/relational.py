"""Longest matches by joins alone: for small corpora and for checking the kernels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def lpm_join(corpus: DataFrame, dictionary: DataFrame, starts: DataFrame | None = None) -> DataFrame:
    """key, pos (from 1), token_id, len: the longest entry at every byte (or at `starts`: key, pos).

    Every length that entries have makes one candidate a place, joined on its bytes with the broadcast dictionary.
    """
    lengths = [r[0] for r in dictionary.select("entry_len").distinct().collect()]  # few: entry lengths
    raw = corpus.select("key", F.encode("value", "UTF-8").alias("b"))
    if starts is None:
        places = raw.where(F.octet_length("b") > 0).select("key", "b", F.explode(F.sequence(F.lit(1), F.octet_length("b"))).alias("pos"))
    else:
        places = starts.join(raw, "key")
    cut = places.select("key", "pos", F.explode(F.array(*[F.struct(F.lit(n).alias("n"), F.substring("b", F.col("pos"), n).alias("e")) for n in lengths])).alias("c"))
    cut = cut.where(F.octet_length("c.e") == F.col("c.n")).select("key", "pos", F.col("c.e").alias("entry"))
    held = F.broadcast(dictionary.select("entry", "token_id", "entry_len"))  # at most 2^16 entries
    return cut.join(held, "entry").groupBy("key", "pos").agg(F.max_by("token_id", "entry_len").alias("token_id"), F.max("entry_len").alias("len"))
