"""Measures: ratio, gain, buckets, footprint, coverage and costs. Frequencies and dictionaries are at most 2^21 rows, so their
windows are bounded."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..dictionary import Dictionary

MIB = float(1 << 20)


def ratio(raw_bytes: int, tokens: int, dictionary: Dictionary | None, bits: int = 16, offsets: int = 0) -> float:
    """raw / (numbers at `bits` bits, in one stream, + dictionary bytes + 4 bytes an entry number of that width)."""
    size = tokens * bits / 8 + offsets
    if dictionary is not None:
        size += sum(map(len, dictionary.entries)) + 4 * (1 << bits)
    return raw_bytes / size if size else 1.0


def encode_totals(corpus: DataFrame, dictionary: Dictionary, column: str = "value") -> tuple[int, int, int]:
    """(raw bytes, numbers emitted, rows) in one narrow pass."""
    import numpy as np
    import pyarrow as pa

    from ..codec import encode_column, flat

    held = corpus.sparkSession.sparkContext.broadcast(dictionary)

    def run(batches):
        raw = n = rows = 0
        for b in batches:
            ids, _, null = encode_column(b.column(0), held.value)
            raw, n, rows = raw + len(flat(b.column(0))[0]), n + len(ids), rows + int(np.count_nonzero(~null))
        yield pa.RecordBatch.from_arrays([pa.array([raw]), pa.array([n]), pa.array([rows])], ["raw", "n", "rows"])

    got = corpus.select(column).mapInArrow(run, "raw long, n long, rows long").agg(F.sum("raw"), F.sum("n"), F.sum("rows")).first()
    return tuple(int(x or 0) for x in got)


def encode_totals_each(corpus: DataFrame, dictionaries: list[Dictionary], at_once: int = 32) -> list[tuple[int, int, int]]:
    """`encode_totals` for many dictionaries: one pass over the corpus serves up to `at_once` of them, fewer where they are large. The pass is
    narrow unless the scan has too few parts for the cores, as a small file has; the text is then dealt out first."""
    import pyarrow as pa

    from ..codec import flat
    from ..match.union import UnionIndex

    sc = corpus.sparkSession.sparkContext
    rows = corpus.select("key", "value")
    if rows.rdd.getNumPartitions() < 2 * sc.defaultParallelism:
        rows = rows.repartition(4 * sc.defaultParallelism, "key")
    rows, out = rows.select("value"), []
    while len(out) < len(dictionaries):
        n = at_once
        while n > 1 and n * sum(len(d.entries) for d in dictionaries[len(out) : len(out) + n]) > 1 << 24:  # at most so many numbers in the table
            n -= 1
        part = dictionaries[len(out) : len(out) + n]
        held = sc.broadcast(UnionIndex(part))

        def run(batches, held=held, many=len(part)):
            raw, count, total = 0, 0, [0] * many
            for b in batches:
                data, offs, null = flat(b.column(0))
                raw, count = raw + len(data), count + len(null) - int(null.sum())
                total = held.value.counts(data, offs) + total
            yield pa.RecordBatch.from_arrays([pa.array([raw]), pa.array([count]), pa.array([[int(x) for x in total]])], ["raw", "rows", "n"])

        sums = rows.mapInArrow(run, "raw long, rows long, n array<long>").agg(F.sum("raw"), F.sum("rows"), *(F.sum(F.col("n")[i]) for i in range(len(part))))
        raw, count, *each = (int(x or 0) for x in sums.first())
        out += [(raw, n, count) for n in each]
    return out


def ratio_report(corpus: DataFrame, dictionary: Dictionary) -> DataFrame:
    """One row: ratio_paper (dictionary charged), ratio_no_dict, ratio_with_row_offsets, mean_token_len."""
    raw, n, rows = encode_totals(corpus, dictionary)
    bits = dictionary.bits
    values = (raw, n, ratio(raw, n, dictionary, bits), ratio(raw, n, None, bits), ratio(raw, n, dictionary, bits, 4 * rows), raw / max(1, n))
    return corpus.sparkSession.createDataFrame([values], "raw_bytes long, n_tokens long, ratio_paper double, ratio_no_dict double, ratio_with_row_offsets double, mean_token_len double")


def token_gain(freq: DataFrame, dictionary: DataFrame, id_bytes: int = 2) -> DataFrame:
    """token_id, entry, entry_len, f, gain = (length - id_bytes) x f - length; entries never emitted have f 0."""
    rows = dictionary.select("token_id", "entry", "entry_len").join(F.broadcast(freq), "token_id", "left")
    f = F.coalesce("f", F.lit(0)).cast("long")
    return rows.select("token_id", "entry", "entry_len", f.alias("f"), ((F.col("entry_len") - id_bytes) * f - F.col("entry_len")).cast("long").alias("gain"))


def gain_by_length(gain: DataFrame) -> DataFrame:
    """entry_len, gain, f, and both as running shares over lengths."""
    each = gain.groupBy("entry_len").agg(F.sum("gain").alias("gain"), F.sum("f").alias("f"))
    upto, all_ = Window.orderBy("entry_len"), Window.partitionBy()
    share = lambda c: F.sum(c).over(upto) / F.sum(c).over(all_)
    return each.select("entry_len", "gain", "f", share("gain").alias("cum_gain_share"), share("f").alias("cum_freq_share"))


def smoothed_gain(gain: DataFrame, window: int | None = None) -> DataFrame:
    """token_id, gain, smoothed: mean over the `window` numbers around (from w // 2 before to (w - 1) // 2 after); 1 % of them if not given."""
    if window is None:
        window = max(1, round(gain.count() / 100))
    w = Window.orderBy("token_id").rowsBetween(-(window // 2), (window - 1) // 2)
    return gain.select("token_id", "gain", F.avg("gain").over(w).alias("smoothed"))


def bucket_sizes(dictionary: DataFrame) -> DataFrame:
    """size, n_buckets, share, cum_share: long entries by their first eight bytes."""
    buckets = dictionary.where("entry_len > 8").groupBy(F.substring("entry", 1, 8).alias("p")).agg(F.count(F.lit(1)).alias("size"))
    each = buckets.groupBy("size").agg(F.count(F.lit(1)).alias("n_buckets"))
    all_ = F.sum("n_buckets").over(Window.partitionBy())
    return each.select("size", "n_buckets", (F.col("n_buckets") / all_).alias("share"), (F.sum("n_buckets").over(Window.orderBy("size")) / all_).alias("cum_share"))


def footprint(dictionary: DataFrame, bits: int = 16) -> DataFrame:
    """entries, data_bytes, offset_bytes (4 a number of that width), total_bytes."""
    offsets = 4 * (1 << bits)
    return dictionary.agg(F.count(F.lit(1)).alias("entries"), F.sum("entry_len").cast("long").alias("data_bytes"), F.lit(offsets).cast("long").alias("offset_bytes"), (F.sum("entry_len") + offsets).cast("long").alias("total_bytes"))


def token_length_histogram(freq: DataFrame, dictionary: DataFrame) -> DataFrame:
    """entry_len, n, share of emitted entries."""
    each = freq.join(dictionary.select("token_id", "entry_len"), "token_id").groupBy("entry_len").agg(F.sum("f").alias("n"))
    return each.select("entry_len", "n", (F.col("n") / F.sum("n").over(Window.partitionBy())).alias("share"))


def coverage_curve(freq: DataFrame, dictionary: DataFrame) -> DataFrame:
    """rank, token_id, cum_bytes, cum_share: emitted entries from the most frequent on (ties by number)."""
    rows = freq.join(dictionary.select("token_id", "entry_len"), "token_id")
    w = Window.orderBy(F.desc("f"), "token_id")
    upto = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return rows.select(F.row_number().over(w).alias("rank"), "token_id", F.sum("entry_len").over(upto).cast("long").alias("cum_bytes"), (F.sum("f").over(upto) / F.sum("f").over(Window.partitionBy())).alias("cum_share"))


def coverage_at(curve: DataFrame, marks=(32 << 10, 256 << 10)) -> DataFrame:
    """mark, share: what the most frequent entries cover that fit into so many bytes."""
    out = [curve.agg(F.lit(m).alias("mark"), F.coalesce(F.max(F.when(F.col("cum_bytes") <= m, F.col("cum_share"))), F.lit(0.0)).alias("share")) for m in marks]
    return out[0].union(out[1]) if len(out) == 2 else out[0]


def lpm_cost(corpus: DataFrame, dictionary: Dictionary, inline: int = 4) -> DataFrame:
    """bytes, tokens, probes, suffix_tests, overflow_visits of the plain search over a corpus."""
    import pyarrow as pa

    from ..match.dynamic import Cost, DynamicMatcher

    held = corpus.sparkSession.sparkContext.broadcast(dictionary)

    def run(batches):
        m, c, size, n = DynamicMatcher(held.value.entries), Cost(), 0, 0
        for b in batches:
            for v in b.column(0).to_pylist():
                raw, at = (v or "").encode(), 0
                size += len(raw)
                while at < len(raw):
                    at += m.tally(raw, at, c, inline)[1]
                    n += 1
        yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (size, n, c.probes, c.suffixes, c.overflow)], ["bytes", "tokens", "probes", "suffix_tests", "overflow_visits"])

    each = corpus.select("value").mapInArrow(run, "bytes long, tokens long, probes long, suffix_tests long, overflow_visits long")
    return each.agg(*(F.sum(c).alias(c) for c in each.columns))


def roundtrip_errors(corpus: DataFrame, dictionary: Dictionary) -> DataFrame:
    """Rows that do not come back as they were: must be empty."""
    from ..codec import decode, encode

    coded = encode(corpus.select("key", "value", F.col("value").alias("was")), "value", dictionary)
    return decode(coded.select("key", "was", "payload"), "payload", dictionary, "back").where(~F.col("was").eqNullSafe(F.col("back")))


def timed(df: DataFrame) -> float:
    """Seconds to make all rows of a DataFrame, without writing them."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def throughput(raw_bytes: int, seconds: float) -> float:
    return raw_bytes / MIB / max(seconds, 1e-9)
