"""Streams: encoding, drift of the ratio, late data, duplicates, interval joins, an online trainer and retraining."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import codec
from ..dictionary import Dictionary
from ..training.kernel import Trainer


def timed_events(stream: DataFrame) -> DataFrame:
    """events with ts as a timestamp with a zone: watermarks refuse the other kind."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def encode_stream(stream: DataFrame, column: str, dictionary: Dictionary) -> DataFrame:
    """Stateless: the same map as in batch."""
    return codec.encode(stream, column, dictionary)


def _ratio(df: DataFrame, group) -> DataFrame:
    got = df.groupBy(group.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("raw").alias("raw_bytes"), (F.sum("n_tokens") * 2).alias("payload_bytes"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "raw_bytes", "payload_bytes", (F.col("raw_bytes") / F.col("payload_bytes")).alias("ratio"))


def measured(stream: DataFrame, column: str, dictionary: Dictionary, late: str = "10 minutes") -> DataFrame:
    """ts, raw, n_tokens: what the ratio of a window is made of, with late rows given `late` to arrive."""
    rows = timed_events(stream).select("ts", F.octet_length(column).alias("raw"), F.col(column).alias("_v"))
    return codec.encode(rows, "_v", dictionary).select("ts", "raw", "n_tokens").withWatermark("ts", late)


def ratio_tumbling(stream, column, dictionary, width="1 hour") -> DataFrame:
    return _ratio(measured(stream, column, dictionary), F.window("ts", width))


def ratio_sliding(stream, column, dictionary, width="1 hour", slide="15 minutes") -> DataFrame:
    return _ratio(measured(stream, column, dictionary), F.window("ts", width, slide))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """user_id, start, end, n: a user's events with pauses under `gap`."""
    rows = timed_events(stream).withWatermark("ts", late)
    got = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return got.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedupe(stream: DataFrame, key: str = "event_id", late: str = "10 minutes") -> DataFrame:
    return timed_events(stream).withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def followed_by(clicks: DataFrame, errors: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Each first event with each second event of the same user that follows within the time given; state ends with it."""
    a = timed_events(clicks).select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("first_ts")).withWatermark("first_ts", late)
    b = timed_events(errors).select(F.col("event_id").alias("second_id"), F.col("user_id").alias("second_user"), F.col("ts").alias("second_ts")).withWatermark("second_ts", late)
    on = (F.col("user_id") == F.col("second_user")) & (F.col("second_ts") >= F.col("first_ts")) & (F.col("second_ts") <= F.col("first_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("user_id", "first_id", "second_id", "first_ts", "second_ts")


def lookup_stream(keys: DataFrame, store) -> DataFrame:
    """A stream of keys against a compressed store; only found rows are decoded."""
    return store.lookup(keys)


def online_trainer(stream: DataFrame, group: str, column: str, bits: int = 10, threshold: int = 2, max_len: int | None = 16, max_bucket: int | None = 128) -> DataFrame:
    """The trainer as keyed state: one dictionary a group that grows with the stream, until it is full.

    Emits group, entries (256 and above, as hex) and n after each batch of a group. State is the dictionary and the live pair
    counters, both bounded by what 2^bits entries need. Rows of a batch are read in order of their text, which makes the state
    independent of partitions.
    """

    def step(key, batches, state):
        t = Trainer(1 << bits, threshold, max_len, max_bucket)
        if state.exists:
            (raw,) = state.get
            old = json.loads(raw)
            for a, b in old["pairs"]:
                t.promote(a, b)
            t.counts.update({int(k): v for k, v in old["counts"].items()})
        for v in sorted(v for pdf in batches for v in pdf["v"] if v is not None):
            if t.stop_reason or not t.feed(v.encode()):
                t.counts.clear()
                break
        pairs = list(zip(t.lefts[256:], t.rights[256:], strict=True))
        state.update((json.dumps({"pairs": pairs, "counts": {str(k): n for k, n in t.counts.items()}}),))
        yield pd.DataFrame({group: [key[0]], "entries": [",".join(e.hex() for e in t.entries[256:])], "n": [len(t.entries)]})

    rows = stream.select(group, F.col(column).alias("v"))
    return rows.groupBy(group).applyInPandasWithState(step, f"`{group}` string, entries string, n int", "state string", "update", "NoTimeout")


class Retrainer:
    """For foreachBatch: encodes each batch, and trains a new dictionary from it when its ratio falls under `floor`."""

    def __init__(self, dictionary: Dictionary, column: str, floor: float, sink: str | None = None, **train_options):
        self.dictionary, self.column, self.floor, self.sink, self.options = dictionary, column, floor, sink, train_options
        self.versions = [dictionary.version]

    def __call__(self, batch: DataFrame, number: int) -> None:
        from ..measures import encode_totals
        from ..training import train

        rows = batch.select(F.xxhash64(self.column).alias("key"), F.col(self.column).alias("value"))
        raw, n, _ = encode_totals(rows, self.dictionary)
        if n and raw / (2 * n) < self.floor:
            new = train(rows, **self.options)
            if new.version not in self.versions:
                self.dictionary = new
                self.versions.append(new.version)
        if self.sink:
            codec.encode(rows, "value", self.dictionary).write.mode("append").parquet(self.sink)
