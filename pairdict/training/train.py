"""Training on Spark: one ordered task over a bounded sample, one task a group, or shards whose entries are ranked by gain."""

from __future__ import annotations

import json
import math
import time
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..corpora import size_bytes
from ..dictionary import Dictionary
from ..sampling import SampleSpec, draw_sample, fitting_fraction
from ..scratch import keep
from .kernel import Trainer, learn

VARIANTS = {"unbounded": (None, None), "bounded16": (16, 128)}
_ROWS = "token_id int, entry binary, left_id int, right_id int, stats string"


@dataclass(frozen=True)
class TrainStats:
    bytes_read: int
    strings_read: int
    entries: int
    pairs_tracked: int
    stop_reason: str
    peak_state_bytes: int


def adaptive_threshold(size_mib: float) -> int:
    """A slowly growing threshold: the whole part of log2 of the corpus's size in MiB, and 2 at least."""
    return 2 if size_mib < 8 else int(math.floor(math.log2(size_mib)))


def adaptive_threshold_col(size_bytes_: Column) -> Column:
    mib = size_bytes_ / F.lit(float(1 << 20))
    return F.greatest(F.lit(2), F.floor(F.log2(F.greatest(mib, F.lit(1.0)))).cast("int"))


def _limits(variant: str, max_len, max_bucket):
    if variant not in VARIANTS:
        raise ValueError(f"variant is one of {sorted(VARIANTS)}")
    a, b = VARIANTS[variant]
    return a if max_len == "variant" else max_len, b if max_bucket == "variant" else max_bucket


def _rows(t: Trainer, head=()) -> pa.RecordBatch:
    n = len(t.entries)
    columns = [pa.array(range(n), pa.int32()), pa.array(t.entries, pa.binary()), pa.array(t.lefts, pa.int32()), pa.array(t.rights, pa.int32()), pa.array([json.dumps(t.stats()), *[None] * (n - 1)], pa.string())]
    names = ["token_id", "entry", "left_id", "right_id", "stats"]
    return pa.RecordBatch.from_arrays([*(pa.array([v] * n, kind) for _, v, kind in head), *columns], [*(name for name, _, _ in head), *names])


def resolve_threshold(corpus: DataFrame, threshold, total: int | None = None) -> tuple[int, int | None]:
    if threshold != "auto":
        return int(threshold), total
    total = size_bytes(corpus) if total is None else total
    return adaptive_threshold(total / 2**20), total


def train(corpus: DataFrame, *, variant: str = "bounded16", bits: int = 16, threshold="auto", sample: SampleSpec | None = None, max_len="variant", max_bucket="variant", total_bytes: int | None = None) -> Dictionary:
    """A dictionary of at most 2^bits entries from one pass over a shuffled sample.

    Only the sample, about twice its max_bytes, goes to the one ordered task, which stops reading when the dictionary is full.
    Pass total_bytes where it is known, else an aggregate over the corpus finds it. Null values teach nothing.
    """
    threshold, total = resolve_threshold(corpus, threshold, total_bytes)
    sample = sample or SampleSpec()
    if sample.fraction is None:
        sample = sample.fitted(size_bytes(corpus) if total is None else total)
    max_len, max_bucket = _limits(variant, max_len, max_bucket)
    kw = dict(capacity=1 << bits, threshold=threshold, max_len=max_len, max_bucket=max_bucket, max_bytes=sample.max_bytes)

    def run(batches):
        yield _rows(learn((v.encode() for batch in batches for v in batch.column(0).to_pylist()), **kw))

    ordered = draw_sample(corpus, sample).repartition(1).sortWithinPartitions("ord", "key").select("value")
    rows = sorted(ordered.mapInArrow(run, _ROWS).collect())
    if not rows:  # no partition at all: an empty corpus
        t = Trainer(**kw)
        return Dictionary(t.entries, t.lefts, t.rights, variant, bits, threshold, t.stats())
    return Dictionary([bytes(r.entry) for r in rows], [r.left_id for r in rows], [r.right_id for r in rows], variant, bits, threshold, json.loads(rows[0].stats))


def train_thresholds(corpus: DataFrame, thresholds, *, variant: str, bits: int, sample: SampleSpec, total_bytes: int) -> dict[int, Dictionary]:
    """What `train` gives at each threshold, side by side: the sample is drawn and ordered once, and each threshold has a task. The tasks
    hold what a trainer may read of it, at most max_bytes and a string."""
    thresholds = list(dict.fromkeys(thresholds))
    max_len, max_bucket = VARIANTS[variant]
    kw = dict(capacity=1 << bits, max_len=max_len, max_bucket=max_bucket, max_bytes=sample.max_bytes)

    def read(batches):
        texts, size = [], 0
        for text in (v.encode() for batch in batches for v in batch.column(0).to_pylist()):
            texts.append(text)
            size += len(text)
            if size >= sample.max_bytes:  # no trainer reads on
                break
        yield pa.RecordBatch.from_arrays([pa.array([b"".join(texts)], pa.binary()), pa.array([list(map(len, texts))], pa.list_(pa.int32()))], ["data", "size"])

    ordered = draw_sample(corpus, sample.fitted(total_bytes)).repartition(1).sortWithinPartitions("ord", "key").select("value")
    drawn = ordered.mapInArrow(read, "data binary, size array<int>").collect()
    held = corpus.sparkSession.sparkContext.broadcast((bytes(drawn[0][0]), list(drawn[0][1])) if drawn else (b"", []))

    def run(batches):
        data, size = held.value
        ends = list(accumulate(size))
        for t in (t for batch in batches for t in batch.column(0).to_pylist()):
            yield _rows(learn((data[e - n : e] for e, n in zip(ends, size, strict=True)), threshold=t, **kw), [("threshold", t, pa.int32())])

    order = sorted(thresholds, reverse=True)  # higher ones read more, and begin first
    each = corpus.sparkSession.range(0, len(order), 1, len(order)).select(F.array(*map(F.lit, order))[F.col("id").cast("int")].alias("threshold"))
    found: dict[int, list] = {t: [] for t in thresholds}
    for r in each.mapInArrow(run, "threshold int, " + _ROWS).collect():  # at most 2^bits rows a threshold
        found[r.threshold].append(r)
    out = {}
    for t, rows in found.items():
        rows.sort(key=lambda r: r.token_id)
        out[t] = Dictionary([bytes(r.entry) for r in rows], [r.left_id for r in rows], [r.right_id for r in rows], variant, bits, t, json.loads(rows[0].stats))
    return out


def train_widths(corpus: DataFrame, widths, *, variant: str, threshold: int, sample: SampleSpec, total_bytes: int) -> dict[int, tuple[Dictionary, float]]:
    """The entries that `train` gives at each width, and the seconds it takes for them, from one run: until a dictionary is full it does
    not matter how many entries it may have, so the narrower ones are what the widest one holds when it reaches their size."""
    widths = sorted(set(widths))
    max_len, max_bucket = VARIANTS[variant]

    def run(batches):
        t, began = Trainer(1 << widths[-1], threshold, max_len, max_bucket, sample.max_bytes), time.perf_counter()
        t.marks = {1 << b: None for b in widths}
        for text in (v.encode() for batch in batches for v in batch.column(0).to_pylist()):
            if not t.feed(text):
                break
        ended = time.perf_counter()
        spent = [(at or ended) - began for at in t.marks.values()] + [ended - began]
        rows = _rows(t)
        yield rows.set_column(4, "stats", pa.array([json.dumps(spent), *[None] * (rows.num_rows - 1)], pa.string()))

    began = time.perf_counter()
    ordered = draw_sample(corpus, sample.fitted(total_bytes)).repartition(1).sortWithinPartitions("ord", "key").select("value")
    rows = sorted(ordered.mapInArrow(run, _ROWS).collect(), key=lambda r: r.token_id)
    wall = time.perf_counter() - began
    if not rows:  # no partition at all: an empty corpus
        rows = [(i, bytes([i]), None, None, json.dumps([0.0] * (len(widths) + 1))) for i in range(256)]
    *spent, last = json.loads(rows[0][4])
    entries, lefts, rights = [bytes(r[1]) for r in rows], [r[2] for r in rows], [r[3] for r in rows]
    cut = lambda b: Dictionary(entries[: 1 << b], lefts[: 1 << b], rights[: 1 << b], variant, b, threshold)
    return {b: (cut(b), wall - last + own) for b, own in zip(widths, spent, strict=True)}


def train_by(corpus: DataFrame, by: list[str], *, variant: str = "bounded16", bits: int = 12, threshold: int = 2, max_bytes: int = 4 << 20, seed: int = 42) -> DataFrame:
    """Dictionaries of groups, one row an entry: by, token_id, entry, left_id, right_id.

    Groups train in parallel. Before the grouping each group is thinned by hash to about twice `max_bytes`, so that a group of
    any size fits a task; the rows left are read in md5 order.
    """
    max_len, max_bucket = VARIANTS[variant]
    sizes = corpus.groupBy(*by).agg(F.sum(F.octet_length("value")).alias("_bytes"))  # one row a group
    rows = corpus.where(F.col("value").isNotNull()).join(sizes, by)
    rows = rows.where(F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(1_000_000)) < F.lit(2e6) * max_bytes / F.col("_bytes"))
    rows = rows.select(*by, F.md5(F.concat(F.lit(f"{seed}:"), F.col("key").cast("string")).cast("binary")).alias("_ord"), "key", "value")
    kinds = [(f.name, f.dataType.simpleString()) for f in corpus.select(*by).schema.fields]
    kw = dict(capacity=1 << bits, threshold=threshold, max_len=max_len, max_bucket=max_bucket, max_bytes=max_bytes)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches)).sort_by([("_ord", "ascending"), ("key", "ascending")])
        yield _rows(learn((v.encode() for v in t["value"].to_pylist()), **kw), [(n, k.as_py(), k.type) for (n, _), k in zip(kinds, key, strict=True)])

    return rows.groupBy(*by).applyInArrow(run, ", ".join(f"`{n}` {k}" for n, k in kinds) + ", " + _ROWS).drop("stats")


def train_sharded(corpus: DataFrame, shards: int = 8, *, variant: str = "bounded16", bits: int = 16, threshold: int = 2, max_bytes: int = 4 << 20, seed: int = 42) -> Dictionary:
    """Shards train apart; their entries are then ranked by the gain they bring on a sample parsed with the union.

    Each shard keeps to `max_bytes`, so the work a task does is bounded while the text seen grows with the shards.
    """
    from ..codec import token_frequencies
    from ..measures import token_gain

    sharded = corpus.withColumn("_shard", F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(shards)).cast("int"))
    entries = train_by(sharded, ["_shard"], variant=variant, bits=bits, threshold=threshold, max_bytes=max_bytes, seed=seed)
    union = keep(entries.where("token_id >= 256").select("entry").distinct())
    # the union is parsed with in parts, dealt by hash, that a dictionary of 21 bits holds: no entry is left out
    many = union.count()
    parts = max(1, -(-many // (1 << 20)))
    sample = corpus.where(F.pmod(F.xxhash64(F.lit(seed + 1), "key"), F.lit(1_000_000)) < int(1e6 * fitting_fraction(size_bytes(corpus), max_bytes)))
    best: list[tuple[int, bytes]] = []
    for part in range(parts):
        found = sorted(bytes(r.entry) for r in union.where(F.pmod(F.xxhash64("entry"), F.lit(parts)) == part).collect())
        every = Dictionary([bytes([b]) for b in range(256)] + found, variant=variant, bits=21, threshold=threshold)
        gain = token_gain(token_frequencies(sample, "value", every), every.frame(corpus.sparkSession))
        top = gain.where("token_id >= 256").orderBy(F.desc("gain"), F.hex("entry")).limit((1 << bits) - 256)
        best = sorted([*best, *((-r.gain, bytes(r.entry)) for r in top.select("gain", "entry").collect())])[: (1 << bits) - 256]
    return Dictionary([bytes([b]) for b in range(256)] + [e for _, e in best], variant=variant, bits=bits, threshold=threshold, stats={"shards": shards, "candidates": many})


def suggest_bits(gain: DataFrame, corpus_bytes: int, least: int = 9, most: int = 16) -> int:
    """The width at which the ratio that charges the dictionary is best, from gains by number under one long dictionary."""
    upto = F.sum("gain").over(Window.orderBy("token_id"))
    rows = {r.token_id: r.s for r in gain.select("token_id", upto.alias("s")).collect()}
    last = max(rows)
    cost = {}
    for b in range(least, most + 1):
        saved = rows[min(last, (1 << b) - 1)]
        cost[b] = (corpus_bytes - saved) * b / 16 + 4 * (1 << b)
    return min(cost, key=cost.get)
