"""Byte-pair encoding by global pair counts: merge the most frequent neighbouring pair, again and again.

Two engines: one DataFrame aggregation a round, the honest cost of global statistics on a cluster; and a kernel over a bounded
sample that keeps each pair's places and a priority queue.
"""

from __future__ import annotations

import heapq
from collections import Counter, defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..corpora import size_bytes
from ..dictionary import Dictionary, single_bytes
from ..sampling import SampleSpec, draw_sample
from ..scratch import keep


def merge_rounds(texts: list[bytes], capacity: int) -> tuple[list[bytes], list, list]:
    """Entries, and the pair each came from. Pairs count left to right without overlap; ties by the bytes of left, then right."""
    entries, lefts, rights = single_bytes(), [None] * 256, [None] * 256
    symbol, follow, before, line = [], [], [], []
    for k, t in enumerate(texts):
        base = len(symbol)
        symbol += list(t)
        line += [k] * len(t)
        follow += [base + i + 1 for i in range(len(t) - 1)] + [-1] * bool(t)
        before += [-1] * bool(t) + [base + i for i in range(len(t) - 1)]
    places: defaultdict[tuple, set] = defaultdict(set)
    for i, j in enumerate(follow):
        if j >= 0:
            places[symbol[i], symbol[j]].add(i)

    def count(pair):
        at = places[pair]
        if pair[0] != pair[1]:
            return len(at)
        n, last = 0, None  # runs of one symbol: every other place
        for i in sorted(at):
            if last is not None and before[i] == last:
                last = None
            else:
                n, last = n + 1, i
        return n

    def entry(pair):
        return (-count(pair), entries[pair[0]], entries[pair[1]], pair)

    heap = [entry(p) for p in places]
    heapq.heapify(heap)
    while heap and len(entries) < capacity:
        top = heapq.heappop(heap)
        pair = top[3]
        now = entry(pair)
        if now != top:
            if now[0]:
                heapq.heappush(heap, now)
            continue
        if -top[0] < 2:
            break
        new = len(entries)
        entries.append(entries[pair[0]] + entries[pair[1]])
        lefts.append(pair[0])
        rights.append(pair[1])
        changed = set()
        for i in sorted(places.pop(pair)):
            j = follow[i]
            if symbol[i] != pair[0] or j < 0 or symbol[j] != pair[1]:
                continue
            a, b = before[i], follow[j]
            if a >= 0:
                places[symbol[a], symbol[i]].discard(a)
                changed.add((symbol[a], new))
                places[symbol[a], new].add(a)
            if b >= 0:
                places[symbol[j], symbol[b]].discard(j)
                changed.add((new, symbol[b]))
                places[new, symbol[b]].add(i)
                before[b] = i
            symbol[i], symbol[j] = new, -1
            follow[i], follow[j], before[j] = b, -1, -1
        for p in changed:
            if places[p]:
                heapq.heappush(heap, entry(p))
    return entries, lefts, rights


def train(corpus: DataFrame, bits: int = 10, sample: SampleSpec = SampleSpec(max_bytes=1 << 20), max_entries: int | None = None) -> Dictionary:
    """The kernel engine: one task over a sample of at most `max_bytes`. Pair counts are exact on a corpus of that size or less."""
    capacity = min(1 << bits, max_entries or 1 << bits)
    if sample.fraction is None:
        sample = sample.fitted(size_bytes(corpus))

    def run(batches):
        texts, size = [], 0
        for batch in batches:
            for v in batch.column(0).to_pylist():
                if size < sample.max_bytes:
                    texts.append(v.encode())
                    size += len(texts[-1])
        e, a, b = merge_rounds(texts, capacity)
        yield pa.RecordBatch.from_arrays([pa.array(range(len(e)), pa.int32()), pa.array(e, pa.binary()), pa.array(a, pa.int32()), pa.array(b, pa.int32())], ["token_id", "entry", "left_id", "right_id"])

    rows = draw_sample(corpus, sample).repartition(1).sortWithinPartitions("ord", "key").select("value").mapInArrow(run, "token_id int, entry binary, left_id int, right_id int")
    return Dictionary.from_frame(rows, variant="bpe", bits=bits)


def train_relational(corpus: DataFrame, rounds: int = 4, checkpoint_every: int = 10) -> DataFrame:
    """token_id, entry (as text), n of the first merges, with one aggregation and one rewriting of the corpus a round.

    Symbols are kept as arrays of strings, so this engine is for text of one-byte characters.
    """
    spark = corpus.sparkSession
    now = corpus.select("key", F.filter(F.split("value", ""), lambda c: c != "").alias("s"))
    found = []
    for k in range(rounds):
        at = now.select("key", F.posexplode("s").alias("pos", "a"))
        here = Window.partitionBy("key").orderBy("pos")
        pairs = at.select("key", "pos", "a", F.lead("a").over(here).alias("b")).where(F.col("b").isNotNull())
        # in a run of one symbol every other place counts: number the places of each run of equal pairs
        run = pairs.withColumn("fresh", F.when((F.lag("a").over(here) == F.col("a")) & (F.lag("b").over(here) == F.col("b")), 0).otherwise(1))
        run = run.withColumn("run", F.sum("fresh").over(here))
        run = run.withColumn("nth", F.row_number().over(Window.partitionBy("key", "run").orderBy("pos"))).where((F.col("a") != F.col("b")) | (F.col("nth") % 2 == 1))
        best = run.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "a", "b").limit(1).collect()  # one row
        if not best or best[0].n < 2:
            break
        a, b, n = best[0]
        found.append((256 + k, a + b, n))
        merged = F.aggregate(
            "s", F.array().cast("array<string>"),
            lambda acc, x: F.when((F.size(acc) > 0) & (F.element_at(acc, -1) == a) & (x == b), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.concat(F.lit(a), x)))).otherwise(F.concat(acc, F.array(x))),
        )
        now = now.select("key", merged.alias("s"))
        if (k + 1) % checkpoint_every == 0:
            now = keep(now)
    return spark.createDataFrame(found, "token_id int, entry string, n long")


def reference_rounds(texts: list[bytes], rounds: int) -> list[tuple[bytes, int]]:
    """The rule written plainly, for tests."""
    lines, out = [[bytes([c]) for c in t] for t in texts], []
    for _ in range(rounds):
        n = Counter()
        for s in lines:
            i, last = 0, None
            while i + 1 < len(s):
                pair = (s[i], s[i + 1])
                if last == i and pair[0] == pair[1] and (s[i - 1], s[i]) == pair:
                    last = None
                else:
                    n[pair] += 1
                    last = i + 1
                i += 1
        if not n:
            break
        (a, b), c = min(n.items(), key=lambda x: (-x[1], x[0]))
        if c < 2:
            break
        out.append((a + b, c))
        for k, s in enumerate(lines):
            t, i = [], 0
            while i < len(s):
                if i + 1 < len(s) and s[i] == a and s[i + 1] == b:
                    t.append(a + b)
                    i += 2
                else:
                    t.append(s[i])
                    i += 1
            lines[k] = t
    return out
