"""Benchmark decontamination with an FM-index for each shard of the training text."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Suffix array by doubling; only suffixes that still tie are sorted again. The last symbol must be the unique least."""
    n = len(text)
    order = np.argsort(text, kind="stable")
    rank = np.empty(n, np.int64)
    heads = np.flatnonzero(np.concatenate([[True], text[order][1:] != text[order][:-1]]))
    rank[order] = np.repeat(heads, np.diff(np.append(heads, n)))  # a group's rank is its first place
    tied, h = order, 1
    while len(tied):
        second = rank[np.minimum(tied + h, n - 1)]
        first = rank[tied]
        by = np.lexsort((second, first))
        tied, first, second = tied[by], first[by], second[by]
        fresh = np.concatenate([[True], (first[1:] != first[:-1]) | (second[1:] != second[:-1])])
        starts = np.flatnonzero(fresh)
        sizes = np.diff(np.append(starts, len(tied)))
        group_first = np.flatnonzero(np.concatenate([[True], first[1:] != first[:-1]]))
        base = np.repeat(group_first, np.diff(np.append(group_first, len(tied))))
        rank[tied] = np.repeat((first - base)[starts] + starts, sizes)
        tied = tied[np.repeat(sizes, sizes) > 1]
        h *= 2
    out = np.empty(n, np.int64)
    out[rank] = np.arange(n)
    return out


class FMIndex:
    """Burrows-Wheeler transform in a wavelet matrix, with every `rate`-th text position kept for locating."""

    def __init__(self, text: np.ndarray, sigma: int, rate: int = 8):
        n = len(text)
        sa = suffix_array(text)
        bwt = text[sa - 1]
        self.n, self.levels = n, max(1, int(sigma - 1).bit_length())
        self.before = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=sigma))])
        self.ones, self.zeros, level = [], [], bwt
        for k in reversed(range(self.levels)):
            bit = (level >> k) & 1
            self.ones.append(np.concatenate([[0], np.cumsum(bit)]).astype(np.int32))
            self.zeros.append(n - int(bit.sum()))
            level = np.concatenate([level[bit == 0], level[bit == 1]])
        sampled = sa % rate == 0
        self.marked = np.concatenate([[0], np.cumsum(sampled)]).astype(np.int32)
        self.places = sa[sampled]

    def rank(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        """How often each symbol stands in the transform before its row."""
        low = np.zeros(len(row), np.int64)
        for k, ones, zeros in zip(reversed(range(self.levels)), self.ones, self.zeros, strict=True):
            bit = (symbol >> k) & 1
            a, b = ones[low], ones[row]
            low, row = np.where(bit, zeros + a, low - a), np.where(bit, zeros + b, row - b)
        return row - low

    def step_back(self, row: np.ndarray) -> np.ndarray:
        """The row of the suffix that starts one symbol earlier: reads the symbol and its rank on one way down."""
        symbol, low, at = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64), row
        for ones, zeros in zip(self.ones, self.zeros, strict=True):
            a, b = ones[low], ones[at]
            bit = ones[at + 1] - b
            symbol = symbol * 2 + bit
            low, at = np.where(bit, zeros + a, low - a), np.where(bit, zeros + b, at - b)
        return self.before[symbol] + at - low

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row range of each pattern (one per row of the matrix), by backward search."""
        low, high = np.zeros(len(patterns), np.int64), np.full(len(patterns), self.n, np.int64)
        live = np.arange(len(patterns))
        for c in patterns.T[::-1]:
            c = c[live]
            a = self.before[c] + self.rank(c, low[live])
            b = self.before[c] + self.rank(c, high[live])
            low[live], high[live] = a, b
            live = live[a < b]
        high = np.maximum(low, high)
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, at, steps, open_ = np.empty(len(rows), np.int64), rows.copy(), 0, np.arange(len(rows))
        while len(open_):
            m = self.marked[at]
            hit = self.marked[at + 1] > m
            out[open_[hit]] = self.places[m[hit]] + steps
            open_, at, steps = open_[~hit], self.step_back(at[~hit]), steps + 1
        return out


def benchmark_block(ids: list, texts: list, width: int = 10) -> dict:
    """Windows of one block of items: vocabulary hashes, window matrices by length, and the items of each window."""
    col = pa.array(texts, pa.string())
    words, owner = [], []
    for a, _, buf, offs in shared.slices(col):
        start, end = shared.word_spans(buf, offs, shared.ALNUM)
        words.append(shared.word_hashes(buf, start, end))
        owner.append(a + np.searchsorted(offs, start, "right") - 1)
    words = np.concatenate(words) if words else np.zeros(0, np.uint64)
    owner = np.concatenate(owner) if owner else np.zeros(0, np.int64)
    vocab, code = np.unique(words, return_inverse=True)
    code = code + 2  # 0 ends the text, 1 parts runs
    by_length: dict[int, list] = {}
    edges = np.searchsorted(owner, np.arange(len(ids) + 1))
    for i in range(len(ids)):
        own = code[edges[i] : edges[i + 1]]
        if len(own):
            w = np.lib.stride_tricks.sliding_window_view(own, min(width, len(own)))
            by_length.setdefault(w.shape[1], []).append((w, np.full(len(w), i)))
    groups = []
    for parts in by_length.values():
        w, inverse = np.unique(np.concatenate([p[0] for p in parts]), axis=0, return_inverse=True)
        pairs = np.unique(np.stack([inverse.ravel(), np.concatenate([p[1] for p in parts])]), axis=1)
        groups.append((w, np.searchsorted(pairs[0], np.arange(len(w) + 1)), pairs[1]))
    return {"ids": [None if i is None else str(i) for i in ids], "vocab": vocab, "groups": groups, "shortest": min((g[0].shape[1] for g in groups), default=0)}


def _hits(hashes: np.ndarray, doc: np.ndarray, n_docs: int, block: dict):
    """Which words of a shard are hit, and the pairs of document and item.

    Only runs of benchmark words as long as the shortest window can hold one, so only those are indexed.
    """
    hit, none = np.zeros(len(hashes), bool), (np.zeros(0, np.int64), np.zeros(0, np.int64))
    if not block["groups"] or not len(hashes):
        return hit, none
    vocab = block["vocab"]
    code = np.searchsorted(vocab, hashes)
    known = vocab[np.minimum(code, len(vocab) - 1)] == hashes
    joined = known & np.concatenate([[False], known[:-1] & (doc[1:] == doc[:-1])])
    first = np.flatnonzero(known & ~joined)
    length = np.diff(np.append(np.flatnonzero(~joined), len(hashes)))[np.searchsorted(np.flatnonzero(~joined), first)]
    keep = length >= block["shortest"]
    first, length = first[keep], length[keep]
    if not len(first):
        return hit, none
    put = np.cumsum(length + 1) - length - 1  # each run is followed by a parting symbol
    within = np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
    text = np.ones(int((length + 1).sum()) + 1, np.int64)
    source = np.full(len(text), -1, np.int64)
    place = np.repeat(put, length) + within
    source[place] = np.repeat(first, length) + within
    text[place] = code[source[place]] + 2
    text[-1] = 0
    index = FMIndex(text, len(vocab) + 2)
    edge = np.zeros(len(hashes) + 1, np.int64)
    pairs = [none]
    for windows, at, items in block["groups"]:
        low, high = index.search(windows)
        found = np.flatnonzero(high > low)
        if not len(found):
            continue
        counts = (high - low)[found]
        rows = np.repeat(low[found] - (np.cumsum(counts) - counts), counts) + np.arange(counts.sum())
        word = source[index.locate(rows)]
        np.add.at(edge, word, 1)
        np.add.at(edge, word + windows.shape[1], -1)
        seen = np.unique(np.stack([np.repeat(found, counts), doc[word]]), axis=1)
        k = at[seen[0] + 1] - at[seen[0]]
        item = items[np.repeat(at[seen[0]] - (np.cumsum(k) - k), k) + np.arange(k.sum())]
        pairs.append((np.repeat(seen[1], k), item))
    return np.cumsum(edge[:-1]) > 0, tuple(np.concatenate(x) for x in zip(*pairs, strict=True))


def _scan(texts: pa.Array, blocks: list):
    """For each text: words, hit words, matching item names, and the byte spans to remove."""
    for a, b, buf, offs in shared.slices(texts):
        start, end = shared.word_spans(buf, offs, shared.ALNUM)
        hashes = shared.word_hashes(buf, start, end)
        doc = np.searchsorted(offs, start, "right") - 1
        hit, names = np.zeros(len(hashes), bool), {}
        for block in blocks:
            block = getattr(block, "value", block)
            now, (who, what) = _hits(hashes, doc, b - a, block)
            hit |= now
            for d, i in set(zip(who.tolist(), what.tolist(), strict=True)):
                names.setdefault(d, set()).add(block["ids"][i])
        n_words, n_hit = np.bincount(doc, minlength=b - a), np.bincount(doc[hit], minlength=b - a)
        on = np.flatnonzero(hit)
        fresh = np.ones(len(on), bool)
        fresh[1:] = (on[1:] != on[:-1] + 1) | (doc[on[1:]] != doc[on[:-1]])
        spans: dict[int, list] = {}
        if len(on):
            begins = on[fresh]
            ends = np.append(on[np.flatnonzero(fresh)[1:] - 1], on[-1])
            for x, y in zip(begins.tolist(), ends.tolist(), strict=True):
                d = int(doc[x])
                spans.setdefault(d, []).append((int(start[x] - offs[d]), int(end[y] - offs[d])))
        for d in range(b - a):
            yield int(n_words[d]), int(n_hit[d]), sorted(names.get(d, set()) - {None}), spans.get(d, []), buf[offs[d] : offs[d + 1]]


def load_benchmark(benchmark: DataFrame, width: int, id_col: str, text_col: str, block_bytes: int) -> list:
    """Broadcast blocks of at most about `block_bytes` of item text each: a larger benchmark makes more blocks, not larger ones."""
    sc = benchmark.sparkSession.sparkContext
    items = benchmark.select(F.col(id_col).cast("string").alias("i"), F.col(text_col).alias("t")).where(F.col("t").isNotNull())
    total = items.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    n = -(-total // block_bytes) or 1
    blocks = []
    for k in range(n):
        rows = items.where(F.pmod(F.xxhash64(F.coalesce("i", "t")), F.lit(n)) == k).collect()
        blocks.append(sc.broadcast(benchmark_block([r.i for r in rows], [r.t for r in rows], width)))
    return blocks


def scan(docs: DataFrame, benchmark: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", extra: list[str] | None = None, block_bytes: int = 16 << 20) -> DataFrame:
    """Match every document against every benchmark item; documents are not shuffled.

    Words are runs of ASCII letters and digits and of all non-ASCII characters, A-Z lower-cased; a window is `width` consecutive
    words of an item, or the whole of a shorter one. Returns id, n_words, n_hit (words inside any occurrence), n_items,
    items (names, sorted as text), spans (byte offsets of merged removal spans), text (without those spans; null stays null)
    and `extra`. Null and empty texts have no words; items without words match nothing; items that repeat an id are one
    item; items without an id are matched like any other but have no name and so no place in n_items and items; repeated documents give repeated rows. Words are compared by 64 bits of hash.
    """
    blocks = load_benchmark(benchmark, width, item_col, item_text_col, block_bytes)
    extra = extra or []
    rows = docs.select(id_col, F.col(text_col).alias(text_col), *extra)
    names = [f for f in rows.schema.fields if f.name != text_col]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in names) + f", n_words long, n_hit long, items array<string>, spans array<struct<start:int,end:int>>, `{text_col}` string"

    def run(batches):
        for batch in batches:
            text = batch.column(batch.schema.get_field_index(text_col))
            got = list(_scan(text, blocks))
            null = text.is_null().to_pylist()
            cleaned = []
            for (_, n_hit, _, spans, raw), no in zip(got, null, strict=True):
                raw = raw.tobytes()
                if n_hit:
                    cuts = [0, *(x for s in spans for x in s), len(raw)]
                    raw = b"".join(raw[x:y] for x, y in zip(cuts[::2], cuts[1::2], strict=True))
                cleaned.append(None if no else raw.decode("utf-8", "replace"))
            columns = [batch.column(batch.schema.get_field_index(f.name)) for f in names]
            columns += [pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64()), pa.array([g[2] for g in got], pa.list_(pa.string()))]
            columns.append(pa.array([[{"start": x, "end": y} for x, y in g[3]] for g in got], pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))))
            columns.append(pa.array(cleaned, pa.string()))
            yield pa.RecordBatch.from_arrays(columns, [*(f.name for f in names), "n_words", "n_hit", "items", "spans", text_col])

    return rows.mapInArrow(shared.tidily(run), schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scan(shared.documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def digest(items) -> str:
    """The query's items_sha256 for a list of item names."""
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
