"""Hierarchical Pitman-Yor language model: seating sampled by Gibbs sweeps over hash buckets of word pairs.

Every word seen in training, and the start of a text, has a restaurant for what follows it; all share one parent, the word
restaurant, whose base is uniform over the known words and one unknown. Words are 64-bit hashes. Totals of the most frequent
words' restaurants (their number has a bound) travel to the driver and back; a rarer word's pairs meet in the bucket of that
word, as a context and as a dish, so its totals stay there. A sweep and the scoring are narrow maps over the same files.
Pairs of two rare words keep one table each (`frame_of` chooses the frequent words so that a second one is rarer than 1 in
1,000) and are scored when what both words' buckets know of them has met. Pairs that make up a notable share of all tokens
are kept without the places they stand at, so that no bucket gathers them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

END = shared.hash_words([b" end"])[0]  # holds a space, as no word does
TAIL = np.uint64(1 << 63)  # marks the code of a rare word: 48 bits of its hash, enough inside a bucket; a frequent word's code is its number
LOW = np.uint64((1 << 48) - 1)
STIRLING = 256
CODE_BITS = 21
_I64 = np.int64


# --- packing of arrays ----------------------------------------------------------------------------------------------------


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays as one string: bytes of like weight lie together, then zstandard."""
    head = [len(arrays).to_bytes(2, "little"), *(a.dtype.str.encode().ljust(4) + len(a).to_bytes(8, "little") for a in arrays)]
    body = b"".join(np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.itemsize).T.tobytes() for a in arrays if len(a))
    return b"".join([*head, len(body).to_bytes(8, "little"), zstandard.ZstdCompressor(level=1).compress(body)])


def unpack(raw: bytes) -> list[np.ndarray]:
    many = int.from_bytes(raw[:2], "little")
    at = 2 + 12 * many
    size = int.from_bytes(raw[at : at + 8], "little")
    body = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw[at + 8 :], size) if size else b"", np.uint8)
    arrays, x = [], 0
    for k in range(2, at, 12):
        kind, n = np.dtype(raw[k : k + 4].decode().strip()), int.from_bytes(raw[k + 4 : k + 12], "little")
        y = x + n * kind.itemsize
        arrays.append(np.ascontiguousarray(body[x:y].reshape(kind.itemsize, n).T).view(kind).ravel() if n else np.zeros(0, kind))
        x = y
    return arrays


def least_type(a: np.ndarray) -> np.ndarray:
    top = int(a.max(initial=0))
    return a.astype(np.uint8 if top < 256 else np.uint16 if top < 65536 else np.uint32 if top < 2**32 else np.uint64)


# --- tokens ---------------------------------------------------------------------------------------------------------------


def tokens(text: pa.Array):
    """For each slice: first row, rows, token hashes (words, then one END a text), and each token's text."""
    for a, b, buf, offs in shared.slices(text):
        start, end = shared.word_spans(buf, offs, shared.SPACED)
        h = shared.word_hashes(buf, start, end)
        n = b - a
        words = np.diff(np.searchsorted(start, offs))
        doc = np.repeat(np.arange(n), words + 1)
        out = np.full(len(doc), END, np.uint64)
        out[np.arange(len(h)) + np.repeat(np.arange(n), words)] = h
        yield a, n, out, doc


# --- seating --------------------------------------------------------------------------------------------------------------


def stirling(d: float, most: int = STIRLING) -> np.ndarray:
    """Logs of generalised Stirling numbers: [c, t] weighs the ways to seat c customers at t tables under discount d."""
    s = np.full((most + 1, most + 1), -np.inf)
    s[1, 1] = 0
    t = np.arange(1, most + 1)
    with np.errstate(divide="ignore"):
        for c in range(1, most):
            s[c + 1, 1:] = np.logaddexp(s[c, :-1], np.log(np.maximum(c - d * t, 1e-300)) + s[c, 1:])
    return s


def seat(count: np.ndarray, rest: np.ndarray, p: np.ndarray, d: float, table: np.ndarray | None, rng: np.random.Generator) -> np.ndarray:
    """Gibbs draw of the number of tables of each dish given its customers and the other dishes' tables.

    rest: strength + discount x tables of the other dishes, as of the last sweep; p: the parent's probability of the dish. The
    t-th table opens at the rate (rest + discount x (t - 1)) x p. Up to STIRLING customers the draw is from the full
    conditional; further customers of a dish sit down in growing parties, at the rates in force when the party comes in.
    Without a table of Stirling numbers every dish has one table.
    """
    t = np.minimum(count, 1).astype(_I64)
    if table is None:
        return t
    small = np.minimum(count, STIRLING)
    log_p = np.log(np.maximum(p, 1e-300))
    many = np.flatnonzero(small > 1)
    many = many[np.argsort(small[many], kind="stable")]
    cuts = np.flatnonzero(np.diff(small[many])) + 1
    for group in np.split(many, cuts) if len(many) else []:
        c = int(small[group[0]])
        for part in np.array_split(group, -(-len(group) * c // 1_000_000)):
            w = np.log(rest[part, None] + d * np.arange(c))
            w += log_p[part, None]
            w = w.cumsum(1) + table[c, 1 : c + 1]
            w = np.exp(w - w.max(1, keepdims=True)).cumsum(1)
            t[part] = 1 + (w < rng.random(len(part))[:, None] * w[:, -1:]).sum(1)
    big = np.flatnonzero(count > STIRLING)
    n = np.full(len(big), STIRLING, _I64)
    while len(big):
        party = np.minimum(n // 4, count[big] - n)
        open_ = (rest[big] + d * t[big]) * p[big]
        t[big] += rng.binomial(party, np.clip(open_ / (open_ + n - d * t[big]), 0, 1))
        n += party
        more = n < count[big]
        big, n = big[more], n[more]
    return t


# --- the model ------------------------------------------------------------------------------------------------------------


class Frame:
    """What stays fixed through the sweeps: frequent words (sorted hashes), their counts, totals, discounts and strengths.

    A frequent word's number is its place among the hashes, as a dish and as a context; `start` is the context of first words.
    """

    def __init__(self, hashes, counts, n, v, d_root, strength=5.0, root_strength=50.0):
        order = np.argsort(hashes)
        self.hashes, self.counts, self.n, self.v = hashes[order], counts[order], n, v
        self.start = len(hashes)
        self.d_root, self.strength, self.root_strength, self.d = d_root, strength, root_strength, 0.75

    def word_ids(self, h: np.ndarray) -> np.ndarray:
        """Place among the frequent words, or -1."""
        if not len(self.hashes):
            return np.full(len(h), -1)
        at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return np.where(self.hashes[at] == h, at, -1)

    def codes(self, h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes of the words and of their contexts."""
        ids = self.word_ids(h)
        w = np.where(ids >= 0, ids.astype(np.uint64), (h & LOW) | TAIL)
        u = np.full(len(w), self.start, np.uint64)
        u[1:] = np.where(doc[1:] == doc[:-1], w[:-1], np.uint64(self.start))
        return w, u


def pair_code(w: np.ndarray, u: np.ndarray) -> np.ndarray:
    """One number for a pair of frequent words."""
    return (w << np.uint64(CODE_BITS)) | u


def places(code: np.ndarray, buckets: int) -> np.ndarray:
    return shared.mix(code ^ np.uint64(0x9E3779B97F4A7C15)) % np.uint64(buckets)


def found(sorted_: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Place of each x in a sorted array, or -1."""
    if not len(sorted_):
        return np.full(len(x), -1)
    at = np.minimum(np.searchsorted(sorted_, x), len(sorted_) - 1)
    return np.where(sorted_[at] == x, at, -1)


class State:
    """One sample: tables of each frequent context, probability of each frequent word in the parent, totals of the parent."""

    def __init__(self, tables, head_p, customers, tables_root):
        self.tables, self.head_p, self.customers, self.tables_root = tables, head_p, customers, tables_root

    def root_new(self, frame: Frame) -> float:
        return (frame.root_strength + frame.d_root * self.tables_root) / (frame.root_strength + self.customers) / (frame.v + 1)


def runs(*columns: np.ndarray) -> np.ndarray:
    """Where runs of equal rows begin."""
    new = np.ones(len(columns[0]), bool)
    if len(new):
        new[1:] = np.any([c[1:] != c[:-1] for c in columns], axis=0)
    return np.flatnonzero(new)


def step(x: np.ndarray) -> np.ndarray:
    return np.diff(x, prepend=x.dtype.type(0))


def summed(order: np.ndarray, n: np.ndarray, *columns: np.ndarray) -> list[np.ndarray]:
    """Equal rows, which `order` brings together, become one with the sum of n."""
    columns, n = [c[order] for c in columns], n[order]
    at = runs(*columns)
    return [*(c[at] for c in columns), np.add.reduceat(n, at) if len(at) else n]


def merge_bucket(blobs) -> tuple[bytes, bytes]:
    """One bucket's pairs with their counts, and where they stand.

    Three parts with places (pairs of frequent words as one code; a rare word and its context; a rare context and a frequent
    word), then hot pairs and copies. blobs: (batch of documents, payload). A place is the number of its batch here x 2^24 +
    its row there.
    """
    batches, parts = [], [[], [], []]
    hot, copies = [], []
    for number, raw in blobs:
        x = unpack(raw)
        on = np.unpackbits(x[0])
        for k in range(3):
            g, o, per, doc, n = x[1 + 5 * k : 6 + 5 * k]
            n = n.astype(_I64)
            parts[k].append((np.repeat(np.cumsum(g), per), np.repeat(o, per), doc.astype(_I64) + (len(batches) << 24), n, n * on[doc]))
        hot.append((np.cumsum(x[16]), x[17].astype(_I64)))
        copies.append((np.cumsum(x[18]), x[19], x[20], x[21].astype(_I64)))
        batches.append(number)
    pairs, where = [], [np.array(batches, _I64)]
    for part in parts:
        g, o, doc, n, learned = (np.concatenate(x) for x in zip(*part, strict=True))
        order = np.lexsort((o, g)) if o.any() else np.argsort(g, kind="stable")  # batches ascend, and so do rows in a batch
        g, o, doc, n = g[order], o[order], doc[order], n[order]
        first = runs(g, o)
        count = np.add.reduceat(learned[order], first) if len(first) else n
        pairs += [step(g[first]), o[first], least_type(count)]
        where += [least_type(np.diff(np.append(first, len(g)))), least_type(doc), least_type(n)]
    code, n = (np.concatenate(x) for x in zip(*hot, strict=True))
    code, n = summed(np.argsort(code), n, code)
    u, w, dest, m = (np.concatenate(x) for x in zip(*copies, strict=True))
    u, w, dest, m = summed(np.lexsort((dest, w, u)), m, u, w, dest)
    return pack(*pairs, step(code), least_type(n), step(u), w, least_type(dest), least_type(m)), pack(*where)


def group_of(sorted_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of a sorted array, and which of them each element is."""
    at = runs(sorted_)
    return sorted_[at], np.repeat(np.arange(len(at)), np.diff(np.append(at, len(sorted_))))


class Bucket:
    """The pairs of a bucket. Those of a rare word w lie in w's bucket; those of a rare context and a frequent word in the
    context's; pairs of two rare words in w's, with their places, and once more, without, in the context's (`copy`)."""

    def __init__(self, raw: bytes):
        x = unpack(raw)
        code, hot = np.cumsum(x[0]), np.cumsum(x[9])
        mask = np.uint64((1 << CODE_BITS) - 1)
        w = [code >> np.uint64(CODE_BITS), np.cumsum(x[3]), x[7], hot >> np.uint64(CODE_BITS), x[12]]
        u = [code & mask, x[4], np.cumsum(x[6]), hot & mask, np.cumsum(x[11])]
        edge = np.cumsum([0, *map(len, w)])
        self.w, self.u, self.dest = np.concatenate(w), np.concatenate(u), x[13]
        self.count = np.concatenate([c.astype(_I64) for c in (x[2], x[5], x[8], x[10], x[14])])
        part = lambda k: np.arange(edge[k], edge[k + 1])
        self.placed, self.hot, self.copy = int(edge[3]), part(3), part(4)
        self.tail = part(1)
        own = u[1] < TAIL
        self.own, self.both_rare = self.tail[own], self.tail[~own]
        self.known = np.concatenate([part(0), part(3)])  # both frequent
        self.after_rare = part(2)
        self.rare_u = np.concatenate([part(2), part(4)])
        self.head_u = np.concatenate([self.known, self.own])
        self.head = np.concatenate([self.known, self.after_rare])
        self.word, self.context = np.zeros(len(self.w), _I64), np.zeros(len(self.w), _I64)
        self.word[self.head], self.context[self.head_u] = self.w[self.head], self.u[self.head_u]
        self.tail_words, self.tail_of = group_of(w[1])
        names = [group_of(u[k]) for k in (2, 4)]
        every = np.union1d(names[0][0], names[1][0])
        self.rare_of = np.concatenate([np.searchsorted(every, n)[at] for n, at in names])
        self.rare_customers = np.bincount(self.rare_of, self.count[self.rare_u], len(every)).astype(_I64)

    def tail_count(self) -> np.ndarray:
        return np.bincount(self.tail_of, self.count[self.tail], len(self.tail_words)).astype(_I64)

    def rare_tables(self, t: np.ndarray) -> np.ndarray:
        return np.bincount(self.rare_of, t[self.rare_u], len(self.rare_customers)).astype(_I64)

    def sweep(self, frame: Frame, state: State, table, root_table, rng):
        """Tables of each pair, and for the rare words the customers and tables in the parent."""
        t = np.minimum(self.count, 1)
        rest = frame.strength + frame.d * np.maximum(state.tables[self.context] - 1, 0)
        on = self.known[self.count[self.known] > 1]
        t[on] = seat(self.count[on], rest[on], state.head_p[self.word[on]], frame.d, table, rng)
        at = np.flatnonzero(self.count[self.after_rare] > 1)
        on = self.after_rare[at]
        for _ in range(2 if len(on) else 0):  # all pairs of a rare context lie here, so they are swept to and fro here
            others = np.maximum(self.rare_tables(t)[self.rare_of[at]] - t[on], 0)
            t[on] = seat(self.count[on], frame.strength + frame.d * others, state.head_p[self.word[on]], frame.d, table, rng)
        on = self.own[self.count[self.own] > 1]
        for again in range(2):  # and so do the parent's customers of a rare word
            customers = np.bincount(self.tail_of, t[self.tail], len(self.tail_words)).astype(_I64)
            root_rest = np.full(len(customers), frame.root_strength + frame.d_root * max(0, state.tables_root - 1))
            tables_root = seat(customers, root_rest, np.full(len(customers), 1 / (frame.v + 1)), frame.d_root, root_table, rng)
            if again or not len(on):
                break
            p = np.maximum(customers - frame.d_root * tables_root, 0) / (frame.root_strength + state.customers) + state.root_new(frame)
            t[on] = seat(self.count[on], rest[on], p[self.tail_of[on - self.tail[0]]], frame.d, table, rng)
        return t, customers, tables_root

    def sums(self, frame: Frame, t, customers, tables_root, width: int):
        """What a sweep adds to the totals: by frequent context, by frequent word, and for the rare words together."""
        out = np.zeros(width, _I64)
        c = frame.start + 1
        out[:c] += np.bincount(self.context[self.head_u], t[self.head_u], c).astype(_I64)
        out[c : c + frame.start] += np.bincount(self.word[self.head], t[self.head], frame.start).astype(_I64)
        out[-2] += int(customers.sum())
        out[-1] += int(tables_root.sum())
        return out


CHUNK = 4096


def _totals(kept: DataFrame, work, width: int) -> np.ndarray:
    """Sum of work(bucket number, Bucket) over all buckets: each task sums its own, chunks of the vector are added up apart."""

    def run(batches):
        total = np.zeros(width, _I64)
        for batch in batches:
            for number, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                total += work(number, Bucket(raw.as_py()))
        rows = [(k, pack(total[a : a + CHUNK])) for k, a in enumerate(range(0, width, CHUNK)) if total[a : a + CHUNK].any()]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["k", "v"])

    def add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = sum(unpack(raw.as_py())[0] for batch in batches for raw in batch.column("v"))
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([pack(total)], pa.binary())], ["k", "v"])

    out = np.zeros(width, _I64)
    for r in kept.select("bucket", "pairs").mapInArrow(run, "k int, v binary").groupBy("k").applyInArrow(add, "k int, v binary").collect():
        out[r.k * CHUNK : r.k * CHUNK + CHUNK] = unpack(bytes(r.v))[0]
    return out


def count_words(docs: DataFrame, text_col: str) -> DataFrame:
    """(h, c): training tokens by hash, END included; counted in the task first."""

    def run(batches):
        held, size = [], 0

        def merged():
            h = np.concatenate([x[0] for x in held])
            c = np.concatenate([x[1] for x in held])
            u, at = np.unique(h, return_inverse=True)
            return u, np.bincount(at, c, len(u)).astype(_I64)

        def batch_of(u, c):
            return pa.RecordBatch.from_arrays([pa.array(u.view(_I64)), pa.array(c)], ["h", "c"])

        for batch in batches:
            for _, _, h, _ in tokens(batch.column(0)):
                u, c = np.unique(h, return_counts=True)
                held.append((u, c))
                size += len(u)
                if size > 2_000_000:
                    held = [merged()]
                    size = len(held[0][0])
                    if size > 1_500_000:
                        yield batch_of(*held[0])
                        held, size = [], 0
        if held:
            yield batch_of(*merged())

    return docs.select(text_col).mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def frame_of(words: DataFrame, head: int, most: int = 1 << 20) -> Frame:
    """Totals and the frequent words: as many as fit into `head` when words of equal frequency class go together.

    Further classes join them, up to `most` words, while a word and a context left out could share a second table with odds
    over 1 in 1,000 (their rate is at most (strength + tables of the context) x the share of the word).
    """
    level = F.floor(F.log2("c") * 8)
    classes = words.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("s")).collect()
    n, v = sum(r.s for r in classes), sum(r.n for r in classes)
    got, cut = 0, None
    for r in sorted(classes, key=lambda r: -r.level):
        top = 2 ** ((r.level + 1) / 8)
        if got + r.n > (most if head and (5 + top) * top / n > 0.001 else head):
            break
        got, cut = got + r.n, r.level
    few = {r.c: r.n for r in words.where("c <= 2").groupBy("c").agg(F.count(F.lit(1)).alias("n")).collect()}
    d = few.get(1, 0) / max(1, few.get(1, 0) + 2 * few.get(2, 0))
    rows = words.where(level >= cut).collect() if cut is not None else []
    hashes = np.array([r.h for r in rows], _I64).view(np.uint64)
    return Frame(hashes, np.array([r.c for r in rows], _I64), int(n), int(v), min(0.95, max(0.1, d)))


def hot_pairs(rows: DataFrame, frame, n: int, least: int, sample: int = 8_000_000, most: int = 1 << 20) -> np.ndarray:
    """Codes of the pairs of frequent words that a bounded sample of the documents holds `least` times or more, `most` at most.

    They only decide which pairs travel without places: any answer gives the same scores.
    """
    parts = max(1, -(-n // sample))

    def run(batches):
        kept = np.zeros(0, np.uint64), np.zeros(0, _I64)
        for batch in batches:
            for _, _, h, doc in tokens(batch.column(0)):
                w, u = frame.value.codes(h, doc)
                codes = np.sort(pair_code(w, u)[(w < TAIL) & (u < TAIL)])
                both = np.concatenate([kept[0], codes])
                kept = tuple(summed(np.argsort(both, kind="stable"), np.concatenate([kept[1], np.ones(len(codes), _I64)]), both))
        yield pa.RecordBatch.from_arrays([pa.array(kept[0].view(_I64)), pa.array(kept[1])], ["code", "n"])

    few = rows.where(F.pmod("ref", F.lit(parts)) == 0).select("text")
    got = few.mapInArrow(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).where(F.col("n") >= least)
    got = shared.keep(got, "hot")
    cut, size = least, 0
    for r in sorted(got.groupBy("n").agg(F.count(F.lit(1)).alias("many")).collect(), key=lambda r: -r.n):
        size += r.many
        if size > most:
            cut = r.n + 1
            break
    codes = got.where(F.col("n") >= cut).select("code").toArrow().column(0).to_numpy()
    shared.forget(got)
    return np.sort(codes.astype(_I64).view(np.uint64))


DOCUMENTS = -1  # the bucket number of rows that name a batch's documents


def occurrences(rows: DataFrame, frame, hot, buckets: int, flush: int = 600_000) -> DataFrame:
    """(bucket, batch, pairs, places): for each bucket its word pairs and the documents they stand in, and for each batch of
    documents (what a task holds at a time) their refs. Pairs of a rare word meet by word, other pairs of a rare context by
    context, the rest by pair."""

    def split(h, doc, train):
        """A slice's tokens: three parts (place, group, other, document), numbers of hot pairs, copies."""
        f = frame.value
        w, u = f.codes(h, doc)
        before = np.zeros_like(h)
        before[1:] = h[:-1]
        rare_w, rare_u = w >= TAIL, u >= TAIL
        on = np.flatnonzero(~rare_w & ~rare_u)
        code = pair_code(w[on], u[on])
        at = found(hot.value, code)
        bare = at >= 0
        bare_at = at[bare & (train[doc[on]] > 0)]
        code, on = code[~bare], on[~bare]
        parts = [(places(code, buckets).astype(np.int32), code, np.zeros(len(on), np.uint8), doc[on])]
        on = np.flatnonzero(rare_w)
        parts.append((places(h[on] | TAIL, buckets).astype(np.int32), w[on], u[on], doc[on]))
        on = np.flatnonzero(rare_u & ~rare_w)
        parts.append((places(before[on] | TAIL, buckets).astype(np.int32), u[on], w[on], doc[on]))
        on = np.flatnonzero(rare_u & rare_w)
        copies = (places(before[on] | TAIL, buckets).astype(np.int32), u[on], w[on], places(h[on] | TAIL, buckets).astype(np.uint32), train[doc[on]].astype(_I64))
        return parts, bare_at, copies

    def blobs(batch, held, ref, train):
        sections, edges, wanted = [], [], []
        for k in range(3):
            place, g, o, doc = (np.concatenate(x) for x in zip(*(h[0][k] for h in held), strict=True))
            order = np.lexsort((g, place)) if not k else np.lexsort((o, g, place))  # documents ascend already
            place, g, o, doc = place[order], g[order], o[order], doc[order]
            at = runs(place, g, o, doc)
            n = np.diff(np.append(at, len(g)))
            place, g, o, doc = place[at], g[at], o[at], doc[at]
            first = np.zeros(len(g), bool)
            first[runs(place, g, o)] = True
            sections.append((g, o, doc, n, first))
            edges.append(place)
        bare = np.bincount(np.concatenate([h[1] for h in held]), minlength=len(hot.value))
        on = np.flatnonzero(bare)
        place = places(hot.value[on], buckets).astype(np.int32)
        order = np.argsort(place, kind="stable")
        free, edge = (hot.value[on][order], bare[on][order]), place[order]
        edges.append(edge)
        place, u, w, dest, m = (np.concatenate(x) for x in zip(*(h[2] for h in held), strict=True))
        place, u, w, dest, m = summed(np.lexsort((dest, w, u, place)), m, place, u, w, dest)
        edges.append(place)
        wanted = np.unique(np.concatenate([np.unique(e) for e in edges]))
        low, high = (np.stack([np.searchsorted(e, wanted, side) for e in edges]).T.tolist() for side in ("left", "right"))
        number, out, marks = [DOCUMENTS], [pack(ref)], np.packbits(train)
        for k, lo, hi in zip(wanted.tolist(), low, high, strict=True):
            arrays = [marks]
            for (g, o, doc, n, first), x, y in zip(sections, lo, hi, strict=False):
                at = np.flatnonzero(first[x:y])
                arrays += [step(g[x:y][at]), o[x:y][at], least_type(np.diff(np.append(at, y - x))), least_type(doc[x:y]), least_type(n[x:y])]
            x, y = lo[3], hi[3]
            arrays += [step(free[0][x:y]), least_type(free[1][x:y])]
            x, y = lo[4], hi[4]
            arrays += [step(u[x:y]), w[x:y], dest[x:y], least_type(m[x:y])]
            number.append(k)
            out.append(pack(*arrays))
        return pa.RecordBatch.from_arrays([pa.array(number, pa.int32()), pa.array([batch] * len(number), pa.int64()), pa.array(out, pa.binary())], ["bucket", "batch", "payload"])

    def run(batches):
        held, refs, size, docs_held = [], [], 0, 0
        name = TaskContext.get().partitionId() << 32
        for batch in batches:
            ref, train = batch.column(0).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False).astype(np.uint8)
            for a, n, h, doc in tokens(batch.column(2)):
                parts, bare, copies = split(h, doc, train[a : a + n])
                held.append(([(*p[:3], (p[3] + docs_held).astype(np.int32)) for p in parts], bare, copies))
                refs.append((ref[a : a + n], train[a : a + n]))
                size, docs_held = size + len(h), docs_held + n
                if size >= flush:
                    yield blobs(name, held, *(np.concatenate(x) for x in zip(*refs, strict=True)))
                    held, refs, size, docs_held, name = [], [], 0, 0, name + 1
        if held:
            yield blobs(name, held, *(np.concatenate(x) for x in zip(*refs, strict=True)))

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs_ = ((n, x.as_py()) for batch in batches for n, x in zip(batch.column("batch").to_pylist(), batch.column("payload"), strict=True))
        bucket, salt = key[0].as_py(), key[1].as_py()
        names = ["bucket", "batch", "pairs", "places"]
        if bucket == DOCUMENTS:
            yield from (pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([n], pa.int64()), pa.array([raw], pa.binary()), pa.nulls(1, pa.binary())], names) for n, raw in blobs_)
        else:
            pairs, where = merge_bucket(blobs_)
            yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([salt], pa.int64()), pa.array([pairs], pa.binary()), pa.array([where], pa.binary())], names)

    salt = F.when(F.col("bucket") == DOCUMENTS, F.col("batch")).otherwise(0)
    packed = rows.select("ref", "train", "text").mapInArrow(run, "bucket int, batch long, payload binary")
    return packed.withColumn("salt", salt).groupBy("bucket", "salt").applyInArrow(merge, "bucket int, batch long, pairs binary, places binary")


class Chain:
    """The Gibbs chain: every sweep is one job over the buckets; its totals make the next state."""

    def __init__(self, kept: DataFrame, frame: Frame, seed: int, sampled: bool = True):
        self.kept, self.frame, self.seed = kept, frame, seed
        c = frame.start + 1
        self.width = width = c + frame.start + 2

        def first(number, b):
            out = np.zeros(2 * c + 2, _I64)
            out[:c] = np.bincount(b.context[b.head_u], b.count[b.head_u], c).astype(_I64)
            out[c : 2 * c] = np.bincount(b.context[b.head_u], b.count[b.head_u] > 0, c).astype(_I64)
            once = b.count[: len(b.w) - len(b.copy)]
            out[-2:] = (once == 1).sum(), (once == 2).sum()
            return out

        got = _totals(kept, first, 2 * c + 2)
        self.customers = got[:c]
        frame.d = float(min(0.95, max(0.1, got[-2] / max(1, got[-2] + 2 * got[-1]))))
        self.table, self.root_table = (stirling(frame.d), stirling(frame.d_root)) if sampled else (None, None)
        self.state = State(got[c : 2 * c], frame.counts / max(1, frame.n), frame.n, frame.v)
        self.samples: list[tuple[State, State, int]] = []

    def sweep(self, number: int, sample: bool) -> None:
        frame, state, table, root_table, seed, width = self.frame, self.state, self.table, self.root_table, self.seed, self.width
        held = self.kept.sparkSession.sparkContext.broadcast((frame, state, table, root_table))

        def work(bucket, b):
            f, s, x, y = held.value
            return b.sums(f, *b.sweep(f, s, x, y, shared.session_seed(seed, number, bucket)), width)

        got = _totals(self.kept, work, width)
        c = frame.start + 1
        customers = got[c : c + frame.start]
        root_rest = np.full(len(customers), frame.root_strength + frame.d_root * max(0, state.tables_root - 1))
        tables = seat(customers, root_rest, np.full(len(customers), 1 / (frame.v + 1)), frame.d_root, root_table, shared.session_seed(seed, number))
        n, t = int(customers.sum() + got[-2]), int(tables.sum() + got[-1])
        new = State(got[:c], None, n, t)
        new.head_p = (customers - frame.d_root * tables) / (frame.root_strength + n) + new.root_new(frame)
        if sample:
            self.samples.append((state, new, number))
        self.state = new
        held.unpersist()

    def pair_scores(self, bucket: int, b: Bucket) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """log10 of each pair's predictive probability, averaged over the samples; and, a row for each sample, the parent's
        probability of each pair of two rare words and what each copy's context leaves for the parent."""
        frame, total, rare, left = self.frame, np.zeros(len(b.w)), [], []
        all_ = frame.strength + self.customers[b.context].astype(float)
        all_[b.rare_u] = frame.strength + b.rare_customers[b.rare_of]
        for before, after, number in self.samples:
            t, customers, tables_root = b.sweep(frame, before, self.table, self.root_table, shared.session_seed(self.seed, number, bucket))
            p = np.zeros(len(b.w))
            p[b.head] = after.head_p[b.word[b.head]]
            p[b.tail] = (np.maximum(customers - frame.d_root * tables_root, 0) / (frame.root_strength + after.customers) + after.root_new(frame))[b.tail_of]
            tables = after.tables[b.context]
            tables[b.rare_u] = b.rare_tables(t)[b.rare_of]
            passed = (frame.strength + frame.d * tables) / all_
            total += (b.count - frame.d * t) / all_ + passed * p
            rare.append(p[b.both_rare])
            left.append(passed[b.copy])
        return np.log10(np.maximum(total / len(self.samples), 1e-300)), np.array(rare), np.array([*left, 1 / all_[b.copy]])


def by_batch(batches: np.ndarray, at: np.ndarray, place: np.ndarray, lm: np.ndarray, known: np.ndarray, base: np.ndarray) -> pa.RecordBatch:
    """Sums of each batch of documents: rows there, then what they add to known, base and score."""
    size = len(place)
    lm = np.bincount(at, lm, size).astype(np.float32)
    known = np.bincount(at, known, size).astype(_I64)
    base = np.bincount(at, base, size).astype(np.float64)
    edge = np.searchsorted(place >> 24, np.arange(len(batches) + 1))
    out = []
    for x, y in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        row = place[x:y] & ((1 << 24) - 1)
        has = np.flatnonzero(base[x:y])
        out.append(pack(np.diff(row, prepend=0).astype(np.uint32), lm[x:y], least_type(np.diff(has, prepend=0)), least_type(known[x:y][has]), base[x:y][has]))
    return pa.RecordBatch.from_arrays([pa.array([SUMS] * len(out), pa.int32()), pa.array(batches), pa.array(out, pa.binary())], ["kind", "target", "payload"])


SUMS, STANDING, LEFT, HOT = range(4)


def score(
    docs: DataFrame, train: Column, head: int = 262144, burn: int = 2, samples: int = 3, seed: int = 11, id_col: str = "doc_id", text_col: str = "text",
    bucket_tokens: int = 1_500_000, hot: int = 3, seating: str = "sampled",
) -> DataFrame:
    """Score all documents by a model learned from the rows where `train` holds (null: not).

    Returns id, n_tokens, n_known, train_tokens, base_score (smoothed word counts) and score (the hierarchical model's log10
    probability of the text and its end; the seating is sampled, predictive probabilities are averaged over `samples` sweeps
    after `burn`). Null and empty texts are one token, the end. Rows that repeat an id and text get equal scores. With no
    training rows every word is unknown. An empty table gives an empty result. `head` words at least have their totals on the
    driver, pairs seen `hot` times or more in a sample may travel without places; neither changes the model.
    seating="single" seats every dish at one table (interpolated Kneser-Ney) in place of the sampler.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("ref"), F.coalesce(train, F.lit(False)).alias("train"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    words = shared.keep(count_words(rows.where("train"), "text"), "words")
    frame = frame_of(words, head)
    shared.forget(words)
    # hashes and counts of frequent words, and codes of hot pairs: both bounded
    held = spark.sparkContext.broadcast(frame)
    hot_codes = hot_pairs(rows, held, frame.n, hot)
    hot_held = spark.sparkContext.broadcast(hot_codes)
    buckets = max(64, -(-frame.n // bucket_tokens))
    both = shared.keep(occurrences(rows, held, hot_held, buckets), "pairs")
    kept, names = both.where(F.col("bucket") != DOCUMENTS), both.where(F.col("bucket") == DOCUMENTS).select("batch", F.col("pairs").alias("payload"))
    chain = Chain(kept, frame, seed, {"sampled": True, "single": False}[seating])
    for k in range(burn + samples):
        chain.sweep(k, k >= burn)
    n, v = frame.n, frame.v
    kept, chain.kept = chain.kept, None
    models = spark.sparkContext.broadcast(chain)

    def weigh(c):
        return np.log10((c + 0.1) / (n + 0.1 * (v + 1)))

    def local(batches):
        f, (codes, scores) = held.value, hot_models.value
        base = weigh(f.counts)
        for batch in batches:
            out = [np.zeros(batch.num_rows, _I64), np.zeros(batch.num_rows, _I64), np.zeros(batch.num_rows), np.zeros(batch.num_rows)]
            for a, m, h, doc in tokens(batch.column(2)):
                w, u = f.codes(h, doc)
                on = np.flatnonzero(w < TAIL)
                ids = w[on].astype(_I64)
                out[0][a : a + m] = np.bincount(doc, minlength=m)
                out[1][a : a + m] = np.bincount(doc[on], minlength=m)
                out[2][a : a + m] = np.bincount(doc[on], base[ids], m)
                on = on[u[on] < TAIL]
                at = found(codes, pair_code(w[on], u[on]))
                out[3][a : a + m] = np.bincount(doc[on[at >= 0]], scores[at[at >= 0]], m)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *map(pa.array, out)], ["id", "ref", "n_tokens", "known", "base", "lm"])

    def far(batches):
        """Each bucket's sums by batch of documents, its hot pairs' scores, its pairs of two rare words and what their contexts
        leave for them."""
        for batch in batches:
            for number, raw, where in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
                b = Bucket(raw.as_py())
                batches_, *where = unpack(where.as_py())
                b_per, b_doc, b_n = (np.concatenate([x.astype(_I64) for x in where[k::3]]) for k in range(3))
                pair, rare, left = models.value.pair_scores(number, b)
                target, out, kind = [0], [pack(pair_code(b.w[b.hot], b.u[b.hot]), pair[b.hot])], [HOT]
                pair[b.both_rare] = 0  # they are scored by `finish`
                per = np.repeat(np.arange(b.placed), b_per)
                count = np.zeros(b.placed, _I64)
                count[b.tail] = b.tail_count()[b.tail_of]
                tail = np.zeros(b.placed, bool)
                tail[b.tail] = True
                place, at = np.unique(b_doc, return_inverse=True)
                yield by_batch(batches_, at, place, pair[per] * b_n, b_n * (tail & (count > 0))[per], np.where(tail, weigh(count), 0)[per] * b_n)
                k = b.both_rare
                if len(k):
                    mine = np.zeros(b.placed, bool)
                    mine[k] = True
                    on = mine[per]
                    target.append(number)
                    kind.append(STANDING)
                    out.append(pack(b.w[k], b.u[k], least_type(b.count[k]), rare.ravel(), b_per[k], b_doc[on], b_n[on], batches_))
                order = np.argsort(b.dest, kind="stable")
                goes, c, left = b.dest[order], b.copy[order], left[:, order]
                first = runs(goes)
                for x, y in zip(first.tolist(), np.append(first, len(goes))[1:].tolist(), strict=True):
                    target.append(int(goes[x]))
                    kind.append(LEFT)
                    out.append(pack(b.w[c[x:y]], b.u[c[x:y]], left[:, x:y].ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(kind, pa.int32()), pa.array(target, pa.int64()), pa.array(out, pa.binary())], ["kind", "target", "payload"])

    def finish(_: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, parts = None, []
        for batch in batches:
            for kind, raw in zip(batch.column("kind").to_pylist(), batch.column("payload"), strict=True):
                if kind == STANDING:
                    here = unpack(raw.as_py())
                else:
                    w, u, left = unpack(raw.as_py())
                    parts.append((w, u, left.reshape(samples + 1, -1)))
        w, u, count, rare, per, doc, times, numbers = here
        aw, au, left = (np.concatenate(x, -1) for x in zip(*parts, strict=True))
        left = left[:, np.lexsort((au, aw))][:, np.argsort(np.lexsort((u, w)))]  # both hold the same pairs
        c = count.astype(_I64)
        p = (c - models.value.frame.d * np.minimum(c, 1)) * left[-1] + (left[:-1] * rare.reshape(samples, -1)).mean(0)
        place, at = np.unique(doc.astype(_I64), return_inverse=True)
        lm = np.repeat(np.log10(p), per) * times
        yield by_batch(numbers, at, place, lm, np.zeros(len(lm)), np.zeros(len(lm)))

    def gather(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ref, parts = None, []
        for batch in batches:
            for is_name, raw in zip(batch.column("name").to_pylist(), batch.column("payload"), strict=True):
                if is_name:
                    ref = unpack(raw.as_py())[0]
                else:
                    parts.append(raw.as_py())
        out = [np.zeros(len(ref), _I64), np.zeros(len(ref)), np.zeros(len(ref))]
        for raw in parts:
            row, lm, has, known, base = unpack(raw)
            row = np.cumsum(row).astype(_I64)
            at = row[np.cumsum(has.astype(_I64))]
            out[0][at] += known.astype(_I64)
            out[1][at] += base
            out[2][row] += lm
        yield pa.RecordBatch.from_arrays([pa.array(ref), *map(pa.array, out)], ["ref", "_known", "_base", "_lm"])

    kind, schema = rows.schema["id"].dataType.simpleString(), "kind int, target long, payload binary"
    sums = shared.keep(kept.select("bucket", "pairs", "places").mapInArrow(far, schema), "sums")
    hot_scores = np.zeros(len(hot_codes))
    for raw in sums.where(F.col("kind") == HOT).select("payload").toArrow().column(0):
        codes, scores = unpack(raw.as_py())
        hot_scores[found(hot_codes, codes)] = scores
    hot_models = spark.sparkContext.broadcast((hot_codes, hot_scores))
    met = sums.where(F.col("kind").isin(STANDING, LEFT)).groupBy("target").applyInArrow(finish, schema)
    near = rows.select("id", "ref", "text").mapInArrow(local, f"id {kind}, ref long, n_tokens long, known long, base double, lm double")
    near = shared.keep(near, "near")
    named = lambda df: df.select(F.col("target").alias("batch"), "payload").withColumn("name", F.lit(False))
    sums = named(sums.where(F.col("kind") == SUMS)).union(named(met)).union(names.withColumn("name", F.lit(True)))
    sums = sums.groupBy("batch").applyInArrow(gather, "ref long, _known long, _base double, _lm double")
    sums = sums.groupBy("ref").agg(*(F.max(c).alias(c) for c in ("_known", "_base", "_lm")))  # rows of one ref are alike
    total = lambda c: F.col(c) + F.col(f"_{c}")
    return near.join(sums, "ref").select(F.col("id").alias(id_col), "n_tokens", total("known").alias("n_known"), F.lit(n).cast("long").alias("train_tokens"), total("base").alias("base_score"), total("lm").alias("score"))


def perplexity(scored: DataFrame) -> DataFrame:
    """Perplexity a token of the model and of the smoothed counts over the rows given."""
    return scored.agg(F.pow(F.lit(10.0), -F.sum("score") / F.sum("n_tokens")).alias("perplexity"), F.pow(F.lit(10.0), -F.sum("base_score") / F.sum("n_tokens")).alias("base_perplexity"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rest = shared.crc_mod("doc_id", 10)
    out = score(shared.documents(spark, sf_dir), rest != 0)
    return out.select("doc_id", F.coalesce(rest == 0, F.lit(False)).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
