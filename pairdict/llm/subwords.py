"""SentencePiece encoding by sampling without replacement, and decoding.

A text is a lattice of vocabulary pieces. It is cut only where no piece can cross: at spaces, line breaks and, in long runs,
anywhere, if no piece holds the two characters there side by side. So the lattice is a chain of small ones, its units, whose sums
are known exactly, and no segmentation is left out. The first segmentation is an exact sample. The others come by perturbed A-star: the sets of segmentations that leave a found path at each unit get
truncated Gumbel scores, the best set is opened, and its unit is searched by A-star over its own lattice.
"""

from __future__ import annotations

import heapq
import math
import random
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MASK = 64  # a path of a unit of so many characters is a word of bits; those of longer units are numbered
SPACE, LITERAL = 0x2581, 0x110000  # the piece alphabet's space; the same sign where it stands in a text


def _hash_points(points: np.ndarray, start: np.ndarray, end: np.ndarray, sums=None) -> np.ndarray:
    _, down = shared.powers(len(points) + 1)
    if sums is None:
        sums = prefix_sums(points)
    return shared.mix((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64))


def prefix_sums(points: np.ndarray) -> np.ndarray:
    up, _ = shared.powers(len(points) + 1)
    out = np.zeros(len(points) + 1, np.uint64)
    np.cumsum(shared.mix(points.astype(np.uint64) + np.uint64(1)) * up[: len(points)], out=out[1:])
    return out


class Vocabulary:
    """Pieces of a SentencePiece file with log probabilities. A BPE file has only ranks: those become p ~ 1 / (rank + 10)."""

    def __init__(self, path: str = MODEL):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        normal = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        pieces = {i: sp.id_to_piece(i) for i in normal}
        self.widest = max(map(len, pieces.values()), default=1)
        score = np.array([sp.get_score(i) for i in pieces])
        if len(score) and (score == np.round(score)).all():
            score = -np.log(10 - score + score.max())
        score = score - np.log(np.exp(score - score.max()).sum()) - score.max()
        points = [np.array([ord(c) for c in p], np.uint32) for p in pieces.values()]
        flat, size = np.concatenate(points), np.array([len(p) for p in points])
        end = np.cumsum(size)
        self.hashes, self.ids, self.scores = _hash_points(flat, end - size, end), np.array(list(pieces)), score
        self.tables, left = [], np.arange(len(size))  # pieces by hash; what finds its place taken goes to the next table
        while len(left):
            t = np.full(1 << (16 if self.tables else 22), -1, np.int32)  # few are left after the first
            at = self.slot(self.hashes[left], len(self.tables))
            t[at] = left
            self.tables.append(t)
            left = left[t[at] != left]
        # beginnings of pieces: where none goes on, no longer piece need be looked up
        begin = np.repeat(end - size, size)
        upto = np.arange(len(flat)) + 1
        self.goes_on = np.zeros(1 << 22, bool)
        self.goes_on[self.slot(_hash_points(flat, begin, upto))] = True
        inner = np.flatnonzero(upto < np.repeat(end, size))
        self.pairs = np.unique(flat[inner].astype(np.int64) << 21 | flat[inner + 1])  # characters side by side in a piece
        self.near = np.zeros(1 << 16, bool)  # most others are told by these bits
        self.near[self.pairs % 65521] = True
        self.byte_ids = np.zeros(256, np.int64)
        self.raw = [b""] * n
        for i, p in pieces.items():
            self.raw[i] = p.replace("▁", " ").encode()
        for i in range(n):
            if sp.is_byte(i):
                value = int(sp.id_to_piece(i)[3:-1], 16)
                self.byte_ids[value] = i
                self.raw[i] = bytes([value])
        self.unknown = float(score.min()) - 10.0  # a byte of a character that no piece holds

    @staticmethod
    def slot(h: np.ndarray, table: int = 0) -> np.ndarray:
        return ((h >> np.uint64(21 * table % 42)) & np.uint64((1 << (16 if table else 22)) - 1)).astype(np.int64)

    def joined(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Whether any piece holds these characters side by side: elsewhere none can cross."""
        pair = left.astype(np.int64) << 21 | right
        out = self.near[pair % 65521]
        on = np.flatnonzero(out)
        out[on] = self.pairs[np.minimum(np.searchsorted(self.pairs, pair[on]), len(self.pairs) - 1)] == pair[on]
        return out

    def find(self, h: np.ndarray, slot: np.ndarray) -> np.ndarray:
        """Place of each hash among the pieces, or -1. slot: its place in the first table."""
        out = self.tables[0][slot]
        for k in range(1, len(self.tables)):
            miss = np.flatnonzero((out >= 0) & (self.hashes[out] != h))
            out[miss] = self.tables[k][self.slot(h[miss], k)]
        return np.where((out >= 0) & (self.hashes[out] == h), out, -1)


@lru_cache(maxsize=4)
def vocabulary(path: str = MODEL) -> Vocabulary:
    return Vocabulary(path)


class Lattices:
    """Lattices of distinct units, side by side.

    Rows are laid out by place, and within a place by unit, longest first: the units that reach a place are then a run of rows,
    and so are the same units some places before. The tables have a column for each length of the last piece: cumulative
    probabilities given that the unit is read up to there, scores, and piece numbers.
    """

    def __init__(self, voc: Vocabulary, points: np.ndarray, start: np.ndarray, size: np.ndarray):
        order = np.argsort(-size, kind="stable")
        self.rank = np.empty(len(size), np.int64)
        self.rank[order] = np.arange(len(size))
        self.size = size
        longest = int(size.max(initial=0))
        wide = np.searchsorted(-size[order], -np.arange(longest + 1), "right")  # units of at least so many characters
        self.block = np.concatenate([[0], np.cumsum(wide)])
        rows = int(self.block[-1])
        within = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
        flat = points[np.repeat(start, size) + within]
        rank = np.repeat(self.rank, size)
        left = np.repeat(size, size) - within
        sums, found, on = prefix_sums(flat), [], np.arange(len(flat))
        for k in range(1, voc.widest + 1):
            on = on[left[on] >= k]
            h = _hash_points(flat, on, on + k, sums)
            slot = voc.slot(h)
            got = voc.find(h, slot)
            hit = np.flatnonzero(got >= 0)
            found.append((self.block[within[on[hit]] + k] + rank[on[hit]], got[hit]))
            on = on[voc.goes_on[slot]]
            if not len(on):
                break
        width = max(1, max((k for k, f in enumerate(found, 1) if len(f[0])), default=1))
        weight = np.full((rows, width), -np.inf, np.float32)
        self.piece = np.full((rows, width), -1, np.int32)
        for k, (at, got) in enumerate(found[:width]):
            weight[at, k] = voc.scores[got]
            self.piece[at, k] = voc.ids[got]
        row = self.block[within + 1] + rank
        lone = np.flatnonzero(np.isneginf(weight[row, 0]))  # byte fallback
        code = flat[lone].astype(np.int64)
        code = np.where(code == LITERAL, SPACE, code)
        weight[row[lone], 0] = voc.unknown * np.select([code < 0x80, code < 0x800, code < 0x10000], [1, 2, 3], 4)
        self.piece[row[lone], 0] = -2 - code
        alpha, ways = np.full(rows, -np.inf), np.zeros(rows)
        alpha[: wide[0]], ways[: wide[0]] = 0, 1
        self.cumulative = np.ones((rows, width), np.float32)
        for p in range(1, longest + 1):
            n, m, at = int(wide[p]), min(p, width), int(self.block[p])
            own = weight[at : at + n, :m]
            w, many = np.empty((n, m)), np.zeros(n)
            for k in range(m):
                back = int(self.block[p - 1 - k])
                np.add(own[:, k], alpha[back : back + n], out=w[:, k])
                many += np.isfinite(own[:, k]) * ways[back : back + n]
            np.minimum(many, 1e15, out=many)  # so many need not be told apart
            top = w.max(1)
            w -= top[:, None]
            c = np.cumsum(np.exp(w, out=w), axis=1, out=w)
            alpha[at : at + n] = top + np.log(c[:, -1])
            np.divide(c, c[:, -1:], out=self.cumulative[at : at + n, :m], casting="same_kind")
            ways[at : at + n] = many
        self.ways, self.weight, self.alpha = ways[self.block[size] + self.rank], weight, alpha

    def search(self, unit: int, barred: set[int], seed: int) -> tuple[int, float]:
        """The best perturbed segmentation of a unit that is not barred, as a mask of the places where pieces end, and its log probability."""
        rng, rank, made = random.Random(seed), int(self.rank[unit]), 0
        gumbel = lambda: -math.log(-math.log(max(rng.random(), 1e-300)))
        heap = [(-gumbel(), int(self.size[unit]), 0.0, 0, None)]  # last: the ends so far, each with those behind it
        while heap:
            g, pos, phi, _, ends = heapq.heappop(heap)
            g = -g
            if pos == 0:
                mask = as_mask(ends)
                if mask not in barred:
                    return mask, phi
                continue
            row, kids = int(self.block[pos]) + rank, []
            for k in range(min(pos, self.weight.shape[1])):
                if (w := float(self.weight[row, k])) > -math.inf:
                    f = phi + w + float(self.alpha[self.block[pos - k - 1] + rank] - self.alpha[row])
                    kids.append((f + gumbel(), f, pos - k - 1))
            top = max(k[0] for k in kids)
            for x, f, to in kids:
                v = g - x + (math.log1p(-math.exp(x - top)) if x < top else -math.inf)
                made += 1
                heapq.heappush(heap, (-(g - max(0.0, v) - math.log1p(math.exp(-abs(v)))), to, f, made, (pos, ends)))
        return 0, -math.inf


def as_mask(ends) -> int:
    """The places where pieces end, linked from the first one on, as bits."""
    places = []
    while ends:
        places.append(ends[0] - 1)
        ends = ends[1]
    if places and places[-1] >= MASK:
        bits = np.zeros(places[-1] + 1, np.uint8)
        bits[places] = 1
        return int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")
    return sum(1 << p for p in places)


def chained(key: np.ndarray, *counters) -> np.ndarray:
    """A hash of a key and counters."""
    for c in counters:
        key = shared.mix(key + (np.atleast_1d(c).astype(np.uint64) + np.uint64(1)) * np.uint64(0xD1B54A32D192ED03))
    return key


def uniform(key: np.ndarray, *counters) -> np.ndarray:
    """Uniform numbers above 0 and below 1 from keys and counters alone."""
    return ((chained(key, *counters) >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53


class Sampler:
    """All texts of a slice: units, their lattices, and the paths found so far."""

    def __init__(self, voc: Vocabulary, texts: list[str], keys: np.ndarray):
        self.voc, self.keys, self.n = voc, keys, len(texts)
        parts = [np.frombuffer((" " + t).encode("utf-32-le", "surrogatepass"), np.uint32) if t else np.zeros(0, np.uint32) for t in texts]
        size = np.array([len(p) for p in parts], np.int64)
        points = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
        points = np.where(points == SPACE, np.uint32(LITERAL), np.where(points == 32, np.uint32(SPACE), points))
        n = len(points)
        new = np.zeros(n, bool)
        first = np.cumsum(size) - size
        new[first[size > 0]] = True
        at = np.flatnonzero((points[1:] == SPACE) | (points[1:] == 10) | (points[:-1] == 10)) + 1
        new[at[~voc.joined(points[at - 1], points[at])]] = True
        run = np.flatnonzero(new)
        far = np.diff(np.append(run, n))
        at = np.flatnonzero(np.repeat(far > MASK, far) & ~new)  # what is left long is cut further
        new[at[~voc.joined(points[at - 1], points[at])]] = True
        start = np.flatnonzero(new)
        length = np.diff(np.append(start, n))
        self.doc = np.searchsorted(np.cumsum(size), start, "right")
        self.edge = np.searchsorted(start, np.append(first, n))
        h = _hash_points(points, start, start + length)
        _, index, self.unit = np.unique(h, return_index=True, return_inverse=True)
        self.lattices = Lattices(voc, points, start[index], length[index])
        self.place = np.arange(len(start)) - self.edge[self.doc] if len(start) else start
        self.far = length > MASK
        self.numbers: dict[int, int] = {}  # paths of long units: their bits, by number and back
        self.paths: list[int] = []

    def number(self, path: int) -> int:
        if path not in self.numbers:
            self.numbers[path] = len(self.paths)
            self.paths.append(path)
        return self.numbers[path]

    def ends(self, number: int) -> np.ndarray:
        """Places where the pieces of a long unit's path end."""
        path = self.paths[number]
        return np.flatnonzero(np.unpackbits(np.frombuffer(path.to_bytes(path.bit_length() // 8 + 1, "little"), np.uint8), bitorder="little")) + 1

    def other(self, at: int, gone, seed: int) -> tuple[int, float]:
        """A path for the unit at a place that is none of those gone."""
        if not self.far[at]:
            return self.lattices.search(int(self.unit[at]), gone, seed)
        path, logp = self.lattices.search(int(self.unit[at]), {self.paths[x] for x in gone}, seed)
        return self.number(path), logp

    def draw(self, which: np.ndarray, path: int) -> tuple[np.ndarray, np.ndarray]:
        """Independent samples for some units: masks of piece ends (of long units their paths' numbers), and log probabilities."""
        lat = self.lattices
        rank, pos = lat.rank[self.unit[which]], lat.size[self.unit[which]].copy()
        mask, logp = np.zeros(len(which), np.uint64), -lat.alpha[lat.block[pos] + rank]  # a step's share of the sums cancels with the next one's
        key = chained(self.keys[self.doc[which]], path, self.place[which])
        live, step = np.arange(len(which)), 0
        far = self.far[which]
        trails = {i: None for i in np.flatnonzero(far).tolist()}
        while len(live):
            for i in live[far[live]].tolist() if trails else ():
                trails[i] = (int(pos[i]), trails[i])
            row = lat.block[pos[live]] + rank[live]
            u = uniform(key[live], step)
            k = (lat.cumulative[row] < u[:, None].astype(np.float32)).sum(1)
            mask[live] |= np.uint64(1) << ((pos[live] - 1) % MASK).astype(np.uint64)
            logp[live] += lat.weight[row, k]
            pos[live] -= k + 1
            live, step = live[pos[live] > 0], step + 1
        for i, ends in trails.items():
            mask[i] = self.number(as_mask(ends))
        return mask, np.minimum(logp, 0.0)

    def ids(self, mask: np.ndarray, docs: np.ndarray) -> list[np.ndarray]:
        """Piece numbers of the texts in `docs` along a path."""
        chosen = np.zeros(self.n, bool)
        chosen[docs] = True
        occ = np.flatnonzero(chosen[self.doc])
        count = np.bitwise_count(mask[occ]).astype(np.int64)
        trails = {i: self.ends(int(mask[occ[i]])) for i in np.flatnonzero(self.far[occ]).tolist()}
        for i, ends in trails.items():
            count[i] = len(ends)
        out = np.empty(int(count.sum()), np.int64)
        at, left = np.cumsum(count) - count, mask[occ]
        rank, last = self.lattices.rank[self.unit[occ]], np.zeros(len(occ), np.int64)
        for i, ends in trails.items():
            out[at[i] : at[i] + count[i]] = self.lattices.piece[self.lattices.block[ends] + rank[i], np.diff(ends, prepend=0) - 1]
        live = np.flatnonzero(~self.far[occ])
        while len(live):
            low = left[live] & (~left[live] + np.uint64(1))
            end = np.bitwise_count(low - np.uint64(1)).astype(np.int64) + 1
            out[at[live]] = self.lattices.piece[self.lattices.block[end] + rank[live], end - last[live] - 1]
            last[live], at[live] = end, at[live] + 1
            left[live] ^= low
            live = live[left[live] > 0]
        owner = np.repeat(self.doc[occ], count)
        odd = np.flatnonzero(out < 0)
        if len(odd):
            raw = [chr(-2 - int(c)).encode("utf-8", "surrogatepass") for c in out[odd]]
            times = np.ones(len(out), np.int64)
            times[odd] = [len(r) for r in raw]
            first = np.cumsum(times) - times
            out, owner = np.repeat(out, times), np.repeat(owner, times)
            for k, r in zip(first[odd].tolist(), raw, strict=True):
                out[k : k + len(r)] = self.voc.byte_ids[list(r)]
        cut = np.searchsorted(owner, docs)
        end = np.searchsorted(owner, docs, "right")
        return [out[a:b] for a, b in zip(cut.tolist(), end.tolist(), strict=True)]

    def best(self, k: int):
        """For each rank up to k: (texts, masks of all units, log probability, perturbed score); and the score next in line."""
        n, units = self.n, len(self.unit)
        has = np.flatnonzero(np.diff(self.edge) > 0)
        found = []
        if not len(has):
            return found, np.full(n, -np.inf)
        mask, logp = self.draw(np.arange(units), 0)
        bound = -np.log(-np.log(uniform(self.keys, 1 << 20)))
        first = self.edge[:-1]
        masks, logps, scores = [mask], [logp], []
        barred = [{} for _ in range(k + 1)]  # for each path: text -> masks that its branching unit may not take
        begin = first.copy()
        found.append((has, mask, np.add.reduceat(logp, first[has]), bound[has].copy()))
        for path in range(k):
            # sets that leave this path at each unit from where it began to differ from older ones
            cum = np.cumsum(logp) - logp
            before = cum - cum[np.minimum(first[self.doc], units - 1)]
            rest = -np.expm1(logp)
            ways = self.lattices.ways[self.unit] - 1
            for d, (at, gone, mass) in barred[path].items():
                ways[at] = self.lattices.ways[self.unit[at]] - len(gone) - 1
                rest[at] = 1 - mass - np.exp(logp[at])
            phi = before + np.log(np.maximum(rest, 1e-300))
            u = uniform(self.keys[self.doc], 2 + path, (1 << 21) + self.place)
            limit = bound[self.doc]
            gap = phi - limit
            g = np.where(gap > 30, limit - np.log1p(-np.log(u) * np.exp(-np.maximum(gap, 0))), phi - np.log(np.exp(np.minimum(gap, 30)) - np.log(u)))
            own = (ways > 0) & (np.arange(units) >= begin[self.doc]) & np.isfinite(limit)
            scores.append(np.where(own, g, -np.inf))
            top = np.stack([np.maximum.reduceat(s, first[has]) for s in scores])
            parent = top.argmax(0)
            value = top.max(0)
            bound = np.full(n, -np.inf)
            bound[has] = value
            if path + 1 == k:
                break
            on = np.flatnonzero(np.isfinite(value))
            texts = has[on]
            mask, logp = masks[0].copy(), logps[0].copy()
            fresh, branch = [], np.full(n, units)
            for d, p in zip(texts.tolist(), parent[on].tolist(), strict=True):
                a, b = int(first[d]), int(self.edge[d + 1])
                at = a + int(scores[p][a:b].argmax())
                mask[a:b], logp[a:b] = masks[p][a:b], logps[p][a:b]
                own_at, gone, mass = barred[p].get(d, (-1, frozenset(), 0.0))
                gone, mass = (gone, mass) if own_at == at else (frozenset(), 0.0)
                gone, mass = gone | {int(masks[p][at])}, mass + math.exp(logps[p][at])
                barred[path + 1][d] = (at, gone, mass)
                seed = int(shared.mix(self.keys[d : d + 1] + np.uint64(path * 7919 + at - a))[0])
                new, lp = self.other(at, gone, seed)
                mask[at], logp[at] = new, lp
                scores[p][at] = -np.inf
                branch[d] = at
                fresh.append(np.arange(at + 1, b))
            if len(texts):
                fresh = np.concatenate(fresh)
                mask[fresh], logp[fresh] = self.draw(fresh, path + 1)
            begin = branch
            masks.append(mask)
            logps.append(logp)
            found.append((texts, mask, np.add.reduceat(logp, first[has])[on], value[on]))
        return found, bound


def decode(voc: Vocabulary, ids) -> str:
    """The text of piece numbers; exact for what `encode` emits."""
    return spelled(voc, ids).decode("utf-8", "surrogatepass")


def spelled(voc: Vocabulary, ids) -> bytes:
    """The same as UTF-8; the space that encoding puts first is taken off again."""
    return b"".join(map(voc.raw.__getitem__, ids))[1:]


def log_inclusion(logp: np.ndarray, limit: np.ndarray) -> np.ndarray:
    """log of 1 - exp(-exp(logp - limit)): how likely a segmentation is to be among the k, given the score next in line."""
    gap = np.where(np.isneginf(limit), 20.0, logp - np.where(np.isneginf(limit), 0.0, limit))
    near = np.log(-np.expm1(-np.exp(np.clip(gap, -20, 20))))
    return np.where(np.isneginf(limit), 0.0, np.where(gap < -20, gap, near))


def encode(docs: DataFrame, k: int = 2, model_file: str = MODEL, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None, check: bool = True, lean: bool = False) -> DataFrame:
    """k distinct sampled segmentations of every text, without replacement: one row for each, with sample (from 1), ids,
    log_prob, perturbed, log_inclusion and exact (whether decoding the ids gives the text), beside the columns in `keep`.

    The row's id seeds the sampling, so results do not depend on partitions; repeated rows get equal samples. Null and empty
    texts give one row without ids (log_prob 0; exact is true, a null stays null in `keep`). Texts with fewer than k
    segmentations give as many as there are. Whole texts are used, with all their segmentations. lean: fewer texts at a time, and
    freed memory goes back after each, for executors that hold much else; the rows are the same.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    keep = shared.kept(docs, keep, ("sample", "ids", "log_prob", "perturbed", "log_inclusion", "exact"))
    rows = docs.select(*keep, F.xxhash64(F.col(id_col)).alias("_pairdict_key"), F.col(text_col).alias("_pairdict_text"))
    held = docs.sparkSession.sparkContext.broadcast(vocabulary(model_file))  # the file's pieces: a fixed size

    def run(batches):
        voc = held.value
        for batch in batches:
            text = batch.column(batch.num_columns - 1)
            keys = batch.column(batch.num_columns - 2).to_numpy().view(np.uint64)
            for a, b, buf, offs in shared.slices(text, (3 << 17) if lean else (3 << 18)):
                part = [t or "" for t in text.slice(a, b - a).to_pylist()]
                whole, cut = buf.tobytes(), offs.tolist()
                sampler = Sampler(voc, part, shared.mix(keys[a:b]))
                found, limit = sampler.best(k)
                row, sample, ids, logp, score, inc, ok = [], [], [], [], [], [], []
                bare = np.array([i for i, t in enumerate(part) if not t], np.int64)
                for rank, (texts, mask, lp, g) in enumerate(found, 1):
                    got = sampler.ids(mask, texts)
                    row.append(texts)
                    sample.append(np.full(len(texts), rank))
                    ids += got
                    logp.append(lp)
                    score.append(g)
                    inc.append(log_inclusion(lp, limit[texts]))
                    ok += [spelled(voc, x.tolist()) == whole[cut[i] : cut[i + 1]] for i, x in zip(texts.tolist(), got, strict=True)] if check else [None] * len(texts)
                row.append(bare)
                sample.append(np.ones(len(bare), np.int64))
                ids += [np.zeros(0, np.int64)] * len(bare)
                for x in (logp, score, inc):
                    x.append(np.zeros(len(bare)))
                ok += [True] * len(bare)
                take = pa.array(np.concatenate(row) + a)
                offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32))
                flat = pa.array((np.concatenate(ids) if ids else np.zeros(0)).astype(np.int32))
                columns = [c.take(take) for c in batch.columns[:-2]]
                columns += [pa.array(np.concatenate(sample).astype(np.int32)), pa.ListArray.from_arrays(offsets, flat), *(pa.array(np.concatenate(x)) for x in (logp, score, inc)), pa.array(ok, pa.bool_())]
                yield pa.RecordBatch.from_arrays(columns, [*keep, "sample", "ids", "log_prob", "perturbed", "log_inclusion", "exact"])
                if lean:
                    del sampler, found, ids, columns
                    shared.tidy()

    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in rows.schema.fields[:-2])
    return rows.mapInArrow(shared.tidily(run), fields + "sample int, ids array<int>, log_prob double, perturbed double, log_inclusion double, exact boolean")


def decode_column(encoded: DataFrame, ids_col: str = "ids", out: str = "text", model_file: str = MODEL, keep: list[str] | None = None) -> DataFrame:
    """Add the decoded text of a column of piece numbers; null stays null."""
    keep = shared.kept(encoded, keep, (out, ids_col))
    rows = encoded.select(*keep, F.col(ids_col).alias("_pairdict_text"))
    held = encoded.sparkSession.sparkContext.broadcast(vocabulary(model_file))

    def run(batches):
        for batch in batches:
            got = [None if x is None else decode(held.value, x) for x in batch.column(batch.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(got, pa.string())], [*keep, out])

    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{fields}`{out}` string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(shared.documents(spark, sf_dir), k=2, keep=["doc_id"])
