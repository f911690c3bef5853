"""The frozen index of the bounded variant: a minimal perfect hash of eight-byte prefixes to fixed-width records."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..dictionary import Dictionary
from .dynamic import SHORT, Cost, DynamicMatcher
from .vector import VectorIndex
from .words import is_prefix_words

_MULTIPLY = np.uint64(0x9E3779B97F4A7C15)


def _spread(word: np.ndarray, seed) -> np.ndarray:
    h = (word ^ (word >> np.uint64(32))) * _MULTIPLY + np.asarray(seed, np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def word_of(raw: bytes) -> int:
    return int.from_bytes(raw[:8].ljust(8, b"\0"), "little")


@dataclass
class PerfectHash:
    """Hash and displace: keys share a displacement by a first hash; displacements are sought, fullest group first."""

    seeds: np.ndarray
    slots: int

    @staticmethod
    def build(keys: np.ndarray) -> PerfectHash:
        n = len(keys)
        groups = max(1, n // 2)
        with np.errstate(over="ignore"):
            group = (_spread(keys, 0) % np.uint64(groups)).astype(np.int64)
            members = np.split(np.argsort(group, kind="stable"), np.cumsum(np.bincount(group, minlength=groups))[:-1]) if n else []
            seeds, taken = np.zeros(groups, np.uint64), np.zeros(n, bool)
            for g in sorted(range(len(members)), key=lambda g: -len(members[g])):
                own = keys[members[g]]
                if not len(own):
                    continue
                first = 1
                while True:  # many displacements tried at once
                    tries = np.arange(first, first + 64, dtype=np.uint64)
                    at = (_spread(own[None, :], tries[:, None]) % np.uint64(n)).astype(np.int64)
                    free = ~taken[at].any(1)
                    if len(own) > 1:
                        s = np.sort(at, 1)
                        free &= (s[:, 1:] != s[:, :-1]).all(1)
                    if free.any():
                        k = int(free.argmax())
                        seeds[g], taken[at[k]] = tries[k], True
                        break
                    first += 64
        return PerfectHash(seeds, n)

    def slot(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            group = (_spread(keys, 0) % np.uint64(len(self.seeds))).astype(np.int64)
            return (_spread(keys, self.seeds[group]) % np.uint64(max(1, self.slots))).astype(np.int64)


class StaticIndex:
    """One record a prefix: the prefix, `inline` suffixes with numbers, and where further suffixes lie. Four inline suffixes
    fill 60 of the 64 bytes of a cache line."""

    def __init__(self, hash_: PerfectHash, records: list, overflow: list, short: DynamicMatcher, inline: int):
        self.hash, self.records, self.overflow, self.short, self.inline = hash_, records, overflow, short, inline

    @staticmethod
    def build(dictionary: Dictionary, inline: int = 4) -> StaticIndex:
        if any(len(e) > 16 for e in dictionary.entries):
            raise ValueError("only the bounded variant has a static index")
        matcher = DynamicMatcher(dictionary.entries)
        prefixes = list(matcher.long)
        keys = np.array([word_of(p) for p in prefixes], np.uint64)
        hash_ = PerfectHash.build(keys)
        records: list = [None] * len(prefixes)
        overflow: list[tuple[bytes, int]] = []
        for p, slot in zip(prefixes, hash_.slot(keys).tolist() if len(keys) else [], strict=True):
            bucket = [(suffix, number) for _, suffix, number in matcher.long[p]]
            more = bucket[inline:]
            records[slot] = (p, len(overflow) if more else -1, len(more), bucket[:inline])
            overflow += more
        short = DynamicMatcher()
        short.short, short.sizes = matcher.short, matcher.sizes
        return StaticIndex(hash_, records, overflow, short, inline)

    def match(self, text: bytes, at: int = 0, cost: Cost | None = None) -> tuple[int, int]:
        if len(text) - at > SHORT and self.records:
            prefix = text[at : at + SHORT]
            found, offset, more, bucket = self.records[int(self.hash.slot(np.array([word_of(prefix)], np.uint64))[0])]
            if found == prefix:
                for k, (suffix, number) in enumerate([*bucket, *self.overflow[offset : offset + more]] if more else bucket):
                    if cost:
                        cost.suffixes += 1
                        cost.overflow += k >= self.inline
                    if text.startswith(suffix, at + SHORT):
                        return number, SHORT + len(suffix)
        return self.short.match(text, at) if len(text) - at <= SHORT else self.short.match(text[at : at + SHORT], 0)

    def parse(self, text: bytes) -> list[int]:
        out, at = [], 0
        while at < len(text):
            number, n = self.match(text, at)
            out.append(number)
            at += n
        return out

    def frames(self, spark: SparkSession) -> tuple[DataFrame, DataFrame]:
        """The records and the overflow vector as tables."""
        rows = [(s, bytearray(p), o, n, [(bytearray(x), len(x), i) for x, i in b]) for s, (p, o, n, b) in enumerate(self.records)]
        more = [(k, bytearray(x), len(x), i) for k, (x, i) in enumerate(self.overflow)]
        return spark.createDataFrame(rows, "slot int, prefix8 binary, offset int, size int, inline array<struct<suffix:binary,len:int,token_id:int>>"), spark.createDataFrame(more, "pos int, suffix binary, len int, token_id int")


class StaticVectorIndex(VectorIndex):
    """The static index for a whole column: one perfect-hash probe a place finds the record; inline suffixes, then those of the
    overflow vector, are tested as 64-bit words, longest first; entries of up to eight bytes stand in the short map."""

    def __init__(self, dictionary: Dictionary, inline: int = 4):
        super().__init__(dictionary, SHORT)
        index = StaticIndex.build(dictionary, inline)
        n = len(index.records)
        self.hash = index.hash
        self.prefix, self.first, self.more = np.zeros(n, np.uint64), np.zeros(n, np.int64), np.zeros(n, np.int64)
        self.words, self.sizes, self.ids = np.zeros((n, inline), np.uint64), np.full((n, inline), 99, np.int64), np.full((n, inline), -1, np.int64)
        for slot, (p, offset, more, bucket) in enumerate(index.records):
            self.prefix[slot], self.first[slot], self.more[slot] = word_of(p), offset, more
            for k, (suffix, number) in enumerate(bucket):
                self.words[slot, k], self.sizes[slot, k], self.ids[slot, k] = word_of(suffix), len(suffix), number
        self.over = tuple(np.array(x, kind) for x, kind in zip(zip(*((word_of(s), len(s), i) for s, i in index.overflow), strict=True), (np.uint64, np.int64, np.int64), strict=True)) if index.overflow else ()

    def match(self, padded: np.ndarray, at: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        number, size = super().match(padded, at, end)
        left = end - at
        on = np.flatnonzero(left > SHORT)
        if not len(self.prefix) or not len(on):
            return number, size
        view = np.ndarray((len(padded) - 7,), "<u8", padded, 0, (1,))
        slot = self.hash.slot(view[at[on]])
        same = self.prefix[slot] == view[at[on]]
        on, slot = on[same], slot[same]
        rest, room = view[at[on] + SHORT], left[on] - SHORT

        def take(live, words, sizes, ids):
            hit = is_prefix_words(rest[live], room[live], words, sizes)
            number[on[live[hit]]], size[on[live[hit]]] = ids[hit], SHORT + sizes[hit]
            return live[~hit]

        live = np.arange(len(on))
        for k in range(self.words.shape[1]):
            live = take(live, self.words[slot[live], k], self.sizes[slot[live], k], self.ids[slot[live], k])
        for k in range(int(self.more.max(initial=0))):
            live = live[self.more[slot[live]] > k]
            place = self.first[slot[live]] + k
            live = take(live, *(x[place] for x in self.over))
        return number, size
