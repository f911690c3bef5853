"""Longest matches for a whole column at once, in numpy.

Texts lie end to end in one buffer. Many cursors walk at the same time: one from the start of each text and one from the start
of each block of long texts; a cursor stops where another has been, since the match at a place depends on the place alone.
The path of each text is then read off. Entry lengths worth trying come from a bit mask kept under a hash of four bytes.
"""

from __future__ import annotations

import numpy as np

from ..dictionary import Dictionary

BLOCK = 192
WIDE = 16
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
_KEEP = np.array([(1 << (8 * n)) - 1 if n < 8 else 2**64 - 1 for n in range(9)], np.uint64)


def _hash(low, high, size):
    h = (low * _A) ^ (high * _B) ^ (size.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    h = h ^ (h >> np.uint64(32))
    h = h * _A
    return h ^ (h >> np.uint64(29))


class VectorIndex:
    """Hash tables over the entries of up to 16 bytes, and buckets of longer ones by their first 16 bytes."""

    def __init__(self, dictionary: Dictionary, most: int | None = None):
        """most: only entries of up to so many bytes take part."""
        entries = [e if most is None or len(e) <= most else b"" for e in dictionary.entries]
        self.lens = np.array([len(e) for e in entries], np.int64)
        packed = np.zeros((len(entries), WIDE), np.uint8)
        for i, e in enumerate(entries):
            packed[i, : min(WIDE, len(e))] = np.frombuffer(e[:WIDE], np.uint8)
        words = packed.view("<u8").reshape(-1, 2)
        self.low, self.high = words[:, 0].copy(), words[:, 1].copy()
        self.longer: dict[bytes, list[tuple[int, bytes, int]]] = {}
        for i, e in enumerate(entries):
            if len(e) > WIDE:
                self.longer.setdefault(e[:WIDE], []).append((len(e), e, i))
        for bucket in self.longer.values():
            bucket.sort(reverse=True)
        short = np.flatnonzero((self.lens <= WIDE) & (self.lens > 1))
        self.bytes_ = np.zeros(256, np.int64)
        for i in np.flatnonzero(self.lens == 1).tolist():
            self.bytes_[entries[i][0]] = i
        self.bits = max(12, int(len(entries) * 8 - 1).bit_length())
        self.tables: list[np.ndarray] = []
        left, h = short, _hash(self.low, self.high, self.lens)
        self.hashes = h
        while len(left):
            t = np.full(1 << self.bits, -1, np.int32)
            at = self._slot(h[left], len(self.tables))
            t[at] = left
            left = left[t[at] != left]
            self.tables.append(t)
        # lengths worth trying: those under eight by a hash of four bytes, the rest by a hash of eight; 17 stands for longer than 16
        self.mask, self.mask8 = np.zeros(1 << 20, np.uint32), np.zeros(1 << 20, np.uint32)
        bit = np.uint32(1) << np.minimum(self.lens, WIDE + 1).astype(np.uint32)
        some, many = (self.lens >= 4) & (self.lens < 8), self.lens >= 8
        np.bitwise_or.at(self.mask, self._first(self.low[some]), bit[some])
        np.bitwise_or.at(self.mask8, self._eight(self.low[many]), bit[many])
        self.three = np.zeros(1 << 16, bool)  # whether any three-byte entry begins with these two
        self.two = np.full(1 << 16, -1, np.int64)
        for i in np.flatnonzero(self.lens == 2).tolist():
            self.two[int(self.low[i])] = i
        self.three[(self.low[self.lens == 3] & np.uint64(0xFFFF)).astype(np.int64)] = True

    def _slot(self, h, k):
        return ((h >> np.uint64(k * 7 % 40)) & np.uint64((1 << self.bits) - 1)).astype(np.int64)

    @staticmethod
    def _first(low):
        return (((low & np.uint64(0xFFFFFFFF)) * _A) >> np.uint64(44)).astype(np.int64)

    @staticmethod
    def _eight(low):
        return (((low ^ (low >> np.uint64(31))) * _B) >> np.uint64(44)).astype(np.int64)

    def probe(self, low, high, size):
        """Number of the entry with these bytes, or -1."""
        low = low & _KEEP[np.minimum(size, 8)]
        high = high & _KEEP[np.maximum(size - 8, 0)]
        h = _hash(low, high, size)
        out = self.tables[0][self._slot(h, 0)].astype(np.int64) if self.tables else np.full(len(h), -1, np.int64)
        for t in range(1, len(self.tables)):  # a free place in a table means that no later one holds the entry
            on = np.flatnonzero((out >= 0) & (self.hashes[out] != h))
            if not len(on):
                break
            out[on] = self.tables[t][self._slot(h[on], t)]
        hit = np.flatnonzero((out >= 0) & (self.hashes[out] == h))
        got = out[hit]
        sure = (self.low[got] == low[hit]) & (self.high[got] == high[hit]) & (self.lens[got] == size[hit])
        out = np.full(len(h), -1, np.int64)
        out[hit[sure]] = got[sure]
        return out

    def match(self, padded: np.ndarray, at: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number, length) of the longest entry at each place of a buffer padded by 16 bytes; end: where the text there ends."""
        view = np.ndarray((len(padded) - 7,), "<u8", padded, 0, (1,))
        low, high, left = view[at], view[at + 8], end - at
        number = self.bytes_[padded[at]]
        size = np.ones(len(at), np.int64)
        able = (self.mask[self._first(low)] | self.mask8[self._eight(low)]) & ((np.uint32(1) << np.minimum(left + 1, WIDE + 2).astype(np.uint32)) - np.uint32(1))
        able[left < 4] = 0
        live = np.flatnonzero(able)
        while len(live):
            n = np.log2(able[live].astype(np.float64)).astype(np.int64)
            got = np.full(len(live), -1, np.int64)
            fits = n <= WIDE
            got[fits] = self.probe(low[live[fits]], high[live[fits]], n[fits])
            for k in np.flatnonzero(~fits).tolist():
                i = live[k]
                a, b = int(at[i]), int(end[i])
                raw = padded[a : a + WIDE].tobytes()
                for m, e, number_ in self.longer.get(raw, ()):
                    if m <= b - a and padded[a : a + m].tobytes() == e:
                        got[k], n[k] = number_, m
                        break
            hit = got >= 0
            number[live[hit]], size[live[hit]] = got[hit], n[hit]
            able[live[hit]] = 0
            miss = live[~hit]
            able[miss] &= ~(np.uint32(1) << n[~hit].astype(np.uint32))
            live = miss[able[miss] > 0]
        pair = (low & np.uint64(0xFFFF)).astype(np.int64)
        rest = np.flatnonzero((size == 1) & (left >= 3) & self.three[pair])
        if len(rest):
            got = self.probe(low[rest], high[rest], np.full(len(rest), 3))
            hit = got >= 0
            number[rest[hit]], size[rest[hit]] = got[hit], 3
        rest = np.flatnonzero((size == 1) & (left >= 2))
        got = self.two[pair[rest]]
        hit = got >= 0
        number[rest[hit]], size[rest[hit]] = got[hit], 2
        return number, size

    def parse(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Entry numbers of all texts, end to end, and how many each has."""
        n = len(data)
        padded = np.concatenate([data, np.zeros(WIDE + 8, np.uint8)])
        size = np.diff(offs)
        blocks = -(-size // BLOCK)
        begin = np.repeat(offs[:-1], blocks) + BLOCK * (np.arange(blocks.sum()) - np.repeat(np.cumsum(blocks) - blocks, blocks))
        end = np.repeat(offs[1:], blocks)
        number, width = np.zeros(n, np.int32), np.zeros(n + 1, np.int32)
        at = begin.astype(np.int64)
        while len(at):
            got, w = self.match(padded, at, end)
            number[at], width[at] = got, w
            at = at + w
            go = at < end
            at, end = at[go], end[go]
            fresh = width[at] == 0
            at, end = at[fresh], end[fresh]
        on = np.zeros(n, bool)
        at, end = offs[:-1][size > 0], offs[1:][size > 0]
        while len(at) > 64:
            on[at] = True
            at = at + width[at]
            go = at < end
            at, end = at[go], end[go]
        for a, b in zip(at.tolist(), end.tolist(), strict=True):
            w = width[a:b].tolist()
            k, m, seen = 0, b - a, []
            while k < m:
                seen.append(k)
                k += w[k]
            on[a + np.array(seen)] = True
        place = np.flatnonzero(on)
        return number[place], np.diff(np.searchsorted(place, offs))

    def match_all(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Longest match at every byte: (number, length)."""
        padded = np.concatenate([data, np.zeros(WIDE + 8, np.uint8)])
        return self.match(padded, np.arange(len(data)), np.repeat(offs[1:], np.diff(offs)))
