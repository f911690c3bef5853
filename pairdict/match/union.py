"""Longest matches under many dictionaries at once, in numpy.

A trie holds the entries of all dictionaries. The longest entry of any of them at a place is found once; what each dictionary
matches there is that entry's longest beginning that the dictionary has, which a table names. Only the jumps from match to match are
made for each dictionary. Every single byte must be an entry.
"""

from __future__ import annotations

import numpy as np

from ..dictionary import Dictionary

SLICE = 1 << 17  # bytes of text looked at together
LANES = 1 << 14  # cursors that walk together
BLOCK, BEFORE = 1024, 32  # bytes of a long text that a cursor walks, and before them
_END = 256  # stands behind each text; no entry goes on with it
_LOW, _UP = np.int64(0xFFFFFFFF), np.int64(32)


class UnionIndex:
    """The trie lies in one array: the child of a node by a byte stands at (base of the node) ^ byte, if that place names the node."""

    def __init__(self, dictionaries: list[Dictionary]):
        number = {e: i for i, e in enumerate(sorted(set().union(*(d.entries for d in dictionaries))))}
        lens = np.fromiter(map(len, number), np.int64, len(number))
        first = np.cumsum(lens) - lens
        data = np.frombuffer(b"".join(number), np.uint8)
        # nodes by depth: the parent and byte of each, and the node at which each entry ends
        at, on = np.zeros(len(lens), np.int64), np.arange(len(lens))
        parents, symbols, levels, nodes = [np.array([-1])], [np.array([0])], [0, 1], 1
        while len(on):
            edges, child = np.unique(at[on] << 8 | data[first[on] + len(levels) - 2], return_inverse=True)
            at[on] = nodes + child
            parents.append(edges >> 8)
            symbols.append(edges & 255)
            nodes += len(edges)
            levels.append(nodes)
            on = on[lens[on] > len(levels) - 2]
        parent, symbol = np.concatenate(parents), np.concatenate(symbols)
        # the longest entry on the way to each node, and the next shorter one on the way to each entry
        best = np.full(nodes, -1)
        best[at] = np.arange(len(lens))
        for a, b in zip(levels[1:], levels[2:], strict=False):
            best[a:b] = np.where(best[a:b] < 0, best[parent[a:b]], best[a:b])
        shorter = best[parent[at]]
        # what each dictionary matches where the longest entry of all is this one; the last column ends a text
        width = np.zeros((len(dictionaries), len(lens) + 1), np.int64)
        for row, d in zip(width, dictionaries, strict=True):
            has = np.fromiter(map(number.__getitem__, d.entries), np.int64, len(d.entries))
            row[has] = lens[has]
        order = np.argsort(lens, kind="stable")
        cuts = np.flatnonzero(np.diff(lens[order])) + 1
        for on in np.split(order, cuts)[1:]:  # by length, so that the shorter ones are known; all single bytes are entries
            got = width[:, on]
            width[:, on] = np.where(got == 0, width[:, shorter[on]], got)
        self.width = width.ravel()
        self.step = self.width | (self.width > 0).astype(np.int64) << _UP
        place, base, size = self._lay(parent, symbol)
        check, bases, entry = np.full(size, -1), np.zeros(size, np.int64), np.full(size, len(lens))
        check[place[1:]], bases[place], entry[place[1:]] = place[parent[1:]], base, best[1:]
        self.table, self.entry = check << _UP | bases, entry
        # by two bytes: the node of the first, or below 0 that of both
        self.pairs = np.zeros((_END + 1, 512), np.int64)
        self.pairs[:_END] = place[1 : _END + 1, None]
        two = slice(levels[2], levels[3] if len(levels) > 3 else nodes)
        self.pairs[symbol[parent[two]], symbol[two]] = -place[two]
        self.pairs = self.pairs.ravel()
        self.row = (np.arange(len(dictionaries)) * (len(lens) + 1))[:, None]

    @staticmethod
    def _lay(parent: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Places for nodes such that no two share one: nodes with many children first, each tries bases until all of its children fit."""
        nodes = len(parent)
        size = max(1024, 1 << int(4 * nodes - 1).bit_length())
        draw, taken, claim = np.random.default_rng(42), np.zeros(size, bool), np.zeros(size, np.int64)
        taken[0] = True
        base, many = np.zeros(nodes, np.int64), np.bincount(parent[1:], minlength=nodes)
        edge = 1 + np.argsort(parent[1:], kind="stable")  # children, by parent
        begin = np.cumsum(many) - many
        step = np.zeros(nodes, np.int64)
        step[many > 0] = np.log2(many[many > 0]).astype(np.int64) + 1
        for k in range(int(step.max()), 0, -1):
            todo = np.flatnonzero(step == k)
            while len(todo):
                tried = draw.integers(0, size, len(todo))
                own = np.repeat(np.arange(len(todo)), many[todo])
                child = edge[np.repeat(begin[todo] - (np.cumsum(many[todo]) - many[todo]), many[todo]) + np.arange(len(own))]
                spot = tried[own] ^ symbol[child]
                claim[spot] = own
                bad = np.bincount(own, taken[spot] | (claim[spot] != own), len(todo)) > 0
                taken[spot[~bad[own]]] = True
                base[todo[~bad]] = tried[~bad]
                todo = todo[bad]
        place = base[parent] ^ symbol
        place[0] = 0
        return place, base, size

    def _longest(self, codes: np.ndarray) -> np.ndarray:
        """At each place the longest entry of all dictionaries; where a text ends, one past the last."""
        pair = codes[:-1] << 9
        pair |= codes[1:]
        state = np.append(self.pairs.take(pair), 0)  # the root, which stands for no entry, where a text ends
        live = np.flatnonzero(state < 0)
        here = -state.take(live)
        state[live] = here
        base, deep = self.table.take(here) & _LOW, 1
        while len(live):
            deep += 1
            there = base ^ codes.take(live + deep)
            word = self.table.take(there)
            on = np.flatnonzero(word >> _UP == here)
            live, here, base = live.take(on), there.take(on), word.take(on) & _LOW
            state[live] = here
        return self.entry.take(state)

    def counts(self, data: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """How many numbers each dictionary emits for texts that lie end to end."""
        total = np.zeros(len(self.row), np.int64)
        a, texts = 0, len(offs) - 1
        while a < texts:  # whole texts, of about SLICE bytes together
            b = max(a + 1, int(np.searchsorted(offs, offs[a] + SLICE, "right")) - 1)
            size = np.diff(offs[a : b + 1])
            begin = np.cumsum(size + 1) - size - 1
            codes = np.full(int(size.sum()) + b - a, _END, np.int64)
            inside = np.ones(len(codes), bool)
            inside[begin + size] = False
            codes[inside] = data[offs[a] : offs[b]]
            longest = self._longest(codes)
            total += self._many(longest, begin[size <= BLOCK], size[size <= BLOCK])
            for at, n in zip(begin[size > BLOCK].tolist(), size[size > BLOCK].tolist(), strict=True):
                total += self._long(longest, at, at + n)
            a = b
        return total

    def _many(self, longest: np.ndarray, begin: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Short texts: one cursor a text and dictionary; those of like length walk together."""
        total, most = np.zeros(len(self.row), np.int64), max(1, LANES // len(self.row))
        begin = begin[np.argsort(-size, kind="stable")]
        for k in range(0, len(begin), most):
            at, turn = np.tile(begin[k : k + most], (len(self.row), 1)), 0  # the matches so far stand above the place
            while at.size:
                entry = longest.take(at & _LOW)
                entry += self.row
                step = self.step.take(entry)
                at += step
                turn += 1
                if not turn & 3:
                    on = step.any(0)
                    if 3 * np.count_nonzero(on) < 2 * len(on):  # of the others all have ended
                        total += (at[:, ~on] >> _UP).sum(1)
                        at = at[:, on]
        return total

    def _long(self, longest: np.ndarray, begin: int, end: int) -> np.ndarray:
        """A long text: one cursor a block and dictionary. Each block is taken to begin where a walk from a little before it comes in, and
        walked again where the block before turns out to end elsewhere, until all agree."""
        edges = np.append(np.arange(begin, end, BLOCK), end)
        stop = edges[1:]
        come = self._walk(longest, np.tile(np.maximum(edges[:-1] - BEFORE, begin), (len(self.row), 1)), edges[:-1])[0]
        out, count = self._walk(longest, come, stop)
        while len(off := np.flatnonzero((come[:, 1:] != out[:, :-1]).any(0))):
            come[:, off + 1] = out[:, off]
            out[:, off + 1], count[:, off + 1] = self._walk(longest, come[:, off + 1], stop[off + 1])
        return count.sum(1)

    def _walk(self, longest: np.ndarray, at: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where cursors first reach their stop or go past it, and the matches up to there."""
        at, count = at.copy(), np.zeros(at.shape, np.int64)
        while (on := at < stop).any():
            entry = longest.take(at)
            entry += self.row
            step = self.width.take(entry)
            step *= on
            at += step
            count += on
        return at, count
