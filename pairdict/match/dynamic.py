"""A matcher that grows: short entries by their bytes, long ones in buckets by their first eight bytes."""

from __future__ import annotations

from bisect import insort
from dataclasses import dataclass

SHORT = 8


@dataclass
class Cost:
    """What searching took: probes of the short map, suffix comparisons, and visits past the inline suffixes."""

    probes: int = 0
    suffixes: int = 0
    overflow: int = 0


class DynamicMatcher:
    """Longest entry at a place. Which lengths of four to eight are worth a probe is kept by the first four bytes."""

    def __init__(self, entries=(), max_bucket: int | None = None):
        self.short: dict[bytes, int] = {}
        self.long: dict[bytes, list[tuple[int, bytes, int]]] = {}
        self.sizes: dict[bytes, list[int]] = {}  # first four bytes -> lengths of short entries, longest first
        self.max_bucket = max_bucket
        for i, e in enumerate(entries):
            self.insert(e, i)

    def insert(self, entry: bytes, number: int) -> bool:
        """Add an entry; False if its bucket is full. Buckets stay sorted, longest suffix first."""
        if len(entry) <= SHORT:
            self.short[entry] = number
            if len(entry) >= 4:
                known = self.sizes.setdefault(entry[:4], [])
                if len(entry) not in known:
                    known.append(len(entry))
                    known.sort(reverse=True)
            return True
        bucket = self.long.setdefault(entry[:SHORT], [])
        if self.max_bucket is not None and len(bucket) >= self.max_bucket:
            return False
        suffix = entry[SHORT:]
        insort(bucket, (-len(suffix), suffix, number))
        return True

    def has_room(self, entry: bytes) -> bool:
        return len(entry) <= SHORT or self.max_bucket is None or len(self.long.get(entry[:SHORT], ())) < self.max_bucket

    def match(self, text: bytes, at: int = 0) -> tuple[int, int]:
        """(number, length) of the longest entry that the text goes on with. Every single byte must be an entry."""
        left = len(text) - at
        if left > SHORT:
            for size, suffix, number in self.long.get(text[at : at + SHORT], ()):
                if text.startswith(suffix, at + SHORT):
                    return number, SHORT - size
        get = self.short.get
        for n in self.sizes.get(text[at : at + 4], ()) if left >= 4 else ():
            if n <= left and (number := get(text[at : at + n])) is not None:
                return number, n
        if left >= 3 and (number := get(text[at : at + 3])) is not None:
            return number, 3
        if left >= 2 and (number := get(text[at : at + 2])) is not None:
            return number, 2
        return self.short[text[at : at + 1]], 1

    def tally(self, text: bytes, at: int, cost: Cost, inline: int = 4) -> tuple[int, int]:
        """As `match`, with every comparison counted as the plain search makes it (all lengths from eight down)."""
        left = len(text) - at
        if left > SHORT:
            cost.probes += 1
            for k, (size, suffix, number) in enumerate(self.long.get(text[at : at + SHORT], ())):
                cost.suffixes += 1
                cost.overflow += k >= inline
                if text.startswith(suffix, at + SHORT):
                    return number, SHORT - size
        for n in range(min(left, SHORT), 0, -1):
            cost.probes += 1
            if (number := self.short.get(text[at : at + n])) is not None:
                return number, n
        raise ValueError("not every byte is an entry")

    def parse(self, text: bytes) -> list[int]:
        out, at = [], 0
        while at < len(text):
            number, n = self.match(text, at)
            out.append(number)
            at += n
        return out
