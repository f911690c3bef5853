"""The sequential part of training: one pass over strings, counting neighbouring matches and promoting frequent pairs."""

from __future__ import annotations

import time
from collections import defaultdict

from ..dictionary import single_bytes
from ..match.dynamic import DynamicMatcher


class Trainer:
    """State of one training run.

    A pair of neighbouring matches is counted, the present occurrence included; at the threshold it becomes an entry, its
    counter goes, and the new entry stands as the previous match. Pairs do not cross strings. A pair that could not become an
    entry (too long, or its bucket is full) is not counted.
    """

    def __init__(self, capacity: int, threshold: int, max_len: int | None, max_bucket: int | None, max_bytes: int | None = None):
        if threshold < 2:
            raise ValueError("the threshold is at least 2")
        if capacity < 256:
            raise ValueError("the single bytes must fit")
        self.entries = single_bytes()
        self.lefts: list[int | None] = [None] * 256
        self.rights: list[int | None] = [None] * 256
        self.matcher = DynamicMatcher(self.entries, max_bucket)
        self.counts: defaultdict[int, int] = defaultdict(int)
        self.capacity, self.threshold, self.max_len, self.max_bytes = capacity, threshold, max_len, max_bytes
        self.bytes_read = self.strings_read = self.peak_pairs = 0
        self.marks: dict[int, float | None] = {}  # numbers of entries, and when they were reached

    @property
    def stop_reason(self) -> str | None:
        if len(self.entries) >= self.capacity:
            return "capacity"
        return "budget" if self.max_bytes is not None and self.bytes_read >= self.max_bytes else None

    def promote(self, left: int, right: int) -> int:
        entry, number = self.entries[left] + self.entries[right], len(self.entries)
        self.matcher.insert(entry, number)
        self.entries.append(entry)
        self.lefts.append(left)
        self.rights.append(right)
        if number + 1 in self.marks:
            self.marks[number + 1] = time.perf_counter()
        return number

    def feed(self, text: bytes) -> bool:
        """Learn from one string; False once no more is wanted."""
        match, counts, entries, threshold, cap = self.matcher.match, self.counts, self.entries, self.threshold, self.max_len
        at, end, before = 0, len(text), -1
        while at < end:
            number, n = match(text, at)
            at += n
            if before >= 0 and (cap is None or len(entries[before]) + n <= cap):
                pair = before << 21 | number
                seen = counts[pair] + 1
                if seen < threshold:
                    counts[pair] = seen
                elif self.matcher.has_room(entries[before] + entries[number]):
                    self.peak_pairs = max(self.peak_pairs, len(counts))
                    del counts[pair]
                    number = self.promote(before, number)
                    if number + 1 >= self.capacity:
                        self.bytes_read += at
                        self.strings_read += 1
                        return False
                else:
                    del counts[pair]
            before = number
        self.bytes_read += end
        self.strings_read += 1
        return self.stop_reason is None

    def stats(self) -> dict:
        pairs = max(self.peak_pairs, len(self.counts))
        return {
            "bytes_read": self.bytes_read, "strings_read": self.strings_read, "entries": len(self.entries), "pairs_tracked": pairs,
            "stop_reason": self.stop_reason or "exhausted", "peak_state_bytes": 16 * pairs + sum(map(len, self.entries)) + 4 * len(self.entries),
        }


def learn(texts, **kw) -> Trainer:
    t = Trainer(**kw)
    if t.capacity > 256:
        for text in texts:
            if not t.feed(text):
                break
    return t
