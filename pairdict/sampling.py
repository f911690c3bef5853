"""Samples for training: a bounded random part of a corpus, in random order, the same for every partitioning."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SampleSpec:
    """max_bytes: the trainer stops reading there. fraction: share of the rows (by hash); None: the share that holds about twice
    max_bytes, so that what is sorted does not grow with the corpus. order: md5 or xxhash64 of seed and key, or `stored` (by
    key, unshuffled)."""

    fraction: float | None = None
    max_bytes: int = 8 << 20
    seed: int = 42
    order: str = "md5"

    def __post_init__(self):
        if (self.fraction is not None and not 0 < self.fraction <= 1) or self.max_bytes < 1 or self.order not in ("md5", "xxhash64", "stored"):
            raise ValueError(f"bad sample: {self}")

    def fitted(self, total_bytes: int) -> SampleSpec:
        """With the fraction that suits a corpus of so many bytes, unless one is given."""
        return self if self.fraction is not None else replace(self, fraction=fitting_fraction(total_bytes, self.max_bytes))


def draw_sample(corpus: DataFrame, spec: SampleSpec = SampleSpec()) -> DataFrame:
    """(ord, key, value). The hash filter is narrow and stands before any sort; without a fraction all rows are drawn."""
    rows = corpus.where(F.col("value").isNotNull())
    if spec.fraction is not None and spec.fraction < 1:
        rows = rows.where(F.pmod(F.xxhash64(F.lit(spec.seed), "key"), F.lit(1_000_000)) < int(spec.fraction * 1_000_000))
    salted = F.concat(F.lit(f"{spec.seed}:"), F.col("key").cast("string"))
    order = {"md5": F.md5(salted.cast("binary")), "xxhash64": F.lpad(F.hex(F.xxhash64(salted)), 16, "0"), "stored": F.lit("")}[spec.order]
    return rows.select(order.alias("ord"), "key", "value")


def fitting_fraction(total_bytes: int, max_bytes: int) -> float:
    """The share that holds about twice the bytes a trainer may read, so that the sample's sort never grows with the corpus."""
    return min(1.0, max(1e-6, 2 * max_bytes / max(1, total_bytes)))
