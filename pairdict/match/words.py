"""Prefix tests on eight bytes packed into a 64-bit word, the first byte lowest."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def pack8(text: Column) -> Column:
    """The first eight bytes of a binary column as a long bit pattern; missing bytes are zero."""
    padded = F.rpad(F.hex(F.substring(text, 1, 8)), 16, "0")
    turned = F.concat(*[F.substring(padded, 15 - 2 * k, 2) for k in range(8)])
    return F.conv(turned, 16, -10).cast("long")


def shared_prefix_len(a: Column, b: Column) -> Column:
    """Equal bytes at the low end of two packed words: the lowest set bit of their difference marks the first unequal byte."""
    d = a.bitwiseXOR(b)
    below = F.bitwise_not(d).bitwiseAND(d - F.lit(1))  # ones under the lowest set bit
    return F.when(d == 0, 8).when(d == F.lit(-(2**63)), 7).otherwise(F.floor(F.bit_count(below) / 8)).cast("int")


def is_prefix64(text: Column, text_len: Column, candidate: Column, candidate_len: Column) -> Column:
    """Whether a packed candidate begins the packed text. A candidate longer than what is left never does, whatever the padding."""
    return (candidate_len <= text_len) & (shared_prefix_len(text, candidate) >= candidate_len)


def shared_prefix_words(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    d = a ^ b
    return np.where(d == 0, 8, np.bitwise_count((d & (~d + np.uint64(1))) - np.uint64(1)) // 8).astype(np.int64)


def is_prefix_words(text, text_len, candidate, candidate_len) -> np.ndarray:
    return (candidate_len <= text_len) & (shared_prefix_words(text, candidate) >= candidate_len)
