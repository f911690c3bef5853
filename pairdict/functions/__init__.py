"""SQL functions bound to one dictionary."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType

from .. import codec
from ..dictionary import Dictionary
from ..match.dynamic import DynamicMatcher


def _payload_list(column: pa.Array, d: Dictionary) -> list:
    ids, count, null = codec.encode_column(column, d)
    body, wide = codec._pairs(ids, d.bits)
    return codec.binary_array(body.view(np.uint8), np.concatenate([[0], np.cumsum(count)]) * wide, null).to_pylist()


def make(dictionary: Dictionary) -> dict:
    """Scalar functions as Arrow-batched UDFs: encode, decode, token_ids, n_tokens; and the aggregate encoded_bytes."""
    strings = lambda s: pa.Array.from_pandas(s, type=pa.string())

    @F.pandas_udf("binary")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series(_payload_list(strings(s), dictionary), dtype=object)

    @F.pandas_udf("string")
    def decode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series(codec.decode_column(pa.Array.from_pandas(s, type=pa.binary()), dictionary).to_pylist(), dtype=object)

    @F.pandas_udf(ArrayType(IntegerType()))
    def token_ids(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            ids, count, null = codec.encode_column(strings(s), dictionary)
            cut = np.concatenate([[0], np.cumsum(count)])
            yield pd.Series([None if z else ids[a:b].astype(np.int32) for a, b, z in zip(cut[:-1], cut[1:], null, strict=True)], dtype=object)

    @F.pandas_udf("int")
    def n_tokens(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            _, count, null = codec.encode_column(strings(s), dictionary)
            yield pd.Series(np.where(null, np.nan, count)).astype("Int32")

    @F.pandas_udf("long")
    def encoded_bytes(s: pd.Series) -> int:
        return int(codec.encode_column(strings(s), dictionary)[1].sum()) * 2

    return {"encode": encode, "decode": decode, "token_ids": token_ids, "n_tokens": n_tokens, "encoded_bytes": encoded_bytes}


def explain_table(dictionary: Dictionary):
    """A table function: (pos, token_id, entry, len) of each match of a value."""

    @F.udtf(returnType="pos int, token_id int, entry binary, len int")
    class Explain:
        def __init__(self):
            self.matcher = DynamicMatcher(dictionary.entries)

        def eval(self, value: str):
            raw, at = (value or "").encode(), 0
            while at < len(raw):
                number, n = self.matcher.match(raw, at)
                yield at, number, raw[at : at + n], n
                at += n

    return Explain


def register_functions(spark: SparkSession, dictionary: Dictionary, prefix: str = "pd_") -> None:
    """Register pd_encode, pd_decode, pd_token_ids, pd_n_tokens, pd_encoded_bytes and the table function pd_explain."""
    for name, f in make(dictionary).items():
        spark.udf.register(prefix + name, f)
    spark.udtf.register(prefix + "explain", explain_table(dictionary))


def token_freq(df: DataFrame, column: str, dictionary: Dictionary) -> DataFrame:
    """The scalable twin of a frequency aggregate: partial counts in each task, then one sum a number."""
    return codec.token_frequencies(df, column, dictionary)
