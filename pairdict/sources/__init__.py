"""Sources and sinks: delimited, JSON and text files with a given schema, and the compressed store as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .store_source import StoreSource, register

__all__ = ["StoreSource", "parquet_bytes", "read_delimited", "read_json", "read_text", "register"]


def _malformed(schema: str, column: str) -> str:
    return f"{schema}, {column} string"


def read_delimited(spark: SparkSession, path: str, schema: str, sep: str = ",", header: bool = True, malformed: str = "_malformed") -> DataFrame:
    """CSV with an explicit schema; lines that do not fit it keep their text in `malformed`."""
    return spark.read.csv(path, schema=_malformed(schema, malformed), sep=sep, header=header, mode="PERMISSIVE", columnNameOfCorruptRecord=malformed)


def read_json(spark: SparkSession, path: str, schema: str, malformed: str = "_malformed") -> DataFrame:
    return spark.read.json(path, schema=_malformed(schema, malformed), mode="PERMISSIVE", columnNameOfCorruptRecord=malformed)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    """value: one row a line."""
    return spark.read.text(path)


def parquet_bytes(df: DataFrame, path: str, codec: str) -> int:
    """Bytes of a table written as Parquet under a page codec, as the file system counts them."""
    df.write.mode("overwrite").option("compression", codec).parquet(path)
    jvm = df.sparkSession._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).getContentSummary(p).getLength()
