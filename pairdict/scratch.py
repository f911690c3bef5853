"""Tables between steps: in the folder that spark.checkpoint.dir names, which all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """A fresh name there; a temporary one in local mode where the setting is empty."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        top = tempfile.gettempdir()
    return f"{top.rstrip('/')}/pairdict-{uuid.uuid4().hex}"


def keep(df: DataFrame) -> DataFrame:
    """Write and read again: cuts the lineage and survives lost executors."""
    path = folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
