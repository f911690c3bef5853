"""spark.read.format("pairdict"): a compressed store read as its values, with equality on key and value pushed down.

The store must lie where every worker can open it by path (a shared or local mount)."""

from __future__ import annotations

import glob
import json

import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition


class StoreSource(DataSource):
    @classmethod
    def name(cls):
        return "pairdict"

    def schema(self):
        return "key long, value string"

    def reader(self, schema):
        return StoreReader(self.options["path"])


class _File(InputPartition):
    def __init__(self, path):
        self.path = path


class StoreReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.keys, self.values = path.removeprefix("file://"), None, None

    def pushFilters(self, filters):
        """Takes equality and IN on key and value; gives everything else back."""
        for f in filters:
            if isinstance(f, (EqualTo, In)) and f.attribute in (("key",), ("value",)):
                wanted = {f.value} if isinstance(f, EqualTo) else set(f.value)
                name = "keys" if f.attribute == ("key",) else "values"
                held = getattr(self, name)
                setattr(self, name, wanted if held is None else held & wanted)
            else:
                yield f

    def partitions(self):
        return [_File(p) for p in sorted(glob.glob(f"{self.path}/rows/**/*.parquet", recursive=True))]

    def read(self, partition):
        from ..codec import decode_column
        from ..codec.store import payloads
        from ..dictionary import Dictionary

        manifest = json.loads(open(sorted(glob.glob(f"{self.path}/dictionary/manifest/part-*"))[0]).read())
        t = pq.read_table(f"{self.path}/dictionary/entries").sort_by("token_id")
        d = Dictionary([bytes(e) for e in t["entry"].to_pylist()], variant=manifest["variant"], bits=manifest["bits"])
        rows = pq.read_table(partition.path, columns=["key", "payload"], filters=None if self.keys is None else [("key", "in", self.keys)] if self.keys else pc.scalar(False))
        if self.values is not None:
            rows = rows.filter(pc.is_in(rows["payload"], pa.array(payloads(sorted(self.values), d), pa.binary())))
        for batch in rows.to_batches():
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), decode_column(batch.column(1), d)], ["key", "value"])


def register(spark: SparkSession) -> None:
    """Make the source known, and let Python sources take filters (a setting of the session that is off by default)."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(StoreSource)
