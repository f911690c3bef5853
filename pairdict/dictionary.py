"""The dictionary: byte strings by number, the first 256 being the single bytes."""

from __future__ import annotations

import hashlib
import json
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

SCHEMA = T.StructType([T.StructField("token_id", T.IntegerType(), False), T.StructField("entry", T.BinaryType(), False), T.StructField("entry_len", T.IntegerType(), False), T.StructField("left_id", T.IntegerType()), T.StructField("right_id", T.IntegerType())])


@dataclass(frozen=True)
class PackedDictionary:
    """All entries in one run of bytes; entry i lies between offsets i and i + 1."""

    data: bytes
    offsets: np.ndarray

    def entry_at(self, i: int) -> bytes:
        return self.data[self.offsets[i] : self.offsets[i + 1]]


@dataclass
class Dictionary:
    entries: list[bytes]
    lefts: list[int | None] = field(default_factory=list)
    rights: list[int | None] = field(default_factory=list)
    variant: str = "bounded16"
    bits: int = 16
    threshold: int = 2
    stats: dict = field(default_factory=dict)

    def __post_init__(self):
        none = [None] * len(self.entries)
        self.lefts, self.rights = self.lefts or none, self.rights or list(none)
        if len(self.entries) > 1 << self.bits:
            raise ValueError("more entries than numbers of this width")

    @cached_property
    def version(self) -> str:
        """Names the contents, which do not change: payloads of different versions must not be compared."""
        h = hashlib.sha256()
        for e in self.entries:
            h.update(len(e).to_bytes(4, "little") + e)
        return h.hexdigest()[:16]

    def pack(self) -> PackedDictionary:
        offsets = np.concatenate([[0], np.cumsum([len(e) for e in self.entries], dtype=np.int64)])
        return PackedDictionary(b"".join(self.entries), offsets)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(i, bytearray(e), len(e), a, b) for i, (e, a, b) in enumerate(zip(self.entries, self.lefts, self.rights, strict=True))]
        return spark.createDataFrame(rows, SCHEMA)

    @staticmethod
    def from_frame(df: DataFrame, **kw) -> Dictionary:
        """From (token_id, entry, left_id, right_id) rows: at most 2^21 of them."""
        rows = sorted(df.select("token_id", "entry", "left_id", "right_id").collect())
        if [r.token_id for r in rows] != list(range(len(rows))):
            raise ValueError("entry numbers must be dense")
        return Dictionary([bytes(r.entry) for r in rows], [r.left_id for r in rows], [r.right_id for r in rows], **kw)

    def save(self, spark: SparkSession, path: str) -> None:
        """Rows as Parquet, and a manifest of one JSON line."""
        self.frame(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/entries")
        manifest = {"version": self.version, "variant": self.variant, "bits": self.bits, "threshold": self.threshold, "stats": self.stats}
        spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Dictionary:
        m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        d = Dictionary.from_frame(spark.read.parquet(f"{path}/entries"), variant=m["variant"], bits=m["bits"], threshold=m["threshold"], stats=m["stats"])
        if d.version != m["version"]:
            raise ValueError("the entries are not those of the manifest")
        return d


def single_bytes() -> list[bytes]:
    return [bytes([b]) for b in range(256)]


#: Lengths of the n-grams of the fixed dictionary, which other engines can rebuild.
GRAM_LENGTHS = (2, 3, 4, 6, 8, 10, 12, 16)


def fixed_frame(corpus: DataFrame, k: int = 400, lengths=GRAM_LENGTHS) -> DataFrame:
    """token_id, entry: the bytes and the `k` most frequent byte n-grams (ties by hex). A declarative stand-in for training."""
    spark = corpus.sparkSession
    raw = corpus.select(F.encode("value", "UTF-8").alias("b"))
    grams = raw.select("b", F.explode(F.array(*[F.lit(n) for n in lengths])).alias("n")).where(F.octet_length("b") >= F.col("n"))
    grams = grams.select(F.explode(F.transform(F.sequence(F.lit(1), F.octet_length("b") - F.col("n") + 1), lambda i: F.substring("b", i, F.col("n")))).alias("entry"))
    top = grams.groupBy("entry").agg(F.count(F.lit(1)).alias("c")).orderBy(F.desc("c"), F.hex("entry")).limit(k)
    ranked = top.select((F.row_number().over(Window.orderBy(F.desc("c"), F.hex("entry"))) + 255).alias("token_id"), "entry")  # k rows
    base = spark.range(256).select(F.col("id").cast("int").alias("token_id"), F.unhex(F.lpad(F.hex("id"), 2, "0")).alias("entry"))
    return base.unionByName(ranked).select("token_id", "entry", F.octet_length("entry").alias("entry_len"))


def fixed_dictionary(corpus: DataFrame, k: int = 400, bits: int = 10) -> Dictionary:
    rows = sorted(fixed_frame(corpus, k).select("token_id", "entry").collect())
    return Dictionary([bytes(r.entry) for r in rows], variant="bounded16", bits=bits)


def offsets_frame(dictionary: DataFrame) -> DataFrame:
    """token_id, at, to: where each entry lies in the packed bytes. A dictionary has a bounded number of rows, so one window serves."""
    upto = F.sum("entry_len").over(Window.orderBy("token_id"))
    return dictionary.select("token_id", (upto - F.col("entry_len")).cast("long").alias("at"), upto.cast("long").alias("to"))
