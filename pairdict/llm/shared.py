"""What the operators share: the scratch folder, Arrow slicing and the byte-level word kernel."""

from __future__ import annotations

import ctypes
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one kernel call works on; a longer single text is still taken whole.
SLICE_BYTES = 1 << 19


def scratch(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir, which driver and executors share.

    Where the setting is empty and the master is local, a temporary folder serves; elsewhere that is an error.
    """
    top = spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        top = tempfile.gettempdir() + "/checkpoints"
    return f"{top.rstrip('/')}/pairdict-{uuid.uuid4().hex}"


def keep(df: DataFrame, name: str = "t") -> DataFrame:
    """Write a table to the shared folder and read it back: cuts the lineage and survives lost executors."""
    path = f"{scratch(df.sparkSession)}/{name}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(*tables: DataFrame) -> None:
    """Delete what `keep` wrote, once no later step reads it."""
    for df in tables:
        jvm = df.sparkSession._jvm
        for name in df.inputFiles()[:1]:
            folder = jvm.org.apache.hadoop.fs.Path(name).getParent().getParent()
            folder.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(folder, True)


def tidy() -> None:
    """Give freed memory back: idle workers keep it otherwise, beside those of the next stage."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        pass


def tidily(run):
    """A mapInArrow function that tidies up when it ends."""

    def wrapped(batches):
        yield from run(batches)
        tidy()

    return wrapped


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def kept(docs: DataFrame, keep: list[str] | None, added) -> list[str]:
    """Columns that go along: those asked for, or all whose names the operator does not give to columns of its own (those it replaces)."""
    return [c for c in (docs.columns if keep is None else keep) if c not in added]


def crc_mod(id_col: str, n: int):
    """crc32 of the id written as text, modulo n."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % n


def slices(text: pa.Array, limit: int = SLICE_BYTES):
    """Yield (first row, row after last, bytes, offsets): runs of rows of about `limit` bytes. Null counts as empty."""
    if isinstance(text, pa.ChunkedArray):
        text = text.combine_chunks()
    text = text.fill_null("")
    n = len(text)
    if not n:
        return
    wide = np.int64 if pa.types.is_large_string(text.type) else np.int32
    offs = np.frombuffer(text.buffers()[1], wide)[text.offset : text.offset + n + 1].astype(np.int64)
    data = np.frombuffer(text.buffers()[2], np.uint8) if text.buffers()[2] is not None else np.zeros(0, np.uint8)
    a = 0
    while a < n:
        b = max(a + 1, int(np.searchsorted(offs, offs[a] + limit, "right")) - 1)
        yield a, b, data[offs[a] : offs[b]], offs[a : b + 1] - offs[a]
        a = b


def byte_table(dropped) -> np.ndarray:
    """Which byte values belong to words; bytes of 0x80 and above always do."""
    t = np.ones(256, bool)
    t[list(dropped)] = False
    return t


#: Words of [^\x20\x09-\x0D]+ and of [^\x00-\x2F\x3A-\x60\x7B-\x7F]+ (after lower-casing A-Z).
SPACED = byte_table([0x20, *range(0x09, 0x0E)])
ALNUM = byte_table([*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def word_spans(buf: np.ndarray, offs: np.ndarray, table: np.ndarray):
    """Starts and ends of the words of all texts in a slice; a word never crosses a text's border."""
    n = len(buf)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    m = table[buf]
    before, after = np.zeros(n, bool), np.zeros(n, bool)
    before[1:], after[:-1] = m[:-1], m[1:]
    first, last = offs[:-1], offs[1:] - 1
    before[first[first < n]] = False
    after[last[last >= 0]] = False
    return np.flatnonzero(m & ~before), np.flatnonzero(m & ~after) + 1


_RNG = np.random.default_rng(20240607)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE = _BYTE[LOWER]
_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_BASE), -1, 2**64))
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int):
    if len(_POWERS[0]) < n:
        m = 1 << (n - 1).bit_length()
        for k, base in enumerate((_BASE, _INVERSE)):
            p = np.full(m, base, np.uint64)
            p[0] = 1
            _POWERS[k] = np.multiply.accumulate(p)
    return _POWERS


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash (xor-shift, multiply)."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def word_hashes(buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hash of each word with A-Z lower-cased: a polynomial over random byte values, then mixed."""
    up, down = powers(len(buf) + 1)
    total = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(_BYTE[buf] * up[: len(buf)], out=total[1:])
    return mix((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64))


def hash_words(words: list[bytes]) -> np.ndarray:
    """The same hash for a list of words."""
    buf = np.frombuffer(b"".join(words), np.uint8)
    offs = np.concatenate([[0], np.cumsum([len(w) for w in words], dtype=np.int64)]).astype(np.int64)
    return word_hashes(buf, offs[:-1], offs[1:])


def session_seed(*parts: int) -> np.random.Generator:
    return np.random.default_rng([p & 0xFFFFFFFF for p in parts])
