"""Parsing, decoding and reading single values."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..dictionary import Dictionary
from ..match.static import StaticVectorIndex
from ..match.vector import VectorIndex

INDEXES = {"dynamic": VectorIndex, "static": StaticVectorIndex}

_CACHE: dict[str, tuple] = {}


def _of(kind: str, dictionary: Dictionary, make):
    """One index or table a worker and dictionary; the newest few stay."""
    name = kind + dictionary.version
    if name not in _CACHE:
        while len(_CACHE) > 7:
            _CACHE.pop(next(iter(_CACHE)))
        _CACHE[name] = make(dictionary)
    return _CACHE[name]


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, offsets and nulls of a string or binary array."""
    null = column.is_null().to_numpy(zero_copy_only=False)
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    column = column.fill_null(b"")
    offs = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data[offs[0] : offs[-1]], offs - offs[0], null


def binary_array(data: np.ndarray, offs: np.ndarray, null: np.ndarray, kind=pa.binary()) -> pa.Array:
    valid = pa.py_buffer(np.packbits(~null, bitorder="little").tobytes())
    wide = offs.astype(np.int32)
    return pa.Array.from_buffers(kind, len(null), [valid, pa.py_buffer(wide.tobytes()), pa.py_buffer(np.ascontiguousarray(data).tobytes())])


def encode_column(column: pa.Array, dictionary: Dictionary, index: str = "dynamic") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entry numbers end to end, how many each value has, and nulls."""
    data, offs, null = flat(column)
    ids, count = _of(index, dictionary, INDEXES[index]).parse(data, offs)
    return ids, count, null


def _pairs(ids: np.ndarray, bits: int) -> tuple[np.ndarray, int]:
    """Stored numbers: two bytes each, or four where the width needs them."""
    return (ids.astype("<u2"), 2) if bits <= 16 else (ids.astype("<u4"), 4)


def _schema(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def pack_column(ids: np.ndarray, count: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of `bits` bits, lowest bit first; each value's run is filled up to whole bytes. The bytes, and where values begin."""
    size = -(-count.astype(np.int64) * bits // 8)
    offs = np.concatenate([[0], np.cumsum(size)])
    place = np.arange(len(ids)) - np.repeat(np.cumsum(count) - count, count)
    first = np.repeat(offs[:-1] * 8, count) + place * bits
    flags = np.zeros(int(offs[-1]) * 8, np.uint8)
    for b in range(bits):
        flags[first + b] = ids >> b & 1
    return np.packbits(flags, bitorder="little"), offs


def unpack_column(data: np.ndarray, offs: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of `pack_column`, and how many each value has (fewer fill bits than a number has)."""
    count = np.diff(offs) * 8 // bits
    flags = np.unpackbits(data, bitorder="little")
    place = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
    first = np.repeat(offs[:-1] * 8, count) + place * bits
    ids = np.zeros(len(first), np.int64)
    for b in range(bits):
        ids |= flags[first + b].astype(np.int64) << b
    return ids, count


def encode(df: DataFrame, column: str, dictionary: Dictionary, out: str = "payload", index: str = "dynamic", packed: bool = False) -> DataFrame:
    """Replace a string or binary column by `out` (numbers, little-endian, two bytes each) and n_tokens; adds dict_version.

    A narrow map: rows are not moved. Null stays null with null n_tokens; the empty string has an empty payload. index: "static"
    parses with the frozen perfect-hash index (bounded dictionaries), to the same numbers. packed: numbers take the
    dictionary's bits in place of whole bytes. Columns of df that bear the new names are replaced.
    """
    if index not in INDEXES:
        raise ValueError(f"index is one of {sorted(INDEXES)}")
    held = df.sparkSession.sparkContext.broadcast(dictionary)  # at most 2^21 entries; 1.25 MiB for the bounded variant at 16 bits
    keep = [c for c in df.columns if c not in (column, out, "n_tokens", "dict_version")]
    rows = df.select(*keep, column)
    version = dictionary.version

    def run(batches):
        d = held.value
        for batch in batches:
            ids, count, null = encode_column(batch.column(batch.num_columns - 1), d, index)
            if packed:
                body, offs = pack_column(ids, count, d.bits)
            else:
                body, wide = _pairs(ids, d.bits)
                offs = np.concatenate([[0], np.cumsum(count)]) * wide
            n = pa.array(count.astype(np.int32), mask=null)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], binary_array(body.view(np.uint8), offs, null), n, pa.array([version] * batch.num_rows)], [*keep, out, "n_tokens", "dict_version"])

    head = _schema(df.select(*keep))
    return rows.mapInArrow(run, (head + ", " if keep else "") + f"`{out}` binary, n_tokens int, dict_version string")


class DecodeTable:
    """Entries as rows of 16 bytes, and the packed bytes for what is longer."""

    def __init__(self, dictionary: Dictionary):
        packed = dictionary.pack()
        self.data, self.offs = np.frombuffer(packed.data, np.uint8), packed.offsets
        self.lens = np.diff(packed.offsets)
        self.rows = np.zeros((len(self.lens), 16), np.uint8)
        for i, e in enumerate(dictionary.entries):
            self.rows[i, : min(16, len(e))] = np.frombuffer(e[:16], np.uint8)
        self.bounded = bool((self.lens <= 16).all())
        self.long_copies = 0

    def expand(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of the entries end to end, and where each begins (and the end)."""
        lens = self.lens[ids]
        at = np.concatenate([[0], np.cumsum(lens)])
        if self.bounded:  # a copy of 16 bytes each, cut to length
            return self.rows[ids][np.arange(16) < lens[:, None]], at
        out = np.empty(at[-1], np.uint8)
        head = np.minimum(lens, 16)
        spot = np.repeat(at[:-1] - (np.cumsum(head) - head), head) + np.arange(head.sum())
        out[spot] = self.rows[ids][np.arange(16) < lens[:, None]]
        long_ = np.flatnonzero(lens > 16)  # only these need the second copy
        self.long_copies += len(long_)
        more = lens[long_] - 16
        within = np.arange(more.sum()) - np.repeat(np.cumsum(more) - more, more)
        out[np.repeat(at[long_] + 16, more) + within] = self.data[np.repeat(self.offs[ids[long_]] + 16, more) + within]
        return out, at


def decode_column(column: pa.Array, dictionary: Dictionary, kind=pa.string(), packed: bool = False) -> pa.Array:
    data, offs, null = flat(column)
    if packed:
        ids, count = unpack_column(np.ascontiguousarray(data), offs, dictionary.bits)
        first = np.concatenate([[0], np.cumsum(count)])
    else:
        wide = 2 if dictionary.bits <= 16 else 4
        ids, first = np.ascontiguousarray(data).view("<u2" if wide == 2 else "<u4").astype(np.int64), offs // wide
    body, at = _of("table", dictionary, DecodeTable).expand(ids)
    return binary_array(body, at[first], null, kind)


def decode(df: DataFrame, column: str, dictionary: Dictionary, out: str = "value", binary: bool = False, packed: bool = False) -> DataFrame:
    """Replace a payload column by the values it stands for. Put it last: filters, joins and limits before it spare the work."""
    held = df.sparkSession.sparkContext.broadcast(dictionary)
    keep = [c for c in df.columns if c not in (column, out)]
    rows = df.select(*keep, column)

    def run(batches):
        for batch in batches:
            got = decode_column(batch.column(batch.num_columns - 1), held.value, pa.binary() if binary else pa.string(), packed)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], got], [*keep, out])

    head = _schema(df.select(*keep))
    return rows.mapInArrow(run, (head + ", " if keep else "") + f"`{out}` {'binary' if binary else 'string'}")


def token_ids(df: DataFrame, column: str, dictionary: Dictionary, out: str = "ids", index: str = "dynamic") -> DataFrame:
    """Replace a column by its entry numbers as an array."""
    held = df.sparkSession.sparkContext.broadcast(dictionary)
    keep = [c for c in df.columns if c not in (column, out)]

    def run(batches):
        for batch in batches:
            ids, count, null = encode_column(batch.column(batch.num_columns - 1), held.value, index)
            offs = pa.array(np.concatenate([[0], np.cumsum(count)]).astype(np.int32))
            got = pa.ListArray.from_arrays(offs, pa.array(ids.astype(np.int32)), mask=pa.array(null))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], got], [*keep, out])

    head = _schema(df.select(*keep))
    return df.select(*keep, column).mapInArrow(run, (head + ", " if keep else "") + f"`{out}` array<int>")


def token_frequencies(df: DataFrame, column: str, dictionary: Dictionary) -> DataFrame:
    """token_id, f: how often each entry is emitted. Counted in each task first: as many rows as entries, never one an id."""
    held = df.sparkSession.sparkContext.broadcast(dictionary)

    def run(batches):
        d = held.value
        total = np.zeros(len(d.entries), np.int64)
        for batch in batches:
            total += np.bincount(encode_column(batch.column(0), d)[0], minlength=len(total))
        on = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(on.astype(np.int32)), pa.array(total[on])], ["token_id", "f"])

    return df.select(column).mapInArrow(run, "token_id int, f long").groupBy("token_id").agg(F.sum("f").alias("f"))


def explode_ids(encoded: DataFrame, payload: str = "payload", key: str = "key") -> DataFrame:
    """key, pos (from 0), token_id of two-byte payloads, by column functions alone."""
    n = (F.octet_length(payload) / 2).cast("int")
    word = lambda i: F.conv(F.concat(F.hex(F.substring(payload, i * 2 + 2, F.lit(1))), F.hex(F.substring(payload, i * 2 + 1, F.lit(1)))), 16, 10).cast("int")
    return encoded.where(n > 0).select(key, F.posexplode(F.transform(F.sequence(F.lit(0), n - 1), word)).alias("pos", "token_id"))


def decode_join(encoded: DataFrame, dictionary: DataFrame, payload: str = "payload", key: str = "key") -> DataFrame:
    """key, value: decoding as a join with the dictionary and an ordered concatenation. Moves a row an id: for checking."""
    parts = explode_ids(encoded, payload, key).join(F.broadcast(dictionary.select("token_id", "entry")), "token_id")
    whole = parts.groupBy(key).agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", F.hex("entry").alias("h")))), lambda x: x["h"]), "").alias("h"))
    empty = encoded.where(F.octet_length(payload) == 0).select(key, F.lit("").alias("value"))
    return whole.select(key, F.decode(F.unhex("h"), "UTF-8").alias("value")).unionByName(empty)
