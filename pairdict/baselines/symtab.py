"""A table of at most 255 symbols of up to eight bytes with one-byte codes; 255 escapes a literal byte."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import codec
from ..dictionary import Dictionary, single_bytes
from ..match.dynamic import DynamicMatcher
from ..sampling import SampleSpec, draw_sample

ESCAPE, MOST, WIDEST = 255, 255, 8


def build(texts: list[bytes], rounds: int = 5) -> list[bytes]:
    """Symbols from a small sample: parse with the present table, count symbols and neighbouring pairs, keep those that gain
    most (count x length), and again."""
    table: list[bytes] = []
    for _ in range(rounds):
        matcher = DynamicMatcher(single_bytes() + [s for s in table if len(s) > 1])
        names = single_bytes() + [s for s in table if len(s) > 1]
        gain: Counter = Counter()
        for t in texts:
            before = b""
            for i in matcher.parse(t):
                s = names[i]
                gain[s] += len(s)
                both = (before + s)[:WIDEST]
                if before and len(before) + len(s) <= WIDEST:
                    gain[both] += len(both)
                before = s
        table = [s for s, _ in sorted(gain.items(), key=lambda x: (-x[1], x[0]))[:MOST]]
    return table


class SymbolTable:
    """Encoding and decoding with a symbol table; matching runs on the column kernel."""

    def __init__(self, symbols: list[bytes]):
        if len(symbols) > MOST or any(not 0 < len(s) <= WIDEST for s in symbols):
            raise ValueError("at most 255 symbols of one to eight bytes")
        self.symbols = symbols
        longer = [s for s in symbols if len(s) > 1]
        self.dictionary = Dictionary(single_bytes() + longer, variant="symtab8", bits=10)
        code = {s: i for i, s in enumerate(symbols)}
        self.code = np.array([code.get(e, ESCAPE) for e in self.dictionary.entries], np.uint8)
        self.width = np.where(self.code == ESCAPE, 2, 1)

    @staticmethod
    def train(corpus: DataFrame, sample_bytes: int = 16 << 10, rounds: int = 5) -> SymbolTable:
        """From a shuffled sample of about 16 KiB, which comes to the driver."""
        rows = draw_sample(corpus, SampleSpec(max_bytes=sample_bytes)).select("ord", "key", F.substring("value", 1, sample_bytes).alias("v")).orderBy("ord", "key").limit(2000).collect()
        texts, size = [], 0
        for r in rows:
            if size < sample_bytes:
                texts.append(r.v.encode()[: sample_bytes - size])
                size += len(texts[-1])
        return SymbolTable(build(texts, rounds))

    def encode_array(self, column: pa.Array) -> tuple[pa.Array, np.ndarray]:
        ids, count, null = codec.encode_column(column, self.dictionary)
        width = self.width[ids]
        at = np.concatenate([[0], np.cumsum(width)])
        out = np.full(at[-1], ESCAPE, np.uint8)
        plain = width == 1
        out[at[:-1][plain]] = self.code[ids[plain]]
        out[at[:-1][~plain] + 1] = ids[~plain]  # the first 256 entries are the bytes
        return codec.binary_array(out, at[np.concatenate([[0], np.cumsum(count)])], null), np.where(null, 0, count)

    def decode_array(self, column: pa.Array) -> pa.Array:
        data, offs, null = codec.flat(column)
        escape = data == ESCAPE
        if escape.any():  # an escape that is itself a literal does not escape: parity within runs
            run = np.flatnonzero(escape & ~np.concatenate([[False], escape[:-1]]))
            start = np.zeros(len(data), np.int64)
            start[run] = run
            first = np.maximum.accumulate(np.where(escape, start, 0))
            escape &= (np.arange(len(data)) - first) % 2 == 0
        literal = np.concatenate([[False], escape[:-1]])
        unit = np.flatnonzero(~escape)
        pieces = self.symbols + [b""] * (256 - len(self.symbols)) + single_bytes()
        number = np.where(literal[unit], 256 + data[unit].astype(np.int64), data[unit])
        table = Dictionary(pieces, variant="symtab8", bits=10)
        body, at = codec._of("table", table, codec.DecodeTable).expand(number)
        return codec.binary_array(body, at[np.searchsorted(unit, offs)], null, pa.string())

    def encode(self, df: DataFrame, column: str = "value", out: str = "payload") -> DataFrame:
        keep = [c for c in df.columns if c != column]
        held = df.sparkSession.sparkContext.broadcast(self)

        def run(batches):
            for b in batches:
                payload, n = held.value.encode_array(b.column(b.num_columns - 1))
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], payload, pa.array(n.astype(np.int32))], [*keep, out, "n_tokens"])

        return df.select(*keep, column).mapInArrow(run, f"{codec._schema(df.select(*keep))}, `{out}` binary, n_tokens int")

    def decode(self, df: DataFrame, column: str = "payload", out: str = "value") -> DataFrame:
        keep = [c for c in df.columns if c != column]
        held = df.sparkSession.sparkContext.broadcast(self)

        def run(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], held.value.decode_array(b.column(b.num_columns - 1))], [*keep, out])

        return df.select(*keep, column).mapInArrow(run, f"{codec._schema(df.select(*keep))}, `{out}` string")

    def size(self) -> int:
        """Bytes of the table: symbols and a length each."""
        return sum(map(len, self.symbols)) + len(self.symbols)
