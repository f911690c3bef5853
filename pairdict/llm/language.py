"""Language identification by cross-parsing: the language whose labelled text needs the fewest phrases wins."""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import shared

SYMBOLS = 64
BLOCK = 1024  # code points parsed on their own; phrases do not cross the border of a block
_LETTER = re.compile(r"[^\W\d_]")
PHRASE = np.int32(1 << 29)  # phrases begun by a step stand above this bit


class Alphabet:
    """Code points folded to SYMBOLS classes: 0 for anything rare, 1 for all white space, own classes for frequent characters."""

    def __init__(self, texts: list[str]):
        counts = Counter()
        for t in texts:
            counts.update(c for c in t.lower() if not c.isspace() and c.isalpha())
        self.chars = sorted(c for c, _ in counts.most_common(SYMBOLS - 2) if len(c) == 1 and ord(c) < 65536)
        table = np.zeros(65536, np.uint8)
        for k in range(65536):
            c = chr(k)
            if c.isspace():
                table[k] = 1
        for k, c in enumerate(self.chars):
            for form in (c, c.upper()):
                if len(form) == 1 and ord(form) < 65536:
                    table[ord(form)] = k + 2
        self.table = table

    def encode(self, text: str) -> np.ndarray:
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        return self.table[np.where(points < 65536, points, 0)]


def automaton(symbols: np.ndarray) -> np.ndarray:
    """Suffix automaton of a text as a table [state, symbol] -> next state + PHRASE x phrases begun.

    Where no longer match exists the entry leads on from the start with that symbol: one phrase more. A symbol that the text
    never has is a phrase of its own; the entry leads back to the start, and the phrase to come is counted ahead."""
    link, length, step = [-1], [0], [{}]
    last = 0
    for c in symbols.tolist():
        now = len(step)
        link.append(0)
        length.append(length[last] + 1)
        step.append({})
        p = last
        while p >= 0 and c not in step[p]:
            step[p][c] = now
            p = link[p]
        if p >= 0:
            q = step[p][c]
            if length[p] + 1 == length[q]:
                link[now] = q
            else:
                twin = len(step)
                length.append(length[p] + 1)
                link.append(link[q])
                step.append(dict(step[q]))
                while p >= 0 and step[p].get(c) == q:
                    step[p][c] = twin
                    p = link[p]
                link[q] = link[now] = twin
        last = now
    table = np.full((len(step), SYMBOLS), -1, np.int32)
    for s, row in enumerate(step):
        for c, to in row.items():
            table[s, c] = to
    start = np.where(table[0] >= 0, table[0] + PHRASE, 2 * PHRASE)
    full = np.where(table >= 0, table, start[None, :])
    full[0] = np.where(table[0] >= 0, table[0], PHRASE)
    return full


class Model:
    def __init__(self, samples: dict[str, list[str]], chars: int = 30_000):
        """samples: labelled texts for each language; at most `chars` code points of each language are learned from."""
        self.langs = sorted(samples)
        self.alphabet = Alphabet([t for ts in samples.values() for t in ts])
        tables, base, self.bits = [], [], []
        at = 0
        for lang in self.langs:
            text = self.alphabet.encode(" ".join(samples[lang]))[:chars]
            table = automaton(text)
            base.append(at)
            tables.append(table + np.int32(at))
            at += len(table)
            self.bits.append(np.log2(max(2, len(text))))
        self.table = np.concatenate(tables).ravel() if tables else np.zeros(0, np.int32)
        self.base = np.array(base, np.int32)
        self.bits = np.array(self.bits)

    def phrases(self, symbols: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Phrases of each text under each language; texts are cut into blocks that are parsed side by side."""
        n, langs = len(offs) - 1, len(self.langs)
        size = np.diff(offs)
        blocks = -(-size // BLOCK)
        owner = np.repeat(np.arange(n), blocks)
        first = np.arange(blocks.sum()) - np.repeat(np.cumsum(blocks) - blocks, blocks)
        start = offs[owner] + first * BLOCK
        length = np.minimum(BLOCK, offs[owner + 1] - start)
        order = np.argsort(-length, kind="stable")
        start, length, owner = start[order], length[order], owner[order]
        state = np.tile(self.base[:, None], (1, len(start)))
        count = np.ones((langs, len(start)), np.int32)
        still = np.searchsorted(-length, -np.arange(length[0] if len(length) else 0), "left")
        for k, w in enumerate(still.tolist()):
            c = symbols[start[:w] + k]
            to = self.table[state[:, :w] * SYMBOLS + c]
            count[:, :w] += to >> 29
            state[:, :w] = to & (PHRASE - 1)
        count -= (state == self.base[:, None]) & (length > 0)
        out = np.zeros((langs, n))
        for k in range(langs):
            out[k] = np.bincount(owner, count[k], n)
        return out

    def predict(self, text: pa.Array) -> tuple[list, np.ndarray]:
        """Language and score of each text. Bits a code point = phrases x log2(learned length) / length; the score is the share
        of the winner when each language weighs 2 ** (-8 x bits). No letters: und, 0."""
        langs, scores = [], []
        for a, b, _, _ in shared.slices(text, 2 << 20):
            part = text.slice(a, b - a).to_pylist()
            parts = [self.alphabet.encode(t or "") for t in part]
            offs = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
            has = np.array([bool(t and _LETTER.search(t)) for t in part])
            if not self.langs:
                langs += ["und"] * len(part)
                scores.append(np.zeros(len(part)))
                continue
            bits = self.phrases(np.concatenate(parts), offs) * self.bits[:, None] / np.maximum(1, np.diff(offs))
            best = bits.argmin(0)
            weight = np.exp2(-8 * (bits - bits.min(0)))
            score = np.where(has, 1 / weight.sum(0), 0.0)
            langs += [self.langs[k] if ok else "und" for k, ok in zip(best.tolist(), has.tolist(), strict=True)]
            scores.append(score)
        return langs, np.concatenate(scores) if scores else np.zeros(0)


def train(docs: DataFrame, rows: int = 64, chars: int = 30_000, row_chars: int = 600, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Learn from a bounded sample: for each language the `rows` labelled texts whose ids hash lowest, `row_chars` code points
    of each, `chars` in all. Rows with a null text or language teach nothing."""
    labelled = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("l"), F.xxhash64(F.col(id_col)).alias("h"), F.substring(text_col, 1, row_chars).alias("t"))
    top = labelled.withColumn("r", F.row_number().over(Window.partitionBy("l").orderBy("h", "t"))).where(F.col("r") <= rows)
    samples: dict[str, list[str]] = {}
    for r in sorted(top.select("l", "h", "t").collect()):
        samples.setdefault(r.l, []).append(r.t)
    return Model(samples, chars)


def identify(docs: DataFrame, model: Model, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Add lang_pred and score to the columns in `keep`. Null texts and texts without a letter get und and 0; ties go to the
    language first in order; repeated rows get equal answers; an untrained model answers und throughout."""
    keep = shared.kept(docs, keep, ("lang_pred", "score"))
    rows = docs.select(*keep, F.col(text_col).alias("_pairdict_text"))
    held = docs.sparkSession.sparkContext.broadcast(model)  # at most SYMBOLS x 2 x chars x 4 bytes a language

    def run(batches):
        for batch in batches:
            langs, score = held.value.predict(batch.column(batch.num_columns - 1))
            columns = [*batch.columns[:-1], pa.array(langs, pa.string()), pa.array(score, pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, [*keep, "lang_pred", "score"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(shared.tidily(run), f"{fields}, lang_pred string, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = shared.documents(spark, sf_dir)
    out = shared.crc_mod("doc_id", 4) == 2
    model = train(docs.where(~F.coalesce(out, F.lit(False))))
    got = identify(docs, model, keep=["doc_id"])
    return got.select("doc_id", F.coalesce(out, F.lit(False)).alias("held_out"), "lang_pred", "score")
