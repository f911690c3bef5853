"""Quality from compression: how much better a dictionary of good text compresses a document than one of bad text."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

BLOCK = 2048  # bytes compressed on their own, so that a dictionary counts in long texts too
LEVEL = 1


class Model:
    def __init__(self, good: list[str], bad: list[str], dictionary_bytes: int = 32 << 10):
        """Two trained dictionaries and a logistic calibration fitted on the same labelled rows, half and half: dictionaries
        come from the even rows and the calibration from the odd ones, where there are enough of both."""
        self.dictionaries = [self._dictionary(x[::2], dictionary_bytes) for x in (good, bad)]
        xs, ys = [], []
        for label, texts in ((1, good), (0, bad)):
            part = texts[1::2] if len(texts) > 8 else texts
            if part:
                xs.append(self.features(pa.array(part, pa.string())))
                ys.append(np.full(len(part), float(label)))
        self.mean, self.scale, self.weights = np.zeros(3), np.ones(3), np.zeros(7)
        if len(xs) == 2:
            x, y = np.concatenate(xs), np.concatenate(ys)
            self.mean, self.scale = x.mean(0), x.std(0) + 1e-9
            self.weights = self._fit(self._expand(x), y)
        elif xs:
            self.weights[-1] = 3.0 if ys[0][0] else -3.0

    @staticmethod
    def _dictionary(texts: list[str], size: int) -> bytes:
        """A zstandard dictionary; where there is too little text to train one, the text itself serves as raw content."""
        chunks = [c for t in texts for b in [t.encode()] for c in (b[i : i + BLOCK] for i in range(0, len(b), BLOCK))]
        try:
            return zstandard.train_dictionary(size, chunks, level=LEVEL).as_bytes()
        except (zstandard.ZstdError, ValueError):
            return b" " + b"".join(chunks)[:size]

    def _compressors(self):
        if "_made" not in self.__dict__:
            made = []
            for d in self.dictionaries:
                held = zstandard.ZstdCompressionDict(d)
                held.precompute_compress(level=LEVEL)
                made.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=held, write_content_size=False, write_checksum=False, write_dict_id=False))
            self._made = made
        return self._made

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_made"}

    def features(self, text: pa.Array) -> np.ndarray:
        """For each text: (size under bad - size under good) / bytes, size under good / bytes, log of the bytes."""
        good, bad = (c.compress for c in self._compressors())
        out = []
        for a, b, buf, offs in shared.slices(text):
            raw = buf.tobytes()
            for x, y in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True):
                parts = [raw[i : min(i + BLOCK, y)] for i in range(x, y, BLOCK)]
                g, w = sum(len(good(p)) for p in parts), sum(len(bad(p)) for p in parts)
                n = max(1, y - x)
                out.append(((w - g) / n, g / n, np.log(n)))
        return np.array(out).reshape(-1, 3)

    def _expand(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        return np.column_stack([z, z[:, 0] * z[:, 2], z[:, 1] * z[:, 2], z[:, 1] ** 2, np.ones(len(z))])

    @staticmethod
    def _fit(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> np.ndarray:
        """Logistic regression by Newton's method with a ridge."""
        w = np.zeros(x.shape[1])
        for _ in range(40):
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
            move = np.linalg.solve(h, x.T @ (y - p) - ridge * w)
            w = w + move
            if abs(move).max() < 1e-6:
                break
        return w

    def scores(self, text: pa.Array) -> np.ndarray:
        x = self.features(text)
        return 1 / (1 + np.exp(-np.clip(self._expand(x) @ self.weights, -30, 30))) if len(x) else np.zeros(0)


def train(docs: DataFrame, labels: DataFrame, rows: int = 3000, row_chars: int = 8192, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Model:
    """Learn from a bounded sample: for each label the `rows` labelled texts whose ids hash lowest, `row_chars` code points of each."""
    marked = labels.where(F.col(label_col).isNotNull()).select(F.col(id_col).alias("i"), F.col(label_col).alias("y"), F.xxhash64(F.col(id_col)).alias("h"))
    samples = []
    for y in (1, 0):
        ids = marked.where(F.col("y") == y).select("i", "h").distinct().orderBy("h", "i").limit(rows)  # bounded by `rows`
        got = docs.join(F.broadcast(ids), docs[id_col] == F.col("i")).where(F.col(text_col).isNotNull()).select("h", F.substring(text_col, 1, row_chars).alias("t"))
        samples.append([r.t for r in sorted(got.orderBy("h", "t").limit(rows).collect())])
    return Model(*samples)


def score(docs: DataFrame, model: Model, threshold: float = 0.3, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Add score (0 to 1) and predicted to the columns in `keep`. Null counts as empty; both get the score of no bytes.
    Whole texts are compressed, in blocks. Equal texts get equal scores. Without labels of both kinds the score is constant."""
    keep = shared.kept(docs, keep, ("score", "predicted"))
    rows = docs.select(*keep, F.col(text_col).alias("_pairdict_text"))
    held = docs.sparkSession.sparkContext.broadcast(model)  # two dictionaries of fixed size

    def run(batches):
        for batch in batches:
            s = held.value.scores(batch.column(batch.num_columns - 1))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(s), pa.array((s >= threshold).astype(np.int32))], [*keep, "score", "predicted"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, f"{fields}, score double, predicted int")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = shared.documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = F.coalesce(shared.crc_mod("doc_id", 5) == 0, F.lit(False))
    model = train(docs, labels.where(~out))
    return score(docs, model, keep=["doc_id"]).select("doc_id", out.alias("held_out"), "score", "predicted")
