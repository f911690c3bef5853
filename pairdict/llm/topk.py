"""Exact top-k search with vector-approximation files.

Vectors are packed into blocks; each block holds quantised cells beside the exact vectors. A task takes one block of queries
and one block of candidates, bounds every inner product from the cells alone, and reads exact vectors in the order of their
bounds until the k-th result is certain. The best k of each pair of blocks then meet in one ranking for each query.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import shared

CELL_BITS = 5


def quantise(v: np.ndarray, bits: int = CELL_BITS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells of a block: code of each component, and the lowest and highest value that each cell of a dimension holds."""
    low, high = v.min(0), v.max(0)
    cells = 1 << bits
    width = np.maximum(1, -(-(high - low + 1) // cells))
    code = ((v - low) // width).astype(np.uint8)
    edge = low[:, None] + width[:, None] * np.arange(cells)
    return code, edge, np.minimum(edge + width[:, None] - 1, np.maximum(high[:, None], edge))


def search_block(queries: np.ndarray, own: np.ndarray, ids: np.ndarray, exact: np.ndarray, k: int, first: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best k of a block for each query: (query row, candidate row, score). own: row of the block that is the query itself, or -1.

    A query's bound for a cell is the larger product with the cell's ends, summed over dimensions; a candidate is skipped only
    if its bound lies under the k-th best exact score so far, so ties are never lost.
    """
    code, low, high = quantise(exact)
    n, dim = exact.shape
    out_q, out_c, out_s = [], [], []
    middle2 = low + high  # twice the middle of each cell
    radius2 = high - low
    dims = np.arange(dim)
    mid, rad = middle2[dims, code].astype(np.float64), radius2[dims, code].astype(np.float64)
    wide = float(np.abs(exact).max(initial=0)) * float(np.abs(queries).max(initial=0)) * dim >= 2**51
    for a in range(0, len(queries), 256):
        q = queries[a : a + 256]
        if wide:
            score = q @ exact.T
            bound = score
        else:
            f = q.astype(np.float64)
            bound = ((f @ mid.T + np.abs(f) @ rad.T) / 2).astype(np.int64)  # halves are exact; the true bound is whole
        for i in range(len(q)):
            b = bound[i].copy()
            me = own[a + i]
            if me >= 0:
                b[me] = -np.iinfo(np.int64).max  # its negative is a number too
            size = n - (me >= 0)
            if size <= 0:
                continue
            take = min(size, max(4 * k, 64))
            while True:
                near = np.argpartition(-b, take - 1)[:take] if take < n else np.flatnonzero(np.arange(n) != me)
                near = near[near != me]
                s = exact[near] @ q[i]
                if take >= size:
                    break
                kth = np.partition(s, len(s) - k)[len(s) - k] if len(s) >= k else np.iinfo(np.int64).min
                need = int((b >= kth).sum())
                if need <= take:
                    break
                take = min(size, max(need, 2 * take)) if need > 2 * take else min(size, need)
            order = np.lexsort((ids[near], -s))[:k]
            out_q.append(np.full(len(order), a + i + first))
            out_c.append(near[order])
            out_s.append(s[order])
    if not out_q:
        z = np.zeros(0, np.int64)
        return z, z, z
    return np.concatenate(out_q), np.concatenate(out_c), np.concatenate(out_s)


def _check_products(rows: DataFrame, every: int) -> None:
    """Raise where the product of a query and another row of its length may not fit 64 bits (rows: id, dim, norm, at)."""
    asks = F.pmod("id", F.lit(every)) == 0
    first = rows.groupBy("dim").agg(F.max(F.struct("norm", "at", asks.alias("asks"))).alias("top"), F.max(F.when(asks, F.col("norm"))).alias("ask")).collect()
    rest = rows.where(~F.col("at").isin([r.top["at"] for r in first])).groupBy("dim").agg(F.max("norm").alias("norm")).collect()
    second = {r.dim: r.norm for r in rest}
    for r in first:
        other = second.get(r.dim, 0.0) if r.top["asks"] else r.ask
        if other is not None and not (r.top["norm"] < 2**62 and r.top["norm"] * other < 2**62):
            raise ValueError(f"inner products of vectors of length {r.dim} may not fit 64 bits")


def top_k(vectors: DataFrame, k: int = 20, every: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 64, block_rows: int = 16384, query_rows: int = 1024) -> DataFrame:
    """The `k` highest integer inner products for every row whose id is divisible by `every`, among all other rows.

    Components become floor(scale * x); vectors that are null, empty, or hold a null or non-finite component take no part, nor
    do rows with a null id. A query meets only vectors of its own length. Rows are told apart by place, not by id: a repeated
    id is a candidate for its twin, and a repeated query returns its ranks as often as it occurs. Ties go to the smaller id.
    Returns query_id, rank, vec_id, score. Where lengths of vectors that meet do not keep
    their products under 2^62, a ValueError says so.
    """
    x = F.transform(F.col(vec_col), lambda v: F.floor(F.lit(scale) * v.cast("double")))
    scaled = F.transform(F.col(vec_col), lambda v: F.floor(F.lit(scale) * v.cast("double")).cast("double"))
    norm = F.sqrt(F.aggregate(scaled, F.lit(0.0), lambda a, v: a + v * v))
    fine = F.forall(vec_col, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v.cast("double")) < F.lit(float("inf"))))
    rows = vectors.where(F.col(id_col).isNotNull() & F.col(vec_col).isNotNull()).where(F.size(vec_col) > 0).where(F.coalesce(fine, F.lit(False)))
    rows = shared.keep(rows.select(F.col(id_col).cast("long").alias("id"), F.size(vec_col).alias("dim"), x.alias("v"), norm.alias("norm"), F.monotonically_increasing_id().alias("at")), "vectors")
    _check_products(rows, every)
    sizes = {r.dim: (r.n, r.q) for r in rows.groupBy("dim").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.pmod("id", F.lit(every)) == 0).alias("q")).collect()}
    if not any(q for _, q in sizes.values()):
        return rows.select(F.col("id").alias("query_id"), F.lit(1).alias("rank"), F.col("id").alias("vec_id"), F.col("id").alias("score")).where("false")
    # block numbers by place in a hash order: near even, whatever the ids are
    blocks = F.create_map(*[F.lit(y) for d, (n, _) in sizes.items() for y in (d, -(-n // block_rows))])
    q_blocks = F.create_map(*[F.lit(y) for d, (_, q) in sizes.items() for y in (d, max(1, -(-q // query_rows)))])
    of = lambda m: F.pmod(F.xxhash64("at"), F.element_at(m, F.col("dim")).cast("long")).cast("int")
    schema = "side int, dim int, block int, ids binary, ats binary, vs binary"

    def pack(side):
        def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            dim, block = int(key[0].as_py()), int(key[1].as_py())
            table = pa.Table.from_batches(list(batches))
            ids, ats = table["id"].to_numpy(), table["at"].to_numpy()
            v = table["v"].combine_chunks().flatten().to_numpy().astype("<i8")
            yield pa.RecordBatch.from_arrays([pa.array([side], pa.int32()), pa.array([dim], pa.int32()), pa.array([block], pa.int32()), pa.array([ids.tobytes()]), pa.array([ats.tobytes()]), pa.array([v.tobytes()])], ["side", "dim", "block", "ids", "ats", "vs"])

        return run

    data = rows.withColumn("block", of(blocks)).groupBy("dim", "block").applyInArrow(pack(0), schema)
    asks = rows.where(F.pmod("id", F.lit(every)) == 0).withColumn("block", of(q_blocks)).groupBy("dim", "block").applyInArrow(pack(1), schema)
    data = data.select("dim", "block", F.col("ids").alias("c_ids"), F.col("ats").alias("c_ats"), F.col("vs").alias("c_vs"))
    # each block of queries goes to every block of candidates of its length: blocks, not rows, are paired
    asks = asks.select("dim", F.explode(F.sequence(F.lit(0), F.element_at(blocks, F.col("dim")) - 1)).alias("block"), "ids", "ats", "vs")

    def run(batches):
        for batch in batches:
            t = batch.to_pydict()
            for dim, ids, ats, vs, c_ids, c_ats, c_vs in zip(*(t[c] for c in ("dim", "ids", "ats", "vs", "c_ids", "c_ats", "c_vs")), strict=True):
                ids, ats, c_ids, c_ats = (np.frombuffer(b, "<i8") for b in (ids, ats, c_ids, c_ats))
                q, c = (np.frombuffer(b, "<i8").reshape(-1, dim) for b in (vs, c_vs))
                order = np.argsort(c_ats)
                place = np.searchsorted(c_ats[order], ats)
                place = np.minimum(place, len(order) - 1)
                own = np.where(c_ats[order][place] == ats, order[place], -1)
                rows_, cand, score = search_block(q, own, c_ids, c, k)
                yield pa.RecordBatch.from_arrays([pa.array(ids[rows_]), pa.array(ats[rows_]), pa.array(c_ids[cand]), pa.array(c_ats[cand]), pa.array(score)], ["query_id", "at", "vec_id", "c_at", "score"])

    found = asks.join(data.hint("shuffle_hash"), ["dim", "block"]).select("dim", "ids", "ats", "vs", "c_ids", "c_ats", "c_vs").mapInArrow(run, "query_id long, at long, vec_id long, c_at long, score long")
    best = Window.partitionBy("query_id", "at").orderBy(F.desc("score"), "vec_id", "c_at")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
