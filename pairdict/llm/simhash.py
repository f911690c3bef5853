"""SimHash near-duplicates: fingerprints, a popcount embedding, a grid range-join and exact verification."""

from __future__ import annotations

from functools import partial
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared
from .components import components
from .near_copies import near_copies

SEGMENTS = 32  # of two bits each
SEED = 42


def fingerprints(text: pa.Array, width: int = 4) -> np.ndarray:
    """64-bit SimHash of each text over its `width`-word shingles, repeats included; 0 where there are no words."""
    out = []
    for a, b, buf, offs in shared.slices(text):
        start, end = shared.word_spans(buf, offs, shared.SPACED)
        # the words of each text, joined by single spaces, as one run of bytes
        size = end - start
        put = np.cumsum(size + 1) - size - 1
        joined = np.full(int((size + 1).sum()), 32, np.uint8)
        within = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
        joined[np.repeat(put, size) + within] = shared.LOWER[buf[np.repeat(start, size) + within]]
        view, hash_ = memoryview(joined), xxhash.xxh64_intdigest
        edges = np.searchsorted(start, offs)
        for d in range(b - a):
            i, j = edges[d], edges[d + 1]
            if i == j:
                out.append(0)
                continue
            k = max(1, j - i - width + 1)
            begins, ends = put[i : i + k].tolist(), (put + size)[j - k : j].tolist()
            h = np.array([hash_(view[x:y], SEED) for x, y in zip(begins, ends, strict=True)], np.uint64)
            counts = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
            out.append(int.from_bytes(np.packbits(counts * 2 > k, bitorder="little").tobytes(), "little"))
    return np.array(out, np.uint64)


def popcounts(fp: np.ndarray) -> np.ndarray:
    """The embedding, packed: the number of set bits of each two-bit segment, two bits each. In place of 32 columns one word."""
    odd = np.uint64(0x5555555555555555)
    return (fp & odd) + ((fp >> np.uint64(1)) & odd)


def manhattan(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Manhattan distance of packed embeddings: at most the Hamming distance of the fingerprints."""
    # coordinates in unary (0, 1, 2 -> 00, 01, 11): then the distance is a popcount
    odd = np.uint64(0x5555555555555555)
    unary = lambda x: ((x >> np.uint64(1)) & odd) | (((x & odd) | ((x >> np.uint64(1)) & odd)) << np.uint64(1))
    return np.bitwise_count(unary(p) ^ unary(q))


def cell_masks(radius: int, groups: int) -> list[tuple[int, np.uint64]]:
    """Grid cells: the segments are dealt into `groups`; within `radius` at least groups - radius of them agree wholly."""
    parts = np.array_split(np.arange(SEGMENTS), groups)
    masks = []
    for k, chosen in enumerate(combinations(range(groups), groups - radius)):
        masks.append((k, np.uint64(sum(3 << (2 * int(s)) for g in chosen for s in parts[g]))))
    return masks


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        up = parent[parent]
        if (up == parent).all():
            return parent
        parent = up


def _hook(n: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Least index of the component of each of n nodes."""
    parent = np.arange(n)
    while len(x):
        a, b = parent[x], parent[y]
        open_ = a != b
        x, y, a, b = x[open_], y[open_], a[open_], b[open_]
        if not len(x):
            break
        np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
        parent = _roots(parent)
    return parent


def link_cells(cell: np.ndarray, fp: np.ndarray, radius: int = 4, small: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """Links (fp, least fp of its part) inside equal cells, which lie next to each other.

    Every pair of a cell is held against the Manhattan bound and then the exact distance, but for pairs already known to be
    joined; only one link for each fingerprint is returned.
    """
    emb, n = popcounts(fp), len(fp)
    first = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]])) if n else np.zeros(0, np.int64)
    size = np.diff(np.append(first, n))
    left = np.repeat(np.where(size <= small, first + size, 0), size)  # end of the cell, for members of small cells
    xs, ys = [], []
    here = np.flatnonzero(left - np.arange(n) > 1)
    for gap in range(1, small):
        here = here[left[here] - here > gap]
        if not len(here):
            break
        near = here[manhattan(emb[here], emb[here + gap]) <= radius]
        near = near[np.bitwise_count(fp[near] ^ fp[near + gap]) <= radius]
        xs.append(near)
        ys.append(near + gap)
    for a, k in zip(first[size > small].tolist(), size[size > small].tolist(), strict=True):
        rest = np.arange(a, a + k)
        while len(rest) > 1:  # one part of the cell after another, from any of its members
            front, rest = [rest[0]], rest[1:]
            while front and len(rest):
                at = front.pop()
                near = manhattan(emb[at : at + 1], emb[rest]) <= radius
                near[near] = np.bitwise_count(fp[at] ^ fp[rest[near]]) <= radius
                if near.any():
                    hit = rest[near]
                    xs.append(np.full(len(hit), at))
                    ys.append(hit)
                    front.extend(hit.tolist())
                    rest = rest[~near]
    if not xs:
        return fp[:0], fp[:0]
    x, y = np.concatenate(xs), np.concatenate(ys)
    root = _hook(n, x, y)
    on = np.flatnonzero(root != np.arange(n))
    return fp[on], fp[root[on]]


def add_fingerprints(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and fp (the 64 bits as a long)."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"))

    def run(batches):
        for batch in batches:
            fp = fingerprints(batch.column(1), width).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp)], ["id", "fp"])

    kind = rows.schema["id"].dataType.simpleString()
    return rows.mapInArrow(run, f"id {kind}, fp long")


def links(distinct: DataFrame, radius: int = 4, groups: int = 6) -> DataFrame:
    """Links a, b between distinct fingerprints (a column fp) that differ in at most `radius` bits: enough of them to connect
    whatever is connected. Cells meet in hash partitions; a cell's links are a forest, never all its pairs."""
    if not radius < groups <= SEGMENTS:
        raise ValueError("groups must exceed radius")
    masks = cell_masks(radius, groups)

    def cells(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy().view(np.uint64)
            emb = popcounts(fp)
            for k, mask in masks:
                key = shared.mix((emb & mask) + np.uint64(k * 0xD1B54A32D192ED03 % 2**64))
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), batch.column(0)], ["cell", "fp"])

    def join(batches):
        held, kept = [], 0
        cell, fp = np.zeros(0, np.int64), np.zeros(0, np.uint64)
        for batch in batches:  # sorted by cell: what ends a batch may go on in the next
            cell = np.concatenate([cell, batch.column(0).to_numpy()])
            fp = np.concatenate([fp, batch.column(1).to_numpy().view(np.uint64)])
            if len(cell) < 500_000:
                continue
            cut = int(np.searchsorted(cell, cell[-1]))
            if cut:
                yield link_cells(cell[:cut], fp[:cut], radius)
                cell, fp = cell[cut:], fp[cut:]
        if len(cell):
            yield link_cells(cell, fp, radius)

    def as_batches(batches):
        for a, b in join(batches):
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    placed = distinct.select("fp").mapInArrow(cells, "cell long, fp long")
    return placed.repartition("cell").sortWithinPartitions("cell").mapInArrow(as_batches, "a long, b long")


def near_duplicates(
    docs: DataFrame, radius: int = 4, width: int = 4, groups: int = 6, similarity: tuple[int, int] | None = None, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """id, fp and component_id for every row: the least id that chains of fingerprints at most `radius` bits apart reach.

    Equal fingerprints meet first, so copies of a text are one fingerprint from there on. Null and empty texts have the
    fingerprint 0, linked like any other. Repeated rows come back as often as they came; null ids never become a component's id.

    With a similarity (num, den) links are the pairs whose shingle sets have a Jaccard coefficient of num / den or more. Fingerprints
    find candidates, linked as above, and the texts decide. No radius of 64 bits finds all: at 0.8 two texts differ in 10 bits
    on average and in 20 at times, as unrelated ones may. So postings find the rest (`near_copies`, which tells the columns).
    """
    if similarity:
        return near_copies(docs, fingerprints, partial(links, radius=radius, groups=groups), width, *similarity, id_col=id_col, text_col=text_col)
    rows = shared.keep(add_fingerprints(docs, width, id_col, text_col), "fingerprints")
    distinct = shared.keep(rows.groupBy("fp").agg(F.min("id").alias("least")), "distinct")
    roots = shared.keep(components(links(distinct, radius, groups)), "roots")
    named = distinct.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    ids = named.groupBy("root").agg(F.min("least").alias("component_id"))
    named = named.select("fp", "root").join(ids, "root").select("fp", "component_id")
    return rows.join(named, "fp").select(F.col("id").alias(id_col), "fp", "component_id")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_duplicates(shared.documents(spark, sf_dir))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
