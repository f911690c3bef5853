"""All pairs of texts of a given Jaccard similarity of word shingles: those that SimHash finds, then the rest by postings of
prefixes, bounds on length, place and parities; all are held against the texts themselves. `simhash.near_duplicates` uses it
where a similarity, not a radius of bits, is asked for."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from .components import components
from .language_model import least_type, pack, runs, unpack

NO_HOT = (np.zeros(0, np.uint64), np.zeros(0, np.int64))
ROW, POSTING, PAIR, MEMBER = range(4)
SMALL = 16  # a posting list of more texts than this is not joined with itself before the obvious links are known
TURNS = 4  # in all but the last one pair a text is read
BITS = 1 << 26  # of the filter that finds wanted texts: 8 MB however many are wanted


def shingle_sets(text: pa.Array, width: int = 5):
    """For each text the sorted 64-bit hashes of its distinct shingles; a shorter text is one shingle, none without words."""
    for a, b, buf, offs in shared.slices(text):
        start, end = shared.word_spans(buf, offs, shared.SPACED)
        h = shared.word_hashes(buf, start, end)
        edges = np.searchsorted(start, offs).tolist()
        whole = np.zeros(max(0, len(h) - width + 1), np.uint64)
        for q in range(width):
            whole = shared.mix(whole + h[q : q + len(whole)])
        for d in range(b - a):
            i, j = edges[d], edges[d + 1]
            if j - i >= width:
                yield np.unique(whole[i : j - width + 1])
                continue
            x = np.zeros(min(1, j - i), np.uint64)
            for q in range(i, j):
                x = shared.mix(x + h[q])
            yield x


def set_key(s: np.ndarray) -> int:
    """64 bits that stand for a whole set; 0 for the empty one."""
    return int(shared.mix(np.array([s.sum(dtype=np.uint64) + np.uint64(len(s))], np.uint64)).view(np.int64)[0]) if len(s) else 0


def parities(s: np.ndarray) -> bytes:
    """Whether a set has an odd number of members in each hash range, as bits: ranges enough to hold a member each at most, a power
    of two. Two sets differ in at least as many members as bits, of which the longer row is first folded to the shorter one."""
    power = min(16, max(8, len(s).bit_length()))
    return np.packbits((np.bincount((s >> np.uint64(64 - power)).astype(np.int64), minlength=1 << power) & 1).astype(np.uint8)).tobytes()


def folded(rows: np.ndarray, size: int) -> np.ndarray:
    """Rows of parities (bytes) over `size` bytes of coarser ranges."""
    if rows.shape[1] == size:
        return rows
    bits = np.unpackbits(rows, axis=1).reshape(len(rows), size * 8, -1)
    return np.packbits(np.bitwise_xor.reduce(bits, axis=2), axis=1)


def bits_apart(x: list[bytes], y: list[bytes]) -> np.ndarray:
    """Differing bits of each pair of rows."""
    sizes = np.array([(len(a), len(b)) for a, b in zip(x, y, strict=True)], np.int64).reshape(-1, 2)
    out = np.zeros(len(sizes), np.int64)
    for m, n in np.unique(sizes, axis=0).tolist():
        on = np.flatnonzero((sizes[:, 0] == m) & (sizes[:, 1] == n))
        left, right = (np.frombuffer(b"".join([z[k] for k in on.tolist()]), np.uint8).reshape(len(on), -1) for z in (x, y))
        size = min(m, n)
        out[on] = np.bitwise_count(folded(left, size) ^ folded(right, size)).sum(1, dtype=np.int64)
    return out


def prefix(s: np.ndarray, hot: tuple[np.ndarray, np.ndarray], num: int, den: int) -> np.ndarray:
    """First places of a set in one order for all sets, frequent shingles last: sets similar enough share one of these."""
    n = len(s)
    if not n:
        return s
    many = n - -(-num * n // den) + 1
    hashes, counts = hot
    if len(hashes):
        at = np.minimum(np.searchsorted(hashes, s), len(hashes) - 1)
        s = s[np.argsort(np.where(hashes[at] == s, counts[at], 0), kind="stable")]
    return s[:many]


def frequent(docs: DataFrame, rows: int, width: int, sample: int = 4_000, most: int = 1 << 17) -> tuple[np.ndarray, np.ndarray]:
    """Frequent shingles of a bounded sample, and their counts. They only set the order of prefixes: any answer gives the same pairs."""

    def run(batches):
        held = [np.zeros(0, np.uint64)]
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                held.append(np.concatenate([held[0][:0], *shingle_sets(batch.column(0).slice(a, 256), width)]))
        h, c = np.unique(np.concatenate(held), return_counts=True)
        on = np.argsort(-c, kind="stable")[:most]
        on = np.sort(on[c[on] > 2])
        yield pa.RecordBatch.from_arrays([pa.array([h[on].tobytes()]), pa.array([c[on].tobytes()])], ["h", "c"])

    few = docs.select("text").where(F.rand(7) * rows < sample)
    got = few.repartition(1).mapInArrow(shared.tidily(run), "h binary, c binary").collect()  # one task over a sample that does not grow
    return (np.frombuffer(bytes(got[0].h), np.uint64), np.frombuffer(bytes(got[0].c), np.int64)) if got else NO_HOT


def fitting(n: np.ndarray, pos: np.ndarray, x: np.ndarray, y: np.ndarray, num: int, den: int) -> np.ndarray:
    """Whether members x and y of one posting list can be similar enough, by their sets' sizes and the shingle's places."""
    less, more = np.minimum(n[x], n[y]), np.maximum(n[x], n[y])
    left = np.minimum(n[x] - pos[x], n[y] - pos[y])
    return (den * less >= num * more) & ((num + den) * left >= num * (n[x] + n[y]))


def distinct_pairs(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    a, b = np.minimum(x, y), np.maximum(x, y)
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    at = runs(a, b)
    at = at[a[at] != b[at]]
    return a[at], b[at]


def join_cells(cell: np.ndarray, key: np.ndarray, n: np.ndarray, pos: np.ndarray, hot: np.ndarray, num: int, den: int):
    """Postings sorted by cell, n, key, without repeats. Pairs (a, b) that fit, and which postings stand in crowded cells (more
    than SMALL texts, or already marked hot): of these only neighbours and pairs with the cell's first text are made."""
    size = len(cell)
    first = runs(cell)
    many = np.diff(np.append(first, size))
    crowded = (many > SMALL) | (np.add.reduceat(hot.astype(np.int64), first) > 0 if size else np.zeros(0, bool))
    in_crowd = np.repeat(crowded, many)
    begin, stop = np.repeat(first, many), np.repeat(first + many, many)
    here = np.flatnonzero(~in_crowd)
    xs, ys, gap = [], [], 1
    while len(here):
        here = here[here + gap < stop[here]]
        # sizes ascend within a cell: past the longest partner there is none further on
        here = here[den * n[here] >= num * n[here + gap]]
        fit = here[fitting(n, pos, here, here + gap, num, den)]
        xs.append(fit)
        ys.append(fit + gap)
        gap += 1
    crowd = np.flatnonzero(in_crowd & (np.arange(size) > begin))
    for other in (begin[crowd], crowd - 1):
        fit = fitting(n, pos, crowd, other, num, den)
        xs.append(crowd[fit])
        ys.append(other[fit])
    x, y = np.concatenate([*xs, here]), np.concatenate([*ys, here])
    return *distinct_pairs(key[x], key[y]), in_crowd


def sorted_once(*arrays: np.ndarray) -> list[np.ndarray]:
    """Postings (cell, n, key, ...) sorted, each text once in a cell: copies of a text have equal postings."""
    order = np.lexsort((arrays[2], arrays[1], arrays[0]))
    held = [x[order] for x in arrays]
    at = runs(*held[:3])
    return [x[at] for x in held]


def post(held, buckets: int, num: int, den: int, kind: str, width: int, prints, flush: int = 400_000):
    """mapInArrow: for every text its row; its prefix as postings, packed by bucket; what crowded cells of a task hold at once."""

    def table(kinds, **columns):
        size = len(kinds)
        null = lambda t: pa.nulls(size, t)
        cols = {"kind": pa.array(np.asarray(kinds, np.int32)), "id": null(kind), "th": null(pa.int64()), "key": null(pa.int64()), "n": null(pa.int32()), "fp": null(pa.int64()), "parity": null(pa.binary()), "cell": null(pa.int64()), "pos": null(pa.int32()), "payload": null(pa.binary())}
        return pa.RecordBatch.from_pydict(cols | columns)

    def flushed(keys, sizes, firsts):
        many = np.array([len(x) for x in firsts], np.int64)
        h = np.concatenate([np.zeros(0, np.uint64), *firsts])
        pos = (np.arange(len(h)) - np.repeat(np.cumsum(many) - many, many)).astype(np.int32)
        key, n = np.repeat(np.array(keys, np.int64), many), np.repeat(np.array(sizes, np.int32), many)
        cell = ((h % np.uint64(buckets)) << np.uint64(32) | h >> np.uint64(32)).astype(np.int64)
        cell, n, key, pos = sorted_once(cell, n, key, pos)
        size = np.diff(np.append(runs(cell), len(cell)))
        dense = np.flatnonzero(np.repeat(size > SMALL, size))
        goes, hot = np.ones(len(cell), bool), np.zeros(len(cell), np.uint8)
        if len(dense):  # crowded already here: its first text tells the bucket
            a, b, _ = join_cells(cell[dense], key[dense], n[dense].astype(np.int64), pos[dense].astype(np.int64), np.zeros(len(dense)), num, den)
            yield table([PAIR] * len(a), key=pa.array(a), cell=pa.array(b))
            yield table([MEMBER] * len(dense), cell=pa.array(cell[dense]), key=pa.array(key[dense]), n=pa.array(n[dense]), pos=pa.array(pos[dense]))
            goes[dense] = False
            leader = dense[runs(cell[dense])]
            goes[leader], hot[leader] = True, 1
        cell, n, key, pos, hot = (x[goes] for x in (cell, n, key, pos, hot))
        bucket = cell >> 32
        tag = (cell & 0xFFFFFFFF).astype(np.uint32)
        at = runs(bucket)
        payload = [pack(np.diff(tag[x:y], prepend=np.uint32(0)), n[x:y], key[x:y], least_type(pos[x:y]), hot[x:y]) for x, y in zip(at.tolist(), np.append(at, len(bucket))[1:].tolist(), strict=True)]
        yield table([POSTING] * len(at), cell=pa.array(bucket[at]), payload=pa.array(payload, pa.binary()))

    def run(batches):
        keys, sizes, firsts, total = [], [], [], 0
        for batch in batches:
            key, n, odd = [], [], []
            for s in shingle_sets(batch.column(2), width):
                key.append(set_key(s))
                n.append(len(s))
                odd.append(parities(s))
                firsts.append(prefix(s, held.value, num, den))
                total += len(firsts[-1])
            fp = pa.array(prints(batch.column(2), width).view(np.int64))
            yield table([ROW] * len(key), id=batch.column(0), th=batch.column(1), key=pa.array(key, pa.int64()), n=pa.array(n, pa.int32()), fp=fp, parity=pa.array(odd, pa.binary()))
            keys, sizes = keys + key, sizes + n
            if total >= flush:
                yield from flushed(keys, sizes, firsts)
                keys, sizes, firsts, total = [], [], [], 0
        yield from flushed(keys, sizes, firsts)

    return shared.tidily(run)


def meet(num: int, den: int):
    """applyInArrow: one bucket's postings: the pairs that may be similar, and the members of crowded cells."""

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = []
        for batch in batches:
            for raw in batch.column("payload"):
                step, *rest = unpack(raw.as_py())
                tag = np.cumsum(step.astype(np.int64)).astype(np.uint32).astype(np.int64)
                parts.append((tag + (key[0].as_py() << 32), rest[0].astype(np.int64), rest[1], rest[2].astype(np.int64), rest[3]))
        cell, n, name, pos, hot = sorted_once(*(np.concatenate(x) for x in zip(*parts, strict=True)))
        a, b, crowd = join_cells(cell, name, n, pos, hot, num, den)
        none = lambda k: pa.nulls(k, pa.int32())
        names = ["kind", "a", "b", "n", "pos"]
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a), PAIR, np.int32)), pa.array(a), pa.array(b), none(len(a)), none(len(a))], names)
        cell, name, n, pos = (x[crowd] for x in (cell, name, n, pos))
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cell), MEMBER, np.int32)), pa.array(cell), pa.array(name), pa.array(n.astype(np.int32)), pa.array(pos.astype(np.int32))], names)
        del parts, cell, n, name, pos, hot, a, b
        shared.tidy()

    return run


def bounded(pairs: DataFrame, marks: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs a, b whose sets' sizes and parities do not rule the similarity out."""

    def run(batches):
        for batch in batches:
            apart = bits_apart(batch.column(4).to_pylist(), batch.column(5).to_pylist())
            both = batch.column(2).to_numpy().astype(np.int64) + batch.column(3).to_numpy()
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array((num + den) * apart <= (den - num) * both))

    mark = lambda k: marks.select(F.col("key").alias(k), F.col("n").alias(f"{k}_n"), F.col("parity").alias(f"{k}_parity"))
    met = pairs.join(mark("a"), "a").join(mark("b"), "b").select("a", "b", "a_n", "b_n", "a_parity", "b_parity")
    return met.mapInArrow(shared.tidily(run), "a long, b long")


def crowded_pairs(members: DataFrame, roots: DataFrame, marks: DataFrame, num: int, den: int, closest: bool, block: int = 20_000) -> DataFrame:
    """Pairs of crowded cells that no link joins yet (members: cell, key, n, without repeats). Cells whose texts all hang together
    need nothing. In the others, the texts outside the largest part meet each other; and they meet the whole of that part, but
    once for all the cells they share with it, in blocks. closest: they meet the largest part alone, and only the pair with the
    fewest parities apart of each such text counts."""

    def run(_: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        key, root, n = (t.column(c).to_numpy().astype(np.int64) for c in ("key", "root", "n"))
        raw = t.column("parity").to_pylist()
        sizes = np.array([len(x) for x in raw], np.int64)
        probe = t.column("probe").to_numpy().astype(bool)
        base = np.flatnonzero(~probe)
        base = base[np.argsort(n[base], kind="stable")]
        tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for size in np.unique(sizes[base]).tolist():
            mine = base[sizes[base] == size]
            tables[size] = mine, np.frombuffer(b"".join([raw[k] for k in mine.tolist()]), np.uint8).reshape(len(mine), size)
        xs, ys = [key[:0]], [key[:0]]
        for i in np.flatnonzero(probe).tolist():
            own, near, far = np.frombuffer(raw[i], np.uint8)[None, :], key[:0], np.zeros(0)
            for size, (mine, rows) in tables.items():
                lo, hi = np.searchsorted(n[mine] * den, num * n[i]), np.searchsorted(n[mine] * num, den * n[i], "right")
                at = np.arange(lo, hi)[root[mine[lo:hi]] != root[i]]
                if len(at):
                    less = min(size, own.shape[1])
                    apart = np.bitwise_count(folded(rows[at], less) ^ folded(own, less)).sum(1, dtype=np.int64)
                    both = n[mine[at]] + n[i]
                    on = (num + den) * apart <= (den - num) * both
                    near, far = np.append(near, key[mine[at[on]]]), np.append(far, apart[on] / both[on])
            if closest and len(near):
                near = near[far.argmin()][None]
            xs.append(np.full(len(near), key[i]))
            ys.append(near)
        a, b = distinct_pairs(np.concatenate(xs), np.concatenate(ys))
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

    named = members.join(roots.select(F.col("node").alias("key"), "root"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    named = shared.keep(named, "members")
    per = named.groupBy("cell", "root").agg(F.count(F.lit(1)).alias("many"))
    cells = per.groupBy("cell").agg(F.max_by("root", "many").alias("main"), F.count(F.lit(1)).alias("roots")).where("roots > 1")
    apart = shared.keep(named.join(cells, "cell").where("root <> main").select("cell", "main", "key", "root", "n", (F.col("roots") > 2).alias("several")), "apart")
    parts = apart.select(F.col("main").alias("group")).distinct()
    cols = ("group", "own", "key", "root", "n", "probe")
    mark = lambda df, own, probe: df.withColumn("own", F.lit(own)).withColumn("probe", F.lit(probe)).select(*cols)
    few = apart.where("several" if not closest else "false").withColumn("group", F.col("cell"))
    base = mark(few, True, False).union(mark(named.select("key", "root", "n").distinct().join(parts, F.col("root") == F.col("group")), False, False))
    probes = mark(few, True, True).union(mark(apart.select(F.col("main").alias("group"), "key", "root", "n").distinct(), False, True))
    blocks = base.groupBy("group", "own").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    base = base.join(blocks, ["group", "own"]).withColumn("salt", F.pmod(F.xxhash64("key"), "blocks").cast("int"))
    probes = probes.join(blocks, ["group", "own"]).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    both = base.select(*cols, "salt").union(probes.select(*cols, "salt")).join(marks.select("key", "parity"), "key")
    return both.groupBy("group", "own", "salt").applyInArrow(run, "a long, b long").distinct()


def bitmap(hashes: DataFrame) -> np.ndarray:
    """A filter of BITS bits, packed, with the bits of all the hashes (a column th) set."""
    chunk = 1 << 16

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        on = np.zeros(chunk, np.uint8)
        for batch in batches:
            on[batch.column("bit").to_numpy() % chunk] = 1
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([pack(np.packbits(on))], pa.binary())], ["k", "bits"])

    bit = F.pmod("th", F.lit(BITS))
    got = hashes.select(bit.alias("bit")).distinct().withColumn("k", F.floor(F.col("bit") / chunk).cast("int")).groupBy("k").applyInArrow(run, "k int, bits binary").collect()
    out = np.zeros((BITS // chunk, chunk // 8), np.uint8)
    for r in got:
        out[r.k] = unpack(bytes(r.bits))[0]
    return out.ravel()


def parted(rows: DataFrame, hashes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The rows (first column: th) that surely have none of the hashes, and the others; nothing moves."""
    held = rows.sparkSession.sparkContext.broadcast(bitmap(hashes))

    def side(wanted: bool):
        def run(batches):
            for batch in batches:
                bit = batch.column(0).to_numpy() % BITS
                yield batch.filter(pa.array((held.value[bit >> 3] >> (7 - (bit & 7)).astype(np.uint8) & 1).astype(bool) == wanted))

        return rows.mapInArrow(shared.tidily(run), rows.schema)

    return side(False), side(True)


def texts_of(source: DataFrame, rows: DataFrame, pairs: DataFrame) -> DataFrame:
    """(key, text) for every key that stands in the pairs: a filter of fixed size picks the texts, so that others never move."""
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct()
    found = shared.keep(rows.select("key", "th").join(wanted, "key", "left_semi").groupBy("key").agg(F.min("th").alias("th")), "wanted")
    held = source.sparkSession.sparkContext.broadcast(bitmap(found))

    def run(batches):
        for batch in batches:
            th = batch.column(0).to_numpy()
            bit = th % BITS
            on = np.flatnonzero(held.value[bit >> 3] >> (7 - (bit & 7)).astype(np.uint8) & 1)
            on = on[np.unique(th[on], return_index=True)[1]]
            yield batch.take(pa.array(on))

    near = source.select("th", "text").mapInArrow(shared.tidily(run), "th long, text string")
    out = shared.keep(near.join(found, "th").select("key", "text").dropDuplicates(["key"]), "texts")
    held.unpersist()
    shared.forget(found)
    return out


def verified(pairs: DataFrame, texts: DataFrame, width: int, num: int, den: int) -> DataFrame:
    """Pairs a, b whose sets are similar enough."""

    def run(batches):
        for batch in batches:
            fine = []
            for x, y in zip(shingle_sets(batch.column(2), width), shingle_sets(batch.column(3), width), strict=True):
                fine.append((num + den) * len(np.intersect1d(x, y, assume_unique=True)) >= num * (len(x) + len(y)))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(fine, pa.bool_()))

    side = lambda k: texts.select(F.col("key").alias(k), F.col("text").alias(f"{k}_text"))
    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "a_text", "b_text").mapInArrow(shared.tidily(run), "a long, b long")


def fingerprint_pairs(rows: DataFrame, links) -> DataFrame:
    """Pairs a, b of keys (rows: key, fp) whose fingerprints SimHash links: each key with the least of its fingerprint, and these
    along the links. Nothing is decided yet: pairs of keys are still held against the texts."""
    least = shared.keep(rows.groupBy("fp").agg(F.min("key").alias("lead")), "prints")
    same = rows.select("key", "fp").distinct().join(least, "fp").where("key <> lead").select(F.col("lead").alias("a"), F.col("key").alias("b"))
    end = lambda k: least.select(F.col("fp").alias(f"{k}_fp"), F.col("lead").alias(k))
    found = links(least).select(F.col("a").alias("a_fp"), F.col("b").alias("b_fp")).join(end("a"), "a_fp").join(end("b"), "b_fp")
    out = shared.keep(same.union(found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))).where("a <> b").distinct(), "linked")
    shared.forget(least)
    return out


def near_copies(docs: DataFrame, prints, links, width: int = 5, num: int = 4, den: int = 5, id_col: str = "doc_id", text_col: str = "text", bucket_postings: int = 400_000) -> DataFrame:
    """For every row its id, text_hash (xxhash64 of the text), class_key and component_id: the least id that chains of texts of
    similarity num / den or more reach; class_key tells chains apart. prints and links are SimHash's: fingerprints of texts, and links
    between them. They come first; what they join needs no reading afterwards, and postings find what is too far apart in bits.

    Similarity is the Jaccard coefficient of the sets of `width`-word shingles (A-Z lower-cased, 64 bits of hash a shingle). No
    chain is broken: where two sets are similar enough their prefixes meet, and a pair goes unread only where it is ruled out or
    joined by other links. Texts of equal sets are one from there on, those without words too; a null text counts as empty.
    Repeated rows come back as often as they came; null ids never become a component's id.
    """
    spark = docs.sparkSession
    source = docs.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("th"), F.col(text_col).alias("text"))
    total = source.agg(F.count(F.lit(1)).alias("rows"), F.sum(F.octet_length("text")).alias("bytes")).first()
    buckets = max(32, -(-(total.bytes or 0) // 30 // bucket_postings))
    # at most 2^17 hashes and counts: a bound that does not grow with the data
    held = spark.sparkContext.broadcast(frequent(source, max(1, total.rows), width))
    kind = source.schema["id"].dataType
    schema = f"kind int, id {kind.simpleString()}, th long, key long, n int, fp long, parity binary, cell long, pos int, payload binary"
    made = shared.keep(source.mapInArrow(post(held, buckets, num, den, arrow_type(kind), width, prints), schema), "made")
    rows = made.where(F.col("kind") == ROW)
    schema = "kind int, a long, b long, n int, pos int"
    met = shared.keep(made.where(F.col("kind") == POSTING).select("cell", "payload").groupBy("cell").applyInArrow(meet(num, den), schema), "met")
    early = made.where(F.col("kind") == PAIR).select(F.col("key").alias("a"), F.col("cell").alias("b"))
    pairs = shared.keep(met.where(F.col("kind") == PAIR).select("a", "b").union(early).distinct(), "pairs")
    members = met.where(F.col("kind") == MEMBER).select(F.col("a").alias("cell"), F.col("b").alias("key"), "n")
    members = shared.keep(members.union(made.where(F.col("kind") == MEMBER).select("cell", "key", "n")).distinct(), "crowds")
    crowds = not members.isEmpty()
    linked = fingerprint_pairs(rows, links)
    wanted = pairs.union(linked).select(F.explode(F.array("a", "b")).alias("key")).union(members.select("key")).distinct()
    marks = shared.keep(rows.select("key", "n", "parity").join(wanted, "key", "left_semi").dropDuplicates(["key"]), "marks")
    near = shared.keep(bounded(pairs, marks, num, den), "near")
    linked_near = shared.keep(bounded(linked, marks, num, den), "linked_near")

    # first what SimHash links, and one pair a text of the others; then one pair a text at a time: mostly these join all that
    # belongs together, and pairs inside a part need no reading. The last turn has all that is left.
    joined, old, left = None, [members, marks, pairs, linked, linked_near], near
    roots = spark.createDataFrame([], "node long, root long")
    for turn in range(TURNS):
        last = turn == TURNS - 1
        if turn and crowds:
            left = left.union(crowded_pairs(members, roots, marks, num, den, not last)).distinct()
        if turn:
            left = shared.keep(left, "left")
            old.append(left)
            if left.isEmpty():
                continue
        read = left if last else left.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")
        if not turn:
            linked_texts = linked_near.select("b").distinct()
            read = linked_near.union(read.join(linked_texts, "b", "left_anti")).distinct()
        read = read if last else shared.keep(read, "read")
        texts = texts_of(source, rows, read)
        fine = verified(read, texts, width, num, den)
        joined = shared.keep(fine if joined is None else joined.union(fine), "joined")
        roots = shared.keep(components(joined), "roots")
        end = lambda k, roots=roots: roots.select(F.col("node").alias(k), F.col("root").alias(f"{k}_root"))
        apart = F.coalesce("a_root", "a") != F.coalesce("b_root", "b")
        old += [read, texts, joined]
        if not last:
            left = left.join(read, ["a", "b"], "left_anti").join(end("a"), "a", "left").join(end("b"), "b", "left").where(apart).select("a", "b")

    least = rows.groupBy("key").agg(F.min("id").alias("least"))
    named = least.join(roots.select(F.col("node").alias("key"), F.col("root").alias("class_key")), "key", "left").withColumn("class_key", F.coalesce("class_key", "key"))
    named = shared.keep(named, "named")
    ids = named.groupBy("class_key").agg(F.min("least").alias("component_id"))
    named = named.select("key", "class_key").join(ids, "class_key")
    out = shared.keep(rows.select("id", "th", "key").join(named, "key").select(F.col("id").alias(id_col), F.col("th").alias("text_hash"), "class_key", "component_id"), "out")
    shared.forget(made, met, near, roots, named, *old)
    return out


def arrow_type(kind) -> pa.DataType:
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)
