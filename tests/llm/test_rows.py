"""Sharding, line dedup, near-duplicates and decontamination against brute force."""

import hashlib
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
import xxhash
from tests.conftest import SF
from hypothesis import given, settings
from hypothesis import strategies as st

from pairdict.llm import decontaminate, line_dedup, sharding, simhash
from pairdict.llm.components import components

from .conftest import EDGE, rows_of

LOWER = {i: i + 32 for i in range(65, 91)}


def docs_of(spark, sf=SF):
    return [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]


def slow_jump(key, n):
    b, j, key = -1, 0, key % 2**64
    while j < n:
        b = j
        key = (key * 2862933555777941757 + 1) % 2**64
        j = int((b + 1) * (2**31 / ((key >> 33) + 1)))
    return b


def test_jump():
    keys = np.random.default_rng(1).integers(-(2**62), 2**62, 500)
    for n in (1, 2, 16, 17):
        assert sharding.jump(keys, n).tolist() == [slow_jump(int(k), n) for k in keys]
    a, b = sharding.jump(keys, 16), sharding.jump(keys, 17)
    assert ((a == b) | (b == 16)).all() and (b == 16).any()


def test_sharding(spark, sf, edge, empty):
    got = sharding.query(spark, sf).collect()
    assert sorted(r.doc_id for r in got) == sorted(i for i, _ in docs_of(spark))
    text = dict(docs_of(spark))
    slots = defaultdict(list)
    for r in got:
        key = int(hashlib.md5(str(r.doc_id).encode()).hexdigest()[:15], 16)
        assert r.shard == slow_jump(key, 16) and r.grown_shard == slow_jump(key, 17)
        assert r["size"] == len(text[r.doc_id].encode()) + 1 and r.text_crc32 == zlib.crc32(text[r.doc_id].encode())
        slots[r.shard].append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    odd = sharding.assign(edge, 3).collect()
    assert len(odd) == len(EDGE) and {r["size"] for r in odd if r.doc_id == 4} == {1}
    assert sharding.assign(empty).count() == 0


def slow_lines(docs, least=20, n=3):
    keyed = lambda t: [(x, x.strip(" \t\n\x0b\f\r").translate(LOWER)) for x in (t or "").split("\n")]
    where = defaultdict(set)
    for i, t in docs:
        for _, k in keyed(t):
            if i is not None and len(k) >= least:
                where[k].add(i)
    out = []
    for i, t in docs:
        lines = keyed(t)
        left = [x for x, k in lines if i is None or len(k) < least or len(where[k]) < n or max(where[k]) == i]
        out.append((i, len(lines), len(lines) - len(left), hashlib.sha256("\n".join(left).encode()).hexdigest()))
    return sorted(out, key=repr)


def test_line_dedup(spark, sf, edge, empty):
    assert rows_of(line_dedup.query(spark, sf), "doc_id", "n_lines", "n_dropped", "kept_sha256") == slow_lines(docs_of(spark))
    got = line_dedup.dedup_lines(edge, extra=["fp", "size"])
    want = slow_lines([(i, t) for i, t, _ in EDGE])
    assert sorted(((r.doc_id, r.n_lines, r.n_dropped, hashlib.sha256(r.text.encode()).hexdigest()) for r in got.collect()), key=repr) == want
    assert line_dedup.dedup_lines(empty).count() == 0


def slow_fp(text, width=4):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + width]).encode(), 42) for i in range(max(1, len(words) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(docs, radius=4):
    fps = {}
    for i, t in docs:
        fps.setdefault(slow_fp(t), []).append(i)
    nodes, parent = list(fps), {f: f for f in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(nodes)):
        for b in range(a):
            if (nodes[a] ^ nodes[b]).bit_count() <= radius:
                parent[find(nodes[a])] = find(nodes[b])
    least = {}
    for f, ids in fps.items():
        least.setdefault(find(f), []).extend(i for i in ids if i is not None)
    return sorted(((i, f"{f:016x}", min(least[find(f)], default=None)) for f, ids in fps.items() for i in ids), key=repr)


@pytest.mark.parametrize("sf_dir", [SF, "/root/testdata/sf0.01"])
def test_simhash(spark, sf_dir):
    assert rows_of(simhash.query(spark, sf_dir), "doc_id", "fingerprint", "component_id") == slow_components(docs_of(spark, sf_dir))


def test_simhash_edges(spark, edge, empty):
    got = simhash.near_duplicates(edge)
    assert sorted(((r.doc_id, f"{r.fp % 2**64:016x}", r.component_id) for r in got.collect()), key=repr) == slow_components([(i, t) for i, t, _ in EDGE])
    assert simhash.near_duplicates(empty).count() == 0


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1), min_size=2, max_size=20), st.integers(0, 2**32))
def test_bound_and_cells(fps, seed):
    rng = np.random.default_rng(seed)
    near = [f ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 7), replace=False)) for f in fps]
    x, y = np.array(fps, np.uint64), np.array(near, np.uint64)
    px, py = simhash.popcounts(x), simhash.popcounts(y)
    exact = np.bitwise_count(x ^ y)
    assert (simhash.manhattan(px, py) <= exact).all()
    slow = [sum(abs((a >> 2 * s & 3).bit_count() - (b >> 2 * s & 3).bit_count()) for s in range(32)) for a, b in zip(fps, near, strict=True)]
    assert simhash.manhattan(px, py).tolist() == slow
    meet = np.zeros(len(x), bool)
    for _, mask in simhash.cell_masks(4, 6):
        meet |= (px & mask) == (py & mask)
    assert meet[exact <= 4].all()


def test_big_cell_equals_small():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 40, dtype=np.uint64)
    fp = np.unique(np.concatenate([base ^ np.uint64(1 << int(b)) ^ np.uint64(1 << int(c)) for b, c in rng.integers(0, 64, (12, 2))]))
    cell = np.zeros(len(fp), np.int64)
    part = lambda small: sorted(zip(*[v.tolist() for v in simhash.link_cells(cell, fp, 4, small)], strict=True))
    assert part(10_000) == part(8) != []


def test_components(spark):
    chain = [(i, i + 1) for i in range(60)] + [(100, 5), (200, 201), (7, 7), (201, 202), (200, 202), (201, 200)]
    got = dict(map(tuple, components(spark.createDataFrame(chain, "a long, b long")).collect()))
    assert all(got[i] == 0 for i in range(61)) and got[100] == 0 and {got[i] for i in (200, 201, 202)} == {200}


def test_fm_index():
    rng = np.random.default_rng(5)
    for sigma, n in ((4, 300), (40, 2000), (3, 1)):
        text = np.append(rng.integers(1, sigma, n), 0)
        text[n // 2 : n // 2 + n // 4] = text[: n // 4]
        index = decontaminate.FMIndex(text, sigma)
        assert decontaminate.suffix_array(text).tolist() == sorted(range(len(text)), key=lambda i: text[i:].tolist())
        for m in (1, 2, 5):
            if m > n:
                continue
            pats = np.array([text[i : i + m] for i in rng.integers(0, n - m + 1, 20)] + [rng.integers(1, sigma, m)])
            low, high = index.search(pats)
            for p, a, b in zip(pats, low, high, strict=True):
                assert sorted(index.locate(np.arange(a, b)).tolist()) == [i for i in range(n - m + 1) if (text[i : i + m] == p).all()]


WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def slow_hits(docs, items, width=10):
    words = lambda t: WORD.findall((t or "").translate(LOWER))
    windows = defaultdict(set)
    for name, t in items:
        w = words(t)
        for i in range(max(1, len(w) - width + 1) if w else 0):
            windows[tuple(w[i : i + width])].add(str(name))
    sizes = {len(k) for k in windows}
    out = []
    for i, t in docs:
        w, hit, names = words(t), set(), set()
        for m in sizes:
            for a in range(len(w) - m + 1):
                if (k := tuple(w[a : a + m])) in windows:
                    hit.update(range(a, a + m))
                    names |= windows[k]
        out.append((i, len(w), len(hit), len(names), decontaminate.digest(names), bool(hit)))
    return sorted(out, key=repr)


COLS = ("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


@pytest.mark.parametrize("sf_dir", [SF, "/root/testdata/sf0.01"])
def test_decontaminate(spark, sf_dir):
    items = [tuple(r) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text").collect()]
    want = slow_hits(docs_of(spark, sf_dir), items)
    assert any(r[5] for r in want) and rows_of(decontaminate.query(spark, sf_dir), *COLS) == want


def test_decontaminate_edges(spark, edge, empty):
    items = [(1, "the same text twice word by word by word and more"), (2, "ipsum"), (3, None), (4, "..."), (5, "IPSUM dolor"), (2, "zwei"), (6, "twice, word by")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.scan(edge, bench, extra=["fp"], block_bytes=20)
    mine = sorted(((r.doc_id, r.n_words, r.n_hit, len(r["items"]), decontaminate.digest(r["items"]), r.n_hit > 0) for r in got.collect()), key=repr)
    assert mine == slow_hits([(i, t) for i, t, _ in EDGE], items)
    left = {r.doc_id: r.text for r in got.collect()}
    assert left[7] == "the same text  word by word" and left[4] is None and left[6] == "Größe ÄÖÜ élan\r\n"
    assert decontaminate.scan(empty, bench).count() == 0
    assert decontaminate.scan(edge, bench.where("item_id = 3")).where("n_hit > 0").count() == 0
