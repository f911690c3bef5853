"""Near copies and the pipeline's stage against brute-force Jaccard similarity."""

import random

import pyarrow as pa
import pytest

import corpus_pipeline
from pairdict.llm import near_copies, simhash
from tests.conftest import SF

from .conftest import EDGE
from .test_rows import LOWER


def shingles(text, width=5):
    w = [x for x in (text or "").translate(LOWER).translate({c: " " for c in range(9, 14)}).split(" ") if x]
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def slow_copies(docs):
    least, named = {}, classes(docs)
    for i, c in named:
        least.setdefault(c, []).extend([i] if i is not None else [])
    return sorted(((i, min(least[c], default=None)) for i, c in named), key=repr)


def found(df):
    return sorted(((r.doc_id, r.component_id) for r in simhash.near_duplicates(df, width=5, similarity=(4, 5)).collect()), key=repr)


def slow_left(docs):
    """Indices of the rows that stay: of each class the least id, of these the least text hash, once."""
    names = {}
    for k, ((i, t), (_, c)) in enumerate(zip(docs, classes(docs), strict=True)):
        names.setdefault(c, []).append((i, xxh(t), k))
    return sorted(min(v)[2] for v in names.values())


def classes(docs):
    sets = [shingles(t) for _, t in docs]
    parent = list(range(len(docs)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, x in enumerate(sets):
        for b, y in enumerate(sets[:a]):
            if 5 * min(len(x), len(y)) >= 4 * max(len(x), len(y)) and 5 * len(x & y) >= 4 * len(x | y):
                parent[find(a)] = find(b)
    return [(i, find(k)) for k, (i, _) in enumerate(docs)]


def xxh(text):
    import xxhash

    return xxhash.xxh64_intdigest((text or "").encode(), 42) - (1 << 64) * (xxhash.xxh64_intdigest((text or "").encode(), 42) >> 63) if text is not None else 42


@pytest.fixture(scope="module")
def edited():
    """Texts and copies with words replaced: similarities from 0.6 to 0.95, many in 0.8 to 0.9."""
    rng, docs = random.Random(5), []
    for k in range(30):
        words = [f"w{rng.randrange(4000)}" for _ in range(rng.choice([9, 60, 200]))]
        docs.append((2 * k, " ".join(words)))
        for j in rng.sample(range(len(words)), max(1, len(words) * rng.randrange(1, 6) // 200)):
            words[j] = "changed"
        docs.append((2 * k + 1, " ".join(words).upper()))
    return docs


def test_edited(spark, edited):
    df = spark.createDataFrame(edited, "doc_id long, text string")
    want = slow_copies(edited)
    assert 5 < sum(i != c for i, c in want) < 30
    assert found(df) == want


def test_stage(spark, edited):
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in edited], "doc_id long, text string, lang string, source string, n_chars long")
    left = sorted(r.doc_id for r in corpus_pipeline.near_duplicates(spark, df, SF).collect())
    assert left == sorted(i for i, c in slow_copies(edited) if i == c)


def stage_rows(spark, docs):
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in docs], "doc_id long, text string, lang string, source string, n_chars long")
    return sorted((r.doc_id, r.text) for r in corpus_pipeline.near_duplicates(spark, df, SF).collect())


def test_stage_keeps_unlike_texts_of_one_id(spark, edited):
    docs = [*edited, (0, "quite another text that bears an id that is taken"), (4, edited[0][1]), (2, edited[3][1] + " tail"), edited[6], edited[6]]
    assert stage_rows(spark, docs) == sorted(docs[k] for k in slow_left(docs))


def test_fingerprints_come_first(spark, edited, monkeypatch):
    """The stage links by SimHash: pairs of fingerprints near in bits, each text's fingerprint being that of its five-word shingles."""
    seen, made = [], simhash.links

    def links(distinct, radius=4, groups=6):
        out = made(distinct, radius, groups)
        seen.append(([r.fp for r in distinct.collect()], [(r.a, r.b) for r in out.collect()]))
        return out

    monkeypatch.setattr(simhash, "links", links)
    left = stage_rows(spark, edited)
    assert left == sorted(edited[k] for k in slow_left(edited))
    ((prints, pairs),) = seen
    want = simhash.fingerprints(pa.array([t for _, t in edited]), 5).view("int64").tolist()
    assert set(prints) == set(want) and pairs
    assert all(((a ^ b) & (1 << 64) - 1).bit_count() <= 4 for a, b in pairs)
    rows = spark.createDataFrame([(k, f) for k, f in enumerate(want)], "key long, fp long")
    found = {(r.a, r.b) for r in near_copies.fingerprint_pairs(rows, made).collect()}
    assert found and all(((want[a] ^ want[b]) & (1 << 64) - 1).bit_count() <= 4 for a, b in found)


def test_crowded_cells(spark):
    """A large group of near copies, two groups that share most of their text, and texts that share one long passage only."""
    rng = random.Random(9)
    words = [f"g{k}" for k in range(120)]
    docs = []
    for k in range(150):
        copy = list(words)
        copy[rng.randrange(120)] = f"own{k}"
        docs.append((k, " ".join(copy)))
    other = [*words[:70], *(f"o{k}" for k in range(40))]  # its copies share up to two thirds of the first group's shingles
    for k in range(60):
        copy = list(other)
        copy[100 + rng.randrange(10)] = f"mine{k}"
        docs.append((1000 + k, " ".join(copy)))
    for k in range(40):
        docs.append((2000 + k, " ".join([*words[:60], *(f"x{rng.randrange(10**6)}" for _ in range(rng.choice([3, 8, 12, 14, 30])))])))
    docs += [(3000 + k, " ".join(words[:20 + k % 3])) for k in range(30)]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(5)
    want = slow_copies(docs)
    assert len({c for _, c in want}) > 20
    assert found(df) == want
    assert stage_rows(spark, docs) == sorted(docs[k] for k in slow_left(docs))


def test_tables_and_edges(spark, sf, edge, empty):
    df = spark.read.parquet(f"{SF}/documents.parquet")
    assert found(df) == slow_copies([(r.doc_id, r.text) for r in df.collect()])
    assert found(edge) == slow_copies([(i, t) for i, t, _ in EDGE])
    assert found(empty) == []
