"""The pipeline's stages against the brute-force versions of its operators."""

import re

import corpus_pipeline
from pairdict.llm import subwords
from tests.conftest import SF

from .conftest import EDGE
from .test_near_copies import slow_left
from .test_rows import LOWER, WORD, slow_lines


def slow_pipeline(docs, items):
    """(id, text) that the first four stages leave."""
    docs = [(i, t) for i, t in docs if t and re.search(r"[^\W\d_]", t)]
    key = lambda x: x.strip(" \t\n\x0b\f\r").translate(LOWER)
    where = {}
    for i, t in docs:
        for x in t.split("\n"):
            where.setdefault(key(x), set()).add(i)
    stays = lambda i, x: i is None or len(key(x)) < 20 or len(where[key(x)] - {None}) < 3 or max(where[key(x)] - {None}) == i
    docs = [(i, "\n".join(x for x in t.split("\n") if stays(i, x))) for i, t in docs]
    named = [x for x in docs if x[0] is not None]
    docs = [*(named[k] for k in slow_left(named)), *(x for x in docs if x[0] is None)]
    windows = set()
    for _, t in items:
        w = WORD.findall(t.translate(LOWER))
        windows |= {tuple(w[k : k + 10]) for k in range(len(w) - 9)}
    out = []
    for i, t in docs:
        spans = [m.span() for m in WORD.finditer(t.translate(LOWER))]
        w = [t[a:b].translate(LOWER) for a, b in spans]
        hit = {x for k in range(len(w) - 9) if tuple(w[k : k + 10]) in windows for x in range(k, k + 10)}
        cut = [(spans[x][0], spans[x + 1][0] if x + 1 in hit else spans[x][1]) for x in sorted(hit)]
        out.append((i, "".join(c for k, c in enumerate(t) if not any(a <= k < b for a, b in cut))))
    return sorted(out, key=repr)


def test_stages_have_an_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "lines", "near_duplicates", "benchmark", "subwords"]
    assert slow_lines([(1, "x")])[0][2] == 0


def test_pipeline(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    got = corpus_pipeline.run(spark, SF).collect()
    voc = subwords.vocabulary()
    texts = sorted({(r.doc_id, subwords.decode(voc, r.ids)) for r in got}, key=repr)
    assert texts == slow_pipeline(rows, items) and all(r.exact for r in got)
    assert len({(r.doc_id, tuple(r.ids)) for r in got}) == len(got)


def test_edges(spark, edge, empty):
    for docs, many in ((edge, True), (empty, False)):
        for name, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, SF)
            if name != "subwords":
                assert docs.columns == list(corpus_pipeline.COLUMNS)
        assert (docs.count() > 0) == many
    left = corpus_pipeline.near_duplicates(spark, edge.select(*corpus_pipeline.COLUMNS), SF).collect()
    assert sum(r.doc_id == 7 for r in left) == 1 and sum(r.doc_id is None for r in left) == sum(i is None for i, _, _ in EDGE)
