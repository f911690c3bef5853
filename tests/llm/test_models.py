"""Language, personal data, top-k, subwords, quality and the language model against brute force and held-out rows."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from pairdict.llm import language, language_model, pii, quality, shared, subwords, topk
from tests.conftest import SF

from .conftest import EDGE, LONG

MID = "/root/testdata/sf0.01"
LOWER = {i: i + 32 for i in range(65, 91)}
crc = lambda i, n: zlib.crc32(str(i).encode()) % n


# --- language -------------------------------------------------------------------------------------------------------------


def slow_phrases(text, learned, block=language.BLOCK):
    n = 0
    for a in range(0, len(text), block):
        part, i = text[a : a + block], 0
        while i < len(part):
            j = i + 1
            while j < len(part) and part[i : j + 1] in learned:
                j += 1
            n, i = n + 1, j
    return n


def test_cross_parse():
    rng = np.random.default_rng(2)
    learned = rng.integers(0, 5, 400).astype(np.uint8)
    model = language.Model({"x": ["ab"]})
    model.table, model.base, model.bits = language.automaton(learned).ravel(), np.array([0], np.int32), np.array([1.0])
    texts = [rng.integers(0, 6, n).astype(np.uint8) for n in (1, 5, 50, 1500, 3000)] + [learned[20:300]]
    offs = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    got = model.phrases(np.concatenate(texts), offs)[0]
    assert got.tolist() == [slow_phrases(t.tobytes(), learned.tobytes()) for t in texts] and got[-1] == 1


def test_language(spark):
    got = language.query(spark, MID).collect()
    true = {r.doc_id: r.lang for r in spark.read.parquet(f"{MID}/documents.parquet").collect()}
    assert len(got) == len(true) and all(r.held_out == (crc(r.doc_id, 4) == 2) and 0 <= r.score <= 1 for r in got)
    out = [r.lang_pred == true[r.doc_id] for r in got if r.held_out]
    assert np.mean(out) >= 0.97


def test_language_edges(edge, empty):
    model = language.train(edge)
    got = {r.doc_id: (r.lang_pred, r.score) for r in language.identify(edge, model).collect()}
    assert got[4] == got[5] == got[10] == ("und", 0.0) and got[8][0] == "en"
    assert language.identify(empty, model).count() == 0
    assert {r.lang_pred for r in language.identify(edge, language.train(empty)).collect()} == {"und"}


# --- personal data --------------------------------------------------------------------------------------------------------


def slow_spans(text):
    text, out = text or "", []
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text):
        out.append((m.start(), 0, m.end()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text):
        if all(int(p) <= 255 for p in m.group().split(".")):
            out.append((m.start(), 1, m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub("[^0-9]", "", m.group())
        if 12 <= len(d) <= 19 and sum(int(c) if k % 2 == 0 else sum(divmod(2 * int(c), 10)) for k, c in enumerate(reversed(d))) % 10 == 0:
            out.append((m.start(), 2, m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15:
            out.append((m.start(), 3, m.end()))
    return sorted(out)


def check_pii(df, docs):
    want = Counter((i, *(sum(s[1] == k for s in b) for k in range(4)), hashlib.sha256(pii.joined(b).encode()).hexdigest()) for i, t in docs for b in [slow_spans(t)])
    got = df.collect()
    assert Counter((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone, pii.digest(r.base) if "base" in r else r.base_sha256) for r in got) == want
    return got


def test_pii(spark):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{MID}/documents.parquet").collect()]
    got = check_pii(pii.query(spark, MID), docs)
    text = dict(docs)
    assert sum(r.n_email + r.n_ip + r.n_card + r.n_phone for r in got) > 50
    for r in got:
        assert set(filter(None, pii.joined(slow_spans(text[r.doc_id])).split(","))) <= set(r.spans.split(","))


def test_pii_edges(spark, edge, empty):
    odd = [(100, "a@b.c_d@e.fg x@@y.z é.a+b@c.de.f 1.2.3.4.5.6.7.8 1.2.3.999 0001.2.3.4 4111 1111 1111 1111-1"), (101, "+49 (30) 1234567 +1+1234567890 +12 " + "1" * 5000 + " a." * 50), (102, "@" * 3000 + "a" * 3000 + "@b.c")]
    odd += [(103, "mail john at example dot com or call (803) 555-5351 today, card 4111-1111-1111-1112")]
    more = spark.createDataFrame(odd, "doc_id long, text string")
    check_pii(pii.detect(edge.select("doc_id", "text").union(more)), [(i, t) for i, t, _ in EDGE] + odd)
    found = pii.detect(more).where("doc_id = 103").first()
    kinds = [s.split(":")[0] for s in found.spans.split(",")]
    assert found.base == "" and "phone" in kinds and "card" not in kinds
    assert pii.detect(empty).count() == 0


@settings(max_examples=150, deadline=None)
@given(st.text("a@.+-_1290 ()é\n", max_size=60))
def test_pii_patterns(text):
    base, every = next(iter(pii.find(pa.array([text]), pii.tagger(60, 10))))
    assert base == slow_spans(text) and set(base) <= set(every)


def test_viterbi():
    model = pii.tagger(60, 10)
    score = np.random.default_rng(1).normal(size=(9, 5)) * 3
    got = model.decode(score, np.array([0, 4]), np.array([4, 5]))
    for a, b in ((0, 4), (4, 9)):
        paths = np.array(np.meshgrid(*[range(5)] * (b - a), indexing="ij")).reshape(b - a, -1)
        value = score[np.arange(a, b)[:, None], paths].sum(0) + model.pairs[paths[:-1], paths[1:]].sum(0)
        assert got[a:b].tolist() == paths[:, value.argmax()].tolist()


# --- top-k ----------------------------------------------------------------------------------------------------------------


def slow_topk(rows, k=20, every=20):
    rows = [(i, np.array([math.floor(64 * x) for x in v])) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for a, (i, q) in enumerate(rows):
        if i % every == 0:
            best = sorted((-int(q @ v), j) for b, (j, v) in enumerate(rows) if b != a and len(v) == len(q))[:k]
            out += [(i, n, j, -s) for n, (s, j) in enumerate(best, 1)]
    return sorted(out)


def test_topk(spark):
    rows = [(r.vec_id, r.embedding) for r in spark.read.parquet(f"{MID}/embeddings.parquet").collect()]
    got = topk.query(spark, MID)
    assert sorted(map(tuple, got.select("query_id", "rank", "vec_id", "score").collect())) == slow_topk(rows)


def test_topk_edges(spark):
    rng = np.random.default_rng(4)
    rows = [(i, [float(x) for x in rng.integers(-3, 4, 6)]) for i in range(300)] + [(0, [1.0] * 6), (20, [2.0, -1.0]), (21, [1.0, 1.0]), (40, None), (60, []), (80, [1.0, None]), (100, [float("nan")] * 6), (120, [float("inf")] * 6), (None, [1.0] * 6)]
    rows += [(1000 + i, [1.0] * 6) for i in range(200)]
    df = spark.createDataFrame([(*r, 1, "x") for r in rows], "vec_id long, embedding array<double>, at int, dim string")
    for block, ask in ((64, 7), (10_000, 1000)):
        got = topk.top_k(df, 20, block_rows=block, query_rows=ask)
        assert sorted(map(tuple, got.select("query_id", "rank", "vec_id", "score").collect())) == slow_topk(rows)
    assert topk.top_k(df.where("vec_id < 0")).count() == 0


# --- subwords -------------------------------------------------------------------------------------------------------------


def segmentations(voc, unit):
    """All segmentations of a unit given in the piece alphabet, with normalised probabilities."""
    score = {voc.raw[i].decode().replace(" ", "▁"): s for i, s in zip(voc.ids, voc.scores, strict=True)}
    out = {}

    def go(i, ends, lp):
        if i == len(unit):
            out[sum(1 << (e - 1) for e in ends)] = lp
        for j in range(i + 1, min(len(unit), i + voc.widest) + 1):
            if unit[i:j] in score:
                go(j, [*ends, j], lp + score[unit[i:j]])

    go(0, [], 0.0)
    z = np.logaddexp.reduce(list(out.values()))
    return {m: lp - z for m, lp in out.items()}


def test_sampling_without_replacement():
    voc = subwords.vocabulary()
    a, b = segmentations(voc, "▁then"), segmentations(voc, "▁an")
    n = 40_000
    sampler = subwords.Sampler(voc, ["then an"] * n, shared.mix(np.arange(n, dtype=np.uint64)))
    found, limit = sampler.best(3)
    paths = [[tuple(f[1][2 * i : 2 * i + 2].tolist()) for i in range(n)] for f in found]
    joint = {(x, y): p + q for x, p in a.items() for y, q in b.items()}
    firsts, seconds = Counter(paths[0]), Counter(paths[1])
    for key, lp in sorted(joint.items(), key=lambda x: -x[1])[:8]:
        p = math.exp(lp)
        assert abs(firsts[key] / n - p) < 5 * math.sqrt(p / n) + 1e-4
        # second draw without replacement: sum over other firsts
        q = sum(math.exp(o) * p / (1 - math.exp(o)) for k, o in joint.items() if k != key)
        assert abs(seconds[key] / n - q) < 5 * math.sqrt(q / n) + 1e-4
    assert all(len({x, y, z}) == 3 for x, y, z in zip(*paths, strict=True))
    for f, path in zip(found, paths, strict=True):
        assert np.allclose(f[2][:200], [joint[k] for k in path[:200]])
    assert (found[0][3] >= found[1][3]).all() and (found[1][3] >= found[2][3]).all() and (found[2][3] >= limit).all()
    # inclusion scores weigh sampled values without bias: the mean of 1 / inclusion over the samples counts the segmentations
    total = sum(np.exp(f[2] - subwords.log_inclusion(f[2], limit)) for f in found)
    assert abs(total.mean() - 1) < 0.05


def test_few_segmentations():
    voc = subwords.vocabulary()
    sampler = subwords.Sampler(voc, ["é", "\U0001f9ea", "", "a"], shared.mix(np.arange(4, dtype=np.uint64)))
    found, limit = sampler.best(30)
    for t, text in ((0, "▁é"), (3, "▁a")):
        masks = [int(f[1][sampler.edge[t]]) for f in found if t in f[0]]
        assert sorted(masks) == sorted(segmentations(voc, text)) and np.isneginf(limit[t])


def test_no_segmentation_is_left_out():
    voc = subwords.vocabulary()
    for text in ("   ab", "a" * 3 + "     "):  # runs of spaces have pieces of their own
        sampler = subwords.Sampler(voc, [text], shared.mix(np.arange(1, dtype=np.uint64)))
        found, limit = sampler.best(400)
        found = [f for f in found if len(f[0])]
        want = segmentations(voc, "▁" + text.replace(" ", "▁"))
        assert len({tuple(sampler.ids(f[1], f[0])[0].tolist()) for f in found}) == len(found) == len(want) < 400 and np.isneginf(limit[0])
        assert np.allclose(sorted(f[2][0] for f in found), sorted(want.values()), atol=2e-3)


@pytest.mark.parametrize("word", ["x" * 150, "internationalization" * 9, "zq" * 16 + "-" * 40])
def test_long_words_are_whole(word):
    """Against plain sums over the word's whole lattice: log probabilities, and how often a piece ends at places that once were cuts."""
    voc, n = subwords.vocabulary(), 1500
    sampler = subwords.Sampler(voc, [word] * n, shared.mix(np.arange(n, dtype=np.uint64)))
    found, limit = sampler.best(2)
    unit = "▁" + word
    score = {voc.raw[i].decode().replace(" ", "▁"): s for i, s in zip(voc.ids, voc.scores, strict=True)}
    by_id = dict(zip(voc.ids.tolist(), voc.scores.tolist(), strict=True))
    pieces = [(i, j) for i in range(len(unit)) for j in range(i + 1, min(len(unit), i + voc.widest) + 1) if unit[i:j] in score]
    upto, back = np.full(len(unit) + 1, -np.inf), np.full(len(unit) + 1, -np.inf)
    upto[0] = back[-1] = 0
    for i, j in pieces:
        upto[j] = np.logaddexp(upto[j], upto[i] + score[unit[i:j]])
    for i, j in sorted(pieces, key=lambda x: -x[1]):
        back[i] = np.logaddexp(back[i], back[j] + score[unit[i:j]])
    paths = []
    for texts, mask, logp, _ in found:
        ids = sampler.ids(mask, texts)
        assert all(subwords.decode(voc, x.tolist()) == word for x in ids[:50])
        assert np.allclose(logp[:200], [sum(map(by_id.get, x.tolist())) - upto[-1] for x in ids[:200]], atol=0.02)
        paths.append([tuple(x.tolist()) for x in ids])
    assert all(x != y for x, y in zip(*paths, strict=True)) and (found[0][3] >= found[1][3]).all() and (found[1][3] >= limit).all()
    for place in (32, 64):
        if place < len(unit):
            p = math.exp(upto[place] + back[place] - upto[-1])
            share = np.mean([place in np.cumsum([len(voc.raw[i].decode()) for i in x]) for x in paths[0]])
            assert abs(share - p) < 5 * math.sqrt(p * (1 - p) / n) + 1e-3


def test_subwords_query(spark):
    import sentencepiece

    got = subwords.query(spark, SF).collect()
    text = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    sp = sentencepiece.SentencePieceProcessor(model_file=subwords.MODEL)
    assert len(got) == 2 * len(text) and all(r.exact for r in got)
    seen = {}
    for r in got:
        assert r.log_inclusion <= 1e-9 and sp.decode(list(r.ids)) == text[r.doc_id]
        assert seen.setdefault(r.doc_id, r.ids) is r.ids or seen[r.doc_id] != r.ids


def test_subwords_edges(spark, edge, empty):
    odd = spark.createDataFrame([(50, "a▁b  c\n\n d\t"), (51, "x" * 500), (52, " lead"), (53, "  "), (54, "")], "doc_id long, text string")
    docs = edge.select("doc_id", "text").union(odd)
    got = subwords.encode(docs, 2)
    assert got.where("not exact").count() == 0
    back = subwords.decode_column(got.withColumnRenamed("text", "was"), keep=["doc_id", "sample", "was"]).collect()
    assert all(r.text == (r.was or "") for r in back)
    assert {tuple(r.ids) for r in got.collect() if r.doc_id in (4, 5)} == {()}
    assert subwords.encode(empty).count() == 0
    plain = lambda df: sorted((str(r.doc_id), r.sample, tuple(r.ids), round(r.log_prob, 6), round(r.perturbed, 6)) for r in df.collect())
    assert plain(got.repartition(5)) == plain(subwords.encode(docs.repartition(3), 2)) == plain(subwords.encode(docs, 2, lean=True))
    with pytest.raises(ValueError):
        subwords.encode(edge, 0)


# --- quality --------------------------------------------------------------------------------------------------------------


def test_quality(spark):
    got = {r.doc_id: r for r in quality.query(spark, MID).collect()}
    marks = [(r.doc_id, r.quality) for r in spark.read.parquet(f"{MID}/labels.parquet").collect()]
    assert len(got) == 1000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) and r.held_out == (crc(i, 5) == 0) for i, r in got.items())
    held = [(got[i].score, y, got[i].predicted) for i, y in marks if got[i].held_out]
    good, bad = ([s for s, y, _ in held if y == k] for k in (1, 0))
    assert np.mean([g > b for g in good for b in bad]) > 0.95 and np.mean([p == y for _, y, p in held]) > 0.93


def test_quality_edges(spark, edge, empty):
    labels = spark.createDataFrame([(1, 1), (2, 0), (3, None), (99, 1), (8, 1), (4, 0), (1, 1)], "doc_id long, quality int")
    model = quality.train(edge, labels)
    got = quality.score(edge, model).collect()
    assert len(got) == len(EDGE) and len({r.score for r in got if r.doc_id in (4, 5)}) == 1 and len({r.score for r in got if r.doc_id == 7}) == 1
    assert quality.score(empty, model).count() == 0
    assert {r.score for r in quality.score(edge, quality.train(empty, labels)).collect()} == {0.5}


# --- language model -------------------------------------------------------------------------------------------------------


def slow_base(docs, train):
    words = lambda t: [*re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER)), None]
    c = Counter(w for (_, t), on in zip(docs, train, strict=True) if on for w in words(t))
    n, v = sum(c.values()), len(c)
    return [(i, len(w), sum(c[x] > 0 for x in w), n, sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w)) for i, t in docs for w in [words(t)]]


def same_base(got, want):
    key = lambda r: (r[0] is None, r[0] or 0, r[1], r[4])
    got = sorted(((r.doc_id, r.n_tokens, r.n_known, r.train_tokens, r.base_score) for r in got), key=key)
    for a, b in zip(got, sorted(want, key=key), strict=True):
        assert a[:4] == b[:4] and math.isclose(a[4], b[4], rel_tol=1e-9)


def test_language_model(spark):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    got = language_model.query(spark, SF)
    rows = got.collect()
    same_base(rows, slow_base(docs, [crc(i, 10) != 0 for i, _ in docs]))
    assert all(r.held_out == (crc(r.doc_id, 10) == 0) for r in rows)
    for held in (True, False):
        p = language_model.perplexity(got.where(F.col("held_out") == held)).first()
        assert 1 < p.perplexity < p.base_perplexity


def test_language_model_edges(spark, edge, empty):
    on = F.col("doc_id") % 3 != 0
    docs = [(i, t) for i, t, _ in EDGE]
    train = [i is not None and i % 3 != 0 for i, _ in docs]
    for head, hot in ((65536, 512), (4, 1), (0, 512)):
        got = language_model.score(edge, on, head=head, hot=hot).collect()
        same_base(got, slow_base(docs, train))
        assert all(math.isfinite(r.score) and r.score < 0 for r in got) and len({round(r.score, 9) for r in got if r.doc_id == 7}) == 1
    assert language_model.score(empty, on).count() == 0
    nothing = language_model.score(edge, F.lit(False)).collect()
    assert all(r.n_known == 0 and math.isfinite(r.score) for r in nothing) and len(nothing) == len(EDGE)


def slow_single(docs, train, strength=5.0, root_strength=50.0):
    """The hierarchical model with one table a dish, from its definition: score of each text, and the next word's probability."""
    words = lambda t: [None, *re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER)), "END "]
    pairs = Counter((u, w) for (_, t), on in zip(docs, train, strict=True) if on for x in [words(t)] for u, w in zip(x, x[1:], strict=False))
    seen = Counter(w for (_, t), on in zip(docs, train, strict=True) if on for w in words(t)[1:])
    discount = lambda c: min(0.95, max(0.1, sum(n == 1 for n in c.values()) / max(1, sum(n == 1 for n in c.values()) + 2 * sum(n == 2 for n in c.values()))))
    d, e, v = discount(pairs), discount(seen), len(seen)
    tables, customers, dish = Counter(), Counter(), Counter()
    for (u, w), c in pairs.items():
        tables[u] += 1
        customers[u] += c
        dish[w] += 1
    n = sum(dish.values())

    def root(w):
        return max(0, dish[w] - e * (dish[w] > 0)) / (root_strength + n) + (root_strength + e * len(dish)) / (root_strength + n) / (v + 1)

    def p(u, w):
        return (pairs[u, w] - d * ((u, w) in pairs)) / (strength + customers[u]) + (strength + d * tables[u]) / (strength + customers[u]) * root(w)

    return [sum(math.log10(p(u, w)) for x in [words(t)] for u, w in zip(x, x[1:], strict=False)) for _, t in docs], p, seen


@pytest.mark.parametrize(("head", "hot"), [(100_000, 10**9), (100_000, 4), (60, 10**9), (0, 10**9)])
def test_single_tables_by_brute_force(spark, head, hot):
    """Frequent and rare words, as contexts and as words, with hot pairs and without: the score is the definition's."""
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    docs += [(9000, None), (9001, ""), (9002, docs[3][1]), (9003, "neverseen " + (docs[5][1] or ""))]
    train = [crc(i, 10) != 0 and i < 9000 for i, _ in docs]
    df = spark.createDataFrame([(*r, on) for r, on in zip(docs, train, strict=True)], "doc_id long, text string, train boolean")
    want, p, seen = slow_single(docs, train)
    for u in (None, next(iter(seen)), "neverseen"):
        assert math.isclose(sum(p(u, w) for w in seen) + p(u, "neverseen"), 1, rel_tol=1e-9)
    got = {r.doc_id: r.score for r in language_model.score(df, F.col("train"), head=head, hot=hot, burn=1, samples=2, seating="single", bucket_tokens=20_000).collect()}
    for (i, _), x in zip(docs, want, strict=True):
        assert math.isclose(got[i], x, rel_tol=2e-6, abs_tol=1e-5)


def test_model_is_a_distribution(spark):
    """Over every known word and one unknown, the next word's sampled probabilities after a context add up to one."""
    rng = np.random.default_rng(8)
    texts = [" ".join(rng.choice(list("abcdef"), 12, p=[0.4, 0.2, 0.1, 0.1, 0.1, 0.1])) for _ in range(60)]
    probe = [" ".join(f"{u} {w}" for w in "abcdef") + f" {u} zz" for u in "abcdef"] + list("abcdef")
    rows = spark.createDataFrame([(i, i < 60, t) for i, t in enumerate(texts + probe)], "ref long, train boolean, text string")
    words = language_model.count_words(rows.where("train"), "text").cache()
    frame = language_model.frame_of(words, 100)
    sc = spark.sparkContext
    kept = language_model.occurrences(rows, sc.broadcast(frame), sc.broadcast(np.zeros(0, np.uint64)), 3).where("bucket >= 0").cache()
    chain = language_model.Chain(kept, frame, 5)
    for k in range(4):
        chain.sweep(k, k > 0)
    total = Counter()
    chain_kept, chain.kept = chain.kept, None
    for r in chain_kept.collect():
        b = language_model.Bucket(bytes(r.pairs))
        for u, x in zip(b.u.tolist(), chain.pair_scores(r.bucket, b)[0], strict=True):
            total[u] += 10**x
    for w in "abcdef":
        assert math.isclose(total[int(frame.word_ids(shared.hash_words([w.encode()]))[0])], 1, rel_tol=1e-9)


def test_seating():
    d, rng = 0.6, np.random.default_rng(0)
    table = language_model.stirling(d, 64)
    # brute force: all seatings of c customers, weighted by the restaurant's rule
    def weights(c):
        state = {(1,): 1.0}
        for m in range(1, c):
            new = Counter()
            for tables, w in state.items():
                for k, size in enumerate(tables):
                    new[tables[:k] + (size + 1,) + tables[k + 1 :]] += w * (size - d)
                new[tables + (1,)] += w
            state = new
        out = Counter()
        for tables, w in state.items():
            out[len(tables)] += w
        return out

    for c in (2, 3, 5):
        w = weights(c)
        assert np.allclose(np.exp(table[c, 1 : c + 1]), [w[t] for t in range(1, c + 1)])
    full = language_model.stirling(d)
    got = language_model.seat(np.full(20_000, 5), np.full(20_000, 3.0), np.full(20_000, 0.4), d, full, rng)
    opened = np.cumprod([(3.0 + d * j) * 0.4 for j in range(5)])  # the t-th table opens at the rate of the restaurant then
    p = np.array([weights(5)[t] * opened[t - 1] for t in range(1, 6)])
    assert np.allclose(np.bincount(got, minlength=6)[1:] / 20_000, p / p.sum(), atol=0.02)
    big = language_model.seat(np.array([10_000, 1, 0]), np.array([20.0, 20.0, 20.0]), np.full(3, 0.1), d, full, rng)
    assert 8 < big[0] < 60 and big[1:].tolist() == [1, 0]


def test_pack():
    arrays = [np.arange(5, dtype=np.uint64), np.zeros(0, np.int64), np.array([1, 300], np.uint16)]
    back = language_model.unpack(language_model.pack(*arrays))
    assert all((a == b).all() and a.dtype == b.dtype for a, b in zip(arrays, back, strict=True))
