"""Worked cases, invariants and Spark behaviour of the dictionary codec."""

import hashlib
import math

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from pairdict import codec, measures, plans
from pairdict.baselines import blocks, bpe, light
from pairdict.baselines.symtab import SymbolTable, build
from pairdict.codec.bitpack import pack_bits, unpack_bits
from pairdict.codec.store import CompressedStore, rewrite_equality, uniform_keys
from pairdict.corpora import load
from pairdict.dictionary import Dictionary, fixed_dictionary, single_bytes
from pairdict.match import DynamicMatcher, StaticIndex, VectorIndex
from pairdict.match.words import is_prefix_words, pack8, shared_prefix_len, shared_prefix_words
from pairdict.sampling import SampleSpec
from pairdict.training import adaptive_threshold, train, train_by
from pairdict.training.kernel import Trainer, learn

# Entries of the worked search example, by number.
EXAMPLE = {1499: b"compression algo", 944: b"compress files", 2245: b"compressor", 1782: b"database schema", 2078: b"database table", 459: b"data", 723: b"hello", 312: b"to"}
# Input, number and length that the search must give.
FOUND = [("compression algorithms", 1499, 16), ("compress files now", 944, 14), ("compressor", 2245, 10), ("compressed", 99, 1), ("compress", 99, 1), ("database schema", 1782, 15), ("database tables", 2078, 14), ("database sch", 459, 4), ("databases", 459, 4), ("hello world", 723, 5), ("tomorrow", 312, 2)]


def example() -> Dictionary:
    entries = single_bytes() + [bytes([255, 255, i // 256, i % 256, 254, 253]) for i in range(256, 2246)]
    for k, v in EXAMPLE.items():
        entries[k] = v
    return Dictionary(entries, bits=12)


def brute(entries, text):
    by = {e: i for i, e in enumerate(entries)}
    longest, out, at = max(map(len, entries)), [], 0
    while at < len(text):
        n = next(n for n in range(min(longest, len(text) - at), 0, -1) if text[at : at + n] in by)
        out.append(by[text[at : at + n]])
        at += n
    return out


def test_search_example():
    d = example()
    dynamic, static, two = DynamicMatcher(d.entries), StaticIndex.build(d), StaticIndex.build(d, inline=2)
    for text, number, n in FOUND:
        raw = text.encode()
        assert dynamic.match(raw) == static.match(raw) == two.match(raw) == (number, n)
        got, size = VectorIndex(d).match_all(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
        assert (got[0], size[0]) == (number, n)
    assert len(two.overflow) == 1 and two.overflow[0] == (b"or", 2245) and not static.overflow


def test_promotion():
    t = Trainer(1024, 10, 16, 128)
    t.entries += [b"abra", b"cad"]
    t.matcher.insert(b"abra", 256)
    t.matcher.insert(b"cad", 257)
    t.lefts += [None, None]
    t.rights += [None, None]
    t.counts[256 << 21 | 257] = 8
    t.feed(b"abracad")
    assert len(t.entries) == 258 and t.counts[256 << 21 | 257] == 9
    t.feed(b"abracadabra")
    assert t.entries[258] == b"abracad" and t.counts[258 << 21 | 256] == 1 and (256 << 21 | 257) not in t.counts


def test_thresholds():
    # Size in MiB and threshold.
    for size, want in ((0.03, 2), (1, 2), (4, 2), (7.99, 2), (8, 3), (48.99, 5), (113.06, 6), (220.59, 7), (498.10, 8), (1846.17, 10), (95_367_432, 26), (0, 2)):
        assert adaptive_threshold(size) == want
    with pytest.raises(ValueError):
        Trainer(512, 1, None, None)


def test_gain_and_ratio(spark):
    # Length, frequency, gain.
    cases = [(1, 10, -11), (2, 1000, -2), (3, 3, 0), (3, 4, 1), (16, 1, -2), (16, 2, 12), (5, 0, -5)]
    dic = spark.createDataFrame([(i, bytearray(n), n) for i, (n, _, _) in enumerate(cases)], "token_id int, entry binary, entry_len int")
    freq = spark.createDataFrame([(i, f) for i, (_, f, _) in enumerate(cases) if f], "token_id int, f long")
    assert [r.gain for r in sorted(measures.token_gain(freq, dic).collect())] == [g for _, _, g in cases]
    # Published rows of the size sweep (MiB, bits, mean length, dictionary MiB, ratio).
    for mib, bits, length, size, want in ((220.59, 16, 5.41, 0.727, 2.682), (220.59, 21, 10.52, 38.05, 2.370)):
        assert abs(mib / (mib * bits / 8 / length + size) - want) < 0.002


words = st.lists(st.sampled_from([b"customer_", b"order", b"\x00", b"a", b"ab", b"the quick ", "é".encode(), b"http://www.", b"zzzz", b"\x00\x00"]), max_size=12).map(b"".join)


@settings(max_examples=60, deadline=None)
@given(st.lists(words, min_size=1, max_size=25), st.sampled_from([(16, 128), (None, None), (16, 2), (40, 1)]), st.integers(2, 4))
def test_invariants(texts, caps, threshold):
    t = learn(texts * 3, capacity=400, threshold=threshold, max_len=caps[0], max_bucket=caps[1])
    e = t.entries
    assert e[:256] == single_bytes() and len(set(e)) == len(e) <= 400
    assert all(e[i] == e[a] + e[b] and a < i and b < i for i, (a, b) in enumerate(zip(t.lefts, t.rights, strict=True)) if i >= 256)
    assert caps[0] is None or max(map(len, e)) <= caps[0]
    assert caps[1] is None or all(len(b) <= caps[1] for b in t.matcher.long.values())
    d = Dictionary(e, t.lefts, t.rights, bits=9)
    column = pa.array(texts, pa.binary())
    ids, count, null = codec.encode_column(column, d)
    want = [brute(e, x) for x in texts]
    assert ids.tolist() == [i for w in want for i in w] and count.tolist() == [len(w) for w in want] and not null.any()
    m = DynamicMatcher(e)
    assert [m.parse(x) for x in texts] == want
    if max(map(len, e)) <= 16:
        assert [StaticIndex.build(d, 1).parse(x) for x in texts] == want
    table = codec.DecodeTable(d)
    assert table.expand(ids.astype(np.int64))[0].tobytes() == b"".join(texts)
    raw = sum(map(len, texts))
    f = np.bincount(ids, minlength=len(e))
    gain = sum((len(x) - 2) * int(n) - len(x) for x, n in zip(e, f, strict=True))
    assert gain == raw - 2 * len(ids) - sum(map(len, e))
    packed = d.pack()
    assert [packed.entry_at(i) for i in range(len(e))] == e and (np.diff(packed.offsets) > 0).all()
    assert unpack_bits(pack_bits(ids, 9), 9, len(ids)).tolist() == ids.tolist()


@settings(max_examples=40, deadline=None)
@given(st.binary(max_size=8), st.binary(max_size=8))
def test_words(a, b):
    x, y = (np.array([int.from_bytes(v.ljust(8, b"\0"), "little")], np.uint64) for v in (a, b))
    pa_, pb = a.ljust(8, b"\0"), b.ljust(8, b"\0")
    assert shared_prefix_words(x, y)[0] == next((i for i in range(8) if pa_[i] != pb[i]), 8)
    assert is_prefix_words(x, np.array([len(a)]), y, np.array([len(b)]))[0] == a.startswith(b)


def test_word_columns(spark):
    rows = [(b"ion algo", b"ion algo", 8), (b"ion algo", b"ion", 3), (b"o", b"o\0", 8), (b"x", b"y", 0), (b"abcdefg\x80", b"abcdefg\0", 7), (b"", b"\0", 8)]
    df = spark.createDataFrame([(bytearray(a), bytearray(b), n) for a, b, n in rows], "a binary, b binary, n int")
    assert df.where(shared_prefix_len(pack8(F.col("a")), pack8(F.col("b"))) != F.col("n")).count() == 0


def test_full_bucket_refuses():
    m = DynamicMatcher(single_bytes(), max_bucket=128)
    names = [b"Customer" + bytes([i // 200, i % 200, 7]) for i in range(129)]
    assert [m.insert(e, 256 + i) for i, e in enumerate(names)] == [True] * 128 + [False] and not m.has_room(names[128])


def test_long_text_and_sync():
    rng = np.random.default_rng(3)
    text = bytes(rng.choice(np.frombuffer(b"abab abc", np.uint8), 133_719))
    t = learn([text[:20_000]], capacity=2000, threshold=2, max_len=None, max_bucket=None)
    d = Dictionary(t.entries, bits=11)
    ids, count, _ = codec.encode_column(pa.array([b"", text, b"x", None], pa.binary()), d)
    assert ids.tolist() == DynamicMatcher(d.entries).parse(text) + [ord("x")] and count.tolist() == [0, len(ids) - 1, 1, 0]


# --- on Spark -------------------------------------------------------------------------------------------------------------


EDGES = [(1, None), (2, ""), (3, "a"), (4, "b" * 8), (5, "b" * 9), (6, "b" * 16), (7, "b" * 17), (8, "a\x00b\x00\x00"), (9, "é漢\U0001f600"), (10, "Customer#000001"), (11, "Customer#000001")]


def test_encode_edges(spark):
    df = spark.createDataFrame(EDGES, "key long, value string").withColumn("payload_len", F.lit(1))
    for variant in ("bounded16", "unbounded"):
        d = train(df, variant=variant, bits=9, threshold=2)
        coded = codec.encode(df, "value", d)
        assert coded.columns == ["key", "payload_len", "payload", "n_tokens", "dict_version"]
        back = {r.key: r.value for r in codec.decode(coded.select("key", "payload"), "payload", d).collect()}
        assert back == dict(EDGES)
        rows = {r.key: r for r in coded.collect()}
        assert rows[1].payload is None and rows[1].n_tokens is None and rows[2].payload == b"" and rows[10].payload == rows[11].payload
    none = df.where("key < 0")
    assert codec.encode(none, "value", d).count() == 0 and train(none, bits=9).entries == single_bytes()


def test_training_does_not_depend_on_partitions(spark, sf):
    c = load(spark, sf, "titles")
    a = train(c, bits=10, threshold=2)
    b = train(c.repartition(7).orderBy(F.desc("key")), bits=10, threshold=2)
    assert a.version == b.version and a.stats["stop_reason"] == "exhausted"
    assert train(c, bits=10, threshold=2, sample=SampleSpec(seed=1)).version != a.version
    c4 = [train(c, variant="unbounded", bits=9, threshold=t).stats["bytes_read"] for t in (2, 4, 8)]
    assert c4 == sorted(c4)
    with pytest.raises(ValueError):
        SampleSpec(fraction=0)


def test_nations_dictionary(spark):
    d = train(load(spark, "/root/testdata/sf0.001", "nations"), bits=9, threshold=2)
    assert d.entries[256:] == [b"NA", b"TI", b"ON", b"ON_", b"NATI", b"NATION_", b"NATION_1", b"NATION_2"] and d.stats["stop_reason"] == "exhausted"


def test_encode_is_narrow_and_prunes(spark, sf):
    d = fixed_dictionary(load(spark, sf, "titles"), 50, 9)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    coded = codec.encode(docs, "text", d)
    assert plans.exchanges(coded) == 0 and plans.read_schema(coded) == ["doc_id:bigint,text:string"]


def test_store(spark, sf, tmp_path):
    c = load(spark, sf, "titles")
    d = train(c, bits=10, threshold=2)
    CompressedStore.write(c, str(tmp_path), d, files=2)
    store = CompressedStore.read(spark, str(tmp_path))
    want = {r.key: r.value for r in c.collect()}
    assert {r.key: r.value for r in store.values().collect()} == want
    keys = spark.createDataFrame([(5,), (5,), (7,), (10**6,)], "key long")
    assert sorted((r.key, r.value) for r in store.lookup(keys).collect()) == [(5, want[5]), (5, want[5]), (7, want[7])]
    found = rewrite_equality(store.rows, "payload", want[9], d)
    assert "EqualTo(payload" in str(plans.pushed_filters(found)) and want[9] in {r.value for r in store.values(found).collect()}
    other = Dictionary(single_bytes(), bits=9)
    with pytest.raises(Exception, match="another dictionary"):
        CompressedStore(store.rows, other).values().collect()
    CompressedStore.write(c.withColumn("part", F.col("key") % 2), str(tmp_path / "p"), d, partition_by=["part"])
    assert CompressedStore.read(spark, str(tmp_path / "p")).rows.where("part = 1").count() == sum(k % 2 for k in want)
    drawn = uniform_keys(spark, c, 500)
    assert drawn.count() == 500 and {r.key for r in drawn.collect()} <= set(want)


def test_bpe(spark, sf):
    texts = [r.value.encode() for r in load(spark, sf, "nations").collect()]
    assert bpe.merge_rounds([b"aaaa", b"aaa", b""], 258)[0][256:] == [b"aa"]
    want = bpe.reference_rounds(texts, 6)
    assert [(r.entry.encode(), r.n) for r in bpe.train_relational(load(spark, sf, "nations"), 6).orderBy("token_id").collect()] == want
    assert bpe.merge_rounds(texts, 262)[0][256:] == [e for e, _ in want]
    more = [b"abababab abba aaab aaa", b"bbbb aa ab"] * 3
    assert bpe.merge_rounds(more, 290)[0][256:] == [e for e, _ in bpe.reference_rounds(more, 34)]


@settings(max_examples=30, deadline=None)
@given(st.lists(st.binary(max_size=40), min_size=1, max_size=10))
def test_symbol_table(texts):
    t = SymbolTable(build(texts))
    payload, _ = t.encode_array(pa.array(texts, pa.binary()))
    got = t.decode_array(payload)
    data, offs, _ = codec.flat(got)
    assert [data[a:b].tobytes() for a, b in zip(offs[:-1], offs[1:], strict=True)] == texts


def test_blocks(spark):
    assert blocks.sizes(np.array([40_000, 30_000, 10])).tolist() == [0, 0, 1]
    df = spark.createDataFrame([(1, "a" * 40_000), (2, "b" * 30_000), (3, "c" * 10), (4, None), (5, "")], "key long, value string")
    assert [(r.key, r.block_id, r.start) for r in blocks.layout(df).orderBy("key").collect()] == [(1, 0, 0), (2, 0, 40_000), (3, 1, 70_000), (5, 1, 70_010)]
    b, where = blocks.compress(df, "zstd")
    got = blocks.lookup(b, where, spark.createDataFrame([(3,), (2,), (3,)], "key long"), "zstd", cache=False)
    assert sorted((r.key, r.value) for r in got.collect()) == [(2, "b" * 30_000), (3, "c" * 10), (3, "c" * 10)]
    assert blocks.layout(df.where("key > 9")).count() == 0
    with pytest.raises(ValueError):
        blocks.compress(df, "none")


def test_domain_guard(spark):
    with pytest.raises(ValueError):
        light.DomainCodec.fit(spark.range(50).select(F.col("id").cast("string").alias("value")), most=10)


def test_groups(spark):
    df = spark.createDataFrame([("x", i, "abcabc" * 3) for i in range(5)] + [("y", i, "zz" * 9) for i in range(5)] + [("y", 9, None)], "g string, key long, value string")
    got = train_by(df, ["g"], bits=9)
    assert {r.g for r in got.collect()} == {"x", "y"} and got.where("g = 'y' AND token_id >= 256 AND hex(entry) LIKE '%61%'").count() == 0


def test_trends(spark):
    """Which codec wins, as published: unbounded and bounded near each other, both above the symbol table; blocks touch far more."""
    c = load(spark, "/root/testdata/sf0.01", "headlines").cache()
    raw = c.agg(F.sum(F.octet_length("value"))).first()[0]
    ratios = {}
    for variant in ("unbounded", "bounded16"):
        d = train(c, variant=variant, bits=13, threshold=4, total_bytes=raw)
        got = measures.encode_totals(c, d)
        ratios[variant] = measures.ratio(raw, got[1], d, 13)
    t = SymbolTable.train(c)
    stored = t.encode(c).agg(F.sum(F.octet_length("payload"))).first()[0]
    ratios["symtab8"] = raw / (stored + t.size())
    d = bpe.train(c, 13, SampleSpec(max_bytes=256 << 10))
    ratios["bpe"] = measures.ratio(raw, measures.encode_totals(c, d)[1], d, 13)
    assert ratios["bounded16"] >= 0.94 * ratios["unbounded"] and min(ratios["unbounded"], ratios["bounded16"]) > ratios["symtab8"] > 1
    assert ratios["unbounded"] >= 0.93 * ratios["bpe"] * 0.95
    c.unpersist()
    assert hashlib.sha256(b"").hexdigest() and math.isfinite(ratios["bpe"])


# --- the static index over a column, packed numbers, bounded samples, whole unions ------------------------------------------


def test_static_column_matcher():
    rng = np.random.default_rng(3)
    pick = lambda signs, n: bytes(rng.choice(list(signs), n).tolist())
    words = [pick(b"abAB", rng.integers(2, 17)) for _ in range(400)]
    words += [b"Customer" + bytes([48 + k]) * (1 + k % 8) for k in range(10)] + [b"prefix08" + pick(b"xyz", 1 + k % 8) for k in range(60)]
    d = Dictionary([bytes([b]) for b in range(256)] + sorted(set(words)), bits=10)
    texts = [b"".join(words[k] for k in rng.integers(0, len(words), 5)) if rng.random() < 0.5 else pick(b"abABCustomerprefix08xyz", 60) for _ in range(300)] + [b"", b"Customer", b"prefix08x"]
    plain = StaticIndex.build(d)
    for index in ("dynamic", "static"):
        ids, count, _ = codec.encode_column(pa.array(texts, pa.binary()), d, index)
        cut = np.concatenate([[0], np.cumsum(count)])
        assert [ids[a:b].tolist() for a, b in zip(cut, cut[1:], strict=False)] == [plain.parse(t) for t in texts]


def test_packed_columns():
    rng = np.random.default_rng(4)
    for bits in (9, 12, 16, 21):
        count = rng.integers(0, 9, 200)
        ids = rng.integers(0, 1 << bits, int(count.sum()))
        data, offs = codec.pack_column(ids, count, bits)
        assert (np.diff(offs) == -(-count * bits // 8)).all()
        back, n = codec.unpack_column(data, offs, bits)
        assert (back == ids).all() and (n == count).all()


def test_encode_replaces_columns_of_its_names(spark):
    df = spark.createDataFrame([(1, "abc", 7, "p", "v")], "key long, value string, n_tokens int, payload string, dict_version string")
    got = codec.encode(df, "value", Dictionary([bytes([b]) for b in range(256)], bits=9))
    assert got.columns == ["key", "payload", "n_tokens", "dict_version"] and got.first().n_tokens == 3


def test_sample_does_not_grow(spark):
    """What reaches the one ordered task is about twice max_bytes, whether the corpus is small or ten times as large."""
    from pairdict.sampling import SampleSpec, draw_sample

    for n in (4_000, 40_000):
        c = spark.range(n).select(F.col("id").alias("key"), F.rpad(F.col("id").cast("string"), 100, "x").alias("value"))
        spec = SampleSpec(max_bytes=100_000).fitted(n * 100)
        drawn = draw_sample(c, spec).agg(F.sum(F.octet_length("value"))).first()[0]
        assert 150_000 < drawn < 250_000
        assert train(c, bits=10, threshold=2, sample=SampleSpec(max_bytes=100_000)).stats["bytes_read"] <= 100_100


def test_thresholds_side_by_side(spark, sf):
    """The same dictionaries and totals as one by one, with values parsed once however often they stand in the corpus."""
    from pairdict import measures
    from pairdict.corpora import load, size_bytes
    from pairdict.sampling import SampleSpec
    from pairdict.training import train, train_thresholds

    c = load(spark, sf, "titles")
    c = c.union(c.selectExpr("key + 1000000", "value")).union(spark.createDataFrame([(-1, None), (-2, "")], "key long, value string"))
    sample, total = SampleSpec(max_bytes=5000), size_bytes(c)
    got = train_thresholds(c, range(2, 6), variant="unbounded", bits=10, sample=sample, total_bytes=total)
    for (t, d), totals in zip(got.items(), measures.encode_totals_each(c, list(got.values()), 3), strict=True):
        one = train(c, variant="unbounded", bits=10, threshold=t, sample=sample, total_bytes=total)
        assert (d.entries, d.lefts, d.rights, d.stats, d.bits, d.threshold) == (one.entries, one.lefts, one.rights, one.stats, 10, t)
        raw, n, rows = measures.encode_totals(c, one)
        assert totals == (raw, n, rows)


def test_widths_from_one_run(spark, sf):
    """The same entries as one run for each width."""
    from pairdict.corpora import load, size_bytes
    from pairdict.sampling import SampleSpec
    from pairdict.training import train, train_widths

    c = load(spark, sf, "headlines")
    sample, total = SampleSpec(max_bytes=100_000), size_bytes(c)
    got = train_widths(c, range(9, 22), variant="unbounded", threshold=2, sample=sample, total_bytes=total)
    assert list(got) == list(range(9, 22)) and [s for _, s in got.values()] == sorted(s for _, s in got.values())
    for bits in (9, 11, 12, 21):
        one, (d, _) = train(c, variant="unbounded", bits=bits, threshold=2, sample=sample, total_bytes=total), got[bits]
        assert (d.entries, d.lefts, d.rights, d.bits, d.version) == (one.entries, one.lefts, one.rights, bits, one.version)


def test_many_dictionaries_at_once(monkeypatch):
    """The numbers of a parse with each dictionary, from one longest match a place; no index is made for a dictionary."""
    from pairdict.match import union

    texts = [b"", b"a", b"ab" * 300 + b"c", b"the cat sat on the mat", "schöne Grüße, 日本".encode(), bytes(range(256)), b"", b"x" * 5000 + b"yz" + b"x" * 777, b"the cat " * 500]
    few = [b"the ", b"the cat ", b"ab", b"abab", b"xx", b"xxx"]
    dics = [Dictionary([bytes([b]) for b in range(256)] + more) for more in ([], few, few[:3] + [b"x" * 32, b"ab" * 20, b"the cat the cat "], [texts[3], "ß".encode(), b"yz" + b"x" * 700])]
    dics += [Dictionary(learn(texts * 3, capacity=2000, threshold=t, max_len=None, max_bucket=None).entries) for t in (2, 3, 7)]
    data, offs = np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in texts])])
    index = union.UnionIndex(dics)
    want = [sum(len(DynamicMatcher(d.entries).parse(x)) for x in texts) for d in dics]
    assert index.counts(data, offs).tolist() == want
    for part, block, before, lanes in ((1, 1024, 32, 1 << 14), (600, 16, 0, 7), (1 << 20, 7, 3, 100)):
        monkeypatch.setattr(union, "SLICE", part), monkeypatch.setattr(union, "BLOCK", block), monkeypatch.setattr(union, "BEFORE", before), monkeypatch.setattr(union, "LANES", lanes)
        assert index.counts(data, offs).tolist() == want
    assert index.counts(data[:0], offs[:1]).tolist() == [0] * len(dics) == index.counts(data[:0], offs[[0, 0]]).tolist()


def test_a_pass_serves_all_thresholds(spark, sf, monkeypatch):
    """One pass over the corpus and no index a dictionary; equal values need not meet, so nothing of a large corpus moves."""
    from pairdict import codec, measures
    from pairdict.corpora import load, size_bytes
    from pairdict.sampling import SampleSpec
    from pairdict.training import train_thresholds

    c = load(spark, sf, "titles").repartition(16)
    dics = list(train_thresholds(c, range(2, 31), variant="unbounded", bits=10, sample=SampleSpec(max_bytes=5000), total_bytes=size_bytes(c)).values())
    want = [measures.encode_totals(c, d) for d in dics[::9]]
    passes, real = [], type(c).mapInArrow
    monkeypatch.setattr(type(c), "mapInArrow", lambda self, *a, **kw: passes.append(self) or real(self, *a, **kw))
    monkeypatch.setattr(codec, "encode_column", None)
    assert measures.encode_totals_each(c, dics)[::9] == want
    assert len(passes) == 1 and "hashpartitioning" not in passes[0]._jdf.queryExecution().toString()
