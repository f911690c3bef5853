"""The experiments, re-expressed on the given tables. Each returns one DataFrame; timings come from actions on the driver."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import codec, measures
from ..baselines import blocks, bpe
from ..baselines.symtab import SymbolTable
from ..codec.store import uniform_keys
from ..corpora import BITS, FIVE, load, size_bytes, summary
from ..dictionary import Dictionary
from ..sampling import SampleSpec
from ..training import adaptive_threshold, train, train_thresholds, train_widths

WIDE = SampleSpec(max_bytes=8 << 20)


def _frame(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _train(corpus: DataFrame, name: str, variant: str, bits: int | None = None, **kw) -> Dictionary:
    return train(corpus, variant=variant, bits=bits or BITS[name], sample=kw.pop("sample", WIDE), **kw)


def w01_threshold_sweep(spark: SparkSession, d: str, corpora=("titles", "headlines"), thresholds=range(2, 31), bits: int | None = None) -> DataFrame:
    """Ratio and training volume by threshold."""
    out = []
    for corpus in corpora:
        c = load(spark, d, corpus)
        dics = train_thresholds(c, thresholds, variant="unbounded", bits=bits or BITS[corpus], sample=WIDE, total_bytes=size_bytes(c))
        for (t, dic), (raw, n, _) in zip(dics.items(), measures.encode_totals_each(c, list(dics.values())), strict=True):
            out.append((corpus, t, measures.ratio(raw, n, dic, dic.bits), dic.stats["bytes_read"], len(dic.entries), dic.stats["stop_reason"]))
    return _frame(spark, out, "corpus string, threshold int, ratio double, bytes_read long, entries int, stop_reason string")


def _gain(spark, d, corpus, variant, bits=None):
    c = load(spark, d, corpus)
    dic = _train(c, corpus, variant, bits)
    return c, dic, measures.token_gain(codec.token_frequencies(c, "value", dic), dic.frame(spark))


def w02_gain_by_length(spark: SparkSession, d: str, corpora=("titles", "headlines"), bits: int | None = None) -> DataFrame:
    parts = [measures.gain_by_length(_gain(spark, d, c, "unbounded", bits)[2]).withColumn("corpus", F.lit(c)) for c in corpora]
    return reduce(DataFrame.unionByName, parts)


def w03_bucket_sizes(spark: SparkSession, d: str, corpora=("titles", "reviews", "tweets", "urls", "ids")) -> DataFrame:
    parts = [measures.bucket_sizes(_train(load(spark, d, c), c, "bounded16").frame(spark)).withColumn("corpus", F.lit(c)) for c in corpora]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def w04_smoothed_gain(spark: SparkSession, d: str, corpus: str = "headlines", bits: int | None = None) -> DataFrame:
    return measures.smoothed_gain(_gain(spark, d, corpus, "unbounded", bits)[2])


def w05_size_sweep(spark: SparkSession, d: str, corpus: str = "headlines", widths=range(9, 22), queries: int = 10_000) -> DataFrame:
    """Ratio, speeds, access time and dictionary size by the width of an entry number, at threshold 2; numbers are stored packed."""
    c = load(spark, d, corpus).cache()
    raw, out = size_bytes(c), []
    keys = uniform_keys(spark, c, queries).cache()
    keys.count()
    for bits, (dic, trained) in train_widths(c, widths, variant="unbounded", threshold=2, sample=WIDE, total_bytes=raw).items():
        t = time.perf_counter()
        coded = codec.encode(c, "value", dic, packed=True).cache()
        n = coded.agg(F.sum("n_tokens")).first()[0]
        t_comp = trained + time.perf_counter() - t
        t_dec = measures.timed(codec.decode(coded.select("key", "payload"), "payload", dic, packed=True))
        t_acc = measures.timed(codec.decode(keys.join(coded.select("key", "payload"), "key"), "payload", dic, packed=True))
        mib = (sum(map(len, dic.entries)) + 4 * (1 << bits)) / measures.MIB
        out.append((bits, measures.ratio(raw, n, dic, bits), measures.throughput(raw, t_comp), measures.throughput(raw, t_dec), t_acc / queries * 1e9, mib, raw / n))
        coded.unpersist()
    c.unpersist()
    return _frame(spark, out, "bits int, ratio double, compress_mib_s double, decompress_mib_s double, access_ns double, dictionary_mib double, mean_token_len double")


def w06_corpora(spark: SparkSession, d: str) -> DataFrame:
    return summary(spark, d)


def w07_comparison(spark: SparkSession, d: str, corpora=FIVE, queries: int = 10_000, bits: dict | None = None) -> DataFrame:
    """Seven codecs on each corpus: ratio, compression and decompression speed, access time."""
    out = []
    for name in corpora:
        c = load(spark, d, name).where("value IS NOT NULL").cache()
        raw, width = size_bytes(c), (bits or BITS)[name]
        keys = uniform_keys(spark, c, queries).cache()
        keys.count()

        def field(label, make, coder=codec.encode, opener=codec.decode, raw=raw, c=c, name=name, width=width, keys=keys):
            t = time.perf_counter()
            dic = make()
            coded = coder(c, "value", dic).cache()
            n, stored = coded.agg(F.sum("n_tokens"), F.sum(F.octet_length("payload"))).first()
            spent = time.perf_counter() - t
            ratio = measures.ratio(raw, n, dic, width) if isinstance(dic, Dictionary) else raw / (stored + dic.size())
            opened = measures.timed(opener(coded.select("key", "payload"), "payload", dic))
            access = measures.timed(opener(keys.join(coded.select("key", "payload"), "key"), "payload", dic))
            coded.unpersist()
            out.append((name, label, ratio, measures.throughput(raw, spent), measures.throughput(raw, opened), access / queries * 1e9))

        plain = measures.timed(c)
        out.append((name, "raw", 1.0, measures.throughput(raw, plain), measures.throughput(raw, plain), measures.timed(keys.join(c, "key")) / queries * 1e9))
        for label, kind in (("block_lz4", "lz4_raw"), ("block_zstd", "zstd")):
            t = time.perf_counter()
            b, where = (x.cache() for x in blocks.compress(c, kind))
            size = b.agg(F.sum(F.octet_length("payload"))).first()[0]
            where.count()
            spent = time.perf_counter() - t
            opened, access = measures.timed(blocks.decompress(b, where, kind)), measures.timed(blocks.lookup(b, where, keys, kind, cache=False))
            out.append((name, label, raw / size, measures.throughput(raw, spent), measures.throughput(raw, opened), access / queries * 1e9))
            b.unpersist()
            where.unpersist()
        field("bpe", lambda: bpe.train(c, width))
        field("symtab8", lambda: SymbolTable.train(c), lambda df, col, t: t.encode(df, col), lambda df, col, t: t.decode(df, col))
        field("pairdict", lambda: _train(c, name, "unbounded", width))
        field("pairdict16", lambda: _train(c, name, "bounded16", width))
        keys.unpersist()
        c.unpersist()
    return _frame(spark, out, "corpus string, codec string, ratio double, compress_mib_s double, decompress_mib_s double, access_ns double")


def w08_footprint(spark: SparkSession, d: str, corpora=FIVE) -> DataFrame:
    out = []
    for name in corpora:
        for variant in ("unbounded", "bounded16"):
            dic = _train(load(spark, d, name), name, variant)
            data = sum(map(len, dic.entries))
            out.append((variant, name, (data + 4 * (1 << dic.bits)) / measures.MIB, data / measures.MIB))
    return _frame(spark, out, "variant string, corpus string, total_mib double, data_mib double")


def w09_token_lengths(spark: SparkSession, d: str, corpora=FIVE) -> DataFrame:
    """Emitted lengths of the symbol table against the bounded variant."""
    out = None
    for name in corpora:
        c = load(spark, d, name)
        for label, dic in (("symtab8", SymbolTable.train(c).dictionary), ("pairdict16", _train(c, name, "bounded16"))):
            h = measures.token_length_histogram(codec.token_frequencies(c, "value", dic), dic.frame(spark)).withColumns({"codec": F.lit(label), "corpus": F.lit(name)})
            out = h if out is None else out.unionByName(h)
    return out


def w10_coverage(spark: SparkSession, d: str, corpora=("titles", "headlines"), bits: int | None = None) -> DataFrame:
    parts = []
    for name in corpora:
        c = load(spark, d, name)
        dic = _train(c, name, "bounded16", bits)
        parts.append(measures.coverage_curve(codec.token_frequencies(c, "value", dic), dic.frame(spark)).withColumn("corpus", F.lit(name)))
    return reduce(DataFrame.unionByName, parts)


def w11_phase_times(spark: SparkSession, d: str, corpora=FIVE) -> DataFrame:
    out = []
    for name in corpora:
        c = load(spark, d, name).cache()
        raw = size_bytes(c)
        for variant in ("unbounded", "bounded16"):
            t = time.perf_counter()
            dic = _train(c, name, variant, threshold=adaptive_threshold(raw / measures.MIB))
            trained = time.perf_counter() - t
            out.append((name, variant, trained, measures.timed(codec.encode(c, "value", dic))))
        c.unpersist()
    return _frame(spark, out, "corpus string, variant string, train_s double, parse_s double")


def w12_access(spark: SparkSession, d: str, corpora=FIVE, queries: int = 10_000) -> DataFrame:
    """Bytes touched and time of uniform point reads, field by field and by blocks."""
    out = []
    for name in corpora:
        c = load(spark, d, name).cache()
        keys = uniform_keys(spark, c, queries).cache()
        wanted = keys.join(c, "key").agg(F.sum(F.octet_length("value"))).first()[0]
        dic = _train(c, name, "bounded16")
        coded = codec.encode(c, "value", dic).select("key", "payload").cache()
        coded.count()
        out.append((name, "raw", queries, measures.timed(keys.join(c, "key")) / queries * 1e9, int(wanted)))
        out.append((name, "pairdict16", queries, measures.timed(codec.decode(keys.join(coded, "key"), "payload", dic)) / queries * 1e9, int(wanted)))
        for label, kind in (("block_lz4", "lz4_raw"), ("block_zstd", "zstd")):
            b, where = (x.cache() for x in blocks.compress(c, kind))
            touched = blocks.bytes_touched(where, b, keys, cache=False).first().bytes_touched
            out.append((name, label, queries, measures.timed(blocks.lookup(b, where, keys, kind, cache=False)) / queries * 1e9, int(touched)))
            b.unpersist()
            where.unpersist()
        for x in (c, keys, coded):
            x.unpersist()
    return _frame(spark, out, "corpus string, codec string, n int, mean_ns double, bytes_touched long")


def w13_full_decode(spark: SparkSession, d: str, corpora=FIVE) -> DataFrame:
    out = []
    for name in corpora:
        c = load(spark, d, name).cache()
        raw = size_bytes(c)
        for variant in ("unbounded", "bounded16"):
            dic = _train(c, name, variant)
            coded = codec.encode(c, "value", dic).select("key", "payload").cache()
            coded.count()
            out.append((name, variant, measures.throughput(raw, measures.timed(codec.decode(coded, "payload", dic)))))
            coded.unpersist()
        c.unpersist()
    return _frame(spark, out, "corpus string, variant string, mib_s double")


def w14_caps(spark: SparkSession, d: str, corpora=("urls", "ids")) -> DataFrame:
    """The length cap and the bucket cap, each on and off: ratio and search work."""
    out = []
    for name in corpora:
        c = load(spark, d, name).cache()
        raw = size_bytes(c)
        for cap in (16, None):
            for bucket in (128, None):
                dic = _train(c, name, "unbounded", 12, max_len=cap, max_bucket=bucket, threshold=2)
                cost = measures.lpm_cost(c, dic).first()
                out.append((name, cap, bucket, measures.ratio(raw, cost.tokens, dic, 12), cost.suffix_tests, cost.probes))
        c.unpersist()
    return _frame(spark, out, "corpus string, max_len int, max_bucket int, ratio double, suffix_tests long, probes long")


def w15_sample_order(spark: SparkSession, d: str, bits: int = 11) -> DataFrame:
    """Training on a shuffled sample against the stored order, of documents stored by language."""
    rank = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3)
    c = spark.read.parquet(f"{d}/documents.parquet").select((rank * F.lit(1 << 40) + F.col("doc_id")).alias("key"), F.col("text").alias("value")).cache()
    out = []
    for order in ("md5", "stored"):
        dic = train(c, bits=bits, threshold=2, sample=SampleSpec(max_bytes=8 << 20, order=order))
        raw, n, _ = measures.encode_totals(c, dic)
        out.append((order, measures.ratio(raw, n, dic, bits), dic.stats["bytes_read"]))
    c.unpersist()
    return _frame(spark, out, "sample_order string, ratio double, bytes_read long")


WORKLOADS = {f.__name__: f for f in (w01_threshold_sweep, w02_gain_by_length, w03_bucket_sizes, w04_smoothed_gain, w05_size_sweep, w06_corpora, w07_comparison, w08_footprint, w09_token_lengths, w10_coverage, w11_phase_times, w12_access, w13_full_decode, w14_caps, w15_sample_order)}
