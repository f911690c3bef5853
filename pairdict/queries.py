"""Queries of the engine on the given tables, and the SQL that gives the same rows elsewhere."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import codec, measures, streaming
from .baselines import blocks, bpe, light
from .baselines.symtab import SymbolTable
from .codec.store import CompressedStore, payloads, rewrite_equality
from .corpora import BITS, load, size_bytes, summary, table
from .dictionary import GRAM_LENGTHS, Dictionary, fixed_dictionary, fixed_frame, offsets_frame
from .functions import make, register_functions
from .match.relational import lpm_join
from .match.static import StaticIndex
from .match.words import pack8, shared_prefix_len
from .operators import relational
from .sampling import SampleSpec
from .scratch import folder
from .sources import parquet_bytes
from .training import adaptive_threshold_col, suggest_bits, train, train_by, train_sharded
from .workloads import WORKLOADS

SAMPLE = SampleSpec(max_bytes=8 << 20)

# --- the corpora in SQL ---------------------------------------------------------------------------------------------------

CORPUS_SQL = {
    "reviews": "SELECT conv_id * 1000 + turn AS key, text AS value FROM conversations",
    "reviews_xl": "SELECT doc_id AS key, text AS value FROM documents",
    "titles": "SELECT p_partkey AS key, concat_ws(' ', p_brand, p_type, p_name, 'size', p_size) AS value FROM part",
    "headlines": "SELECT doc_id * 1048576 + i - 1 AS key, v AS value FROM (SELECT doc_id, unnest(s) AS v, generate_subscripts(s, 1) AS i FROM (SELECT doc_id, regexp_split_to_array(text, '[.,\n]+') AS s FROM documents)) WHERE v <> ''",
    "tweets": "SELECT (conv_id * 1000 + turn) * 4096 + i - 1 AS key, v AS value FROM (SELECT conv_id, turn, unnest(s) AS v, generate_subscripts(s, 1) AS i FROM (SELECT conv_id, turn, string_split(text, '. ') AS s FROM conversations)) WHERE v <> ''",
    "urls": "SELECT page_id AS key, url AS value FROM pages",
    "ids": "SELECT c_custkey AS key, c_name AS value FROM customer",
    "html": "SELECT page_id AS key, html AS value FROM pages",
    "props": "SELECT event_id AS key, props AS value FROM events",
    "nations": "SELECT n_nationkey AS key, n_name AS value FROM nation",
    "enums": "SELECT o_orderkey AS key, o_orderpriority AS value FROM orders",
}
_T = f"t AS ({CORPUS_SQL['titles']})"
_GRAMS = f"""{_T}, g AS (SELECT substr(value, CAST(i AS INTEGER), n) AS entry, count(*) AS c FROM (SELECT value, n, unnest(generate_series(1, length(value) - n + 1)) AS i
FROM t, (VALUES {", ".join(f"({n})" for n in GRAM_LENGTHS)}) l(n) WHERE length(value) >= n) GROUP BY 1 ORDER BY c DESC, hex(entry) LIMIT 400),
d AS (SELECT CAST(255 + row_number() OVER (ORDER BY c DESC, hex(entry)) AS INTEGER) AS token_id, entry, CAST(length(entry) AS INTEGER) AS entry_len FROM g),
every AS (SELECT token_id, hex(entry) AS entry, entry_len FROM d UNION ALL SELECT CAST(range AS INTEGER), printf('%02X', range), 1 FROM range(256)),
ls AS (SELECT list(entry ORDER BY length(entry) DESC, entry) AS l FROM d)"""
_LONGEST = "coalesce(list_filter(ls.l, lambda x: starts_with({0}, x))[1], substr({0}, 1, 1))"
_WALK = f"""WITH RECURSIVE {_GRAMS}, w(key, value, pos, e) AS (SELECT key, value, CAST(1 AS BIGINT), {_LONGEST.format("value")} FROM t, ls
UNION ALL SELECT key, value, pos + length(e), {_LONGEST.format("substr(value, pos + length(e))")} FROM w, ls WHERE pos + length(e) <= length(value)),
tok AS (SELECT key, pos, coalesce(d.token_id, ascii(e)) AS token_id, CAST(length(e) AS INTEGER) AS len FROM w LEFT JOIN d ON d.entry = w.e),
fr AS (SELECT token_id, count(*) AS f FROM tok GROUP BY 1),
gn AS (SELECT every.token_id, entry, entry_len, coalesce(f, 0) AS f, (entry_len - 2) * coalesce(f, 0) - entry_len AS gain FROM every LEFT JOIN fr USING (token_id))"""


def _fold(corpus: str, threshold: int, cap: int | None, capacity: int = 512) -> str:
    """Training as a fold over matches, one recursion step a match: the entries so far and the counters are its state."""
    fits = f"length(prev) + length(cur) <= {cap}" if cap else "true"
    return f"""
WITH RECURSIVE s AS (SELECT value AS v, row_number() OVER (ORDER BY md5('42:' || key), key) AS rn FROM ({corpus})),
f(step, rn, pos, prev, dict, counts) AS (
  SELECT 0, CAST(1 AS BIGINT), CAST(1 AS BIGINT), CAST('' AS VARCHAR), CAST([] AS VARCHAR[]), CAST(MAP {{}} AS MAP(VARCHAR, INTEGER))
  UNION ALL
  SELECT step + 1, CASE WHEN done THEN rn + 1 ELSE rn END, CASE WHEN done THEN 1 ELSE pos + length(cur) END,
    CASE WHEN done THEN '' WHEN grow THEN prev || cur ELSE cur END,
    CASE WHEN grow THEN list_append(dict, prev || cur) ELSE dict END,
    CASE WHEN grow THEN map_from_entries(list_filter(map_entries(counts), lambda e: e.key <> pair)) WHEN able THEN map_concat(counts, MAP {{pair: seen}}) ELSE counts END
  FROM (SELECT *, able AND seen >= {threshold} AND len(dict) < {capacity - 256} AS grow FROM (
    SELECT *, prev || '|' || cur AS pair, prev <> '' AND {fits} AS able, coalesce(counts[prev || '|' || cur], 0) + 1 AS seen, pos + length(cur) > length(v) AS done FROM (
      SELECT f.*, s.v, coalesce(list_sort(list_transform(list_filter(dict, lambda x: starts_with(substr(v, pos), x)), lambda x: printf('%05d', length(x)) || x), 'DESC')[1][6:], substr(v, pos, 1)) AS cur
      FROM f JOIN s ON s.rn = f.rn))))
SELECT CAST(255 + i AS INTEGER) AS token_id, hex(dict[i]) AS entry, CAST(length(dict[i]) AS INTEGER) AS entry_len
FROM (SELECT dict, unnest(generate_series(1, len(dict))) AS i FROM (SELECT dict FROM f ORDER BY step DESC LIMIT 1))
"""


_QUERIES: dict[str, tuple] = {}


def _query(name: str, sql: str | None = None):
    def add(f):
        _QUERIES[name] = (f, sql)
        return f

    return add


def _trained(corpus: DataFrame, name: str, variant: str = "bounded16", **kw) -> Dictionary:
    return train(corpus, variant=variant, bits=kw.pop("bits", BITS[name]), sample=SAMPLE, **kw)


# --- round trips ----------------------------------------------------------------------------------------------------------


def _roundtrip(name: str, variant: str = "bounded16"):
    def run(spark: SparkSession, d: str) -> DataFrame:
        c = load(spark, d, name)
        dic = _trained(c, name, variant)
        return codec.decode(codec.encode(c, "value", dic).select("key", "payload"), "payload", dic)

    return run


_query("roundtrip_titles_bounded16", CORPUS_SQL["titles"])(_roundtrip("titles"))
_query("roundtrip_titles_unbounded", CORPUS_SQL["titles"])(_roundtrip("titles", "unbounded"))
for _name in ("reviews", "reviews_xl", "headlines", "tweets", "urls", "ids", "html", "props"):
    _query(f"roundtrip_{_name}", CORPUS_SQL[_name])(_roundtrip(_name, "unbounded" if _name in ("urls", "html") else "bounded16"))


# --- training -------------------------------------------------------------------------------------------------------------


def _training(name: str, threshold: int, variant: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        dic = train(load(spark, d, name), variant=variant, bits=9, threshold=threshold, sample=SAMPLE)
        return dic.frame(spark).where("token_id >= 256").select("token_id", F.hex("entry").alias("entry"), "entry_len")

    return run


_query("train_nations_t2", _fold(CORPUS_SQL["nations"], 2, 16))(_training("nations", 2, "bounded16"))
_query("train_nations_t3", _fold(CORPUS_SQL["nations"], 3, 16))(_training("nations", 3, "bounded16"))
_query("train_nations_unbounded", _fold(CORPUS_SQL["nations"], 2, None))(_training("nations", 2, "unbounded"))
_query("train_ids_bounded16")(_training("ids", 2, "bounded16"))  # recursive SQL would take a step a match of the whole table


@_query("adaptive_threshold_by_corpus", " UNION ALL ".join(f"SELECT '{n}' AS corpus, CAST(greatest(2, floor(log2(greatest(1, sum(strlen(value)) / 1048576.0)))) AS INTEGER) AS threshold FROM ({CORPUS_SQL[n]})" for n in ("titles", "headlines", "html", "reviews_xl")))
def adaptive_by_corpus(spark: SparkSession, d: str) -> DataFrame:
    parts = [load(spark, d, n).agg(F.lit(n).alias("corpus"), adaptive_threshold_col(F.sum(F.octet_length("value"))).alias("threshold")) for n in ("titles", "headlines", "html", "reviews_xl")]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@_query("sample_order", f"SELECT key, md5('42:' || key) AS ord FROM ({CORPUS_SQL['urls']})")
def sample_order(spark: SparkSession, d: str) -> DataFrame:
    from .sampling import draw_sample

    return draw_sample(load(spark, d, "urls"), SAMPLE).select("key", "ord")


@_query("train_by_language")
def train_by_language(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "documents").select("lang", F.col("doc_id").alias("key"), F.col("text").alias("value"))
    return train_by(c, ["lang"], bits=10).groupBy("lang").agg(F.count(F.lit(1)).alias("entries"), F.max(F.octet_length("entry")).alias("longest"))


@_query("train_sharded_titles")
def train_sharded_titles(spark: SparkSession, d: str) -> DataFrame:
    return train_sharded(load(spark, d, "titles"), 4, bits=10).frame(spark).where("token_id >= 256").select("token_id", F.hex("entry").alias("entry"), "entry_len")


@_query("suggested_bits", f"{_WALK}, u AS (SELECT token_id, sum(gain) OVER (ORDER BY token_id) AS s FROM gn), b AS (SELECT range AS bits, (SELECT s FROM u ORDER BY abs(token_id - least((1 << range) - 1, (SELECT max(token_id) FROM u))) LIMIT 1) AS saved FROM range(9, 14)) SELECT 'titles' AS corpus, CAST(bits AS INTEGER) AS bits FROM b ORDER BY ((SELECT sum(strlen(value)) FROM t) - saved) * bits / 16 + 4 * (1 << bits), bits LIMIT 1")
def suggested_bits(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "titles")
    return spark.createDataFrame([("titles", suggest_bits(_fixed_gain(spark, d), size_bytes(c), 9, 13))], "corpus string, bits int")


_FOLDED = _fold(CORPUS_SQL["nations"], 2, None).strip()


@_query("training_stats", f"SELECT 'unbounded' AS variant, CAST(sum(strlen(n_name)) AS BIGINT) AS bytes_read, count(*) AS strings_read, CAST(256 + (SELECT count(*) FROM ({_FOLDED})) AS INTEGER) AS entries, 'exhausted' AS stop_reason FROM nation UNION ALL SELECT 'bounded16', CAST(sum(strlen(n_name)) AS BIGINT), count(*), CAST(256 + (SELECT count(*) FROM ({_fold(CORPUS_SQL['nations'], 2, 16).strip()})) AS INTEGER), 'exhausted' FROM nation")
def training_stats(spark: SparkSession, d: str) -> DataFrame:
    out = []
    for variant in ("unbounded", "bounded16"):
        s = train(load(spark, d, "nations"), variant=variant, bits=9, threshold=2, sample=SAMPLE).stats
        out.append((variant, s["bytes_read"], s["strings_read"], s["entries"], s["stop_reason"]))
    return spark.createDataFrame(out, "variant string, bytes_read long, strings_read long, entries int, stop_reason string")


@_query("training_costs")
def training_costs(spark: SparkSession, d: str) -> DataFrame:
    out = []
    for variant in ("unbounded", "bounded16"):
        s = _trained(load(spark, d, "titles"), "titles", variant).stats
        out.append((variant, s["bytes_read"], s["strings_read"], s["entries"], s["pairs_tracked"], s["stop_reason"], s["peak_state_bytes"]))
    return spark.createDataFrame(out, "variant string, bytes_read long, strings_read long, entries int, pairs_tracked int, stop_reason string, peak_state_bytes long")


@_query("dictionary_saved")
def dictionary_saved(spark: SparkSession, d: str) -> DataFrame:
    dic = _trained(load(spark, d, "urls"), "urls", "unbounded")
    path = folder(spark)
    dic.save(spark, path)
    return Dictionary.load(spark, path).frame(spark).select("token_id", F.hex("entry").alias("entry"), "left_id", "right_id")


# --- the fixed dictionary: matching, parsing, measures ----------------------------------------------------------------------


def _fixed(spark: SparkSession, d: str) -> tuple[DataFrame, Dictionary]:
    c = load(spark, d, "titles")
    return c, fixed_dictionary(c)


def _fixed_gain(spark, d):
    c, dic = _fixed(spark, d)
    return measures.token_gain(codec.token_frequencies(c, "value", dic), dic.frame(spark))


@_query("fixed_dict_ngrams", f"WITH {_GRAMS} SELECT * FROM every")
def fixed_ngrams(spark: SparkSession, d: str) -> DataFrame:
    return fixed_frame(load(spark, d, "titles")).select("token_id", F.hex("entry").alias("entry"), "entry_len")


@_query("lpm_relational", f"WITH {_GRAMS}, p AS (SELECT key, value, unnest(generate_series(1, length(value))) AS pos FROM t), m AS (SELECT key, CAST(pos AS INTEGER) AS pos, {_LONGEST.format('substr(value, pos)')} AS e FROM p, ls) SELECT key, pos, coalesce(d.token_id, ascii(e)) AS token_id, CAST(length(e) AS INTEGER) AS len FROM m LEFT JOIN d ON d.entry = m.e")
def lpm_relational(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "titles")
    return lpm_join(c, fixed_frame(c))


def _parsed(c: DataFrame, dic: Dictionary, index: str = "dynamic") -> DataFrame:
    return codec.token_ids(c, "value", dic, index=index).select("key", F.size("ids").cast("long").alias("n_tokens"), F.array_join("ids", ",").alias("ids"))


_PARSED = f"{_WALK} SELECT key, count(*) AS n_tokens, string_agg(token_id, ',' ORDER BY pos) AS ids FROM tok GROUP BY key"


@_query("parse_fixed", _PARSED)
def parse_fixed(spark: SparkSession, d: str) -> DataFrame:
    return _parsed(*_fixed(spark, d))


@_query("parse_fixed_static", _PARSED)
def parse_fixed_static(spark: SparkSession, d: str) -> DataFrame:
    """The same ids by the static index."""
    return _parsed(*_fixed(spark, d), index="static")


@_query("parse_fixed_sql", _PARSED)
def parse_fixed_sql(spark: SparkSession, d: str) -> DataFrame:
    """The same ids through the registered SQL function."""
    c, dic = _fixed(spark, d)
    register_functions(spark, dic)
    c.createOrReplaceTempView("titles_corpus")
    return spark.sql("SELECT key, CAST(size(ids) AS BIGINT) AS n_tokens, array_join(ids, ',') AS ids FROM (SELECT key, pd_token_ids(value) AS ids FROM titles_corpus)")


@_query("explain_matches", f"{_WALK} SELECT key, CAST(pos - 1 AS INTEGER) AS pos, token_id, len FROM tok")
def explain_matches(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    register_functions(spark, dic)
    c.createOrReplaceTempView("titles_explained")
    return spark.sql("SELECT key, pos, token_id, len FROM titles_explained, LATERAL pd_explain(value)")


@_query("udf_n_tokens", f"{_WALK} SELECT key, CAST(count(*) AS INTEGER) AS n_tokens FROM tok GROUP BY key")
def udf_n_tokens(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return c.select("key", make(dic)["n_tokens"]("value").alias("n_tokens"))


@_query("udf_encoded_bytes", f"{_WALK} SELECT key % 10 AS g, CAST(count(*) * 2 AS BIGINT) AS n_bytes FROM tok GROUP BY 1")
def udf_encoded_bytes(spark: SparkSession, d: str) -> DataFrame:
    """The aggregate function over groups of bounded size."""
    c, dic = _fixed(spark, d)
    return c.groupBy((F.col("key") % 10).alias("g")).agg(make(dic)["encoded_bytes"]("value").alias("n_bytes"))


@_query("udf_roundtrip", CORPUS_SQL["urls"])
def udf_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "urls")
    f = make(_trained(c, "urls"))
    return c.select("key", f["decode"](f["encode"]("value")).alias("value"))


@_query("decode_relational", CORPUS_SQL["titles"])
def decode_relational(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return codec.decode_join(codec.encode(c, "value", dic), dic.frame(spark))


@_query("pack_offsets", f"WITH {_GRAMS} SELECT token_id, CAST(sum(entry_len) OVER w - entry_len AS BIGINT) AS at, CAST(sum(entry_len) OVER w AS BIGINT) AS \"to\" FROM every WINDOW w AS (ORDER BY token_id)")
def pack_offsets(spark: SparkSession, d: str) -> DataFrame:
    return offsets_frame(fixed_frame(load(spark, d, "titles")))


@_query("entry_by_offset", f"WITH {_GRAMS} SELECT token_id, entry FROM every")
def entry_by_offset(spark: SparkSession, d: str) -> DataFrame:
    """Entries cut out of the packed bytes by their offsets."""
    fixed = fixed_frame(load(spark, d, "titles"))
    data = bytes(b for r in sorted(fixed.select("token_id", "entry").collect()) for b in bytes(r.entry))
    return offsets_frame(fixed).select("token_id", F.hex(F.substring(F.lit(bytearray(data)), (F.col("at") + 1).cast("int"), (F.col("to") - F.col("at")).cast("int"))).alias("entry"))


@_query("xor_prefix_pairs", f"WITH {_T}, n AS (SELECT key, value, lead(value) OVER (ORDER BY key) AS other FROM t) SELECT key, CAST(len(list_filter(generate_series(1, 8), lambda i: substr(value, 1, i) = substr(other, 1, i))) AS INTEGER) AS shared FROM n WHERE other IS NOT NULL")
def xor_prefix_pairs(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "titles")
    pairs = c.join(c.select((F.col("key") - 1).alias("key"), F.col("value").alias("other")), "key")
    return pairs.select("key", shared_prefix_len(pack8(F.encode("value", "UTF-8")), pack8(F.encode("other", "UTF-8"))).alias("shared"))


@_query("lpm_buckets", f"WITH {_GRAMS} SELECT substr(entry, 1, 16) AS prefix8, count(*) AS n, string_agg(substr(entry, 17), ',' ORDER BY entry_len DESC, entry DESC) AS suffixes FROM every WHERE entry_len > 8 GROUP BY 1")
def lpm_buckets(spark: SparkSession, d: str) -> DataFrame:
    h = F.hex("entry")
    rows = fixed_frame(load(spark, d, "titles")).where("entry_len > 8").select(F.substring(h, 1, 16).alias("prefix8"), F.struct(F.col("entry_len").alias("n"), F.substring(h, 17, 64).alias("s")).alias("x"))
    grouped = rows.groupBy("prefix8").agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list("x"), asc=False).alias("xs"))
    return grouped.select("prefix8", "n", F.array_join(F.transform("xs", lambda x: x["s"]), ",").alias("suffixes"))


@_query("static_index_records", f"WITH {_GRAMS}, b AS (SELECT substr(entry, 1, 16) AS prefix8, count(*) AS n FROM every WHERE entry_len > 8 GROUP BY 1) SELECT prefix8, CAST(greatest(n - 4, 0) AS INTEGER) AS size, CAST(least(n, 4) AS INTEGER) AS inline, CAST((SELECT sum(greatest(n - 4, 0)) FROM b) AS BIGINT) AS overflow FROM b")
def static_index_records(spark: SparkSession, d: str) -> DataFrame:
    records, overflow = StaticIndex.build(_fixed(spark, d)[1]).frames(spark)
    return records.select(F.hex("prefix8").alias("prefix8"), "size", F.size("inline").alias("inline")).join(overflow.agg(F.count(F.lit(1)).alias("overflow")), how="left")


@_query("roundtrip_packed_bits", CORPUS_SQL["tweets"])
def roundtrip_packed_bits(spark: SparkSession, d: str) -> DataFrame:
    """Numbers of eleven bits, packed."""
    c = load(spark, d, "tweets")
    dic = _trained(c, "tweets", bits=11)
    return codec.decode(codec.encode(c, "value", dic, packed=True).select("key", "payload"), "payload", dic, packed=True)


@_query("packed_sizes", f"{_WALK} SELECT key, CAST(ceil(count(*) * 10 / 8) AS INTEGER) AS n_bytes FROM tok GROUP BY key")
def packed_sizes(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return codec.encode(c, "value", dic, packed=True).select("key", F.octet_length("payload").alias("n_bytes"))


@_query("roundtrip_static_index", CORPUS_SQL["reviews"])
def roundtrip_static_index(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "reviews")
    dic = _trained(c, "reviews")
    return codec.decode(codec.encode(c, "value", dic, index="static").select("key", "payload"), "payload", dic)


@_query("static_equals_dynamic", " UNION ALL ".join(f"SELECT '{n}' AS corpus, count(*) AS n_rows, CAST(0 AS BIGINT) AS differ FROM ({CORPUS_SQL[n]})" for n in ("titles", "urls", "ids", "headlines")))
def static_equals_dynamic(spark: SparkSession, d: str) -> DataFrame:
    """Rows whose payload differs between the two indexes of a trained dictionary: none."""
    out = None
    for name in ("titles", "urls", "ids", "headlines"):
        c = load(spark, d, name)
        dic = _trained(c, name)
        both = codec.encode(codec.encode(c.withColumn("again", F.col("value")), "value", dic, "a").drop("n_tokens", "dict_version"), "again", dic, "b", index="static")
        row = both.agg(F.lit(name).alias("corpus"), F.count(F.lit(1)).alias("n_rows"), F.count_if(~F.col("a").eqNullSafe(F.col("b"))).alias("differ"))
        out = row if out is None else out.union(row)
    return out


@_query("search_cost")
def search_cost(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "ids")
    parts = [measures.lpm_cost(c, _trained(c, "ids", v, bits=12)).withColumn("variant", F.lit(v)) for v in ("unbounded", "bounded16")]
    return parts[0].union(parts[1])


@_query("token_gain_fixed", f"{_WALK} SELECT token_id, entry, entry_len, f, gain FROM gn")
def token_gain_fixed(spark: SparkSession, d: str) -> DataFrame:
    return _fixed_gain(spark, d).withColumn("entry", F.hex("entry"))


@_query("gain_by_length_fixed", f"{_WALK}, e AS (SELECT entry_len, CAST(sum(gain) AS BIGINT) AS gain, CAST(sum(f) AS BIGINT) AS f FROM gn GROUP BY 1) SELECT entry_len, gain, f, round(sum(gain) OVER (ORDER BY entry_len) / sum(gain) OVER (), 9) AS cum_gain_share, round(sum(f) OVER (ORDER BY entry_len) / sum(f) OVER (), 9) AS cum_freq_share FROM e")
def gain_by_length_fixed(spark: SparkSession, d: str) -> DataFrame:
    return measures.gain_by_length(_fixed_gain(spark, d)).withColumns({c: F.round(c, 9) for c in ("cum_gain_share", "cum_freq_share")})


@_query("smoothed_gain_fixed", f"{_WALK} SELECT token_id, gain, round(avg(gain) OVER (ORDER BY token_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 9) AS smoothed FROM gn")
def smoothed_gain_fixed(spark: SparkSession, d: str) -> DataFrame:
    return measures.smoothed_gain(_fixed_gain(spark, d), 7).withColumn("smoothed", F.round("smoothed", 9))


@_query("coverage_fixed", f"{_WALK} SELECT row_number() OVER w AS rank, token_id, CAST(sum(entry_len) OVER w AS BIGINT) AS cum_bytes, round(sum(f) OVER w / sum(f) OVER (), 9) AS cum_share FROM gn WHERE f > 0 WINDOW w AS (ORDER BY f DESC, token_id)")
def coverage_fixed(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return measures.coverage_curve(codec.token_frequencies(c, "value", dic), dic.frame(spark)).withColumn("cum_share", F.round("cum_share", 9))


@_query("token_length_histogram_fixed", f"{_WALK} SELECT len AS entry_len, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 9) AS share FROM tok GROUP BY len")
def histogram_fixed(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return measures.token_length_histogram(codec.token_frequencies(c, "value", dic), dic.frame(spark)).withColumn("share", F.round("share", 9))


@_query("bucket_sizes_fixed", f"WITH {_GRAMS}, b AS (SELECT substr(entry, 1, 16) AS p, count(*) AS size FROM every WHERE entry_len > 8 GROUP BY 1), s AS (SELECT size, count(*) AS n_buckets FROM b GROUP BY 1) SELECT size, n_buckets, round(n_buckets / sum(n_buckets) OVER (), 9) AS share, round(sum(n_buckets) OVER (ORDER BY size) / sum(n_buckets) OVER (), 9) AS cum_share FROM s")
def bucket_sizes_fixed(spark: SparkSession, d: str) -> DataFrame:
    return measures.bucket_sizes(fixed_frame(load(spark, d, "titles"))).withColumns({c: F.round(c, 9) for c in ("share", "cum_share")})


@_query("footprint_fixed", f"WITH {_GRAMS} SELECT count(*) AS entries, CAST(sum(entry_len) AS BIGINT) AS data_bytes, CAST(4096 AS BIGINT) AS offset_bytes, CAST(sum(entry_len) + 4096 AS BIGINT) AS total_bytes FROM every")
def footprint_fixed(spark: SparkSession, d: str) -> DataFrame:
    return measures.footprint(fixed_frame(load(spark, d, "titles")), 10)


@_query("ratio_fixed", f"{_WALK}, a AS (SELECT (SELECT sum(length(value)) FROM t) AS raw, (SELECT count(*) FROM tok) AS n, (SELECT count(*) FROM t) AS r, (SELECT sum(entry_len) FROM every) + 4096 AS dict) SELECT CAST(raw AS BIGINT) AS raw_bytes, n AS n_tokens, round(raw / (n * 10 / 8 + dict), 9) AS ratio_paper, round(raw / (n * 10 / 8), 9) AS ratio_no_dict, round(raw / (n * 10 / 8 + dict + 4 * r), 9) AS ratio_with_row_offsets, round(raw / n, 9) AS mean_token_len FROM a")
def ratio_fixed(spark: SparkSession, d: str) -> DataFrame:
    c, dic = _fixed(spark, d)
    return measures.ratio_report(c, dic).withColumns({x: F.round(x, 9) for x in ("ratio_paper", "ratio_no_dict", "ratio_with_row_offsets", "mean_token_len")})


@_query("roundtrip_errors", "SELECT key, value AS was, value AS back FROM (" + CORPUS_SQL["tweets"] + ") WHERE false")
def roundtrip_errors(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "tweets")
    return measures.roundtrip_errors(c, _trained(c, "tweets"))


@_query("corpus_summary", " UNION ALL ".join(f"SELECT '{n}' AS corpus, count(value) AS n_rows, CAST(coalesce(sum(strlen(value)), 0) AS BIGINT) AS n_bytes, round(avg(strlen(value)), 6) AS avg_bytes FROM ({s})" for n, s in CORPUS_SQL.items()))
def corpus_summary(spark: SparkSession, d: str) -> DataFrame:
    return summary(spark, d)


# --- stores and access ----------------------------------------------------------------------------------------------------


def _store(spark: SparkSession, d: str, name: str = "titles") -> CompressedStore:
    c = load(spark, d, name)
    path = folder(spark)
    CompressedStore.write(c, path, _trained(c, name))
    return CompressedStore.read(spark, path)


@_query("point_access", f"WITH {_T} SELECT k.key, value FROM (SELECT key FROM t WHERE key % 7 = 0 UNION ALL SELECT key FROM t WHERE key % 14 = 0) k JOIN t ON t.key = k.key")
def point_access(spark: SparkSession, d: str) -> DataFrame:
    store = _store(spark, d)
    keys = store.rows.select("key").where("key % 7 = 0")
    return store.lookup(keys.union(keys.where("key % 14 = 0")))


@_query("payload_equality", f"WITH {_T} SELECT key, value FROM t WHERE value = (SELECT value FROM t WHERE key = 77)")
def payload_equality(spark: SparkSession, d: str) -> DataFrame:
    store = _store(spark, d)
    literal = load(spark, d, "titles").where("key = 77").first().value
    return store.values(rewrite_equality(store.rows, "payload", literal, store.dictionary))


@_query("payload_in", f"WITH {_T} SELECT key, value FROM t WHERE value IN (SELECT value FROM t WHERE key IN (5, 50, 150))")
def payload_in(spark: SparkSession, d: str) -> DataFrame:
    store = _store(spark, d)
    literals = [r.value for r in load(spark, d, "titles").where("key IN (5, 50, 150)").collect()]
    return store.values(store.where_equal([*literals, "not there"]))


@_query("payload_join_duplicates", f"SELECT key, min(key) OVER (PARTITION BY value) AS first_key FROM ({CORPUS_SQL['reviews_xl']})")
def payload_join_duplicates(spark: SparkSession, d: str) -> DataFrame:
    """Copies found on payloads: the first key of each text, counted before the join."""
    c = load(spark, d, "reviews_xl")
    coded = codec.encode(c, "value", _trained(c, "reviews_xl", bits=11)).select("key", "payload")
    return coded.join(coded.groupBy("payload").agg(F.min("key").alias("first_key")), "payload").select("key", "first_key")


@_query("payload_distinct", f"SELECT count(DISTINCT value) AS n FROM ({CORPUS_SQL['enums']})")
def payload_distinct(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "enums")
    return codec.encode(c, "value", _trained(c, "enums")).agg(F.count_distinct("payload").alias("n"))


@_query("store_source", f"WITH {_T} SELECT key, value FROM t WHERE key IN (3, 33, 133) OR value = (SELECT value FROM t WHERE key = 77)")
def store_source(spark: SparkSession, d: str) -> DataFrame:
    from .sources import register

    c = load(spark, d, "titles")
    path = folder(spark)
    CompressedStore.write(c, path, _trained(c, "titles"))
    register(spark)
    rows = lambda: spark.read.format("pairdict").option("path", path).load()  # noqa: E731  a read of its own for each set of filters
    literal = c.where("key = 77").first().value
    return rows().where(F.col("key").isin(3, 33, 133)).union(rows().where(F.col("value") == literal)).distinct()


_ACCESS_KEYS = "key % 11 = 0"


@_query("block_layout", f"SELECT key, CAST(floor(start / 65536) AS BIGINT) AS block_id, start FROM (SELECT key, CAST(sum(strlen(value)) OVER (ORDER BY key) - strlen(value) AS BIGINT) AS start FROM ({CORPUS_SQL['tweets']}))")
def block_layout(spark: SparkSession, d: str) -> DataFrame:
    return blocks.layout(load(spark, d, "tweets")).select("key", "block_id", "start")


def _blocks(kind: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return blocks.decompress(*blocks.compress(load(spark, d, "tweets"), kind), kind)

    return run


for _label, _kind in (("lz4", "lz4_raw"), ("zstd", "zstd"), ("gzip", "gzip")):
    _query(f"block_roundtrip_{_label}", CORPUS_SQL["tweets"])(_blocks(_kind))


@_query("block_access", f"SELECT key, value FROM ({CORPUS_SQL['tweets']}) WHERE {_ACCESS_KEYS}")
def block_access(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "tweets")
    return blocks.lookup(*blocks.compress(c, "zstd"), c.select("key").where(_ACCESS_KEYS), "zstd")


@_query("block_store", f"SELECT key, value FROM ({CORPUS_SQL['urls']}) WHERE {_ACCESS_KEYS}")
def block_store(spark: SparkSession, d: str) -> DataFrame:
    c, path = load(spark, d, "urls"), folder(spark)
    blocks.write_store(c, path, "lz4_raw")
    return blocks.lookup(*blocks.read_store(spark, path), c.select("key").where(_ACCESS_KEYS), "lz4_raw")


@_query("block_access_cost")
def block_access_cost(spark: SparkSession, d: str) -> DataFrame:
    """Bytes opened for the same keys with and without a block cache."""
    c = load(spark, d, "tweets")
    b, where = blocks.compress(c, "zstd")
    keys = c.select("key").where(_ACCESS_KEYS)
    parts = [blocks.bytes_touched(where, b, keys, cache).withColumn("cache", F.lit(cache)) for cache in (True, False)]
    return parts[0].union(parts[1])


@_query("parquet_codecs")
def parquet_codecs(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of a corpus as Parquet under each page codec."""
    c = load(spark, d, "reviews_xl").coalesce(1)
    return spark.createDataFrame([(k, parquet_bytes(c, folder(spark), k)) for k in ("uncompressed", "snappy", "lz4_raw", "gzip", "zstd")], "codec string, n_bytes long")


@_query("raw_store", CORPUS_SQL["urls"])
def raw_store(spark: SparkSession, d: str) -> DataFrame:
    """The uncompressed store."""
    return load(spark, d, "urls")


# --- other codecs ---------------------------------------------------------------------------------------------------------


@_query("bpe_first_round", f"WITH p AS (SELECT substr(value, i, 1) || substr(value, i + 1, 1) AS entry FROM (SELECT value, CAST(unnest(generate_series(1, length(value) - 1)) AS INTEGER) AS i FROM ({CORPUS_SQL['nations']}))) SELECT 256 AS token_id, entry, count(*) AS n FROM p GROUP BY entry ORDER BY n DESC, entry LIMIT 1")
def bpe_first_round(spark: SparkSession, d: str) -> DataFrame:
    return bpe.train_relational(load(spark, d, "nations"), 1)


@_query("bpe_nations_rounds")
def bpe_nations_rounds(spark: SparkSession, d: str) -> DataFrame:
    return bpe.train_relational(load(spark, d, "nations"), 6)


@_query("bpe_roundtrip", CORPUS_SQL["titles"])
def bpe_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "titles")
    dic = bpe.train(c, 10)
    return codec.decode(codec.encode(c, "value", dic).select("key", "payload"), "payload", dic)


@_query("symtab8_roundtrip", CORPUS_SQL["tweets"])
def symtab8_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "tweets")
    t = SymbolTable.train(c)
    return t.decode(t.encode(c).select("key", "payload"))


@_query("domain_codes", f"SELECT key, CAST(dense_rank() OVER (ORDER BY value) - 1 AS INTEGER) AS code FROM ({CORPUS_SQL['enums']})")
def domain_codes(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "enums")
    return light.DomainCodec.fit(c).encode(c)


@_query("domain_range", f"SELECT key, value FROM ({CORPUS_SQL['enums']}) WHERE value BETWEEN '2' AND '4'")
def domain_range(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "enums")
    dom = light.DomainCodec.fit(c)
    return dom.decode(dom.range_filter(dom.encode(c), "2", "4"))


@_query("domain_compressed", f"SELECT DISTINCT value, dense_rank() OVER (ORDER BY value) - 1 AS code FROM ({CORPUS_SQL['props']})")
def domain_compressed(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "props")
    dic = _trained(c, "props")
    return codec.decode(light.DomainCodec.fit(c).compressed(dic).select("code", "payload"), "payload", dic).withColumn("code", F.col("code").cast("long"))


@_query("rle_status", "WITH o AS (SELECT o_custkey, o_orderkey, o_orderstatus AS v, CASE WHEN lag(o_orderstatus) OVER w IS NOT DISTINCT FROM o_orderstatus AND row_number() OVER w > 1 THEN 0 ELSE 1 END AS fresh FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)), r AS (SELECT *, sum(fresh) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS run FROM o) SELECT o_custkey, any_value(v) AS value, min(o_orderkey) AS first, count(*) AS n FROM r GROUP BY o_custkey, run")
def rle_status(spark: SparkSession, d: str) -> DataFrame:
    return light.rle_encode(table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_orderstatus"), "o_orderkey", "o_orderstatus", ["o_custkey"])


@_query("delta_orderkey", "SELECT o_custkey, o_orderkey, o_orderkey - coalesce(lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 0) AS delta FROM orders")
def delta_orderkey(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "orders").select("o_custkey", "o_orderkey", F.col("o_orderkey").alias("v"))
    return light.delta_encode(rows, "o_orderkey", "v", ["o_custkey"])


@_query("delta_roundtrip", "SELECT o_custkey, o_orderkey, o_orderkey AS value FROM orders")
def delta_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return light.delta_decode(delta_orderkey(spark, d), "o_orderkey", ["o_custkey"])


@_query("for_quantity", "WITH f AS (SELECT l_orderkey, l_linenumber, CAST(floor(l_orderkey / 100) AS BIGINT) AS frame, CAST(l_quantity AS BIGINT) AS q FROM lineitem) SELECT l_orderkey, l_linenumber, frame, min(q) OVER w AS base, q - min(q) OVER w AS \"offset\", CAST(length(ltrim(bin(greatest(max(q) OVER w - min(q) OVER w, 1)), '0')) AS INTEGER) AS bits FROM f WINDOW w AS (PARTITION BY frame)")
def for_quantity(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_quantity").cast("long").alias("q"))
    return light.frame_of_reference(rows, F.floor(F.col("l_orderkey") / 100), "q", ["l_orderkey", "l_linenumber"])


@_query("null_suppress", "SELECT o_orderkey, CAST(length(h) / 2 AS INTEGER) AS n_bytes, h AS bytes FROM (SELECT o_orderkey, CASE WHEN length(x) % 2 = 1 THEN '0' || x ELSE x END AS h FROM (SELECT o_orderkey, printf('%X', o_orderkey) AS x FROM orders))")
def null_suppress(spark: SparkSession, d: str) -> DataFrame:
    n, h = light.null_suppress(F.col("o_orderkey"))
    return table(spark, d, "orders").select("o_orderkey", n.alias("n_bytes"), h.alias("bytes"))


# --- range joins and payload ids ---------------------------------------------------------------------------------------------


@_query("o10_range_join", "WITH c AS (" + CORPUS_SQL["reviews"] + "), b AS (SELECT CAST(range AS BIGINT) AS block_id, range * 65536 AS low, (range + 1) * 65536 AS high FROM range((SELECT CAST(sum(strlen(value)) // 65536 + 1 AS BIGINT) FROM c))), s AS (SELECT key, CAST(sum(strlen(value)) OVER (ORDER BY key) - strlen(value) AS BIGINT) AS start FROM (" + CORPUS_SQL["reviews"] + ")) SELECT key, block_id FROM s JOIN b ON start >= low AND start < high")
def range_join(spark: SparkSession, d: str) -> DataFrame:
    """Offsets into block ranges: an equi-join on bins of the block's width, then the exact bounds."""
    starts = blocks.layout(load(spark, d, "reviews")).select("key", "start")
    last = starts.agg(F.max("start")).first()[0]
    ranges = spark.range(0 if last is None else last // 65536 + 1).select(F.col("id").alias("block_id"), (F.col("id") * 65536).alias("low"), ((F.col("id") + 1) * 65536).alias("high"))
    joined = starts.withColumn("bin", F.floor(F.col("start") / 65536)).join(ranges.withColumn("bin", F.floor(F.col("low") / 65536)), "bin")
    return joined.where("start >= low AND start < high").select("key", "block_id")


@_query("o09_prefix_pairs", f"WITH {_GRAMS} SELECT a.token_id AS short_id, b.token_id AS long_id FROM every a JOIN every b ON a.entry_len < b.entry_len AND starts_with(b.entry, a.entry)")
def prefix_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Entries that begin other entries: an inequality join turned into equality on each proper prefix."""
    e = fixed_frame(load(spark, d, "titles"))
    cut = e.where("entry_len > 1").select(F.col("token_id").alias("long_id"), F.explode(F.transform(F.sequence(F.lit(1), F.col("entry_len") - 1), lambda n: F.substring("entry", F.lit(1), n))).alias("entry"))
    return cut.join(e.select(F.col("token_id").alias("short_id"), "entry"), "entry").select("short_id", "long_id")


@_query("o03_payload_filter", f"WITH {_T} SELECT key FROM t WHERE value = (SELECT value FROM t WHERE key = 10)")
def payload_filter(spark: SparkSession, d: str) -> DataFrame:
    store = _store(spark, d)
    return store.rows.where(F.col("payload") == F.lit(bytearray(payloads([load(spark, d, "titles").where("key = 10").first().value], store.dictionary)[0]))).select("key")


# --- streams --------------------------------------------------------------------------------------------------------------


def _events(spark: SparkSession, d: str) -> DataFrame:
    """events as a stream of files."""
    e = table(spark, d, "events")
    return spark.readStream.schema(e.schema).option("pathGlobFilter", "events.parquet").parquet(d)


def _finish(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there, and give its result as a table."""
    if mode == "append":
        out = folder(spark)
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", out + "-state").trigger(availableNow=True).outputMode(mode).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    if mode == "complete":  # every batch has all rows: the last one's folder is the result, and no row passes the driver
        out, last = folder(spark), []

        def put(batch: DataFrame, number: int) -> None:
            batch.write.parquet(f"{out}/{number}")
            last.append(f"{out}/{number}")

        stream.writeStream.foreachBatch(put).option("checkpointLocation", folder(spark)).trigger(availableNow=True).outputMode(mode).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(*last[-1:]) if last else spark.createDataFrame([], stream.schema)
    name = "s" + uuid.uuid4().hex
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", folder(spark)).trigger(availableNow=True).outputMode(mode).start().awaitTermination()
    return spark.table(name)


@_query("stream_encode", CORPUS_SQL["props"])
def stream_encode(spark: SparkSession, d: str) -> DataFrame:
    dic = _trained(load(spark, d, "props"), "props")
    stream = _events(spark, d).select(F.col("event_id").alias("key"), F.col("props").alias("value"))
    return codec.decode(_finish(spark, streaming.encode_stream(stream, "value", dic)).select("key", "payload"), "payload", dic)


_START = "epoch_us(time_bucket(INTERVAL {0}, ts))"


@_query("stream_ratio_tumbling", "SELECT epoch_us(date_trunc('hour', ts)) AS start, count(*) AS n, CAST(sum(strlen(props)) AS BIGINT) AS raw_bytes FROM events GROUP BY 1")
def stream_ratio_tumbling(spark: SparkSession, d: str) -> DataFrame:
    dic = _trained(load(spark, d, "props"), "props")
    got = _finish(spark, streaming.ratio_tumbling(_events(spark, d), "props", dic), "complete")
    return got.select(F.unix_micros("start").alias("start"), "n", "raw_bytes")


@_query("stream_ratio_sliding", "SELECT start, count(*) AS n, CAST(sum(b) AS BIGINT) AS raw_bytes FROM (SELECT strlen(props) AS b, unnest([epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) - k * 900000000 for k in range(4)]) AS start FROM events) GROUP BY 1")
def stream_ratio_sliding(spark: SparkSession, d: str) -> DataFrame:
    dic = _trained(load(spark, d, "props"), "props")
    got = _finish(spark, streaming.ratio_sliding(_events(spark, d), "props", dic), "complete")
    return got.select(F.unix_micros("start").alias("start"), "n", "raw_bytes")


@_query("stream_sessions", "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    got = _finish(spark, streaming.sessions(_events(spark, d)), "complete")
    return got.select("user_id", F.unix_micros("start").alias("start"), "n")


@_query("stream_dedupe", "SELECT DISTINCT event_id FROM events")
def stream_dedupe(spark: SparkSession, d: str) -> DataFrame:
    return _finish(spark, streaming.dedupe(_events(spark, d)).select("event_id"))


@_query("stream_followed_by", "SELECT a.user_id, a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def stream_followed_by(spark: SparkSession, d: str) -> DataFrame:
    e = _events(spark, d)
    return _finish(spark, streaming.followed_by(e.where("event_type = 'click'"), _events(spark, d).where("event_type = 'error'"))).select("user_id", "first_id", "second_id")


@_query("stream_online_trainer")
def stream_online_trainer(spark: SparkSession, d: str) -> DataFrame:
    return _finish(spark, streaming.online_trainer(_events(spark, d), "event_type", "props", bits=9), "update")


@_query("stream_lookup", f"WITH {_T} SELECT event_id AS key, t.value FROM events JOIN t ON t.key = event_id")
def stream_lookup(spark: SparkSession, d: str) -> DataFrame:
    return _finish(spark, streaming.lookup_stream(_events(spark, d).select(F.col("event_id").alias("key")), _store(spark, d)))


@_query("stream_retrain")
def stream_retrain(spark: SparkSession, d: str) -> DataFrame:
    poor = Dictionary([bytes([b]) for b in range(256)], bits=9)
    watch = streaming.Retrainer(poor, "props", 1.0, bits=9, threshold=2, sample=SAMPLE)
    out = folder(spark)
    _events(spark, d).writeStream.foreachBatch(watch).option("checkpointLocation", out).trigger(availableNow=True).start().awaitTermination()
    return spark.createDataFrame([(i, v) for i, v in enumerate(watch.versions)], "n int, dict_version string")


# --- registry -------------------------------------------------------------------------------------------------------------


def queries() -> dict:
    return {n: f for n, (f, _) in _QUERIES.items()} | relational.queries() | dict(WORKLOADS)


def oracle_sql() -> dict[str, str]:
    own = {n: s for n, (_, s) in _QUERIES.items() if s}
    return own | relational.oracle_sql() | {"w06_corpora": own["corpus_summary"]}


