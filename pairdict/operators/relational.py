"""Relational operators around the codecs, each as one query on the given tables with the SQL that another engine can run."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..corpora import load, table

_QUERIES: dict[str, tuple] = {}


def _query(name: str, sql: str | None):
    def add(f):
        _QUERIES[name] = (f, sql)
        return f

    return add


def queries() -> dict:
    return {n: f for n, (f, _) in _QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in _QUERIES.items() if s}


@_query("o01_projection", "SELECT doc_id, strlen(text) AS n_bytes, length(text) AS n_points FROM documents")
def projection(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.char_length("text").cast("long").alias("n_points"))


@_query("o02_filters", "SELECT page_id, url FROM pages WHERE starts_with(url, 'https://') AND page_id BETWEEN 10 AND 5000 AND url IS NOT NULL AND page_id NOT IN (11, 13) AND regexp_matches(url, '[0-9]+') AND url LIKE '%/%'")
def filters(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages")
    return p.where(p.url.startswith("https://") & p.page_id.between(10, 5000) & p.url.isNotNull() & ~p.page_id.isin(11, 13) & p.url.rlike("[0-9]+") & p.url.like("%/%")).select("page_id", "url")


@_query("o04_join_broadcast", "SELECT c_nationkey, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    small = F.broadcast(table(spark, d, "nation"))  # one row a nation
    j = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(small, F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


_LINES = "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _lines(spark, d, hint):
    j = table(spark, d, "lineitem").join(table(spark, d, "orders").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


@_query("o05_join_merge", _LINES)
def join_merge(spark: SparkSession, d: str) -> DataFrame:
    return _lines(spark, d, "merge")


@_query("o05_join_hash", _LINES)
def join_hash(spark: SparkSession, d: str) -> DataFrame:
    return _lines(spark, d, "shuffle_hash")


@_query("o07_join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").join(table(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@_query("o07_join_full", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NULL AS no_document, l.doc_id IS NULL AS no_label FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full(spark: SparkSession, d: str) -> DataFrame:
    a, b = table(spark, d, "documents").select(F.col("doc_id").alias("a")), table(spark, d, "labels").select(F.col("doc_id").alias("b"))
    return a.join(b, F.col("a") == F.col("b"), "full").select(F.coalesce("a", "b").alias("doc_id"), F.col("a").isNull().alias("no_document"), F.col("b").isNull().alias("no_label"))


@_query("o08_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 0)")
def semi(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels").where("quality = 0"), "doc_id", "left_semi").select("doc_id", "lang")


@_query("o08_anti", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def anti(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


@_query("o11_as_of", """
SELECT o_orderkey, (SELECT max(e.event_id) FROM events e WHERE e.user_id = o.o_custkey AND e.ts = m.ts) AS event_id FROM orders o
JOIN (SELECT o_orderkey AS k, max(e.ts) AS ts FROM orders o2 JOIN events e ON e.user_id = o2.o_custkey AND e.ts <= o2.o_orderdate + INTERVAL 20 YEAR GROUP BY 1) m ON m.k = o.o_orderkey
""")
def as_of(spark: SparkSession, d: str) -> DataFrame:
    """The last event of a customer up to a date: both sides in one window a customer instead of a join on inequality."""
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("u"), (F.col("o_orderdate") + F.expr("INTERVAL 20 YEARS")).alias("t"), F.lit(1).alias("side"), F.col("o_orderkey"), F.lit(None).cast("long").alias("event_id"))
    e = table(spark, d, "events").select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("u").orderBy("t", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = o.unionByName(e).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w))
    return both.where("side = 1 AND event_id IS NOT NULL").select("o_orderkey", "event_id")


@_query("o12_interval_join", """
SELECT b.event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error'
AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR GROUP BY 1
""")
def interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Binned by the interval's width, so a hot user is split by time: each earlier event goes to its bin and the next."""
    six = 6 * 3600 * 1_000_000
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    a = e.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("us").alias("a_us"), F.explode(F.array(F.floor(F.col("us") / six), F.floor(F.col("us") / six) + 1)).alias("bin"))
    b = e.select("event_id", F.col("user_id").alias("u"), F.col("us").alias("b_us"), F.floor(F.col("us") / six).alias("bin"))
    return a.join(b, ["u", "bin"]).where((F.col("b_us") > F.col("a_us")) & (F.col("b_us") <= F.col("a_us") + six)).groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))


@_query("o13_grid", "SELECT f AS flag, q AS quantity FROM (SELECT DISTINCT l_returnflag AS f FROM lineitem) CROSS JOIN (SELECT DISTINCT l_quantity AS q FROM lineitem)")
def grid(spark: SparkSession, d: str) -> DataFrame:
    """A grid of the values of two columns, which are few: a cross join of what is distinct."""
    rows = table(spark, d, "lineitem")
    return rows.select(F.col("l_quantity").alias("quantity")).distinct().crossJoin(F.broadcast(rows.select(F.col("l_returnflag").alias("flag")).distinct()))


@_query("o14_explode", "SELECT doc_id, word, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, ' ')) AS word FROM documents) WHERE word <> '' GROUP BY 1, 2")
def explode(spark: SparkSession, d: str) -> DataFrame:
    words = table(spark, d, "documents").select("doc_id", F.explode(F.split("text", " ")).alias("word"))
    return words.where("word <> ''").groupBy("doc_id", "word").agg(F.count(F.lit(1)).alias("n"))


@_query("o15_aggregate", "SELECT lang, count(*) AS n, CAST(sum(strlen(text)) AS BIGINT) AS n_bytes, max(n_chars) AS longest FROM documents GROUP BY lang")
def aggregate(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("n_bytes"), F.max("n_chars").alias("longest"))


@_query("o16_sort_aggregate", "SELECT p_brand, max(p_name) AS last, min(p_type) AS first FROM part GROUP BY p_brand")
def sort_aggregate(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").groupBy("p_brand").agg(F.max("p_name").alias("last"), F.min("p_type").alias("first"))


@_query("o17_distinct", "SELECT lang, count(DISTINCT text) AS n_texts, count(DISTINCT source) AS n_sources FROM documents GROUP BY lang")
def distinct(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").groupBy("lang").agg(F.count_distinct("text").alias("n_texts"), F.count_distinct("source").alias("n_sources"))


_SUMS = "count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level FROM documents GROUP BY"


def _levels(df):
    return df.agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.grouping_id().cast("long").alias("level"))


@_query("o18_rollup", f"SELECT lang, source, {_SUMS} ROLLUP (lang, source)")
def rollup(spark: SparkSession, d: str) -> DataFrame:
    return _levels(table(spark, d, "documents").rollup("lang", "source"))


@_query("o18_cube", f"SELECT lang, source, {_SUMS} CUBE (lang, source)")
def cube(spark: SparkSession, d: str) -> DataFrame:
    return _levels(table(spark, d, "documents").cube("lang", "source"))


@_query("o18_grouping_sets", f"SELECT lang, source, {_SUMS} GROUPING SETS ((lang), (source), ())")
def grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return _levels(table(spark, d, "documents").groupingSets([["lang"], ["source"], []], "lang", "source"))


@_query("o19_ordered_aggregate", "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles FROM conversations GROUP BY conv_id")
def ordered_aggregate(spark: SparkSession, d: str) -> DataFrame:
    rows = F.sort_array(F.collect_list(F.struct("turn", "role")))
    return table(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(rows, lambda x: x["role"]), ",").alias("roles"))


@_query("o20_quantiles", None)
def quantiles(spark: SparkSession, d: str) -> DataFrame:
    """Sketches: length quantiles and distinct values by language."""
    return table(spark, d, "documents").groupBy("lang").agg(F.percentile_approx("n_chars", [0.5, 0.9, 0.99], 1000).alias("quantiles"), F.approx_count_distinct("text").alias("texts"))


@_query("o20_heavy_hitters", None)
def heavy_hitters(spark: SparkSession, d: str) -> DataFrame:
    """The most frequent four-byte strings of a corpus by a sketch of bounded size."""
    grams = load(spark, d, "titles").select(F.explode(F.transform(F.sequence(F.lit(1), F.length("value") - 3), lambda i: F.substring("value", i, F.lit(4)))).alias("g"))
    return grams.agg(F.expr("approx_top_k(g, 10, 10000)").alias("top")).select(F.explode("top").alias("t")).select("t.item", "t.count")


@_query("o21_pivot", "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY source")
def pivot(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().na.fill(0)


@_query("o21_unpivot", "SELECT l_orderkey, l_linenumber, name, value FROM lineitem UNPIVOT (value FOR name IN (l_quantity, l_extendedprice, l_tax))")
def unpivot(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").unpivot(["l_orderkey", "l_linenumber"], ["l_quantity", "l_extendedprice", "l_tax"], "name", "value")


@_query("o22_ranking", """
SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr, round(percent_rank() OVER p, 9) AS pr, ntile(4) OVER w AS quarter FROM orders
WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)
""")
def ranking(spark: SparkSession, d: str) -> DataFrame:
    w, p = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.round(F.percent_rank().over(p), 9).alias("pr"), F.ntile(4).over(w).alias("quarter"))


@_query("o23_analytic", """
SELECT conv_id, turn, lag(role) OVER w AS before, lead(role, 1, 'end') OVER w AS after, first_value(role) OVER w AS first,
nth_value(role, 2) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)
""")
def analytic(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role", 1, "end").over(w).alias("after"), F.first_value("role").over(w).alias("first"), F.nth_value("role", 2).over(whole).alias("second"))


@_query("o24_frames", """
SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS last_hour,
round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS last_three FROM events
""")
def frames(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    three = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return e.select("event_id", F.count(F.lit(1)).over(hour).alias("last_hour"), F.round(F.sum("value").over(three), 6).alias("last_three"))


@_query("o25_top", "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20 OFFSET 5")
def top(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").offset(5).limit(20)


@_query("o26_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier UNION SELECT n_regionkey + 100 FROM nation")
def union(spark: SparkSession, d: str) -> DataFrame:
    a, b, c = (table(spark, d, t).select(F.expr(k).alias("k")) for t, k in (("customer", "c_nationkey"), ("supplier", "s_nationkey"), ("nation", "n_regionkey + 100")))
    return a.unionByName(b).unionByName(c).distinct()


@_query("o26_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def intersect_all(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@_query("o26_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def except_all(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(table(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@_query("o27_stratified", None)
def stratified(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").sampleBy("lang", {"en": 0.2, "de": 0.5, "fr": 0.5, "es": 0.5}, 42).select("doc_id", "lang")


@_query("o28_dedupe", "SELECT text, min(doc_id) AS doc_id, count(*) AS n FROM documents GROUP BY text")
def dedupe(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").groupBy("text").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n"))


_LONGER = "SELECT doc_id, n_chars FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.lang = d.lang) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND n_chars < (SELECT max(n_chars) FROM documents)"


@_query("o29_subqueries", _LONGER)
def subqueries(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "documents").createOrReplaceTempView("documents")
    table(spark, d, "labels").createOrReplaceTempView("labels")
    return spark.sql(_LONGER)


_CHAIN = """WITH RECURSIVE s(flag, b) AS (SELECT l_returnflag, CAST(max(l_quantity) AS BIGINT) FROM lineitem GROUP BY l_returnflag),
c(flag, n, a, b) AS (SELECT flag, 1, CAST(0 AS BIGINT), b FROM s UNION ALL SELECT flag, n + 1, b, a + b FROM c WHERE n < 60) SELECT flag, n, a FROM c"""


@_query("o30_recursion", _CHAIN)
def recursion(spark: SparkSession, d: str) -> DataFrame:
    """A chain of sums for each return flag, from its largest quantity on."""
    table(spark, d, "lineitem").createOrReplaceTempView("lineitem")
    return spark.sql(_CHAIN)
