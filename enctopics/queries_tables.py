"""Queries of the operators around the schemes: sources, joins, sums, windows, sets, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from enctopics.operators import asof, tokens
from enctopics.operators.vectors import dot, norm
from enctopics.registry import OCC, P, handle_sql, query
from enctopics.sources.tables import conversation_docs, page_text, table

T = table


@query("page_text", r"""SELECT page_id AS doc_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '<(script|style)\b.*?</(script|style)>', ' ', 'gis'), '<[^>]*>', ' ', 'gs'),
    '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&'), '\s+', ' ', 'g')) AS text FROM pages""")
def pages_as_text(spark: SparkSession, d: str) -> DataFrame:
    return page_text(T(spark, d, "pages"))


@query("conversation_docs", "SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM conversations GROUP BY conv_id")
def conversations_as_docs(spark: SparkSession, d: str) -> DataFrame:
    return conversation_docs(T(spark, d, "conversations"))


@query("lang_filter", "SELECT doc_id, n_chars FROM documents WHERE lang = 'de'")
def lang_filter(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").where("lang = 'de'").select("doc_id", "n_chars")


@query("length_filter", "SELECT doc_id, lang FROM documents WHERE n_chars BETWEEN 500 AND 2000")
def length_filter(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").where(F.col("n_chars").between(500, 2000)).select("doc_id", "lang")


@query("quality_filter", "SELECT doc_id FROM documents SEMI JOIN (SELECT doc_id FROM labels WHERE quality = 1) USING (doc_id)")
def quality_filter(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id").join(T(spark, d, "labels").where("quality = 1").select("doc_id"), "doc_id", "left_semi")


@query("like_filter", "SELECT doc_id FROM documents WHERE text LIKE '%tion%' AND text NOT LIKE '%!!%'")
def like_filter(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").where(F.col("text").like("%tion%") & ~F.col("text").like("%!!%")).select("doc_id")


@query("null_safe_filter", "SELECT d.doc_id FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.toxic IS NOT DISTINCT FROM NULL")
def null_safe_filter(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id").join(T(spark, d, "labels"), "doc_id", "left").where(F.col("toxic").eqNullSafe(F.lit(None))).select("doc_id")


@query("docs_labels_inner", "SELECT doc_id, lang, quality FROM documents JOIN labels USING (doc_id)")
def docs_labels_inner(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").join(T(spark, d, "labels"), "doc_id").select("doc_id", "lang", "quality")


@query("docs_labels_left", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def docs_labels_left(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").join(T(spark, d, "labels"), "doc_id", "left").select("doc_id", "quality")


@query("docs_labels_full", "SELECT coalesce(d.doc_id, l.doc_id + 500) AS doc_id, lang, toxic FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id + 500")
def docs_labels_full(spark: SparkSession, d: str) -> DataFrame:
    """Labels are moved by 500, so that both sides have rows of their own."""
    moved = T(spark, d, "labels").select((F.col("doc_id") + 500).alias("doc_id"), "toxic")
    return T(spark, d, "documents").join(moved, "doc_id", "full").select("doc_id", "lang", "toxic")


@query("docs_labelled", "SELECT doc_id, source FROM documents SEMI JOIN labels USING (doc_id)")
def docs_labelled(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id", "source").join(T(spark, d, "labels"), "doc_id", "left_semi")


@query("docs_unlabelled", "SELECT doc_id, source FROM documents ANTI JOIN labels USING (doc_id)")
def docs_unlabelled(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id", "source").join(T(spark, d, "labels"), "doc_id", "left_anti")


@query("lang_pairs", "SELECT a.lang, b.lang AS other FROM (SELECT DISTINCT lang FROM documents) a CROSS JOIN (SELECT DISTINCT lang FROM documents) b")
def lang_pairs(spark: SparkSession, d: str) -> DataFrame:
    """A product of two sets of languages, the one place where a product is meant."""
    langs = T(spark, d, "documents").select("lang").distinct()
    return langs.crossJoin(langs.select(F.col("lang").alias("other")))


_BANDS = [(0, 100), (100, 1000), (1000, 5000), (5000, 20000), (20000, 1 << 40)]


@query("length_band_join", f"SELECT low, count(*) AS n FROM documents JOIN (VALUES {', '.join(map(str, _BANDS))}) b(low, high) ON n_chars >= low AND n_chars < high GROUP BY low")
def length_band_join(spark: SparkSession, d: str) -> DataFrame:
    bands = F.broadcast(spark.createDataFrame(_BANDS, "low long, high long"))
    return T(spark, d, "documents").join(bands, (F.col("n_chars") >= F.col("low")) & (F.col("n_chars") < F.col("high"))).groupBy("low").agg(F.count("*").alias("n"))


@query("orders_shipped_within", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAY GROUP BY o_orderkey")
def orders_shipped_within(spark: SparkSession, d: str) -> DataFrame:
    o, li = T(spark, d, "orders"), T(spark, d, "lineitem")
    soon = F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"))
    return o.join(li, (F.col("o_orderkey") == F.col("l_orderkey")) & soon).groupBy("o_orderkey").agg(F.count("*").alias("n"))


@query("event_asof", """SELECT p.event_id, s.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p
    LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') s ON s.user_id = p.user_id AND (s.ts, s.event_id) <= (p.ts, p.event_id) QUALIFY row_number() OVER (PARTITION BY p.event_id ORDER BY s.ts DESC, s.event_id DESC) = 1""")
def event_asof(spark: SparkSession, d: str) -> DataFrame:
    e = T(spark, d, "events")
    return asof.last_before(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "event_id", "last_view")


@query("token_cooc_pairs", f"WITH {P} SELECT x.tok AS a, y.tok AS b, count(*) AS n FROM p x JOIN p y ON x.doc_id = y.doc_id AND x.tok < y.tok GROUP BY x.tok, y.tok HAVING count(*) >= 2")
def token_cooc_pairs(spark: SparkSession, d: str) -> DataFrame:
    p = tokens.keywords(T(spark, d, "documents"), 10)
    a, b = p.select(F.col("tok").alias("a"), "doc_id"), p.select(F.col("tok").alias("b"), "doc_id")
    return a.join(b, "doc_id").where("a < b").groupBy("a", "b").agg(F.count("*").alias("n")).where("n >= 2")


@query("revenue_by_region", "SELECT r_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def revenue_by_region(spark: SparkSession, d: str) -> DataFrame:
    li, o, c = T(spark, d, "lineitem"), T(spark, d, "orders"), T(spark, d, "customer")
    places = T(spark, d, "nation").join(T(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    by = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return by.groupBy("r_name").agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("docs_by_lang", "SELECT lang, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, min(n_chars) AS least, max(n_chars) AS most FROM documents GROUP BY lang")
def docs_by_lang(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"), F.min("n_chars").alias("least"), F.max("n_chars").alias("most"))


@query("distinct_tokens", f"WITH {OCC} SELECT lang, count(DISTINCT tok) AS types FROM occ JOIN documents USING (doc_id) GROUP BY lang")
def distinct_tokens(spark: SparkSession, d: str) -> DataFrame:
    rows = T(spark, d, "documents").select("lang", F.explode(F.array_distinct(tokens.token_array(F.col("text")))).alias("tok"))
    return rows.distinct().groupBy("lang").agg(F.count("*").alias("types"))


@query("approx_tokens")
def approx_tokens(spark: SparkSession, d: str) -> DataFrame:
    return tokens.tokenize(T(spark, d, "documents")).agg(F.approx_count_distinct("tok", 0.02).alias("about"), F.hll_sketch_estimate(F.hll_sketch_agg("tok", 14)).alias("sketched"))


_CUBE = "SELECT lang, source, count(*) AS n, CAST(grouping(lang) AS INT) AS all_langs, CAST(grouping(source) AS INT) AS all_sources FROM documents GROUP BY "


def _grouped(g) -> DataFrame:
    return g.agg(F.count("*").alias("n"), F.grouping("lang").cast("int").alias("all_langs"), F.grouping("source").cast("int").alias("all_sources"))


@query("docs_cube", _CUBE + "CUBE (lang, source)")
def docs_cube(spark: SparkSession, d: str) -> DataFrame:
    return _grouped(T(spark, d, "documents").cube("lang", "source"))


@query("docs_rollup", _CUBE + "ROLLUP (lang, source)")
def docs_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _grouped(T(spark, d, "documents").rollup("lang", "source"))


@query("docs_grouping_sets", _CUBE + "GROUPING SETS ((lang), (source))")
def docs_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return _grouped(T(spark, d, "documents").groupingSets([("lang",), ("source",)], "lang", "source"))


@query("lang_pivot", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def lang_pivot(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


@query("having_df", f"WITH {P} SELECT tok, df FROM st WHERE df >= 5")
def having_df(spark: SparkSession, d: str) -> DataFrame:
    return tokens.keywords(T(spark, d, "documents"), 10).groupBy("tok").agg(F.count("*").alias("df")).where("df >= 5")


@query("filtered_aggregates", "SELECT event_type, count(*) FILTER (value > 50) AS high, round(sum(value) FILTER (value <= 50), 4) AS low_sum FROM events GROUP BY event_type")
def filtered_aggregates(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.sum(F.when(F.col("value") <= 50, F.col("value"))), 4).alias("low_sum"))


@query("percentile_chars", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
def percentile_chars(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@query("stddev_chars", "SELECT lang, round(stddev_samp(n_chars), 4) AS sd, round(avg(n_chars), 4) AS mean, round(var_pop(n_chars), 2) AS var FROM documents GROUP BY lang")
def stddev_chars(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").groupBy("lang").agg(F.round(F.stddev_samp("n_chars"), 4).alias("sd"), F.round(F.avg("n_chars"), 4).alias("mean"), F.round(F.var_pop("n_chars"), 2).alias("var"))


@query("token_rank_lang", "SELECT doc_id, lang, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS quarter, round(percent_rank() OVER v, 6) AS pr FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars DESC, doc_id), v AS (PARTITION BY lang ORDER BY n_chars DESC)")
def token_rank_lang(spark: SparkSession, d: str) -> DataFrame:
    w, v = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id"), Window.partitionBy("lang").orderBy(F.desc("n_chars"))
    return T(spark, d, "documents").select("doc_id", "lang", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"))


_BY_USER = "PARTITION BY user_id ORDER BY ts, event_id"


def by_user() -> Window:
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@query("event_gaps", f"SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER ({_BY_USER})) AS gap_us, lead(event_type) OVER ({_BY_USER}) AS next_type FROM events")
def event_gaps(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "events").select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(by_user()).cast("timestamp"))).alias("gap_us"), F.lead("event_type").over(by_user()).alias("next_type"))


@query("moving_avg_value", f"SELECT event_id, round(avg(value) OVER ({_BY_USER} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS avg3 FROM events")
def moving_avg_value(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "events").select("event_id", F.round(F.avg("value").over(by_user().rowsBetween(-2, 0)), 6).alias("avg3"))


@query("events_last_hour", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def events_last_hour(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return T(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@query("user_first_last", "SELECT user_id, arg_min(event_type, (ts, event_id)) AS first, arg_max(event_type, (ts, event_id)) AS last FROM events GROUP BY user_id")
def user_first_last(spark: SparkSession, d: str) -> DataFrame:
    at = F.struct("ts", "event_id")
    return T(spark, d, "events").groupBy("user_id").agg(F.min_by("event_type", at).alias("first"), F.max_by("event_type", at).alias("last"))


@query("docs_sorted", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id")
def docs_sorted(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id")


@query("topk_tokens", f"WITH {OCC} SELECT tok, count(*) AS n FROM occ GROUP BY tok ORDER BY n DESC, tok LIMIT 20")
def topk_tokens(spark: SparkSession, d: str) -> DataFrame:
    return tokens.tokenize(T(spark, d, "documents")).groupBy("tok").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "tok").limit(20)


@query("page_two", f"WITH {OCC} SELECT tok, count(*) AS n FROM occ GROUP BY tok ORDER BY n DESC, tok LIMIT 20 OFFSET 20")
def page_two(spark: SparkSession, d: str) -> DataFrame:
    return tokens.tokenize(T(spark, d, "documents")).groupBy("tok").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "tok").offset(20).limit(20)


def _by_lang(spark: SparkSession, d: str, lang: str) -> DataFrame:
    return tokens.tokenize(T(spark, d, "documents").where(F.col("lang") == lang)).select("tok")


_SETS = OCC + ", x AS (SELECT tok FROM occ JOIN documents USING (doc_id) WHERE lang = 'es'), y AS (SELECT tok FROM occ JOIN documents USING (doc_id) WHERE lang = 'fr')"
for _name, _op, _f in (
    ("tokens_union", "UNION", lambda x, y: x.union(y).distinct()), ("tokens_intersect", "INTERSECT", lambda x, y: x.intersect(y)), ("tokens_except", "EXCEPT", lambda x, y: x.subtract(y)),
    ("tokens_union_all", "UNION ALL", lambda x, y: x.union(y)), ("tokens_intersect_all", "INTERSECT ALL", lambda x, y: x.intersectAll(y)), ("tokens_except_all", "EXCEPT ALL", lambda x, y: x.exceptAll(y)),
):
    query(_name, f"WITH {_SETS} SELECT tok FROM x {_op} SELECT tok FROM y")(lambda spark, d, f=_f: f(_by_lang(spark, d, "es"), _by_lang(spark, d, "fr")))


@query("string_functions", "SELECT doc_id, lower(substring(text, 1, 10)) AS head, CAST(length(text) AS INT) AS n, concat_ws('-', lang, source) AS tag, regexp_replace(substring(text, 1, 30), '[aeiou]', '*', 'g') AS masked, CAST(levenshtein(source, 'src10') AS INT) AS edits, trim(split_part(text, '.', 1)) AS first_part FROM documents")
def string_functions(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "documents").select("doc_id", F.lower(F.substring("text", 1, 10)).alias("head"), F.length("text").alias("n"), F.concat_ws("-", "lang", "source").alias("tag"), F.regexp_replace(F.substring("text", 1, 30), "[aeiou]", "*").alias("masked"), F.levenshtein("source", F.lit("src10")).alias("edits"), F.trim(F.split_part("text", F.lit("."), F.lit(1))).alias("first_part"))


@query("date_functions", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '1999-01-01') AS INT) AS days, strftime(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH, '%Y-%m-%d') AS later FROM orders")
def date_functions(spark: SparkSession, d: str) -> DataFrame:
    day = F.col("o_orderdate").cast("date")
    return T(spark, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.year(day).alias("y"), F.quarter(day).alias("q"), F.datediff(F.lit("1999-01-01").cast("date"), day).alias("days"), F.date_format(F.add_months(day, 2), "yyyy-MM-dd").alias("later"))


@query("math_functions", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS ln, round(sqrt(l_quantity), 6) AS root, round(pow(l_discount, 2), 6) AS sq, abs(l_linenumber - 4) AS off, l_linenumber % 3 AS m FROM lineitem")
def math_functions(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("l_linenumber")
    return T(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("ln"), F.round(F.sqrt("l_quantity"), 6).alias("root"), F.round(F.pow("l_discount", 2), 6).alias("sq"), F.abs(n - 4).alias("off"), (n % 3).alias("m"))


_KW = f"WITH {P}, g AS (SELECT doc_id, list_sort(list(tok)) AS toks, list(f) AS fs FROM p GROUP BY doc_id)"


def _lists(spark: SparkSession, d: str) -> DataFrame:
    return tokens.keywords(T(spark, d, "documents"), 10).groupBy("doc_id").agg(F.sort_array(F.collect_list("tok")).alias("toks"), F.collect_list("f").alias("fs"))


@query("array_functions", _KW + " SELECT doc_id, CAST(len(toks) AS INT) AS n, array_to_string(list_transform(toks, lambda t: t || length(t)), ',') AS sized, CAST(len(list_filter(toks, lambda t: length(t) > 8)) AS INT) AS long_ones, CAST(list_sum(fs) AS BIGINT) AS total, list_has_any(toks, ['the', 'und']) AS common, CAST(len(list_intersect(toks, ['the', 'und'])) AS INT) AS hits FROM g")
def array_functions(spark: SparkSession, d: str) -> DataFrame:
    two = F.array(F.lit("the"), F.lit("und"))
    return _lists(spark, d).select("doc_id", F.size("toks").alias("n"), F.array_join(F.transform("toks", lambda t: F.concat(t, F.length(t))), ",").alias("sized"), F.size(F.filter("toks", lambda t: F.length(t) > 8)).alias("long_ones"), F.aggregate("fs", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"), F.arrays_overlap("toks", two).alias("common"), F.size(F.array_intersect("toks", two)).alias("hits"))


@query("map_functions", f"WITH {P} SELECT doc_id, string_agg(tok, ',' ORDER BY tok) AS keys, CAST(sum(f) AS BIGINT) AS total FROM p GROUP BY doc_id")
def map_functions(spark: SparkSession, d: str) -> DataFrame:
    m = tokens.keywords(T(spark, d, "documents"), 10).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("tok", "f"))).alias("m"))
    return m.select("doc_id", F.array_join(F.sort_array(F.map_keys("m")), ",").alias("keys"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


@query("posexplode_vector", "SELECT vec_id, CAST(unnest(range(0, len(embedding))) AS INT) AS pos, round(CAST(unnest(embedding) AS DOUBLE), 6) AS x FROM embeddings")
def posexplode_vector(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "x")).withColumn("x", F.round(F.col("x").cast("double"), 6))


@query("json_functions", "SELECT event_id, json_extract_string(props, '$.page') AS page, len(props) > 2 AS some FROM events")
def json_functions(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "events").select("event_id", F.get_json_object("props", "$.page").alias("page"), (F.length("props") > 2).alias("some"))


@query("vector_cosine", "WITH m AS (SELECT embedding AS e FROM embeddings WHERE vec_id = (SELECT min(vec_id) FROM embeddings)) SELECT vec_id, round(list_sum(list_transform(list_zip(embedding, e), lambda z: CAST(z[1] AS DOUBLE) * z[2])) / sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))) / sqrt(list_sum(list_transform(e, lambda x: CAST(x AS DOUBLE) * x))), 6) AS cosine FROM embeddings, m")
def vector_cosine(spark: SparkSession, d: str) -> DataFrame:
    """Cosine of every vector with the first one."""
    v = T(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    first = v.agg(F.min_by("v", "vec_id").alias("e"))
    return v.crossJoin(F.broadcast(first)).select("vec_id", F.round(dot(F.col("v"), F.col("e")) / norm(F.col("v")) / norm(F.col("e")), 6).alias("cosine"))


_HOUR = "epoch_us(ts) // 3600000000"


@query("events_tumbling", f"SELECT CAST({_HOUR} AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def events_tumbling(spark: SparkSession, d: str) -> DataFrame:
    w = T(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.floor(F.unix_micros("window.start") / 3_600_000_000).cast("long").alias("hour"), "event_type", "n")


@query("events_sliding", "SELECT CAST(h AS BIGINT) AS start_half, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 1800000000, epoch_us(ts) // 1800000000 - 1]) AS h FROM events) GROUP BY h")
def events_sliding(spark: SparkSession, d: str) -> DataFrame:
    w = T(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n"))
    return w.select(F.floor(F.unix_micros("window.start") / 1_800_000_000).cast("long").alias("start_half"), "n")


@query("events_session", f"WITH g AS (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER ({_BY_USER})) < 7200000000 THEN 0 ELSE 1 END AS opens FROM events), s AS (SELECT *, sum(opens) OVER ({_BY_USER}) AS no FROM g) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, no")
def events_session(spark: SparkSession, d: str) -> DataFrame:
    w = T(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "2 hours")).agg(F.count("*").alias("n"))
    return w.select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")


@query("hash_sample", "SELECT doc_id FROM documents WHERE substring(sha256(CAST(doc_id AS VARCHAR)), 1, 2) < '40'")
def hash_sample(spark: SparkSession, d: str) -> DataFrame:
    """A sampling operator: about a quarter, the same whenever it is drawn."""
    return T(spark, d, "documents").where(F.substring(F.sha2(F.col("doc_id").cast("string"), 256), 1, 2) < "40").select("doc_id")


@query("strat_sample", "SELECT doc_id, lang FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY sha256(CAST(doc_id AS VARCHAR)), doc_id) <= 50")
def strat_sample(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("lang").orderBy(F.sha2(F.col("doc_id").cast("string"), 256), "doc_id")
    return T(spark, d, "documents").select("doc_id", "lang", F.row_number().over(w).alias("rn")).where("rn <= 50").drop("rn")


@query("sql_face", f"WITH {P} SELECT {handle_sql('fixture-key')} AS handle, df FROM st WHERE df >= 3")
def sql_face(spark: SparkSession, d: str) -> DataFrame:
    """Views and a registered function, from SQL."""
    from enctopics.functions import sql

    sql.register(spark, "fixture-key", postings=tokens.keywords(T(spark, d, "documents"), 10))
    return spark.sql("SELECT token_handle(tok) AS handle, count(*) AS df FROM postings GROUP BY tok HAVING count(*) >= 3")
