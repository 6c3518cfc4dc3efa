"""Queries of the schemes themselves."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from enctopics.config import Config
from enctopics.functions import crypto
from enctopics.operators import abstracts, baselines, centres, dynamic, index, kestimate, metrics, relate, search, tokens, vectors
from enctopics.plans import batch, encrypted, static
from enctopics.registry import A, C10, N, OCC, P, SEP, STATIC, TF, centres_sql, eligible_sql, encrypted_sql, handle_sql, query
from enctopics.session import kept, new_path
from enctopics.sources import sinks
from enctopics.sources.tables import table
from enctopics.streaming import stream

CFG = Config()


def docs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents")


def postings(spark: SparkSession, d: str) -> DataFrame:
    return tokens.keywords(docs(spark, d), CFG.keywords_per_doc)


def trimmed(spark: SparkSession, d: str) -> DataFrame:
    return kestimate.trim(postings(spark, d))


def top_ten(a: DataFrame) -> DataFrame:
    return centres.by_document_count(index.token_stats(a), 10)


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


# ---- edge: tokens, encryption, index

@query("tokenize_counts", f"WITH {OCC} SELECT tok, count(*) AS n FROM occ GROUP BY tok")
def tokenize_counts(spark: SparkSession, d: str) -> DataFrame:
    return tokens.tokenize(docs(spark, d)).groupBy("tok").agg(F.count("*").alias("n"))


@query("phrase_counts", r"""WITH t AS (SELECT doc_id, regexp_extract_all(lower(text), '\p{L}{3,}') AS ts FROM documents),
    ph AS (SELECT unnest(list_transform(range(1, len(ts)), lambda i: ts[i] || ' ' || ts[i + 1])) AS tok FROM t WHERE len(ts) >= 2)
    SELECT tok, count(*) AS n FROM ph GROUP BY tok""")
def phrase_counts(spark: SparkSession, d: str) -> DataFrame:
    return tokens.phrases(docs(spark, d)).groupBy("tok").agg(F.count("*").alias("n"))


@query("keyword_postings", f"WITH {P} SELECT tok, doc_id, f FROM p")
def keyword_postings(spark: SparkSession, d: str) -> DataFrame:
    return postings(spark, d)


@query("keyword_postings_tf", f"WITH {TF}, d2 AS (SELECT tok FROM tf GROUP BY tok HAVING count(*) >= 2), r AS (SELECT tok, doc_id, f, row_number() OVER (PARTITION BY doc_id ORDER BY f DESC, tok) AS rk FROM tf JOIN d2 USING (tok)) SELECT tok, doc_id, f FROM r WHERE rk <= 10")
def keyword_postings_tf(spark: SparkSession, d: str) -> DataFrame:
    return tokens.keywords(docs(spark, d), 10, score="tf")


@query("keyword_postings_position", r"""WITH t AS (SELECT doc_id, regexp_extract_all(lower(text), '\p{L}{3,}') AS ts FROM documents),
    o AS (SELECT doc_id, unnest(ts) AS tok, unnest(range(0, len(ts))) AS pos FROM t), g AS (SELECT doc_id, tok, count(*) AS f, min(pos) AS pos FROM o GROUP BY doc_id, tok),
    d2 AS (SELECT tok FROM g GROUP BY tok HAVING count(*) >= 2), r AS (SELECT tok, doc_id, f, row_number() OVER (PARTITION BY doc_id ORDER BY pos, tok) AS rk FROM g JOIN d2 USING (tok))
    SELECT tok, doc_id, f FROM r WHERE rk <= 10""")
def keyword_postings_position(spark: SparkSession, d: str) -> DataFrame:
    return tokens.keywords(docs(spark, d), 10, score="position")


@query("encrypted_index", f"WITH {P} SELECT {handle_sql(CFG.key)} AS handle, doc_id, f FROM p")
def encrypted_index(spark: SparkSession, d: str) -> DataFrame:
    return index.encrypt(postings(spark, d), CFG.key)


@query("seal_roundtrip")
def seal_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Distinct tokens, envelopes, and whether each opens to its token."""
    t = postings(spark, d).select("tok").distinct()
    sealed = t.withColumn("sealed", crypto.seal(F.col("tok"), CFG.key))
    return sealed.select("tok", F.base64("sealed").alias("sealed"), (crypto.open_(F.col("sealed"), CFG.key) == F.col("tok")).alias("opens"))


@query("document_envelopes")
def document_envelopes(spark: SparkSession, d: str) -> DataFrame:
    e = docs(spark, d).select("doc_id", F.sha2("text", 256).alias("text_hash"), crypto.seal_document(F.col("text"), CFG.key).alias("sealed"))
    return e.select("doc_id", "text_hash", F.sha2("sealed", 256).alias("envelope_hash"))


@query("grouped_index", f"WITH {P} SELECT tok, doc_id, f FROM p")
def grouped_index(spark: SparkSession, d: str) -> DataFrame:
    return index.flatten(index.build(postings(spark, d)))


#: Documents in six batches: shares 500, 25, 50, 100, 20, 200 of 895, in the order of a keyed hash.
SIZES = (500, 25, 50, 100, 20, 200)
_BATCHES = "b AS (SELECT *, CASE " + " ".join(f"WHEN rn * 895 <= {sum(SIZES[: i + 1])} * nn THEN {i}" for i in range(6)) + " END AS batch_id FROM (SELECT *, row_number() OVER (ORDER BY sha256(doc_id || '#{seed}'), doc_id) AS rn, count(*) OVER () AS nn FROM documents))"


def batches(documents: DataFrame, seed: int = 0) -> DataFrame:
    """documents with a batch_id from 0, the base, to 5; hashes are ordered by partitions, without a single task."""
    keyed = documents.select("doc_id", F.sha2(F.concat(F.col("doc_id").cast("string"), F.lit(f"#{seed}")), 256).alias("tok"), F.lit(0).alias("df"))
    total = documents.count()
    at = F.when(F.lit(False), -1)
    for i in range(6):
        at = at.when(F.col("rank") * 895 <= sum(SIZES[: i + 1]) * total, i)
    numbered = centres.ranked(keyed.select("tok", "df")).join(keyed.select("doc_id", "tok"), "tok")
    return documents.join(numbered.select("doc_id", at.alias("batch_id")), "doc_id")


@query("temp_index", f"WITH {_BATCHES.format(seed=0)}, o AS (SELECT batch_id, doc_id, unnest(regexp_extract_all(lower(text), '\\p{{L}}{{3,}}')) AS tok FROM b), g AS (SELECT batch_id, doc_id, tok, count(*) AS f FROM o GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY f DESC, tok) AS rk FROM g) SELECT batch_id, tok, doc_id, f FROM r WHERE rk <= 10")
def temp_index(spark: SparkSession, d: str) -> DataFrame:
    dealt = kept(batches(docs(spark, d)))
    return tokens.keywords(dealt, 10, score="tf", min_df=1).join(dealt.select("doc_id", "batch_id"), "doc_id").select("batch_id", "tok", "doc_id", "f")


#: Postings with their batch: keywords over all documents, then dealt out.
_PB = f"{P}, {_BATCHES.format(seed=0)}, pb AS MATERIALIZED (SELECT p.*, batch_id FROM p JOIN b USING (doc_id))"


def dealt_postings(spark: SparkSession, d: str) -> DataFrame:
    documents = docs(spark, d)
    return kept(postings(spark, d).join(batches(documents).select("doc_id", "batch_id"), "doc_id"))


@query("index_merge", f"WITH {_PB} SELECT tok, doc_id, CAST(sum(f) AS BIGINT) AS f FROM (SELECT * FROM pb WHERE batch_id <= 3 UNION ALL SELECT * FROM pb WHERE batch_id >= 2) GROUP BY tok, doc_id")
def index_merge(spark: SparkSession, d: str) -> DataFrame:
    """Two indexes that overlap in batches 2 and 3."""
    pb = dealt_postings(spark, d)
    return index.merge(pb.where("batch_id <= 3"), pb.where("batch_id >= 2"))


@query("index_remove", f"WITH {_PB} SELECT tok, doc_id, f FROM pb WHERE batch_id <> 5")
def index_remove(spark: SparkSession, d: str) -> DataFrame:
    pb = dealt_postings(spark, d)
    return index.remove(pb.select("tok", "doc_id", "f"), pb.where("batch_id = 5"))


@query("new_tokens", f"WITH {_PB} SELECT DISTINCT tok FROM pb WHERE batch_id > 0 AND tok NOT IN (SELECT tok FROM pb WHERE batch_id = 0)")
def new_tokens(spark: SparkSession, d: str) -> DataFrame:
    pb = dealt_postings(spark, d)
    return index.new_tokens(pb.where("batch_id > 0"), pb.where("batch_id = 0"))


@query("token_stats", f"WITH {P} SELECT tok, df, tf, tf2 FROM st")
def token_stats(spark: SparkSession, d: str) -> DataFrame:
    return index.token_stats(postings(spark, d))


# ---- number of clusters

@query("df_trim", f"WITH {A} SELECT tok, doc_id, f FROM a")
def df_trim(spark: SparkSession, d: str) -> DataFrame:
    return trimmed(spark, d)


@query("df_trim_floor", f"WITH {P} SELECT p.tok, doc_id, f FROM p JOIN st USING (tok) WHERE df >= 3")
def df_trim_floor(spark: SparkSession, d: str) -> DataFrame:
    return kestimate.trim(postings(spark, d), 3)


@query("freq_matrix", f"WITH {A} SELECT tok, doc_id, f FROM a")
def freq_matrix(spark: SparkSession, d: str) -> DataFrame:
    return kestimate.frequency_matrix(trimmed(spark, d))


@query("norm_matrix", f"WITH {N} SELECT tok, doc_id, round(n, 6) AS n FROM n")
def norm_matrix(spark: SparkSession, d: str) -> DataFrame:
    return rounded(kestimate.normalise(trimmed(spark, d)), "n").select("tok", "doc_id", "n")


@query("importance_r", f"WITH {N} SELECT tok, doc_id, round(n / sum(n) OVER (PARTITION BY tok), 6) AS r FROM n")
def importance_r(spark: SparkSession, d: str) -> DataFrame:
    return rounded(kestimate.token_importance(kestimate.normalise(trimmed(spark, d))), "r").select("tok", "doc_id", "r")


@query("importance_s", f"WITH {N} SELECT tok, doc_id, round(n / sum(n) OVER (PARTITION BY doc_id), 6) AS s FROM n")
def importance_s(spark: SparkSession, d: str) -> DataFrame:
    return rounded(kestimate.document_importance(trimmed(spark, d)), "s").select("tok", "doc_id", "s")


@query("topic_similarity", f"WITH {N}, rs AS (SELECT tok, doc_id, n / sum(n) OVER (PARTITION BY tok) AS r, n / sum(n) OVER (PARTITION BY doc_id) AS s FROM n) SELECT x.tok, y.tok AS other, round(sum(x.r * y.s), 6) AS q FROM rs x JOIN rs y USING (doc_id) GROUP BY x.tok, y.tok")
def topic_similarity(spark: SparkSession, d: str) -> DataFrame:
    return rounded(kestimate.topic_similarity(trimmed(spark, d)), "q")


@query("separation", f"WITH {SEP} SELECT tok, round(q, 6) AS q FROM sep")
def separation(spark: SparkSession, d: str) -> DataFrame:
    return rounded(kestimate.separation(trimmed(spark, d)), "q")


@query("shared_similarity", f"WITH {N}, rs AS (SELECT tok, doc_id, n / sum(n) OVER (PARTITION BY tok) AS r, n / sum(n) OVER (PARTITION BY doc_id) AS s FROM n) SELECT x.tok, round(sum(CASE WHEN x.tok = y.tok THEN 0 ELSE x.r * y.s END), 6) AS shared FROM rs x JOIN rs y USING (doc_id) GROUP BY x.tok")
def shared_similarity(spark: SparkSession, d: str) -> DataFrame:
    """From the diagonal; the SQL adds up the rest of each row."""
    s = kestimate.shared_similarity(kestimate.separation(trimmed(spark, d)))
    return s.select("tok", F.abs(F.round("shared", 6)).alias("shared"))


@query("k_estimate", f"WITH {SEP} SELECT count(*) AS m, round(sum(q), 6) AS trace, CAST(ceil(sum(q) - 1e-9) AS BIGINT) AS k FROM sep")
def k_estimate(spark: SparkSession, d: str) -> DataFrame:
    return kestimate.estimate_k(trimmed(spark, d))


@query("k_by_language", f"WITH {A}, g AS (SELECT a.*, lang FROM a JOIN documents USING (doc_id)), v AS (SELECT lang, tok, f / max(f) OVER (PARTITION BY lang, doc_id) AS v, f / sum(f) OVER (PARTITION BY lang, doc_id) AS s FROM g), q AS (SELECT lang, tok, sum(v * s) / sum(v) AS q FROM v GROUP BY lang, tok) SELECT lang, count(*) AS m, round(sum(q), 6) AS trace, CAST(ceil(sum(q) - 1e-9) AS BIGINT) AS k FROM q GROUP BY lang")
def k_by_language(spark: SparkSession, d: str) -> DataFrame:
    by = trimmed(spark, d).join(docs(spark, d).select("doc_id", "lang"), "doc_id")
    return kestimate.estimate_k_by(by, "lang")


# ---- centres

@query("token_rank", f"WITH {A} SELECT tok, df, row_number() OVER (ORDER BY df DESC, tok) AS rank FROM ast")
def token_rank(spark: SparkSession, d: str) -> DataFrame:
    return centres.ranked(index.token_stats(trimmed(spark, d)))


@query("uniqueness_vs_top", f"WITH {C10}, u AS (SELECT DISTINCT a.doc_id FROM a JOIN c ON a.tok = c.centre) SELECT tok, count(*) FILTER (u.doc_id IS NULL) AS new_docs, count(u.doc_id) AS seen_docs FROM a LEFT JOIN u USING (doc_id) GROUP BY tok")
def uniqueness_vs_top(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return centres.uniqueness(a, a.join(F.broadcast(top_ten(a).select("tok")), "tok", "left_semi").select("doc_id"))


@query("eligible_centres", f"WITH RECURSIVE {eligible_sql()} SELECT tok, new_docs, seen_docs, rank FROM el")
def eligible_centres(spark: SparkSession, d: str) -> DataFrame:
    return centres.eligible(kept(trimmed(spark, d)))


@query("centrality", f"WITH RECURSIVE {centres_sql()} SELECT tok, new_docs, seen_docs, el.rank, round(q, 6) AS q, round(phi, 6) AS phi FROM sc el")
def centrality(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    return rounded(centres.centrality(centres.eligible(a), kestimate.separation(a)), "q", "phi")


def _centres(a: DataFrame, zero: str = "unit", inclusive: bool = False) -> DataFrame:
    k = kestimate.estimate_k(a).first()["k"]
    return rounded(centres.choose(a, k, kestimate.separation(a), inclusive, zero), "phi")


_CENTRES = "SELECT CAST(rank AS INT) AS rank, tok, new_docs, seen_docs, round(phi, 6) AS phi FROM ce"
_INFINITE = "CASE WHEN seen_docs > 0 THEN new_docs / seen_docs * q * (1 - q) WHEN q * (1 - q) = 0 THEN 0 ELSE CAST('inf' AS DOUBLE) END"


@query("centres", f"WITH RECURSIVE {centres_sql()} {_CENTRES}")
def chosen_centres(spark: SparkSession, d: str) -> DataFrame:
    return _centres(kept(trimmed(spark, d)))


@query("centres_infinite", f"WITH RECURSIVE {centres_sql(phi=_INFINITE)} {_CENTRES}")
def centres_infinite(spark: SparkSession, d: str) -> DataFrame:
    return _centres(kept(trimmed(spark, d)), "infinite")


@query("centres_inclusive", f"WITH RECURSIVE {centres_sql('>=')} {_CENTRES}")
def centres_inclusive(spark: SparkSession, d: str) -> DataFrame:
    return _centres(kept(trimmed(spark, d)), inclusive=True)


@query("centres_naive", f"WITH {A} SELECT CAST(row_number() OVER (ORDER BY df DESC, tok) AS INT) AS rank, tok, df FROM ast ORDER BY df DESC, tok LIMIT 100")
def centres_naive(spark: SparkSession, d: str) -> DataFrame:
    return centres.by_document_count(index.token_stats(trimmed(spark, d)), 100)


@query("centre_overlap", f"WITH {C10}, x AS (SELECT doc_id, count(*) AS c FROM a JOIN c ON a.tok = c.centre GROUP BY doc_id) SELECT count(*) AS docs, count(*) FILTER (c > 1) AS shared_docs, CAST(sum(c * (c - 1) / 2) AS BIGINT) AS pairs FROM x")
def centre_overlap(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return centres.overlap(top_ten(a), a)


# ---- relatedness

@query("cooccurrence", f"WITH {C10} SELECT centre, tok, co FROM agg")
def cooccurrence(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return relate.cooccurrence(a, top_ten(a))


@query("disparity", f"WITH {C10} SELECT centre, agg.tok, co, t.df + u.df - 2 * co AS dis FROM agg JOIN ast t ON t.tok = agg.tok JOIN ast u ON u.tok = centre")
def disparity(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return relate.disparity(a, top_ten(a))


_U = "u AS (SELECT centre, tok, doc_id, met.f / agg.a * met.fc / agg.b AS u FROM met JOIN agg USING (centre, tok))"
_PHI = """z AS (SELECT x.centre, x.tok, coalesce(t.doc_id, y.doc_id) AS doc_id, t.f, y.f AS fc FROM (SELECT centre, tok FROM agg) x JOIN a t ON t.tok = x.tok LEFT JOIN a y ON y.tok = x.centre AND y.doc_id = t.doc_id WHERE y.f IS NULL
        UNION ALL SELECT x.centre, x.tok, y.doc_id, NULL, y.f FROM (SELECT centre, tok FROM agg) x JOIN a y ON y.tok = x.centre LEFT JOIN a t ON t.tok = x.tok AND t.doc_id = y.doc_id WHERE t.f IS NULL),
    phi AS (SELECT centre, tok, doc_id, coalesce(f / sum(f) OVER w, 0) + coalesce(fc / sum(fc) OVER w, 0) AS phi FROM z WINDOW w AS (PARTITION BY centre, tok))"""


@query("cooc_value", f"WITH {C10}, {_U} SELECT centre, tok, doc_id, round(u, 6) AS u FROM u")
def cooc_value(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    return rounded(relate.value_by_document(a, top_ten(a)), "u")


@query("disp_value", f"WITH {C10}, {_PHI} SELECT centre, tok, doc_id, round(phi, 6) AS phi FROM phi")
def disp_value(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    return rounded(relate.disparity_by_document(a, top_ten(a)), "phi")


@query("relative_cooc", f"WITH {C10}, {_U}, {_PHI} SELECT centre, tok, doc_id, round(u, 6) AS rho FROM u UNION ALL SELECT centre, tok, doc_id, round(-phi, 6) FROM phi")
def relative_cooc(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    return rounded(relate.relative_by_document(a, top_ten(a)), "rho")


@query("relatedness", f"WITH {C10} SELECT centre, tok, round(r, 6) AS r FROM rel")
def relatedness(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return rounded(relate.relatedness(a, top_ten(a)), "r")


@query("relatedness_no_disparity", f"WITH {C10} SELECT centre, tok, round(g / (a * b) / t.tf, 6) AS r FROM agg JOIN ast t USING (tok)")
def relatedness_no_disparity(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return rounded(relate.relatedness(a, top_ten(a), "off"), "r")


@query("relatedness_symmetric", f"WITH {C10} SELECT centre, rel.tok, round(r - CASE WHEN u.tf > agg.b THEN (u.tf2 - agg.wc) / (u.tf - agg.b) ELSE 0 END / u.tf, 6) AS r FROM rel JOIN agg USING (centre, tok) JOIN ast u ON u.tok = centre")
def relatedness_symmetric(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    return rounded(relate.relatedness(a, top_ten(a), "symmetric"), "r")


_ASSIGN = """SELECT s.tok, CAST(coalesce(x.rank, -1) AS INT) AS cluster_id, false AS is_centre FROM ast s LEFT JOIN
    (SELECT tok, rank FROM {edges} JOIN c USING (centre) QUALIFY row_number() OVER (PARTITION BY tok ORDER BY {score} DESC, rank) = 1) x USING (tok) WHERE s.tok NOT IN (SELECT centre FROM c)
    UNION ALL SELECT centre, CAST(rank AS INT), true FROM c"""


@query("assign", f"WITH {C10} {_ASSIGN.format(edges='rel', score='round(r, 12)')}")
def assign(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    c = kept(top_ten(a))
    return relate.distribute(relate.relatedness(a, c), c, a)


@query("assign_by_count", f"WITH {C10} {_ASSIGN.format(edges='rel', score='co')}")
def assign_by_count(spark: SparkSession, d: str) -> DataFrame:
    a = trimmed(spark, d)
    c = kept(top_ten(a))
    return relate.distribute(relate.cooccurrence(a, c), c, a, score="co")


_STATIC = f"WITH RECURSIVE {STATIC} {_ASSIGN.format(edges='rel', score='round(r, 12)')}"


@query("static_clusters", _STATIC)
def static_clusters(spark: SparkSession, d: str) -> DataFrame:
    return static.cluster(docs(spark, d)).clusters


@query("static_clusters_literal")
def static_clusters_literal(spark: SparkSession, d: str) -> DataFrame:
    """Orphans go where the formula puts them."""
    return static.cluster(docs(spark, d), Config(orphan="literal")).clusters


# ---- abstracts and search

_ABS = f"""{P}, bl AS MATERIALIZED (SELECT lang, tok, CAST(sum(f) AS BIGINT) AS f FROM p JOIN documents USING (doc_id) GROUP BY lang, tok),
    own AS MATERIALIZED (SELECT tok, dense_rank() OVER (ORDER BY lang) AS cluster_id FROM (SELECT tok, lang FROM bl QUALIFY row_number() OVER (PARTITION BY tok ORDER BY f DESC, lang DESC) = 1)),
    ab AS MATERIALIZED (SELECT cluster_id, tok, tf AS f, row_number() OVER (PARTITION BY cluster_id ORDER BY tf DESC, tok) AS rank FROM own JOIN st USING (tok) QUALIFY rank <= 10)"""


def language_clusters(spark: SparkSession, d: str, p: DataFrame) -> DataFrame:
    """Languages as clusters: a token belongs to the language that has most of it."""
    by = p.join(docs(spark, d).select("doc_id", "lang"), "doc_id").groupBy("lang", "tok").agg(F.sum("f").alias("f"))
    own = by.groupBy("tok").agg(F.max(F.struct("f", "lang"))["lang"].alias("lang"))
    langs = own.select("lang").distinct().withColumn("cluster_id", F.row_number().over(Window.orderBy("lang")))  # a few languages
    return own.join(F.broadcast(langs), "lang").select("tok", "cluster_id")


@query("abstracts_by_language", f"WITH {_ABS} SELECT CAST(cluster_id AS INT) AS cluster_id, tok, f, CAST(rank AS INT) AS rank FROM ab")
def abstracts_by_language(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    return abstracts.build(language_clusters(spark, d, p), index.token_stats(p))


_QUERIES = r"q AS MATERIALIZED (SELECT item_id AS query_id, tok FROM (SELECT DISTINCT item_id, unnest(regexp_extract_all(lower(text), '\p{L}{3,}')) AS tok FROM benchmark) JOIN st USING (tok) QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY df, tok) <= 3)"
_FULL = """sc AS (SELECT query_id, p.doc_id, round(sum(p.f * ln((SELECT CAST(count(*) AS DOUBLE) FROM documents) / st.df)), 6) AS score FROM q JOIN p USING (tok) JOIN st USING (tok) GROUP BY query_id, p.doc_id),
    top AS (SELECT query_id, doc_id, score, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS INT) AS rank FROM sc QUALIFY rank <= 10)"""


def asked(spark: SparkSession, d: str, p: DataFrame) -> DataFrame:
    return kept(search.benchmark_queries(table(spark, d, "benchmark"), index.token_stats(p)))


@query("query_topics_jaccard", f"WITH {_ABS}, {_QUERIES} SELECT query_id, CAST(cluster_id AS INT) AS cluster_id, round(count(*) / ((SELECT count(*) FROM q y WHERE y.query_id = q.query_id) + (SELECT count(*) FROM ab z WHERE z.cluster_id = ab.cluster_id) - count(*)), 6) AS score FROM q JOIN ab USING (tok) GROUP BY query_id, cluster_id")
def query_topics_jaccard(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    ab = kept(abstracts.build(language_clusters(spark, d, p), index.token_stats(p)))
    return search.jaccard_abstracts(asked(spark, d, p), ab)


@query("query_topics")
def query_topics(spark: SparkSession, d: str) -> DataFrame:
    """Routes of the benchmark queries by document cosine."""
    made = static.cluster(docs(spark, d))
    q = asked(spark, d, made.trimmed)
    sims = vectors.doc_cosine(made.trimmed, q, made.abstracts)
    return search.route(search.score_abstracts(q, made.abstracts, sims))


@query("search_full", f"WITH {P}, {_QUERIES}, {_FULL} SELECT query_id, doc_id, score, rank FROM top")
def search_full(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    return search.full(asked(spark, d, p), p, docs(spark, d).count())


@query("search_pruned")
def search_pruned(spark: SparkSession, d: str) -> DataFrame:
    """Postings are stored by cluster; only the folders of routed clusters are read."""
    made = static.cluster(docs(spark, d))
    stats = kept(index.token_stats(made.trimmed))
    q = kept(search.benchmark_queries(table(spark, d, "benchmark"), stats))
    routed = kept(search.route(search.score_abstracts(q, made.abstracts, vectors.doc_cosine(made.trimmed, q, made.abstracts))))
    path = new_path(spark, "by-cluster")
    sinks.write_by_cluster(made.trimmed, made.clusters, path, 64)
    store = sinks.read_clusters(spark, path, routed, 64)
    return search.from_store(q, store, routed, stats, docs(spark, d).count())


@query("search_pruned_in_memory")
def search_pruned_in_memory(spark: SparkSession, d: str) -> DataFrame:
    """The same over the index as it is; the rows are those of search_pruned."""
    made = static.cluster(docs(spark, d))
    stats = kept(index.token_stats(made.trimmed))
    q = kept(search.benchmark_queries(table(spark, d, "benchmark"), stats))
    sims = vectors.doc_cosine(made.trimmed, q, made.abstracts)
    return search.pruned(q, made.trimmed, made.clusters, made.abstracts, docs(spark, d).count(), sims=sims, stats=stats)


# ---- the same in the cloud

@query("encrypted_k", encrypted_sql(f"WITH {SEP} SELECT count(*) AS m, round(sum(q), 6) AS trace, CAST(ceil(sum(q) - 1e-9) AS BIGINT) AS k FROM sep", CFG.key))
def encrypted_k(spark: SparkSession, d: str) -> DataFrame:
    cloud = encrypted.upload(kept(postings(spark, d)), CFG.key)
    return kestimate.estimate_k(kestimate.trim(cloud.index.withColumnRenamed("handle", "tok")))


@query("encrypted_clusters", encrypted_sql(f"SELECT tok AS handle, cluster_id, is_centre FROM ({_STATIC})", CFG.key))
def encrypted_clusters(spark: SparkSession, d: str) -> DataFrame:
    """What the cloud makes of handles."""
    return encrypted.run(docs(spark, d))[2].clusters.select(F.col("tok").alias("handle"), "cluster_id", "is_centre")


@query("encrypted_abstracts", encrypted_sql(f"WITH x AS ({_STATIC}), y AS (WITH {P} SELECT * FROM st), n AS (SELECT DISTINCT tok AS plain, {handle_sql(CFG.key)} AS tok FROM (SELECT unnest(regexp_extract_all(lower(text), '\\p{{L}}{{3,}}')) AS tok FROM documents)) SELECT cluster_id, plain AS tok, tf AS f, CAST(row_number() OVER (PARTITION BY cluster_id ORDER BY tf DESC, x.tok) AS INT) AS rank FROM x JOIN y USING (tok) JOIN n USING (tok) WHERE cluster_id >= 0 QUALIFY rank <= 10", CFG.key))
def encrypted_abstracts(spark: SparkSession, d: str) -> DataFrame:
    """Abstracts of the cloud's clusters, opened at the edge."""
    _, cloud, made = encrypted.run(docs(spark, d))
    return encrypted.revealed(made, cloud, CFG.key)


@query("encrypted_search", f"WITH {P}, {_QUERIES}, {_FULL} SELECT query_id, doc_id, score, rank FROM top")
def encrypted_search(spark: SparkSession, d: str) -> DataFrame:
    """Handles of the benchmark queries over the cloud's index: what the search over plain tokens gives."""
    p = kept(postings(spark, d))
    cloud = encrypted.upload(p, CFG.key)
    return search.full(encrypted.ask(asked(spark, d, p), CFG.key), cloud.index.withColumnRenamed("handle", "tok"), docs(spark, d).count())


@query("encrypted_search_pruned")
def encrypted_search_pruned(spark: SparkSession, d: str) -> DataFrame:
    """Routed at the edge by opened abstracts, answered in the cloud from the routed clusters of handles."""
    p, cloud, made = encrypted.run(docs(spark, d))
    q = asked(spark, d, kestimate.trim(p))
    tops = kept(encrypted.revealed(made, cloud, CFG.key))
    routed = kept(encrypted.routes(q, tops, p))
    inside = made.trimmed.join(made.clusters.select("tok", "cluster_id"), "tok")
    store = inside.join(routed.select("cluster_id").distinct(), "cluster_id", "left_semi")
    return search.from_store(encrypted.ask(q, CFG.key), store, routed, index.token_stats(made.trimmed), docs(spark, d).count())


@query("encrypted_update")
def encrypted_update(spark: SparkSession, d: str) -> DataFrame:
    """New tokens of the later batches, placed at the edge, as it pushes them: handles, envelopes and clusters."""
    pb = dealt_postings(spark, d)
    base = kept(pb.where("batch_id = 0").select("tok", "doc_id", "f"))
    state = batch.start(base)
    after = batch.step(state, pb.where("batch_id > 0").select("tok", "doc_id", "f"), Config(unit=1e9))
    fresh = after.clustering.clusters.join(base.select("tok").distinct(), "tok", "left_anti")
    pushed = encrypted.add(encrypted.upload(base, CFG.key), fresh, CFG.key)
    return pushed.select("handle", F.base64("sealed").alias("sealed"), "cluster_id")


@query("search_expanded")
def search_expanded(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    q = asked(spark, d, p)
    every = p.select("tok").distinct()
    return search.full(search.expand(q, vectors.doc_cosine(p, q, every)), p, docs(spark, d).count())


@query("search_cost", f"WITH {P}, {_QUERIES} SELECT query_id, (SELECT count(*) FROM p) AS visited, count(DISTINCT doc_id) AS docs_scored, 1.0::DOUBLE AS share FROM q JOIN p USING (tok) GROUP BY query_id")
def search_cost(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    return search.cost(asked(spark, d, p), p)


@query("search_cost_pruned")
def search_cost_pruned(spark: SparkSession, d: str) -> DataFrame:
    made = static.cluster(docs(spark, d))
    q = asked(spark, d, made.trimmed)
    routed = kept(search.route(search.score_abstracts(q, made.abstracts, vectors.doc_cosine(made.trimmed, q, made.abstracts))))
    return search.cost(q, made.trimmed, made.clusters, routed)


_TRUTH = "truth AS (SELECT DISTINCT item_id AS query_id, doc_id FROM documents JOIN benchmark ON contains(documents.text, substring(benchmark.text, 21, 60)) WHERE length(substring(benchmark.text, 21, 60)) = 60)"


@query("relevance", f"WITH {_TRUTH} SELECT query_id, doc_id FROM truth")
def relevance(spark: SparkSession, d: str) -> DataFrame:
    return search.relevance(table(spark, d, "benchmark"), docs(spark, d))


@query("tsap_at_10", f"WITH {P}, {_QUERIES}, {_FULL}, {_TRUTH}, h AS (SELECT top.query_id, rank, CASE WHEN truth.doc_id IS NULL THEN 0 ELSE 1 END AS rel FROM top LEFT JOIN truth USING (query_id, doc_id)), r AS (SELECT query_id, CASE WHEN rel = 1 THEN sum(rel) OVER (PARTITION BY query_id ORDER BY rank) / rank ELSE 0 END AS r FROM h), s AS (SELECT query_id, sum(r) AS s FROM r GROUP BY query_id) SELECT t.query_id, round(coalesce(s.s, 0) / 10, 6) AS tsap, count(*) AS n_relevant FROM truth t LEFT JOIN s USING (query_id) GROUP BY t.query_id, s.s")
def tsap_at_10(spark: SparkSession, d: str) -> DataFrame:
    return metrics.tsap(search_full(spark, d), relevance(spark, d))


# ---- batches

_COUNTS = f"""{_PB}, cnt AS MATERIALIZED (SELECT b.batch_id, count(DISTINCT pb.tok) AS new, (SELECT count(DISTINCT tok) FROM pb e WHERE e.batch_id < b.batch_id) AS existing,
    (SELECT count(DISTINCT tok) FROM pb n WHERE n.batch_id = b.batch_id AND n.tok NOT IN (SELECT tok FROM pb e WHERE e.batch_id < b.batch_id)) AS unseen
    FROM (SELECT unnest(range(1, 6)) AS batch_id) b JOIN pb ON pb.batch_id = b.batch_id GROUP BY b.batch_id)"""


def batch_counts(pb: DataFrame) -> DataFrame:
    """batch_id, new, existing, unseen of each batch but the base: one sum by token, none a batch."""
    first = pb.groupBy("tok").agg(F.min("batch_id").alias("first"))
    per = pb.select("tok", "batch_id").distinct().join(first, "tok").groupBy("batch_id").agg(F.count("*").alias("new"), F.count_if(F.col("first") == F.col("batch_id")).alias("unseen"))
    before = Window.orderBy("batch_id").rowsBetween(Window.unboundedPreceding, -1)  # six batches
    return per.withColumn("existing", F.sum("unseen").over(before)).where("batch_id > 0").select("batch_id", "new", "existing", "unseen")


@query("chi_square_batches", f"WITH {_COUNTS} SELECT CAST(batch_id AS INT) AS batch_id, new, existing, unseen, round((new - existing) * (new - existing) / existing, 6) AS stat, round((unseen - existing) * (unseen - existing) / existing, 6) AS stat_unseen FROM cnt")
def chi_square_batches(spark: SparkSession, d: str) -> DataFrame:
    c = batch_counts(dealt_postings(spark, d))
    stat = lambda n: F.round(dynamic.statistic(F.col(n), F.col("existing")), 6)
    return c.withColumns({"stat": stat("new"), "stat_unseen": stat("unseen")})


@query("chi_square_pair", f"WITH {_COUNTS} SELECT CAST(batch_id AS INT) AS batch_id, round((new - existing) * (new - existing) / (new + existing), 6) AS stat FROM cnt")
def chi_square_pair(spark: SparkSession, d: str) -> DataFrame:
    return batch_counts(dealt_postings(spark, d)).select("batch_id", F.round(dynamic.statistic(F.col("new"), F.col("existing"), "pair"), 6).alias("stat"))


@query("chi_square_unit", f"WITH {_COUNTS} SELECT CAST(batch_id AS INT) AS batch_id, round(10 * (1 - new / existing) * (1 - new / existing), 6) AS stat FROM cnt")
def chi_square_unit(spark: SparkSession, d: str) -> DataFrame:
    return batch_counts(dealt_postings(spark, d)).select("batch_id", F.round(dynamic.statistic(F.col("new"), F.col("existing"), unit=10.0), 6).alias("stat"))


@query("chi_square_by_cluster", f"WITH {_PB}, bl AS (SELECT lang, tok, sum(f) AS f FROM p JOIN documents USING (doc_id) GROUP BY lang, tok), own AS (SELECT tok, lang FROM bl QUALIFY row_number() OVER (PARTITION BY tok ORDER BY f DESC, lang DESC) = 1), x AS (SELECT lang, count(DISTINCT tok) FILTER (batch_id > 0) AS new, count(DISTINCT tok) FILTER (batch_id = 0) AS existing FROM pb JOIN own USING (tok) GROUP BY lang) SELECT round(sum((new - existing) * (new - existing) / existing), 6) AS stat, count(*) AS cells FROM x")
def chi_square_by_cluster(spark: SparkSession, d: str) -> DataFrame:
    """All later batches against the base, a cell for each cluster, with languages as clusters."""
    pb = dealt_postings(spark, d)
    own = language_clusters(spark, d, pb)
    rows = pb.select("tok", (F.col("batch_id") > 0).alias("later")).distinct().join(own, "tok")
    cells = rows.groupBy("cluster_id").agg(F.count_if("later").alias("new"), F.count_if(~F.col("later")).alias("existing"))
    return cells.agg(F.round(F.sum(dynamic.statistic(F.col("new"), F.col("existing"))), 6).alias("stat"), F.count("*").alias("cells"))


@query("accumulated_counts", f"WITH {_COUNTS} SELECT CAST(batch_id AS INT) AS batch_id, new, false AS recluster, CAST(sum(new) OVER (ORDER BY batch_id) AS BIGINT) AS accumulated FROM cnt")
def accumulated_counts(spark: SparkSession, d: str) -> DataFrame:
    return dynamic.accumulate(batch_counts(dealt_postings(spark, d)).select("batch_id", "new", F.lit(False).alias("recluster")))


_COH = _ABS + """, pr AS (SELECT p.tok, doc_id, p.f / sqrt(tf2) AS x FROM p JOIN st USING (tok)),
    sm AS (SELECT x.cluster_id, sum(u.x * v.x) AS s FROM ab x JOIN ab y ON x.cluster_id = y.cluster_id AND x.tok < y.tok JOIN pr u ON u.tok = x.tok JOIN pr v ON v.tok = y.tok AND v.doc_id = u.doc_id GROUP BY x.cluster_id),
    coh AS (SELECT z.cluster_id, coalesce(s, 0) / (p * (p - 1) / 2) AS coherency FROM (SELECT cluster_id, count(*) AS p FROM ab GROUP BY cluster_id HAVING count(*) > 1) z LEFT JOIN sm USING (cluster_id))"""


def _coherencies(spark: SparkSession, d: str) -> DataFrame:
    p = kept(postings(spark, d))
    ab = kept(abstracts.build(language_clusters(spark, d, p), index.token_stats(p)))
    return dynamic.abstract_coherency(ab, vectors.doc_cosine(p, ab, ab))


@query("abstract_coherency", f"WITH {_COH} SELECT CAST(cluster_id AS INT) AS cluster_id, round(coherency, 6) AS coherency FROM coh")
def abstract_coherency(spark: SparkSession, d: str) -> DataFrame:
    return rounded(_coherencies(spark, d), "coherency")


@query("theta", f"WITH {_COH} SELECT round(min(coherency), 6) AS theta FROM coh")
def theta(spark: SparkSession, d: str) -> DataFrame:
    return rounded(dynamic.threshold(_coherencies(spark, d)), "theta")


@query("attach_existing", f"""WITH {_ABS}, pr AS MATERIALIZED (SELECT p.tok, doc_id, p.f / sqrt(tf2) AS x FROM p JOIN st USING (tok)),
    s AS (SELECT u.tok, ab.cluster_id, ab.tok AS b, sum(u.x * v.x) AS sim FROM ab JOIN pr v ON v.tok = ab.tok JOIN pr u ON u.doc_id = v.doc_id WHERE u.tok NOT IN (SELECT tok FROM ab) GROUP BY u.tok, ab.cluster_id, ab.tok),
    m AS (SELECT tok, cluster_id, max(sim) AS sim FROM s GROUP BY tok, cluster_id)
    SELECT tok, CAST(cluster_id AS INT) AS cluster_id, round(sim, 6) AS sim FROM m WHERE sim > 0.1 QUALIFY row_number() OVER (PARTITION BY tok ORDER BY round(sim, 9) DESC, cluster_id) = 1""")
def attach_existing(spark: SparkSession, d: str) -> DataFrame:
    """All tokens outside the language abstracts, as if new, by document cosine beyond 0.1."""
    p = kept(postings(spark, d))
    ab = kept(abstracts.build(language_clusters(spark, d, p), index.token_stats(p)))
    new = p.select("tok").distinct().join(ab.select("tok"), "tok", "left_anti")
    return rounded(dynamic.best_existing(new, ab, vectors.doc_cosine(p, new, ab), 0.1), "sim")


@query("attach_full")
def attach_full(spark: SparkSession, d: str) -> DataFrame:
    """Tokens of the later batches against the clusters of the base; founders included."""
    pb = dealt_postings(spark, d)
    state = batch.start(kept(pb.where("batch_id = 0").select("tok", "doc_id", "f")))
    after = batch.step(state, pb.where("batch_id > 0").select("tok", "doc_id", "f"), Config(unit=1e9))
    return after.clustering.clusters


@query("attach_by_relatedness", f"""WITH {_PB}, base AS (SELECT tok, count(*) AS df FROM pb WHERE batch_id = 0 GROUP BY tok), c AS MATERIALIZED (SELECT tok AS centre, row_number() OVER (ORDER BY df DESC, tok) AS rank FROM base ORDER BY df DESC, tok LIMIT 10),
    nw AS (SELECT DISTINCT tok FROM pb WHERE batch_id > 0 AND tok NOT IN (SELECT tok FROM base)),
    m AS (SELECT c.centre, t.tok, sum(t.f) AS a, sum(x.f) AS b, sum(t.f * t.f) AS w, sum(t.f * t.f * x.f) AS g FROM c JOIN p x ON x.tok = c.centre JOIN p t ON t.doc_id = x.doc_id WHERE t.tok IN (SELECT tok FROM nw) GROUP BY c.centre, t.tok),
    r AS (SELECT m.tok, rank, (g / (a * b) - CASE WHEN st.tf > a THEN (st.tf2 - w) / (st.tf - a) ELSE 0 END) / st.tf AS r FROM m JOIN st USING (tok) JOIN c USING (centre))
    SELECT nw.tok, CAST(coalesce(rank, -1) AS INT) AS cluster_id FROM nw LEFT JOIN (SELECT tok, rank FROM r QUALIFY row_number() OVER (PARTITION BY tok ORDER BY round(r, 12) DESC, rank) = 1) USING (tok)""")
def attach_by_relatedness(spark: SparkSession, d: str) -> DataFrame:
    pb = dealt_postings(spark, d)
    base = pb.where("batch_id = 0")
    c = kept(centres.by_document_count(index.token_stats(base), 10))
    return dynamic.attach_by_relatedness(pb.select("tok", "doc_id", "f"), index.new_tokens(pb.where("batch_id > 0"), base), c)


def arriving(documents: DataFrame, seed: int = 0, n: int = CFG.keywords_per_doc) -> DataFrame:
    """Postings with batch_id: the keywords of each batch are chosen by what is known when it comes, the batch itself."""
    return arrived(kept(batches(documents, seed)), n)


def arrived(dealt: DataFrame, n: int = CFG.keywords_per_doc, found: DataFrame | None = None) -> DataFrame:
    """The same for documents with batch_id; found: their frequencies (doc_id, tok, f), where several dealings go by them."""
    if found is None:
        base = tokens.keywords(dealt.where("batch_id = 0"), n).withColumn("batch_id", F.lit(0))
        return kept(reduce(DataFrame.unionByName, [index.temporary(dealt.where(F.col("batch_id") == i), i, n) for i in range(1, len(SIZES))], base))
    place = dealt.select("doc_id", "batch_id")
    rows = found.join(place, "doc_id")
    known = (F.col("batch_id") > 0) | (F.col("df") >= 2)
    df = rows.groupBy("batch_id", "tok").agg(F.count("*").alias("df")).where(known)
    total = F.broadcast(place.groupBy("batch_id").agg(F.count("*").cast("double").alias("total")))
    return kept(tokens.best(rows.join(df, ["batch_id", "tok"]).join(total, "batch_id"), tokens.tfidf(), n).select("tok", "doc_id", "f", "batch_id"))


def run_batches(spark: SparkSession, d: str, cfg: Config, allow_recluster: bool = True) -> batch.State:
    pb = arriving(docs(spark, d))
    one = lambda i: kept(pb.where(F.col("batch_id") == i).select("tok", "doc_id", "f"))
    state = batch.start(one(0), cfg)
    for i in range(1, 6):
        state = batch.step(state, one(i), cfg, allow_recluster)
    return state


@query("batch_update_log")
def batch_update_log(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(list(run_batches(spark, d, Config(unit=10.0)).log), batch.LOG)


@query("batch_word_vectors")
def batch_word_vectors(spark: SparkSession, d: str) -> DataFrame:
    """Clusters after all batches with word vectors, trained on the documents that have come by then, for new tokens and their threshold; a token without one founds."""
    dealt = kept(batches(docs(spark, d)))
    pb = arrived(dealt)
    state = batch.start(kept(pb.where("batch_id = 0").select("tok", "doc_id", "f")), Config(unit=10.0))
    for i in range(1, len(SIZES)):
        words = lambda i=i: kept(vectors.word2vec(dealt.where(F.col("batch_id") <= i)))
        state = batch.step(state, kept(pb.where(F.col("batch_id") == i).select("tok", "doc_id", "f")), Config(unit=10.0), words=words)
    return state.clustering.clusters


@query("baseline_no_recluster")
def baseline_no_recluster(spark: SparkSession, d: str) -> DataFrame:
    return run_batches(spark, d, Config(unit=10.0), allow_recluster=False).clustering.clusters


@query("removal_update")
def removal_update(spark: SparkSession, d: str) -> DataFrame:
    """The last batch is taken out again."""
    pb = dealt_postings(spark, d)
    state = batch.start(kept(pb.select("tok", "doc_id", "f")))
    return batch.remove(state, pb.where("batch_id = 5")).clustering.clusters


@query("cold_start")
def cold_start(spark: SparkSession, d: str) -> DataFrame:
    return rounded(stream.cold_start(kept(postings(spark, d))), "sim")


# ---- baselines

@query("baseline_fixed_ten", f"WITH {C10} {_ASSIGN.format(edges='rel', score='co')}")
def baseline_fixed_ten(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fixed_k(kept(trimmed(spark, d)))


_PRIOR = centres_sql() + """, c AS MATERIALIZED (SELECT tok AS centre, rank FROM ce),
    met AS (SELECT c.centre, t.tok, count(*) AS co FROM c JOIN a x ON x.tok = c.centre JOIN a t ON t.doc_id = x.doc_id WHERE t.tok NOT IN (SELECT centre FROM c) GROUP BY c.centre, t.tok)"""


@query("baseline_prior", f"WITH RECURSIVE {_PRIOR} {_ASSIGN.format(edges='met', score='co')}")
def baseline_prior(spark: SparkSession, d: str) -> DataFrame:
    return baselines.prior_encrypted(kept(trimmed(spark, d)))


@query("baseline_hier")
def baseline_hier(spark: SparkSession, d: str) -> DataFrame:
    return baselines.hierarchical(kept(vectors.hashed_profiles(trimmed(spark, d))), 50)


@query("baseline_vector")
def baseline_vector(spark: SparkSession, d: str) -> DataFrame:
    vecs = vectors.word2vec(docs(spark, d)).join(trimmed(spark, d).select("tok").distinct(), "tok", "left_semi")
    return baselines.vector_kmeans(kept(vecs), 50)


@query("baseline_vector_est_k")
def baseline_vector_est_k(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    vecs = vectors.word2vec(docs(spark, d)).join(a.select("tok").distinct(), "tok", "left_semi")
    return baselines.vector_kmeans(kept(vecs), kestimate.estimate_k(a).first()["k"])


@query("baseline_random_kmeans")
def baseline_random_kmeans(spark: SparkSession, d: str) -> DataFrame:
    """Rounds and cost of k-means from arbitrary first centres."""
    rounds, cost = baselines.kmeans_cost(kept(vectors.hashed_profiles(trimmed(spark, d))), 50)
    return spark.createDataFrame([(rounds, cost)], "rounds int, cost double")


@query("subsumption_parents", f"""WITH {A}, b AS (SELECT x.tok, y.tok AS parent, count(*) AS n FROM a x JOIN a y USING (doc_id) WHERE x.tok <> y.tok GROUP BY x.tok, y.tok)
    SELECT b.tok, b.parent FROM b JOIN ast t ON t.tok = b.tok JOIN ast u ON u.tok = b.parent WHERE n >= 0.8 * t.df AND u.df > t.df QUALIFY row_number() OVER (PARTITION BY b.tok ORDER BY u.df, b.parent) = 1""")
def subsumption_parents(spark: SparkSession, d: str) -> DataFrame:
    return baselines.subsumption_parents(trimmed(spark, d))


@query("baseline_taxonomy")
def baseline_taxonomy(spark: SparkSession, d: str) -> DataFrame:
    return baselines.taxonomy(kept(trimmed(spark, d)), 50)


@query("baseline_taxonomy_est_k")
def baseline_taxonomy_est_k(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    return baselines.taxonomy(a, kestimate.estimate_k(a).first()["k"])


# ---- measures

_CELLS = "cell AS (SELECT vec_id AS id, label, unnest(range(1, len(embedding) + 1)) AS pos, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), mean AS (SELECT label, pos, count(*) AS n, avg(x) AS m FROM cell GROUP BY label, pos)"


def given(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label", F.col("embedding").alias("vec"))


_SIL = """pd AS (SELECT a.vec_id AS id, a.label, b.label AS l2, avg({d}) AS d FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id GROUP BY a.vec_id, a.label, b.label),
    e AS (SELECT id, max(d) FILTER (label = l2) AS a, min(d) FILTER (label <> l2) AS b FROM pd GROUP BY id) SELECT round(avg(CASE WHEN a IS NULL OR b IS NULL THEN 0 ELSE (b - a) / greatest(a, b) END), 6) AS sc FROM e"""
_DIST = "list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (CAST(z[1] AS DOUBLE) - z[2]) * (CAST(z[1] AS DOUBLE) - z[2])))"


@query("silhouette", "WITH " + _SIL.format(d=f"{_DIST}"))
def silhouette(spark: SparkSession, d: str) -> DataFrame:
    return metrics.silhouette(given(spark, d))


@query("calinski_harabasz", f"WITH {_CELLS}, g AS (SELECT pos, avg(x) AS gm FROM cell GROUP BY pos), t AS (SELECT count(DISTINCT id) AS n, count(DISTINCT label) AS k FROM cell), w AS (SELECT sum((x - m) * (x - m)) AS w FROM cell JOIN mean USING (label, pos)), b AS (SELECT sum(n * (m - gm) * (m - gm)) AS b FROM mean JOIN g USING (pos)) SELECT round((b / (k - 1)) / (w / (n - k)), 6) AS ci FROM t, w, b")
def calinski_harabasz(spark: SparkSession, d: str) -> DataFrame:
    return metrics.calinski_harabasz(given(spark, d))


@query("davies_bouldin", f"WITH {_CELLS}, dd AS (SELECT id, label, sqrt(sum((x - m) * (x - m))) AS d FROM cell JOIN mean USING (label, pos) GROUP BY id, label), s AS (SELECT label, avg(d) AS s FROM dd GROUP BY label), c AS (SELECT x.label AS l1, y.label AS l2, sqrt(sum((x.m - y.m) * (x.m - y.m))) AS m FROM mean x JOIN mean y ON x.pos = y.pos AND x.label <> y.label GROUP BY x.label, y.label), r AS (SELECT l1, max((s1.s + s2.s) / m) AS r FROM c JOIN s s1 ON s1.label = l1 JOIN s s2 ON s2.label = l2 GROUP BY l1) SELECT round(avg(r), 6) AS di FROM r")
def davies_bouldin(spark: SparkSession, d: str) -> DataFrame:
    return metrics.davies_bouldin(given(spark, d))


@query("coherency", "WITH len AS (SELECT vec_id, label, embedding, sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))) AS len FROM embeddings), pr AS (SELECT a.label, avg(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: CAST(z[1] AS DOUBLE) * z[2])) / (a.len * b.len)) AS c, count(*) AS np FROM len a JOIN len b ON a.label = b.label AND a.vec_id < b.vec_id GROUP BY a.label), s AS (SELECT label, count(*) AS p FROM len GROUP BY label) SELECT round(avg(c), 6) AS coherency, round(sum(c * p) / sum(p) FILTER (p > 1), 6) AS weighted, count(c) AS clusters, count(*) FILTER (p = 1) AS single FROM s LEFT JOIN pr USING (label)")
def coherency(spark: SparkSession, d: str) -> DataFrame:
    return metrics.coherency(given(spark, d))


@query("cluster_sizes", f"WITH {C10}, x AS ({_ASSIGN.format(edges='rel', score='round(r, 12)')}), g AS (SELECT cluster_id, count(*) AS n FROM x GROUP BY cluster_id) SELECT count(*) FILTER (cluster_id >= 0) AS clusters, CAST(sum(n) AS BIGINT) AS tokens, CAST(coalesce(sum(n) FILTER (cluster_id < 0), 0) AS BIGINT) AS orphans, max(n) FILTER (cluster_id >= 0) AS largest, round(avg(n) FILTER (cluster_id >= 0), 6) AS mean_size FROM g")
def cluster_sizes(spark: SparkSession, d: str) -> DataFrame:
    return metrics.cluster_sizes(assign(spark, d))


@query("purity_by_language", f"WITH {C10}, x AS ({_ASSIGN.format(edges='rel', score='round(r, 12)')}), o AS (SELECT tok, lang FROM a JOIN documents USING (doc_id) GROUP BY tok, lang QUALIFY row_number() OVER (PARTITION BY tok ORDER BY count(*) DESC, lang DESC) = 1), g AS (SELECT cluster_id, lang, count(*) AS n FROM x JOIN o USING (tok) WHERE cluster_id >= 0 GROUP BY cluster_id, lang), m AS (SELECT max(n) AS top, sum(n) AS every FROM g GROUP BY cluster_id) SELECT round(sum(top) / sum(every), 6) AS purity FROM m")
def purity_by_language(spark: SparkSession, d: str) -> DataFrame:
    a = kept(trimmed(spark, d))
    c = kept(top_ten(a))
    langs = a.join(docs(spark, d).select("doc_id", F.col("lang").alias("class")), "doc_id").groupBy("tok", "class").agg(F.count("*").alias("n"))
    return metrics.purity(relate.distribute(relate.relatedness(a, c), c, a), langs)


@query("leakage_profile", f"WITH {P}, g AS (SELECT df, tf, count(*) AS n FROM st GROUP BY df, tf) SELECT CAST(sum(n) AS BIGINT) AS tokens, count(*) AS profiles, count(*) FILTER (n = 1) AS unique_profiles FROM g")
def leakage_profile(spark: SparkSession, d: str) -> DataFrame:
    return metrics.leakage(postings(spark, d))

