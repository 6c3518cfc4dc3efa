"""Queries by name, with the SQL that gives the same rows where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from enctopics.functions.crypto import mac_pads

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"two queries are called {name}")
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


#: DuckDB: parts that queries share. Postings p (tok, doc_id, f), trimmed postings a, statistics st, and others.
OCC = r"occ AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}{3,}')) AS tok FROM documents)"
TF = OCC + ", tf AS (SELECT doc_id, tok, count(*) AS f FROM occ GROUP BY doc_id, tok)"


def postings_sql(n: int = 10, min_df: int = 2, name: str = "tok") -> str:
    return TF + f""", wdf AS (SELECT tok, count(*) AS wdf FROM tf GROUP BY tok HAVING count(*) >= {min_df}),
        rk AS (SELECT tok, doc_id, f, row_number() OVER (PARTITION BY doc_id ORDER BY round(f * ln((SELECT CAST(count(*) AS DOUBLE) FROM documents) / wdf), 6) DESC, tok) AS rk
            FROM tf JOIN wdf USING (tok)),
        p AS MATERIALIZED (SELECT {name} AS tok, doc_id, f FROM rk WHERE rk <= {n}),
        st AS MATERIALIZED (SELECT tok, count(*) AS df, CAST(sum(f) AS BIGINT) AS tf, CAST(sum(f * f) AS BIGINT) AS tf2 FROM p GROUP BY tok)"""


P = postings_sql()
A = P + """, a AS MATERIALIZED (SELECT p.* FROM p SEMI JOIN (SELECT tok FROM st WHERE df * (SELECT count(*) FROM st) >= (SELECT sum(df) FROM st)) k USING (tok)),
        ast AS MATERIALIZED (SELECT tok, count(*) AS df, CAST(sum(f) AS BIGINT) AS tf, CAST(sum(f * f) AS BIGINT) AS tf2 FROM a GROUP BY tok)"""
N = A + ", n AS (SELECT tok, doc_id, f, f / max(f) OVER (PARTITION BY doc_id) AS n FROM a)"
SEP = N + """, sep AS MATERIALIZED (SELECT tok, sum(n * s) / sum(n) AS q FROM (SELECT tok, n, f / sum(f) OVER (PARTITION BY doc_id) AS s FROM n) GROUP BY tok)"""
def handle_sql(key: str, tok: str = "tok") -> str:
    """The keyed digest of a token."""
    inner, outer = (f"unhex('{x.hex()}')" for x in mac_pads(key))
    return f"sha256({outer} || unhex(sha256({inner} || encode({tok}))))"


def encrypted_sql(sql: str, key: str) -> str:
    """SQL over P, with handles for tokens from the index on."""
    return sql.replace(P, postings_sql(name=handle_sql(key)))


#: The ten most widespread tokens as centres, and the pairs that meet.
C10 = A + """, c AS MATERIALIZED (SELECT tok AS centre, row_number() OVER (ORDER BY df DESC, tok) AS rank FROM ast ORDER BY df DESC, tok LIMIT 10),
        met AS MATERIALIZED (SELECT c.centre, t.tok, t.doc_id, x.f AS fc, t.f FROM c JOIN a x ON x.tok = c.centre JOIN a t ON t.doc_id = x.doc_id WHERE t.tok NOT IN (SELECT centre FROM c)),
        agg AS MATERIALIZED (SELECT centre, tok, count(*) AS co, CAST(sum(f) AS BIGINT) AS a, CAST(sum(fc) AS BIGINT) AS b, CAST(sum(f * f) AS BIGINT) AS w, CAST(sum(f * f * fc) AS BIGINT) AS g, CAST(sum(fc * fc) AS BIGINT) AS wc FROM met GROUP BY centre, tok),
        rel AS MATERIALIZED (SELECT centre, tok, co, (g / (a * b) - CASE WHEN t.tf > a THEN (t.tf2 - w) / (t.tf - a) ELSE 0 END) / t.tf AS r FROM agg JOIN ast t USING (tok))"""

#: The walk over tokens by rank, one row a step, with the documents covered so far; {more} is > or >=.
WALK = """tk AS MATERIALIZED (SELECT row_number() OVER (ORDER BY count(*) DESC, tok) AS rank, tok, list(doc_id) AS docs FROM a GROUP BY tok),
        w AS (SELECT CAST(0 AS BIGINT) AS rank, CAST(NULL AS VARCHAR) AS tok, CAST([] AS BIGINT[]) AS covered, CAST(0 AS BIGINT) AS new_docs, CAST(0 AS BIGINT) AS seen_docs, false AS kept
            UNION ALL SELECT rank, tok, CASE WHEN new_docs {more} seen_docs THEN list_distinct(list_concat(covered, docs)) ELSE covered END, new_docs, seen_docs, new_docs {more} seen_docs
            FROM (SELECT t.rank, t.tok, t.docs, w.covered, len(t.docs) - len(list_intersect(t.docs, w.covered)) AS new_docs, len(list_intersect(t.docs, w.covered)) AS seen_docs FROM w JOIN tk t ON t.rank = w.rank + 1)),
        el AS MATERIALIZED (SELECT tok, new_docs, seen_docs, rank FROM w WHERE kept)"""


def eligible_sql(more: str = ">") -> str:
    return f"{SEP}, {WALK.format(more=more)}"


def centres_sql(more: str = ">", phi: str = "new_docs / greatest(seen_docs, 1) * q * (1 - q)") -> str:
    return eligible_sql(more) + f""", sc AS MATERIALIZED (SELECT el.*, q, {phi} AS phi FROM el JOIN sep USING (tok)),
        ce AS MATERIALIZED (SELECT row_number() OVER (ORDER BY round(phi, 9) DESC, new_docs DESC, tok) AS rank, tok, new_docs, seen_docs, phi FROM (SELECT * EXCLUDE (rank) FROM sc) QUALIFY rank <= (SELECT ceil(sum(q) - 1e-9) FROM sep))"""


#: The static scheme: chosen centres, and the pairs that meet, as for the ten above.
STATIC = centres_sql() + ", c AS MATERIALIZED (SELECT tok AS centre, rank FROM ce)" + C10[C10.index("LIMIT 10)") + len("LIMIT 10)") :]
