"""Queries of the corpus operators, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, html_content, jaccard_join, language_id, media_boxes, paragraph_dedup, projected_nn, secret_scan, slack_packing, token_file
from .shared import spread, table


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(spread(table(spark, sf_dir, "documents")))


def op2_paragraph_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paragraph_dedup.dedup(spread(table(spark, sf_dir, "documents")))


def op3_projected_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return projected_nn.search(vectors, vectors.where("vec_id % 100 = 0"))


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return slack_packing.pack(spread(table(spark, sf_dir, "documents")))


def op5_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(spread(table(spark, sf_dir, "documents")))


def op6_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_file.store_and_read(spread(table(spark, sf_dir, "documents")))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(spread(table(spark, sf_dir, "documents")))


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join(spread(table(spark, sf_dir, "documents")))


def op9_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_boxes.describe(media_boxes.store(spread(table(spark, sf_dir, "documents"))))


def op10_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_content.extract(spread(table(spark, sf_dir, "pages")))


def queries() -> dict:
    return {f.__name__: f for f in (op1_language_id, op2_paragraph_dedup, op3_projected_neighbours, op4_best_fit_packing, op5_bpe_round_trip, op6_token_file, op7_secret_scan, op8_jaccard_join, op9_media_columns, op10_html_main_text)}


def _secrets_sql() -> str:
    """op7 in SQL: matches and the gaps between them give places; values are counted by owners and repositories."""
    kinds = []
    for number, (_, pattern, group, least) in enumerate(secret_scan.KINDS):
        p = "'" + pattern.replace("'", "''") + "'"
        fit = f"length(v) >= {least}" + (" AND regexp_matches(v, '[0-9]') AND regexp_matches(v, '[a-z]') AND regexp_matches(v, '[A-Z]')" if number == secret_scan.BASE else "")
        kinds.append(
            f"SELECT r, doc_id, owner, {number} AS kind, nth, v, {fit} AS fit, length(whole) AS size, sum(length(gap) + length(whole)) OVER (PARTITION BY r ORDER BY nth) AS stop"
            f" FROM (SELECT r, doc_id, owner, unnest(range(len(m))) AS nth, unnest(m) AS whole, unnest(g) AS v, unnest(s[1:len(m)]) AS gap"
            f" FROM (SELECT *, regexp_extract_all(t, {p}, 0) AS m, regexp_extract_all(t, {p}, {group}) AS g, regexp_split_to_array(t, {p}) AS s FROM d))"
        )
    told = lambda test: f"coalesce(string_agg([{', '.join(repr(k[0]) for k in secret_scan.KINDS)}][kind + 1] || ':' || start || ':' || stop, ',' ORDER BY start, kind) FILTER (WHERE {test}), '')"  # noqa: E731
    count = lambda test: f"count(*) FILTER (WHERE {test})"  # noqa: E731
    return (
        "WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(source, '') AS owner, coalesce(text, '') AS t FROM documents),"
        f" f AS (SELECT r, doc_id, owner, kind, v, (stop - size)::BIGINT AS start, stop::BIGINT AS stop FROM ({' UNION ALL '.join(kinds)}) WHERE fit),"
        f" o AS (SELECT v, count(DISTINCT owner) <= {secret_scan.MAX_OWNERS} AND count(DISTINCT (owner, doc_id)) <= {secret_scan.MAX_REPOSITORIES} AS live FROM f GROUP BY v),"
        " j AS (SELECT f.*, live FROM f JOIN o USING (v)),"
        f" k AS (SELECT * FROM j WHERE kind < {secret_scan.BASE} OR (live AND NOT EXISTS (SELECT 1 FROM j b WHERE b.r = j.r AND b.kind < {secret_scan.BASE} AND b.start < j.stop AND j.start < b.stop)))"
        f" SELECT d.doc_id, {count('kind = 0')} AS n_assign, {count('kind = 1')} AS n_access, {count('kind = 2')} AS n_hex, sha256({told(f'kind < {secret_scan.BASE}')}) AS base_sha256, {told('kind IS NOT NULL')} AS spans,"
        f" {count(f'kind = {secret_scan.BASE}')} AS n_owned, {count('live')} AS n_live, {count('NOT live')} AS n_example FROM d LEFT JOIN k ON d.r = k.r GROUP BY d.r, d.doc_id"
    )


# op8 in SQL: all pairs that share a shingle, by counts; then the least id that links reach.
JACCARD_SQL = r"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^ 	-]+') AS w FROM documents),
s AS (SELECT r, doc_id, CASE WHEN len(w) = 0 THEN []::VARCHAR[] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
  ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END AS g FROM d),
x AS (SELECT r, unnest(g) AS shingle, len(g) AS n FROM s),
links AS (SELECT a.r AS a, b.r AS b FROM x a JOIN x b USING (shingle) GROUP BY a.r, b.r, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
reach(a, b) AS (SELECT a, b FROM links UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a),
least AS (SELECT reach.a AS r, min(s.doc_id) AS component_id FROM reach JOIN s ON s.r = reach.b GROUP BY 1)
SELECT s.doc_id, len(g)::BIGINT AS n_shingles, coalesce(component_id, s.doc_id) AS component_id FROM s LEFT JOIN least USING (r)
"""


def oracle_sql() -> dict[str, str]:
    """SQL where DuckDB can say it; the other operators learn, hash, tokenize or pack, and tests hold them against brute force."""
    return {"op7_secret_scan": _secrets_sql(), "op8_jaccard_join": JACCARD_SQL}
