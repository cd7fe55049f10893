"""The queries opN_<name> and pipeline, and DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, decontam, fixity, language, line_dedup, packing, pii, simhash, token_counts, token_output
from .common import read_table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_graph_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = ann.nearest(read_table(spark, sf_dir, "embeddings"), "vec_id", "embedding", lambda c: c % 50 == 0, k=5)
    return found.select("query_id", "rank", F.col("id").alias("vec_id"), "score")


def op2_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.token_output(read_table(spark, sf_dir, "documents"), tokenizer_path(), end_id=1)


def op3_merkle_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Audit of the pages against a replica with deterministic damage."""
    pages = read_table(spark, sf_dir, "pages")
    return fixity.audit(pages, fixity.damaged(pages))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_report(read_table(spark, sf_dir, "documents"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.find_leaks(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(read_table(spark, sf_dir, "documents"), tokenizer_path())


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read_table(spark, sf_dir, "documents"), tokenizer_path())


def op9_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pseudonymize(read_table(spark, sf_dir, "documents")).select("doc_id", F.size("pii").alias("n_pii"), F.array_join("pii", ",").alias("kinds"), "text")


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(read_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_graph_neighbours, op2_token_output, op3_merkle_fixity, op4_line_dedup, op5_decontamination, op6_simhash, op7_token_counts, op8_packing, op9_pseudonyms, op10_language)}


OP3_SQL = f"""
WITH raw AS (
  SELECT page_id, coalesce(url, '') AS url, coalesce(html, '') AS html, substr(sha256(coalesce(CAST(page_id AS VARCHAR), '')), 1, 2) AS mark FROM pages
), rec AS (
  SELECT page_id, 'a' AS side, url, html FROM raw
  UNION ALL
  SELECT page_id, 'b', url, CASE WHEN mark < '03' AND length(html) > 0 THEN '?' || substr(html, 2) ELSE html END FROM raw WHERE mark <> '03'
  UNION ALL
  SELECT page_id, 'b', url, 'gained' FROM raw WHERE mark = '04'
), bytes AS (
  SELECT page_id, side, 'WARC/1.0' || nl || 'WARC-Type: response' || nl || 'WARC-Record-ID: <urn:page:' || coalesce(CAST(page_id AS VARCHAR), '') || '>' || nl || 'WARC-Date: {fixity.DATE}' || nl
         || 'WARC-Target-URI: ' || url || nl || 'Content-Type: application/http' || nl || 'Content-Length: ' || strlen(html) || nl || nl || html || nl || nl AS r
  FROM rec, (SELECT chr(13) || chr(10) AS nl)
), once AS (
  SELECT side, page_id, sha256(r) AS digest, strlen(r) AS bytes, count(*) AS copies, page_id // {fixity.SEGMENT} AS segment FROM bytes GROUP BY ALL
), placed AS (
  SELECT *, coalesce(sum(bytes * copies) OVER (PARTITION BY side, segment ORDER BY page_id, digest ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS "offset" FROM once
), hashed AS (
  SELECT *, sha256(digest || ':' || copies) AS h FROM once WHERE side = 'a'
), pages0 AS (
  SELECT o.page_id AS node, o.bytes, sha256('0:' || o.n || ':' || s.p) AS d
  FROM (SELECT page_id, sum(bytes * copies)::BIGINT AS bytes, count(*) AS n FROM hashed GROUP BY page_id) o
  JOIN (SELECT page_id, string_agg(p, ':' ORDER BY k) AS p FROM (SELECT page_id, k, sum(('0x' || substr(h, 1 + 15 * k, 15))::HUGEINT)::VARCHAR AS p FROM hashed, (SELECT unnest(range(4)::BIGINT[]) AS k) GROUP BY page_id, k) GROUP BY page_id) s
    ON s.page_id IS NOT DISTINCT FROM o.page_id
), l1 AS (
  SELECT up AS node, sum(bytes)::BIGINT AS bytes, sha256(string_agg(coalesce(node::VARCHAR, '') || '@' || lo || '-' || (lo + bytes) || ':' || d || ',', '' ORDER BY node NULLS FIRST)) AS d
  FROM (SELECT *, node // {fixity.FANOUT} AS up, coalesce(sum(bytes) OVER (PARTITION BY node // {fixity.FANOUT} ORDER BY node ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS lo FROM pages0) GROUP BY up
), l2 AS (
  SELECT up AS node, sum(bytes)::BIGINT AS bytes, sha256(string_agg(coalesce(node::VARCHAR, '') || '@' || lo || '-' || (lo + bytes) || ':' || d || ',', '' ORDER BY node NULLS FIRST)) AS d
  FROM (SELECT *, node // {fixity.FANOUT} AS up, coalesce(sum(bytes) OVER (PARTITION BY node // {fixity.FANOUT} ORDER BY node ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS lo FROM l1) GROUP BY up
), l3 AS (
  SELECT up AS node, sum(bytes)::BIGINT AS bytes, sha256(string_agg(coalesce(node::VARCHAR, '') || '@' || lo || '-' || (lo + bytes) || ':' || d || ',', '' ORDER BY node NULLS FIRST)) AS d
  FROM (SELECT *, node // {fixity.FANOUT} AS up, coalesce(sum(bytes) OVER (PARTITION BY node // {fixity.FANOUT} ORDER BY node ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS lo FROM l2) GROUP BY up
), matched AS (
  SELECT a.page_id AS ap, a.digest AS ad, a.copies AS ac, b.page_id AS bp, b.digest AS bd, b.copies AS bc
  FROM (SELECT * FROM once WHERE side = 'a') a FULL JOIN (SELECT * FROM once WHERE side = 'b') b ON a.page_id IS NOT DISTINCT FROM b.page_id AND a.digest = b.digest
), la AS (
  SELECT ap, ad, row_number() OVER (PARTITION BY ap ORDER BY ad) AS k FROM matched WHERE bd IS NULL
), lb AS (
  SELECT bp, bd, row_number() OVER (PARTITION BY bp ORDER BY bd) AS k FROM matched WHERE ad IS NULL
), status AS (
  SELECT 'a' AS side, ap AS page_id, ad AS digest, CASE WHEN ac = bc THEN 'ok' WHEN ac > bc THEN 'missing' ELSE 'extra' END AS status FROM matched WHERE ad = bd
  UNION ALL SELECT 'a', ap, ad, CASE WHEN bd IS NULL THEN 'missing' ELSE 'corrupt' END FROM la LEFT JOIN lb ON ap IS NOT DISTINCT FROM bp AND la.k = lb.k
  UNION ALL SELECT 'b', bp, bd, 'extra' FROM lb LEFT JOIN la ON ap IS NOT DISTINCT FROM bp AND la.k = lb.k WHERE ad IS NULL
)
SELECT p.segment, p.page_id, p.digest, p."offset", p.bytes, p.copies, l3.d AS root, s.status
FROM status s JOIN placed p ON p.side = s.side AND p.page_id IS NOT DISTINCT FROM s.page_id AND p.digest = s.digest LEFT JOIN l3 ON l3.node IS NOT DISTINCT FROM p.segment
"""

OP4_SQL = f"""
WITH split AS (
  SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents
), lines AS (
  SELECT doc_id, unnest(range(len(ls))) AS line_no, unnest(ls) AS line FROM split WHERE ls IS NOT NULL
), judged AS (
  SELECT *, min({{'d': doc_id, 'l': line_no}}) OVER (PARTITION BY line) AS first FROM lines WHERE length(trim(line, ' ' || chr(9) || chr(13) || chr(12) || chr(11))) > 0
), distinct_lines AS (
  SELECT line, first, length(line) AS n FROM judged WHERE length(line) >= {line_dedup.MIN_CHARS} GROUP BY ALL
), pairs AS (
  SELECT a.line AS x, b.line AS y, a.first AS fx, b.first AS fy
  FROM distinct_lines a JOIN (SELECT *, unnest([n - 2, n - 1, n]) AS m FROM distinct_lines) b ON a.n = b.m AND (a.n < b.n OR a.line < b.line)
  WHERE CASE WHEN a.n >= {line_dedup.LONG} THEN levenshtein(a.line, b.line) <= 2 ELSE b.n - a.n <= 1 AND levenshtein(a.line, b.line) <= 1 END
), ends AS (
  SELECT x AS line, fy < fx AS near FROM pairs UNION ALL SELECT y, fx < fy FROM pairs
), linked AS (
  SELECT line, bool_or(near) AS near, count(*) AS links FROM ends GROUP BY line
), found AS (
  SELECT j.doc_id, count(*) FILTER (WHERE {{'d': j.doc_id, 'l': j.line_no}} <> j.first) AS n_exact,
         count(*) FILTER (WHERE {{'d': j.doc_id, 'l': j.line_no}} = j.first AND l.near) AS n_near, coalesce(sum(l.links), 0) AS n_links, count(*) AS n_judged
  FROM judged j LEFT JOIN linked l USING (line) GROUP BY j.doc_id
)
SELECT s.doc_id, coalesce(len(s.ls), 0)::BIGINT AS n_lines, coalesce(f.n_judged, 0)::BIGINT AS n_judged, coalesce(f.n_exact, 0)::BIGINT AS n_exact,
       coalesce(f.n_near, 0)::BIGINT AS n_near, coalesce(f.n_links, 0)::BIGINT AS n_links,
       (coalesce(len(s.ls), 0) - coalesce(f.n_exact, 0) - coalesce(f.n_near, 0))::BIGINT AS n_kept
FROM split s LEFT JOIN found f ON f.doc_id = s.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_merkle_fixity": OP3_SQL, "op4_line_dedup": OP4_SQL}
