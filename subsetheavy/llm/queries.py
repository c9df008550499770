"""The registered queries of the text operators and, where SQL can say them, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .common import table
from .decontamination import benchmark_leaks
from .embeddings import near_vectors
from .jaccard import jaccard_classes
from .language import languages
from .packing import packed
from .quality import quality_scores
from .secrets import secret_digests
from .tokens import read_ids, token_counts, write_ids
from .toxicity import toxicity_scores
from .urls import BLOCKED, url_verdicts


#: Words that a worker of these two queries keeps; nothing else runs there.
WORDS = 700_000


def tokenizer_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(token_counts(table(spark, sf_dir, "documents"), tokenizer_file(), words=WORDS))


def op4_token_id_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_ids(spark, write_ids(table(spark, sf_dir, "documents"), tokenizer_file(), words=WORDS))


def op6_embedding_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"), line=0.95)


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_verdicts(table(spark, sf_dir, "pages"))


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return benchmark_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_digests(table(spark, sf_dir, "documents"))



def op2_quality_boosted_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_toxicity_factorization(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_language_rank_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return languages(table(spark, sf_dir, "documents"))


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents"), k=5, share=80)


OP3_SQL = """
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws
  FROM documents),
s AS (
  SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')) END) AS sh FROM w),
n AS (SELECT doc_id, len(sh) AS n FROM s),
e AS (SELECT doc_id, unnest(sh) AS t FROM s),
links AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM e a JOIN e b ON a.t = b.t AND a.doc_id < b.doc_id
  JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, na.n, nb.n HAVING 100 * count(*) >= 80 * (na.n + nb.n - count(*))),
u AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
r(doc_id, hop) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.doc_id, u.b FROM r JOIN u ON u.a = r.hop),
c AS (SELECT doc_id, min(hop) AS component_id FROM r GROUP BY doc_id)
SELECT doc_id, CAST(n AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS representative FROM n JOIN c USING (doc_id)
"""


OP6_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, CASE WHEN embedding IS NULL OR len(embedding) = 0 OR len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) > 0
    OR len(list_filter(embedding, lambda x: x <> 0)) = 0 THEN NULL ELSE CAST(embedding AS DOUBLE[]) END AS e FROM embeddings),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.95),
r(vec_id, hop) AS (SELECT vec_id, vec_id FROM v UNION SELECT r.vec_id, links.b FROM r JOIN links ON links.a = r.hop),
c AS (SELECT vec_id, min(hop) AS component_id FROM r GROUP BY vec_id),
n AS (SELECT a AS vec_id, count(*) AS n FROM links GROUP BY a)
SELECT c.vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, component_id, c.vec_id = component_id AS kept FROM c LEFT JOIN n ON n.vec_id = c.vec_id
"""

OP8_SQL = f"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
q AS (SELECT page_id, regexp_extract(coalesce(rest, ''), '^[^?#]*') AS rest FROM u),
p AS (SELECT page_id, translate(regexp_extract(rest, '^[^/]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '/.*$', 0, 's') AS path FROM q),
r(rule_host, rule_path, verdict) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
fits AS (SELECT page_id, rule_host || rule_path AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(rule_host || rule_path) DESC, length(rule_host) DESC) AS k
  FROM p JOIN r ON ('.' || host) LIKE ('%.' || rule_host) AND starts_with(path, rule_path)),
b(site) AS (VALUES {", ".join(f"('{h}')" for h in BLOCKED)}),
listed AS (SELECT DISTINCT page_id FROM p JOIN b ON ('.' || host) LIKE ('%.' || site))
SELECT p.page_id, host, path, rule, coalesce(fits.verdict, CASE WHEN listed.page_id IS NULL THEN 'allow' ELSE 'block' END) AS verdict
FROM p LEFT JOIN fits ON fits.page_id = p.page_id AND k = 1 LEFT JOIN listed ON listed.page_id = p.page_id
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    made = (op1_best_fit_packing, op2_quality_boosted_trees, op3_ngram_jaccard_join, op4_token_id_records, op5_toxicity_factorization,
            op6_embedding_near_duplicates, op7_language_rank_order, op8_url_filter, op9_benchmark_decontamination, op10_secret_scan)
    return {f.__name__: f for f in made}


def oracle_sql() -> dict[str, str]:
    return {"op3_ngram_jaccard_join": OP3_SQL, "op6_embedding_near_duplicates": OP6_SQL, "op8_url_filter": OP8_SQL}
