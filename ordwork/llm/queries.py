"""The queries of this subpackage: each operator over its whole table, with production parameters."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork.llm.common import table

#: Tokens beyond which a document counts as over the limit.
TOKEN_LIMIT = 512
#: The rules of the URL filter's query.
RULES = [
    ("com/en/", "block"),
    ("example.com/en/7", "allow"),
    ("net/de/", "allow"),
    ("example.net/de/8", "block"),
    ("org/es/", "block"),
]


def tokenizer_path() -> str:
    """The vocabulary file, found on the driver only."""
    if "ORDWORK_TOKENIZER" in os.environ:
        return os.environ["ORDWORK_TOKENIZER"]
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.line_dedup import dedup_lines

    return dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_lines", "n_removed", "text")


def url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.url_filter import Rule, judge, mine

    rules = [Rule(text, verdict) for text, verdict in RULES]
    pages, labels = table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels")
    bad = labels.groupBy(F.col("doc_id").alias("page_id")).agg(F.max((F.col("toxic") == 1) | (F.col("quality") == 0)).alias("bad"))
    mined = mine(pages.select("page_id", "url").join(bad, "page_id"), "url", "bad")
    return judge(pages.select("page_id", "url"), rules, mined).select("page_id", "host", "path", "rule", "verdict", F.col("mined").cast("long").alias("mined"))


def embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.embedding_dedup import near_vectors

    rows = near_vectors(table(spark, sf_dir, "embeddings"))
    return rows.withColumn("kept", F.col("vec_id") == F.col("component_id"))


def html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.html_extract import main_text

    return main_text(table(spark, sf_dir, "pages")).withColumn("n_chars", F.char_length("text").cast("long"))


def decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.decontaminate import report

    rows = report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return rows.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )


def suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.suffix_dedup import digest

    return digest(table(spark, sf_dir, "documents"))


def simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.simhash import near_duplicates

    rows = near_duplicates(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.token_count import count_tokens

    rows = count_tokens(table(spark, sf_dir, "documents"), tokenizer_path())
    return rows.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > TOKEN_LIMIT).alias("over_limit"))


def bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.bpe_codec import digests

    return digests(table(spark, sf_dir, "documents"), tokenizer_path())


def language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ordwork.llm.language_id import fit, held_out, predict

    docs = table(spark, sf_dir, "documents")
    rows = predict(docs, fit(docs.where(~held_out())))
    return rows.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def queries():
    return {
        "op1_line_dedup": line_dedup,
        "op2_url_filter": url_filter,
        "op3_embedding_dedup": embedding_dedup,
        "op4_decontamination": decontamination,
        "op5_token_counts": token_counts,
        "op6_suffix_dedup": suffix_dedup,
        "op7_bpe_codec": bpe_codec,
        "op8_html_extract": html_extract,
        "op9_language_id": language_id,
        "op10_simhash": simhash,
    }


LINE_DEDUP_SQL = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS i
  FROM documents WHERE text IS NOT NULL
), f AS (
  SELECT *, trim(line, ' ' || chr(9) || chr(13)) AS bare FROM l
), n AS (
  SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY i) - 1 AS pos FROM f WHERE bare <> ''
), w AS (
  SELECT doc_id, pos, bare AS a, lead(bare, 1) OVER d AS b, lead(bare, 2) OVER d AS c FROM n WINDOW d AS (PARTITION BY doc_id ORDER BY pos)
), late AS (
  SELECT doc_id, pos FROM (SELECT *, row_number() OVER (PARTITION BY a, b, c ORDER BY doc_id, pos) AS k FROM w WHERE c IS NOT NULL) WHERE k > 1
), gone AS (
  SELECT DISTINCT doc_id, pos + unnest([0, 1, 2]) AS pos FROM late
), gone_lines AS (
  SELECT n.doc_id, n.i FROM n JOIN gone USING (doc_id, pos)
), rest AS (
  SELECT f.doc_id, string_agg(f.line, chr(10) ORDER BY f.i) AS text FROM f ANTI JOIN gone_lines g ON f.doc_id = g.doc_id AND f.i = g.i GROUP BY f.doc_id
)
SELECT d.doc_id,
  (SELECT count(*) FROM n WHERE n.doc_id = d.doc_id)::BIGINT AS n_lines,
  (SELECT count(*) FROM gone WHERE gone.doc_id = d.doc_id)::BIGINT AS n_removed,
  CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(r.text, '') END AS text
FROM documents d LEFT JOIN rest r ON r.doc_id = d.doc_id
"""

DECONTAMINATION_SQL = r"""
WITH dw AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents
), iw AS (
  SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark
), win AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(list_slice(w, s + 1, s + least(len(w), 10)), ' ') AS g
  FROM iw, unnest(range(len(w) - least(len(w), 10) + 1)) AS t(s) WHERE len(w) > 0
), sizes AS (SELECT DISTINCT n FROM win), words AS (SELECT DISTINCT n, string_split(g, ' ')[1] AS head FROM win),
cand AS (
  SELECT doc_id, s, z.n, array_to_string(list_slice(w, s + 1, s + z.n), ' ') AS g FROM dw, unnest(range(len(w))) AS t(s), sizes z
  WHERE s + z.n <= len(w) AND w[s + 1] IN (SELECT head FROM words)
), hit AS (
  SELECT c.doc_id, c.s, c.n, win.item_id FROM cand c JOIN win ON c.n = win.n AND c.g = win.g
), pos AS (
  SELECT doc_id, count(DISTINCT p) AS k FROM (SELECT doc_id, s + unnest(range(n)) AS p FROM (SELECT DISTINCT doc_id, s, n FROM hit)) GROUP BY doc_id
), its AS (
  SELECT doc_id, count(*) AS k, string_agg(i, ',' ORDER BY i) AS l FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS i FROM hit) GROUP BY doc_id
)
SELECT dw.doc_id, len(w)::BIGINT AS n_words, coalesce(pos.k, 0)::BIGINT AS n_hit, coalesce(its.k, 0)::BIGINT AS n_items,
  sha256(coalesce(its.l, '')) AS items_sha256, coalesce(pos.k, 0) > 0 AS contaminated
FROM dw LEFT JOIN pos ON dw.doc_id = pos.doc_id LEFT JOIN its ON dw.doc_id = its.doc_id
"""


EMBEDDING_SQL = r"""
WITH RECURSIVE v AS (
  SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0
), l AS MATERIALIZED (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.9
), c(id, low) USING KEY (id) AS (
  SELECT vec_id, vec_id FROM embeddings
  UNION
  SELECT l.b, min(c.low) FROM c JOIN l ON l.a = c.id JOIN recurring.c AS r ON r.id = l.b WHERE c.low < r.low GROUP BY l.b
)
SELECT c.id AS vec_id, (SELECT count(*) FROM l WHERE l.a = c.id)::BIGINT AS n_links, c.low AS component_id, c.id = c.low AS kept FROM c
"""

def oracle_sql():
    return {
        "op1_line_dedup": LINE_DEDUP_SQL,
        "op3_embedding_dedup": EMBEDDING_SQL,
        "op4_decontamination": DECONTAMINATION_SQL,
    }
