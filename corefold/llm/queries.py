"""Queries of the operators of this subpackage, and SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corefold.llm.common import table

Query = Callable[[SparkSession, str], DataFrame]


def bpe_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import topk

    return topk.search(table(spark, sf_dir, "embeddings"), every=50, k=5)


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import suffix_dedup

    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"), w=100).drop("kept")


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import bpe

    return bpe.encode_decode(table(spark, sf_dir, "documents"), bpe_path())


def op4_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import html_extract

    return html_extract.extract_pages(table(spark, sf_dir, "pages"))


def op5_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import licenses

    return licenses.scan(table(spark, sf_dir, "documents"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import packing

    return packing.length_histogram(packing.token_lengths(table(spark, sf_dir, "documents"), bpe_path()))


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import packing

    return packing.pack(table(spark, sf_dir, "documents"), bpe_path(), limit=1024, end_id=2)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import quality

    judged = quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), columns=["doc_id", "lang"])
    return judged.select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failed_rules")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import simhash

    return simhash.near_duplicates(table(spark, sf_dir, "documents"), size=3, distance=2).drop("tid")


def op10_debruijn(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corefold.llm import debruijn

    cleaned = debruijn.remove_repeats(table(spark, sf_dir, "documents"), w=50)
    return cleaned.select("doc_id", "n_words", "n_removed", "kept_sha256")


def queries() -> dict[str, Query]:
    return {
        "op1_top_k": op1_top_k,
        "op2_suffix_dedup": op2_suffix_dedup,
        "op3_bpe": op3_bpe,
        "op4_html": op4_html,
        "op5_licenses": op5_licenses,
        "op6_token_counts": op6_token_counts,
        "op7_best_fit_packing": op7_best_fit_packing,
        "op8_quality": op8_quality,
        "op9_simhash": op9_simhash,
        "op10_debruijn": op10_debruijn,
    }


OP1_SQL = """
WITH u AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 256) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_inner_product(CAST(q.v AS DOUBLE[]), CAST(c.v AS DOUBLE[])) AS BIGINT) AS score
  FROM u q JOIN u c ON q.vec_id <> c.vec_id
  WHERE q.vec_id % 50 = 0
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rn FROM s
)
SELECT query_id, CAST(rn AS INTEGER) AS "rank", vec_id, score FROM r WHERE rn <= 5
"""

#: Bytes as hexadecimal digits; positions count within a document (below 10^9 bytes).
OP2_SQL = """
WITH docs AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
bounds AS (SELECT doc_id, h, unnest(generate_series(0, CAST(length(h) // 2 AS BIGINT), 1000)) AS base FROM docs),
pieces AS (SELECT doc_id, base, substr(h, 2 * base + 1, 2198) AS p FROM bounds),
starts AS (SELECT doc_id, base, p, unnest(generate_series(0, least(999, CAST(length(p) // 2 AS BIGINT) - 100))) AS i FROM pieces WHERE length(p) >= 200),
win AS (SELECT doc_id, base + i AS pos, md5_number(substr(p, 2 * i + 1, 200)) AS w FROM starts),
firsts AS (SELECT w, min(doc_id * 1000000000 + pos) AS earliest FROM win GROUP BY w HAVING count(*) > 1),
repeats AS (SELECT doc_id, pos FROM win JOIN firsts USING (w) WHERE doc_id * 1000000000 + pos > earliest),
marked AS (SELECT doc_id, pos, coalesce(pos > lag(pos) OVER (PARTITION BY doc_id ORDER BY pos) + 100, true) AS opens FROM repeats),
numbered AS (SELECT doc_id, pos, sum(CAST(opens AS INTEGER)) OVER (PARTITION BY doc_id ORDER BY pos) AS run FROM marked),
spans AS (SELECT doc_id, min(pos) AS a, max(pos) + 100 AS b FROM numbered GROUP BY doc_id, run),
gaps AS (SELECT doc_id, a, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM spans),
totals AS (SELECT doc_id, sum(b - a) AS n_removed, count(*) AS n_spans, max(b) AS last FROM spans GROUP BY doc_id),
kept AS (SELECT doc_id, string_agg(substr(h, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) AS k FROM gaps JOIN docs USING (doc_id) GROUP BY doc_id)
SELECT doc_id, CAST(length(h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans,
       sha256(unhex(coalesce(k, '') || substr(h, 2 * coalesce(last, 0) + 1))) AS kept_sha256
FROM docs LEFT JOIN totals USING (doc_id) LEFT JOIN kept USING (doc_id)
"""

OP10_SQL = """
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents
), win AS (
  SELECT doc_id, i, md5_number(array_to_string(ws[i:i + 49], ' ')) AS g
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM w WHERE len(ws) >= 50)
), first AS (
  SELECT g, min(doc_id) AS f FROM win GROUP BY g
), gone AS (
  SELECT DISTINCT doc_id, i + k AS p FROM (SELECT doc_id, i FROM win JOIN first USING (g) WHERE f < doc_id), (SELECT range AS k FROM range(0, 50))
), kept AS (
  SELECT doc_id, string_agg(word, ' ' ORDER BY p) AS t, count(*) AS n
  FROM (SELECT doc_id, unnest(range(1, len(ws) + 1)) AS p, unnest(ws) AS word FROM w) ANTI JOIN gone USING (doc_id, p) GROUP BY doc_id
)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(ws) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept ON kept.doc_id = w.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_top_k": OP1_SQL, "op2_suffix_dedup": OP2_SQL, "op10_debruijn": OP10_SQL}
