"""Queries of the training-data operators, with production parameters over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecrag.llm import ball, bpe, chat, cnn, html, licenses, mixing, ppm, simhash, spots
from vecrag.llm.common import held_out, table


def op1_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages"))


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = ppm.identify(docs, ppm.train(docs))
    return found.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def op3_spotsigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spots.fingerprint_edits(table(spark, sf_dir, "documents"))


def spotsigs_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of documents whose spot signature sets are alike, and how many other sets each is linked with."""
    return spots.near_duplicates(table(spark, sf_dir, "documents"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.cluster(table(spark, sf_dir, "documents"))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op6_ball_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ball.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = cnn.score(docs, cnn.train(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= cnn.CUT).cast("int").alias("predicted"))


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = F.concat_ws("/", F.coalesce("source", F.lit("unknown")), F.coalesce("lang", F.lit("und")), F.col("doc_id").cast("string"))
    return licenses.scan(table(spark, sf_dir, "documents"), path)


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return bpe.encode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, digests=True)


def op10_preference(spark: SparkSession, sf_dir: str) -> DataFrame:
    convs = chat.conversations(table(spark, sf_dir, "conversations"))
    return chat.preference(chat.reply_swaps(convs), ["conv_id"])


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_html, op2_language, op3_spotsigs, spotsigs_matches, op4_simhash, op5_mixing, op6_ball_tree, op7_toxicity, op8_licenses, op9_bpe, op10_preference, pipeline)
}

_OP6 = """
WITH v AS (
    SELECT vec_id, list_transform(embedding, lambda x: floor(x::DOUBLE * 256)) AS v, row_number() OVER () AS row FROM embeddings
    WHERE embedding IS NOT NULL AND len(embedding) > 0 AND vec_id IS NOT NULL
      AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
    SELECT q.row, q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score
    FROM v q JOIN v c ON q.row <> c.row AND len(q.v) = len(c.v) WHERE q.vec_id % 50 = 0
), r AS (
    SELECT *, row_number() OVER (PARTITION BY row ORDER BY score DESC, vec_id) AS rank FROM s
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5
"""

_OP10 = """
WITH keyed AS (
    SELECT *, coalesce('c' || conv_id, 'n' || row_number() OVER ()) AS key FROM conversations
), t AS (
    SELECT key, conv_id, coalesce(role, 'user') AS role, coalesce(text, '') AS content,
           row_number() OVER (PARTITION BY key ORDER BY turn NULLS FIRST, coalesce(role, 'user'), coalesce(text, '')) AS k
    FROM keyed
), c AS (
    SELECT key, any_value(conv_id) AS conv_id, count(*) AS n, max(k) FILTER (WHERE role = 'assistant') AS last FROM t GROUP BY key
), reply AS (
    SELECT 'c' || xor(t.conv_id, 1) AS key, t.content FROM t JOIN c ON c.key = t.key AND c.last = t.k
), p AS (
    SELECT c.key, c.conv_id, coalesce(c.last, c.n + 1) AS at, reply.content AS theirs,
           (own.content IS NOT NULL AND own.content IS NOT DISTINCT FROM reply.content) AS same
    FROM c LEFT JOIN t own ON own.key = c.key AND own.k = c.last LEFT JOIN reply ON reply.key = c.key
), parts AS (
    SELECT t.*, p.at, p.same, '<|' || role || '|>' || chr(10) || content || '<|end|>' || chr(10) AS r,
           length('<|' || role || '|>' || chr(10)) AS head, t.k < p.at + p.same::INT AS shared
    FROM t JOIN p USING (key)
), placed AS (
    SELECT *, coalesce(sum(CASE WHEN shared THEN 0 ELSE length(r) END) OVER (PARTITION BY key ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS off FROM parts
), own AS (
    SELECT key, count(*) FILTER (WHERE shared) AS n_common,
           coalesce(string_agg(r, '' ORDER BY k) FILTER (WHERE shared), '') AS prompt,
           coalesce(string_agg(r, '' ORDER BY k) FILTER (WHERE NOT shared), '') AS chosen,
           coalesce(list({'start': CAST(off + head AS INTEGER), 'stop': CAST(off + length(r) AS INTEGER)} ORDER BY k) FILTER (WHERE NOT shared AND role = 'assistant'), []) AS chosen_spans
    FROM placed GROUP BY key
)
SELECT p.conv_id, CAST(n_common AS INTEGER) AS n_common, prompt, chosen,
       CASE WHEN same OR theirs IS NULL THEN '' ELSE '<|assistant|>' || chr(10) || theirs || '<|end|>' || chr(10) END AS rejected,
       chosen_spans,
       CASE WHEN same OR theirs IS NULL THEN [] ELSE [{'start': 14, 'stop': CAST(14 + length(theirs) + 8 AS INTEGER)}] END AS rejected_spans
FROM own JOIN p USING (key)
"""

SQL: dict[str, str] = {"op6_ball_tree": _OP6, "op10_preference": _OP10}
