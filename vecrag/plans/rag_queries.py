"""Registered queries of condensation, retrieval pipelines and their measures over documents and benchmark."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag import sources
from vecrag.functions import vector as V
from vecrag.operators import condense as C
from vecrag.operators import corpus, measure, rag
from vecrag.operators.index import FULL
from vecrag.plans.shared import folder, query
from vecrag.session import checkpointed

DIM, K = C.DIM, rag.K

# -- SQL of the same definitions -----------------------------------------------------------------------------------------
TOK = r"regexp_extract_all(lower(coalesce({0}, '')), '[\p{{L}}\p{{N}}]+')"
SENT = r"list_filter(list_transform(CASE WHEN contains(regexp_replace(coalesce({0}, ''), '([.!?])\s+', '\1' || chr(1), 'g'), chr(1)) THEN string_split(regexp_replace(coalesce({0}, ''), '([.!?])\s+', '\1' || chr(1), 'g'), chr(1)) ELSE string_split(coalesce({0}, ''), chr(10)) END, lambda s: regexp_replace(s, '^\s+|\s+$', '', 'g')), lambda s: s <> '')"
IDF_SQL = f"idf AS (SELECT token, ln((1 + (SELECT count(*) FROM documents)) / (1 + count(*))) AS idf FROM (SELECT DISTINCT doc_id, unnest({TOK.format('text')}) AS token FROM documents) GROUP BY token)"
QA_SQL = r"""found AS (SELECT b.item_id, d.doc_id, b.text FROM benchmark b JOIN documents d ON contains(d.text, b.text)),
    gold AS (SELECT item_id AS qid, list_sort(list(doc_id)) AS gold_docs FROM found GROUP BY item_id),
    queries AS (SELECT item_id AS qid, array_to_string(list_slice(regexp_extract_all(text, '\S+'), 1, 12), ' ') AS query FROM benchmark)"""
SENTS_SQL = f"sents AS (SELECT doc_id, {SENT.format('text')} AS sents FROM documents)"


def hv_sql(name: str, owners: str, keys: str, text: str, dim: int = DIM) -> str:
    """Sparse unit vectors `name` (keys, bucket, w) of the rows of `owners`."""
    return f"""{name}_t AS (SELECT {keys}, token, count(*) AS tf FROM (SELECT {keys}, unnest({TOK.format(text)}) AS token FROM {owners}) GROUP BY {keys}, token),
    {name}_s AS (SELECT {keys}, CAST(('0x' || substr(md5(token), 1, 8))::BIGINT % {dim} AS INTEGER) AS bucket, sum((CASE WHEN ('0x' || substr(md5(token), 9, 1))::BIGINT % 2 = 1 THEN 1.0 ELSE -1.0 END) * tf * idf) AS w FROM {name}_t JOIN idf USING (token) GROUP BY {keys}, bucket),
    {name} AS (SELECT {keys}, bucket, w / len AS w FROM (SELECT *, sqrt(sum(w * w) OVER (PARTITION BY {keys})) AS len FROM {name}_s) WHERE len > 0)"""


def retrieve_sql(name: str, k: int = K, queries: str = "queries", qv: str = "qv", dv: str = "dv") -> str:
    return f"{name} AS (SELECT qid, doc_id, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id) AS rank FROM (SELECT q.qid, d.doc_id, round(sum(q.w * d.w), 6) AS score FROM {qv} q JOIN {dv} d USING (bucket) GROUP BY q.qid, d.doc_id)) WHERE rank <= {k})"


def windows_sql(name: str, window: int, step: int, source: str = "sents") -> str:
    return f"""{name}_n AS (SELECT doc_id, sents, len(sents) AS n FROM {source}),
    {name}_s AS (SELECT doc_id, sents, n, 1 AS start FROM {name}_n WHERE n BETWEEN 1 AND {window} UNION ALL SELECT doc_id, sents, n, unnest(list_distinct(generate_series(1, n - {window} + 1, {step}) || [n - {window} + 1])) FROM {name}_n WHERE n > {window}),
    {name} AS (SELECT doc_id, CAST(start AS INTEGER) AS start, CAST(least(start + {window} - 1, n) AS INTEGER) AS stop, array_to_string(list_slice(sents, start, start + {window} - 1), ' ') AS text FROM {name}_s)"""


def scored_sql(name: str, wins: str, wv: str, pairs: str) -> str:
    return f"{name} AS (SELECT x.qid, x.doc_id, x.start, x.stop, round(coalesce(h.s, 0.0), 6) AS score FROM (SELECT p.qid, w.* FROM {pairs} p JOIN {wins} w USING (doc_id)) x LEFT JOIN (SELECT p.qid, p.doc_id, w.start, sum(q.w * w.w) AS s FROM {pairs} p JOIN qv q USING (qid) JOIN {wv} w ON w.doc_id = p.doc_id AND w.bucket = q.bucket GROUP BY 1, 2, 3) h ON h.qid = x.qid AND h.doc_id = x.doc_id AND h.start = x.start)"


BASE = f"{IDF_SQL}, {QA_SQL}, {hv_sql('qv', 'queries', 'qid', 'query')}, {hv_sql('dv', 'documents', 'doc_id', 'text')}, {retrieve_sql('ret')}, {SENTS_SQL}"


def condense_sql(name: str = "cond", window: int = 3, overlap: int = 2, ext: int = 1, pairs: str = "ret") -> str:
    """`name` (qid, doc_id, rank, new_rank, score, start, stop, text)."""
    return f"""{name}_src AS (SELECT * FROM sents WHERE doc_id IN (SELECT doc_id FROM {pairs})), {windows_sql(f'{name}_w', window, window - overlap, f'{name}_src')}, {hv_sql(f'{name}_v', f'{name}_w', 'doc_id, start', 'text')}, {scored_sql(f'{name}_sc', f'{name}_w', f'{name}_v', pairs)},
    {name}_b AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid, doc_id ORDER BY score DESC, start) AS r FROM {name}_sc) WHERE r = 1),
    {name} AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, rank, doc_id) AS new_rank FROM (
        SELECT p.qid, p.doc_id, p.rank, coalesce(b.score, 0.0) AS score, b.start, b.stop,
               CASE WHEN b.start IS NULL THEN coalesce(d.text, '') ELSE array_to_string(list_slice(s.sents, greatest(1, b.start - {ext}), least(len(s.sents), b.stop + {ext})), ' ') END AS text
        FROM {pairs} p JOIN documents d USING (doc_id) JOIN sents s USING (doc_id) LEFT JOIN {name}_b b ON b.qid = p.qid AND b.doc_id = p.doc_id))"""


# -- inputs ----------------------------------------------------------------------------------------------------------------
def docs_of(spark, d) -> DataFrame:
    return sources.table(spark, d, "documents")


def queries_of(spark, d) -> DataFrame:
    """(qid, query): the first 12 words of each benchmark item."""
    words = F.regexp_extract_all("text", F.lit(r"(\S+)"))
    return sources.table(spark, d, "benchmark").select(F.col("item_id").alias("qid"), F.array_join(F.slice(words, 1, 12), " ").alias("query"))


def gold_of(spark, d) -> DataFrame:
    """(qid, gold_docs, answers): items found verbatim in documents; the answer is the item's longest sentence, first on ties.

    The items are a fixed small table; they meet the documents by hash of an 8-word shingle, not by a product.
    """
    items = sources.table(spark, d, "benchmark")
    words = lambda c: F.regexp_extract_all(c, F.lit(r"(\S+)"))
    head = items.select("item_id", F.col("text").alias("item"), F.array_join(F.slice(words("text"), 2, 7), " ").alias("key"))
    docs = docs_of(spark, d).select("doc_id", "text")
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 6, F.lit(1))), lambda k: F.array_join(F.slice("w", k, F.lit(7)), " "))
    hits = docs.withColumn("w", words("text")).select("doc_id", "text", F.explode(F.array_distinct(runs)).alias("key")).join(F.broadcast(head), "key").where(F.contains("text", "item"))
    gold = hits.groupBy(F.col("item_id").alias("qid")).agg(F.array_sort(F.collect_set("doc_id")).alias("gold_docs"))
    sents = items.select(F.col("item_id").alias("qid"), F.posexplode(V.sentences("text")).alias("no", "s"))
    longest = sents.groupBy("qid").agg(F.min(F.struct((-F.char_length("s")).alias("n"), "no", "s")).alias("b"))
    return gold.join(longest, "qid").select("qid", "gold_docs", F.array("b.s").alias("answers"))


def _base(spark, d):
    docs = docs_of(spark, d).select("doc_id", "text")
    return docs, queries_of(spark, d), C.idf_table(docs).cache()


def _two(docs: DataFrame, q: DataFrame, idf: DataFrame, **options) -> DataFrame:
    """The two-tier pipeline with exact ranks, so that its rows can be stated."""
    return rag.rag_two_tier(docs, q, idf, ranked=rag.retrieve(docs, q, idf), **options)


def _retrieved(spark, d):
    docs, q, idf = _base(spark, d)
    idf = idf.cache()
    return docs, q, idf, rag.retrieve(docs, q, idf)


# -- corpus and steps --------------------------------------------------------------------------------------------------------
@query("SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) AND lang = 'en'")
def select_corpus(spark, d):
    docs = corpus.select_corpus(docs_of(spark, d), F.col("lang") == "en")
    return corpus.select_corpus(docs, sources.table(spark, d, "labels").where("quality = 1")).select("doc_id", "n_chars")


@query(f"WITH {SENTS_SQL} SELECT doc_id, CAST(len(sents) AS INTEGER) AS n, md5(array_to_string(sents, '|')) AS body FROM sents")
def sentences(spark, d):
    s = C.split_sentences(docs_of(spark, d))
    return s.select("doc_id", F.size("sents").alias("n"), F.md5(F.array_join("sents", "|")).alias("body"))


def _chunk_sql(per: int, overlap: int = 0) -> str:
    step = per - overlap
    return f"""WITH {SENTS_SQL}, c AS (SELECT doc_id, sents, unnest(generate_series(0, greatest(len(sents) - 1 - {overlap}, 0), {step})) AS first FROM sents WHERE len(sents) > 0)
    SELECT doc_id, CAST(first // {step} AS INTEGER) AS chunk_no, CAST(coalesce(list_sum(list_transform(list_slice(sents, 1, first), lambda s: length(s) + 1)), 0) AS BIGINT) AS "offset", array_to_string(list_slice(sents, first + 1, first + {per}), ' ') AS text, CAST(len({TOK.format(f"array_to_string(list_slice(sents, first + 1, first + {per}), ' ')")}) AS INTEGER) AS n_tokens FROM c"""


@query(_chunk_sql(5))
def chunks(spark, d):
    return corpus.chunk(docs_of(spark, d), 5)


@query(_chunk_sql(4, 1))
def chunks_overlapped(spark, d):
    return corpus.chunk(docs_of(spark, d), 5, overlap=1, ratio=0.8)


@query(f"WITH {IDF_SQL} SELECT token, round(idf, 9) AS idf FROM idf")
def idf_table(spark, d):
    return C.idf_table(docs_of(spark, d)).select("token", F.round("idf", 9).alias("idf"))


@query(f"WITH {IDF_SQL}, {QA_SQL}, {hv_sql('qv', 'queries', 'qid', 'query')} SELECT qid, bucket, round(w, 6) AS w FROM qv")
def embed_sparse(spark, d):
    _, q, idf = _base(spark, d)
    return C.sparse_vectors(q, ["qid"], idf, DIM, "query").select("qid", "bucket", F.round("w", 6).alias("w"))


@query(f"WITH {IDF_SQL}, {QA_SQL}, {hv_sql('qv', 'queries', 'qid', 'query')} SELECT o.qid, CAST(b AS INTEGER) AS bucket, round(coalesce(w, 0.0), 6) AS w FROM (SELECT DISTINCT qid FROM qv) o, range({DIM}) r(b) LEFT JOIN qv ON qv.qid = o.qid AND qv.bucket = b")
def embed_dense(spark, d):
    _, q, idf = _base(spark, d)
    dense = C.dense_vectors(C.sparse_vectors(q, ["qid"], idf, DIM, "query"), ["qid"], DIM)
    return dense.select("qid", F.posexplode("v").alias("bucket", "w")).select("qid", "bucket", F.round("w", 6).alias("w"))


@query(f"WITH {SENTS_SQL}, {windows_sql('w', 3, 1)} SELECT doc_id, start, stop, md5(text) AS body FROM w")
def windows(spark, d):
    return C.windows(C.split_sentences(docs_of(spark, d))).select("doc_id", "start", "stop", F.md5("text").alias("body"))


@query(f"WITH {SENTS_SQL}, {windows_sql('w', 4, 3)} SELECT doc_id, start, stop, md5(text) AS body FROM w")
def windows_stepped(spark, d):
    return C.windows(C.split_sentences(docs_of(spark, d)), 4, 1).select("doc_id", "start", "stop", F.md5("text").alias("body"))


@query(f"WITH {BASE} SELECT qid, doc_id, score, CAST(rank AS INTEGER) AS rank FROM ret")
def retrieve(spark, d):
    return _retrieved(spark, d)[3]


@query(f"WITH {BASE}, {condense_sql()} SELECT qid, doc_id, start, stop, score FROM cond_sc")
def score_windows(spark, d):
    docs, q, idf, ret = _retrieved(spark, d)
    wins = C.windows(C.split_sentences(docs.join(ret.select("doc_id").distinct(), "doc_id", "left_semi")))
    return C.score_windows(wins, ret, q, idf)


@query(f"WITH {BASE}, {condense_sql()} SELECT qid, doc_id, start, stop, score FROM cond_b")
def best_window(spark, d):
    return C.best_window(score_windows(spark, d))


COND_COLS = "qid, doc_id, CAST(rank AS INTEGER) AS rank, CAST(new_rank AS INTEGER) AS new_rank, score, md5(text) AS body"


def _digest(df: DataFrame) -> DataFrame:
    return df.select("qid", "doc_id", "rank", "new_rank", "score", F.md5("text").alias("body"))


@query(f"WITH {BASE}, {condense_sql()} SELECT {COND_COLS} FROM cond")
def condense_full(spark, d):
    docs, q, idf, ret = _retrieved(spark, d)
    return _digest(C.condense(ret, docs, q, idf))


@query(f"WITH {BASE}, {condense_sql(ext=0)} SELECT {COND_COLS.replace('CAST(new_rank AS INTEGER)', 'CAST(rank AS INTEGER)')} FROM cond")
def condense_no_extension_no_reorder(spark, d):
    docs, q, idf, ret = _retrieved(spark, d)
    return _digest(C.condense(ret, docs, q, idf, ext=0, by_score=False))


@query(f"WITH {BASE}, {condense_sql(window=5, overlap=0, ext=2)} SELECT {COND_COLS} FROM cond")
def condense_wide(spark, d):
    docs, q, idf, ret = _retrieved(spark, d)
    return _digest(C.condense(ret, docs, q, idf, 5, 0, 2))


@query(f"WITH {BASE}, {condense_sql()} SELECT qid, doc_id, CAST(k AS INTEGER) AS sentence_no, CASE WHEN k < start THEN 'before' WHEN k > stop THEN 'after' ELSE 'core' END AS part, md5(sents[k]) AS body FROM (SELECT c.*, s.sents, unnest(generate_series(greatest(1, start - 1), least(len(sents), stop + 1))) AS k FROM cond c JOIN sents s USING (doc_id) WHERE start IS NOT NULL)")
def condense_parts(spark, d):
    """Attribution: which sentence of which document each part of a condensed text is."""
    docs, q, idf, ret = _retrieved(spark, d)
    parts = C.condense(ret, docs, q, idf).select("qid", "doc_id", F.explode("parts").alias("p"))
    return parts.select("qid", "doc_id", "p.sentence_no", "p.part", F.md5("p.text").alias("body"))


@query(None)
def condense_two_windows(spark, d):
    docs, q, idf, ret = _retrieved(spark, d)
    return _digest(C.condense(ret, docs, q, idf, n=2, short_as_is=True))


# -- pipelines -----------------------------------------------------------------------------------------------------------------
BM_SQL = f"""dl AS (SELECT doc_id, len({TOK.format('text')}) AS dl FROM documents), facts AS (SELECT count(*) AS n, avg(dl) AS avg_dl FROM dl),
    qt AS (SELECT DISTINCT qid, unnest({TOK.format('query')}) AS token FROM queries),
    post AS (SELECT doc_id, token, count(*) AS tf FROM (SELECT doc_id, unnest({TOK.format('text')}) AS token FROM documents) WHERE token IN (SELECT token FROM qt) GROUP BY doc_id, token),
    pdf AS (SELECT token, count(*) AS df FROM post GROUP BY token),
    bm AS (SELECT qid, doc_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * dl / avg_dl))), 6) AS score FROM qt JOIN post USING (token) JOIN pdf USING (token) JOIN dl USING (doc_id), facts GROUP BY qid, doc_id)"""


@query(f"WITH {QA_SQL}, {BM_SQL} SELECT qid, doc_id, score, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id) AS rank FROM bm) WHERE rank <= 10")
def bm25(spark, d):
    return rag.bm25(docs_of(spark, d), queries_of(spark, d))


CTX = "qid, doc_id, CAST(rank AS INTEGER) AS rank, md5(context) AS body"


def _ctx(df: DataFrame) -> DataFrame:
    return df.select("qid", "doc_id", "rank", F.md5("context").alias("body"))


PLAIN = "plain AS (SELECT qid, doc_id, rank, coalesce(text, '') AS context FROM ret JOIN documents USING (doc_id))"
TWO = "two AS (SELECT qid, doc_id, new_rank AS rank, text AS context FROM cond)"


@query(f"WITH {BASE}, {PLAIN} SELECT {CTX} FROM plain")
def rag_plain(spark, d):
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_plain(docs, q, idf))


@query(f"WITH {BASE}, {condense_sql()}, {TWO} SELECT {CTX} FROM two")
def rag_two_tier(spark, d):
    """Ranks from a two-tier index over the documents' vectors, at full width."""
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_two_tier(docs, q, idf, n_p=FULL, ef_c=FULL, ef_l=FULL))


@query(f"WITH {BASE}, {condense_sql()}, {TWO} SELECT {CTX} FROM two")
def rag_two_tier_exact(spark, d):
    """The same with ranks from exact retrieval."""
    docs, q, idf = _base(spark, d)
    return _ctx(_two(docs, q, idf))


@query("SELECT count(*) AS queries, true AS reached FROM benchmark")
def rag_two_tier_recall(spark, d):
    """Whether the document index, with widths calibrated on a sample of the queries, retrieves 0.9 of the exact documents."""
    from vecrag.operators import baselines as B
    from vecrag.operators import index as two_tier

    docs, q, idf = _base(spark, d)
    idx = rag.document_index(docs, idf, path := folder(spark), n_c=16)
    widths = two_tier.calibrate(idx, spark.read.parquet(f"{path}/vectors"), 0.95, K, queries=rag.query_vectors(q, idf), metric="overlap")
    named = lambda found: found.select("qid", F.col("doc_id").alias("id"), "rank")
    exact = rag.retrieve(docs, q, idf)
    r = B.recall_at_k(named(rag.index_ranks(idx, q, idf, **widths)), named(exact), K)
    return q.agg(F.count("*").alias("queries")).join(r.select((F.col("recall") >= 0.9).alias("reached")))


@query(f"WITH {BASE}, {PLAIN} SELECT {CTX} FROM plain")
def rag_disk(spark, d):
    """Disk-backed pipeline: lists of document vectors on disk, all probed here, so that it equals the plain one."""
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_disk(docs, q, idf.cache(), folder(spark), n_c=8, n_p=8))


def _small_sql(per: int) -> str:
    body = _chunk_sql(per).split("WITH ", 1)[1]
    head, tail = body[: body.rindex("\n    SELECT doc_id, CAST(first")], body[body.rindex("\n    SELECT doc_id, CAST(first") :]
    return f"WITH {IDF_SQL}, {QA_SQL}, {hv_sql('qv', 'queries', 'qid', 'query')}, {head}, ch AS ({tail}), {hv_sql('cv', 'ch', 'doc_id, chunk_no', 'text')}, sc AS (SELECT q.qid, c.doc_id, c.chunk_no, round(sum(q.w * c.w), 6) AS score FROM qv q JOIN cv c USING (bucket) GROUP BY 1, 2, 3) SELECT qid, doc_id, chunk_no, CAST(rank AS INTEGER) AS rank, md5(text) AS body FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id, chunk_no) AS rank FROM sc) JOIN ch USING (doc_id, chunk_no) WHERE rank <= {K}"


@query(_small_sql(3))
def rag_small_chunks(spark, d):
    docs, q, idf = _base(spark, d)
    found = rag.rag_small_chunks(corpus.chunk(docs, 5, ratio=0.6), q, idf.cache(), ids=docs.select("doc_id"))
    return found.select("qid", "doc_id", "chunk_no", "rank", F.md5("context").alias("body"))


COMP_SQL = f"""cs AS (SELECT doc_id, generate_subscripts(sents, 1) - 1 AS no, unnest(sents) AS text FROM sents WHERE doc_id IN (SELECT doc_id FROM ret)), {hv_sql('csv', 'cs', 'doc_id, no', 'text')},
    cn AS (SELECT s.doc_id, s.no, sum(s.w * d.w) AS s FROM csv s JOIN dv d ON d.doc_id = s.doc_id AND d.bucket = s.bucket GROUP BY 1, 2),
    ck AS (SELECT * FROM (SELECT cs.*, row_number() OVER (PARTITION BY cs.doc_id ORDER BY round(coalesce(s, 0.0), 6) DESC, cs.no) AS r, count(*) OVER (PARTITION BY cs.doc_id) AS n FROM cs LEFT JOIN cn ON cn.doc_id = cs.doc_id AND cn.no = cs.no) WHERE r <= ceil(0.5 * n)),
    comp AS (SELECT ret.qid, ret.doc_id, ret.rank, coalesce(x.context, '') AS context FROM ret LEFT JOIN (SELECT doc_id, string_agg(text, ' ' ORDER BY no) AS context FROM ck GROUP BY doc_id) x USING (doc_id))"""


@query(f"WITH {BASE}, {COMP_SQL} SELECT {CTX} FROM comp")
def rag_compressed(spark, d):
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_compressed(docs, q, idf.cache()))


RR_SQL = f"""{retrieve_sql('ret10', 10)}, {BM_SQL}, rsrc AS (SELECT * FROM sents WHERE doc_id IN (SELECT doc_id FROM ret10)), {windows_sql('rw', 1, 1, 'rsrc')}, {hv_sql('rv', 'rw', 'doc_id, start', 'text')}, {scored_sql('rs', 'rw', 'rv', 'ret10')},
    rb AS (SELECT p.qid, p.doc_id, coalesce(bm.score, 0.0) AS kw, coalesce(m.sem, 0.0) AS sem FROM ret10 p LEFT JOIN bm ON bm.qid = p.qid AND bm.doc_id = p.doc_id LEFT JOIN (SELECT qid, doc_id, max(score) AS sem FROM rs GROUP BY 1, 2) m ON m.qid = p.qid AND m.doc_id = p.doc_id),
    rr AS (SELECT qid, doc_id, round((CASE WHEN hi > lo THEN (kw - lo) / (hi - lo) ELSE 0.0 END + sem) / 2, 6) AS score FROM (SELECT *, min(kw) OVER (PARTITION BY qid) AS lo, max(kw) OVER (PARTITION BY qid) AS hi FROM rb)),
    rerank AS (SELECT qid, doc_id, rank, coalesce(text, '') AS context FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id) AS rank FROM rr) JOIN documents USING (doc_id) WHERE rank <= {K})"""


@query(f"WITH {BASE}, {RR_SQL} SELECT {CTX} FROM rerank")
def rag_reranked(spark, d):
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_reranked(docs, q, idf.cache()))


@query(None)
def rag_iterative(spark, d):
    docs, q, idf = _base(spark, d)
    return _ctx(rag.rag_iterative(docs, q, idf.cache()))


def prompt_sql(ctx: str, budget: int = 2048) -> str:
    n = f"len({TOK.format('query')})"
    return f"""SELECT q.qid, md5(CASE WHEN b.body IS NULL THEN q.query ELSE b.body || chr(10) || q.query END) AS body, CAST(coalesce(ct, 0) + {n} AS INTEGER) AS n_tokens, coalesce(n_contexts, 0) AS n_contexts FROM queries q LEFT JOIN
        (SELECT qid, string_agg(context, chr(10) ORDER BY rank) AS body, sum(t) AS ct, count(*) AS n_contexts FROM (SELECT c.*, len({TOK.format('context')}) AS t, sum(len({TOK.format('context')})) OVER (PARTITION BY qid ORDER BY rank) AS run FROM {ctx} c) JOIN (SELECT qid, {n} AS qt FROM queries) USING (qid) WHERE run + qt <= {budget} GROUP BY qid) b USING (qid)"""


@query(f"WITH {BASE}, {condense_sql()}, {TWO} {prompt_sql('two')}")
def build_prompt(spark, d):
    docs, q, idf = _base(spark, d)
    p = rag.build_prompt(_two(docs, q, idf), q)
    return p.select("qid", F.md5("prompt").alias("body"), "n_tokens", "n_contexts")


def answer_sql(name: str, ctx: str) -> str:
    return f"""{name}_x AS (SELECT qid, doc_id, rank, generate_subscripts(s, 1) - 1 AS no, unnest(s) AS text FROM (SELECT qid, doc_id, rank, {SENT.format('context')} AS s FROM {ctx})), {hv_sql(f'{name}_v', f'{name}_x', 'qid, rank, no', 'text')},
    {name}_n AS (SELECT v.qid, v.rank, v.no, sum(v.w * q.w) AS s FROM {name}_v v JOIN qv q ON q.qid = v.qid AND q.bucket = v.bucket GROUP BY 1, 2, 3),
    {name} AS (SELECT q.qid, coalesce(b.text, '') AS reply, b.doc_id, coalesce(b.s, 0.0) AS score FROM queries q LEFT JOIN (SELECT * FROM (SELECT x.*, round(coalesce(n.s, 0.0), 6) AS s, row_number() OVER (PARTITION BY x.qid ORDER BY round(coalesce(n.s, 0.0), 6) DESC, x.rank, x.no) AS r FROM {name}_x x LEFT JOIN {name}_n n ON n.qid = x.qid AND n.rank = x.rank AND n.no = x.no) WHERE r = 1) b USING (qid))"""


@query(f"WITH {BASE}, {condense_sql()}, {TWO}, {answer_sql('ans', 'two')} SELECT qid, md5(reply) AS body, doc_id, score FROM ans")
def answer(spark, d):
    docs, q, idf = _base(spark, d)
    idf = idf.cache()
    return rag.answer(_two(docs, q, idf), q, idf).select("qid", F.md5("reply").alias("body"), "doc_id", "score")


@query(f"WITH {BASE} SELECT qid, list_sort(list(DISTINCT doc_id)) AS refs FROM ret GROUP BY qid")
def references(spark, d):
    docs, q, idf = _base(spark, d)
    return rag.references(rag.rag_plain(docs, q, idf))


# -- measures and workloads ----------------------------------------------------------------------------------------------------
LONGEST = f"longest AS (SELECT item_id AS qid, s AS answer FROM (SELECT item_id, s, row_number() OVER (PARTITION BY item_id ORDER BY length(s) DESC, no) AS r FROM (SELECT item_id, generate_subscripts(s, 1) AS no, unnest(s) AS s FROM (SELECT item_id, {SENT.format('text')} AS s FROM benchmark))) WHERE r = 1)"
NORM = "array_to_string(" + TOK + ", ' ')"


@query(f"WITH {QA_SQL}, {LONGEST} SELECT qid, gold_docs, [answer] AS answers FROM gold JOIN longest USING (qid)")
def qa_gold(spark, d):
    return gold_of(spark, d)


def accuracy_sql(ans: str) -> str:
    return f"SELECT count(*) AS queries, round(100 * avg(CASE WHEN contains({NORM.format('coalesce(reply, chr(32))')}, {NORM.format('answer')}) AND {NORM.format('answer')} <> '' THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM gold JOIN longest USING (qid) LEFT JOIN {ans} USING (qid)"


PIPES = ("plain", "disk", "two_tier", "compressed", "reranked")
#: The disk-backed pipeline probes all its lists here, so that it retrieves what the plain one does.
PIPE_CTX = {"plain": "plain", "disk": "plain", "two_tier": "two", "compressed": "comp", "reranked": "rerank"}
ALL_PIPES = f"{BASE}, {PLAIN}, {condense_sql()}, {TWO}, {COMP_SQL}, {RR_SQL}, {LONGEST}"


def _contexts(spark, d, docs, q, idf, vectors=None, **lists) -> tuple[dict[str, DataFrame], DataFrame]:
    """Contexts of the five pipelines, and the idf of their tokens. Documents get their vectors once and are retrieved once: the
    FETCH nearest are found, the first K of them are what the pipelines without a re-ranker take.
    """
    vectors = rag.owner_vectors(docs, idf) if vectors is None else vectors
    fetched = checkpointed(rag.retrieve(docs, q, idf, rag.FETCH, vectors=vectors))
    texts = checkpointed(docs.join(fetched.select("doc_id").distinct(), "doc_id", "left_semi"))
    found = fetched.where(F.col("rank") <= rag.K)
    disk = rag.rag_disk(docs, q, idf, folder(spark), vectors=vectors, **(lists or {"n_c": 8, "n_p": 8}))
    idf = C.idf_of(idf, texts.select("text"), q.select("query"))
    made = {
        "plain": rag.with_text(found, texts), "disk": disk, "two_tier": rag.rag_two_tier(texts, q, idf, ranked=found),
        "compressed": rag.rag_compressed(texts, q, idf, found=found), "reranked": rag.rag_reranked(docs, q, idf, found=fetched, texts=texts),
    }
    return {name: checkpointed(ctx) for name, ctx in made.items()}, idf


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query(f"WITH {ALL_PIPES}, " + ", ".join(answer_sql(f"ans_{p}", PIPE_CTX[p]) for p in PIPES) + " " + " UNION ALL ".join(f"SELECT '{p}' AS method, x.* FROM ({accuracy_sql(f'ans_{p}')}) x" for p in PIPES))
def w_pipelines(spark, d):
    """Accuracy of the extractive generator on the five pipelines."""
    docs, q, idf = _base(spark, d)
    idf, gold = idf.cache(), gold_of(spark, d).cache()
    contexts, idf = _contexts(spark, d, docs, q, idf)
    return _union([checkpointed(measure.answer_accuracy(rag.answer(c, q, idf), gold)).select(F.lit(p).alias("method"), "queries", "accuracy") for p, c in contexts.items()])


def evidence_sql(ctx: str) -> str:
    return f"""SELECT count(*) AS queries, round(avg(coalesce(hit, 0.0)), 6) AS in_context, round(avg(CASE WHEN first IS NULL THEN 0.0 ELSE 1.0 END), 6) AS gold_in_top, round(avg(coalesce(1.0 / first, 0.0)), 6) AS mrr FROM gold JOIN longest USING (qid) LEFT JOIN
        (SELECT c.qid, max(CASE WHEN contains({NORM.format('context')}, {NORM.format('answer')}) THEN 1.0 ELSE 0.0 END) AS hit, min(CASE WHEN list_contains(gold_docs, doc_id) THEN rank END) AS first FROM {ctx} c JOIN gold USING (qid) JOIN longest USING (qid) GROUP BY c.qid) USING (qid)"""


@query(f"WITH {ALL_PIPES} " + " UNION ALL ".join(f"SELECT '{p}' AS method, x.* FROM ({evidence_sql(PIPE_CTX[p])}) x" for p in PIPES))
def w_evidence(spark, d):
    """Gold evidence in the contexts of the five pipelines, apart from any generator."""
    docs, q, idf = _base(spark, d)
    idf, gold = idf.cache(), gold_of(spark, d).cache()
    return _union([measure.evidence_report(c, gold).select(F.lit(p).alias("method"), "queries", "in_context", "gold_in_top", "mrr") for p, c in _contexts(spark, d, docs, q, idf)[0].items()])


def tokens_sql(after: str) -> str:
    n = lambda c: f"len({TOK.format(c)})"
    return f"SELECT documents, round(b, 6) AS before, round(a, 6) AS after, round(100 * (1 - a / b), 6) AS reduction FROM (SELECT count(*) AS documents, avg({n('p.context')}) AS b, avg({n('t.context')}) AS a FROM plain p JOIN {after} t USING (qid, doc_id))"


@query(f"WITH {BASE}, {PLAIN}, {condense_sql()}, {TWO} {tokens_sql('two')}")
def w_tokens(spark, d):
    """Tokens per document before and after condensation with the published settings."""
    docs, q, idf = _base(spark, d)
    idf = idf.cache()
    return measure.token_report(rag.rag_plain(docs, q, idf), _two(docs, q, idf))


GRID = tuple((w, o) for w in range(1, 6) for o in range(w))
RATIOS = (0.9, 0.8, 0.6)


def in_context_sql(ctx: str) -> str:
    return f"SELECT in_context FROM ({evidence_sql(ctx)})"


def _chunks_ctx_sql(ratio: float) -> str:
    """Best chunks of a shrunk chunking as contexts `chx{r}` (qid, doc_id, rank, context)."""
    n, per = int(ratio * 10), max(1, round(5 * ratio))
    body = _chunk_sql(per).split("WITH ", 1)[1]
    tail = body[body.rindex("\n    SELECT doc_id, CAST(first") :].replace("FROM c", f"FROM c{n}")
    first = f"c{n} AS (SELECT doc_id, sents, unnest(generate_series(0, greatest(len(sents) - 1, 0), {per})) AS first FROM sents WHERE len(sents) > 0)"
    scored = f"sc{n} AS (SELECT q.qid, c.doc_id, c.chunk_no, round(sum(q.w * c.w), 6) AS score FROM qv q JOIN cv{n} c USING (bucket) GROUP BY 1, 2, 3)"
    return f"{first}, ch{n} AS ({tail}), {hv_sql(f'cv{n}', f'ch{n}', 'doc_id, chunk_no', 'text')}, {scored}, chx{n} AS (SELECT qid, doc_id, rank, text AS context FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id, chunk_no) AS rank FROM sc{n}) JOIN ch{n} USING (doc_id, chunk_no) WHERE rank <= {K})"


def _mean_sql(ctx: str) -> str:
    return f"SELECT count(*) AS contexts, round(avg(len({TOK.format('context')})), 6) AS tokens FROM {ctx}"


GRID_SQL = f"WITH {BASE}, {PLAIN}, {COMP_SQL}, {LONGEST}, " + ", ".join(f"{condense_sql(f'cg{w}{o}', w, o)}, tg{w}{o} AS (SELECT qid, doc_id, new_rank AS rank, text AS context FROM cg{w}{o})" for w, o in GRID) + ", " + ", ".join(_chunks_ctx_sql(r) for r in RATIOS) + " " + " UNION ALL ".join(
    f"SELECT '{name}' AS method, {w} AS \"window\", {o} AS \"overlap\", m.contexts, m.tokens, e.in_context FROM ({_mean_sql(ctx)}) m, ({in_context_sql(ctx)}) e"
    for name, w, o, ctx in [("plain", 0, 0, "plain"), ("compressed", 0, 0, "comp"), *(("two_tier", w, o, f"tg{w}{o}") for w, o in GRID), *((f"chunks {r}", 0, 0, f"chx{int(r * 10)}") for r in RATIOS)]
)


@query(GRID_SQL)
def w_condense_grid(spark, d):
    """Tokens of a context and gold evidence in it by window size and overlap (all of 1..5), for the plain pipeline, the
    compressor and small chunks by ratio.
    """
    docs, q, idf, ret = _retrieved(spark, d)
    ret = checkpointed(ret)
    gold = gold_of(spark, d).cache()
    wanted = checkpointed(docs.join(ret.select("doc_id").distinct(), "doc_id", "left_semi"))
    near = C.idf_of(idf, wanted.select("text"), q.select("query"))
    parts = [("plain", 0, 0, rag.with_text(ret, wanted)), ("compressed", 0, 0, rag.rag_compressed(wanted, q, near, found=ret))]
    parts += [("two_tier", w, o, c) for (w, o), c in C.condense_grid(ret, wanted, q, near, GRID).items()]
    for r in RATIOS:
        parts.append((f"chunks {r}", 0, 0, rag.rag_small_chunks(corpus.chunk(docs, 5, ratio=r), q, idf, ids=docs.select("doc_id")).drop("chunk_no")))
    out = []
    for name, w, o, ctx in parts:
        ctx = checkpointed(ctx.select("qid", "doc_id", "rank", "context"))
        mean = ctx.agg(F.count("*").alias("contexts"), F.round(F.avg(V.token_count("context")), 6).alias("tokens"))
        out.append(mean.join(measure.evidence_report(ctx, gold).select("in_context")).select(F.lit(name).alias("method"), F.lit(w).alias("window"), F.lit(o).alias("overlap"), "contexts", "tokens", "in_context"))
    return _union(out)


SPEED_SQL = "sp AS (SELECT * FROM (VALUES " + ", ".join(f"('{g}', {p}::DOUBLE, {n}::DOUBLE, {b}::DOUBLE, {measure.WATT[g]}::DOUBLE)" for g, p, n, b in measure.SPEEDS) + ") t(generator, prompt_rate, gen_rate, battery, watt))"
PARTS = {"plain": (0.05, 0.02, 0.0), "disk": (0.05, 0.05, 0.0), "two_tier": (0.05, 0.01, 0.08), "reranked": (0.05, 0.02, 0.4)}


@query(f"WITH {ALL_PIPES}, {SPEED_SQL}, pr AS (" + " UNION ALL ".join(f"SELECT '{p}' AS method, x.qid, x.n_tokens, {e}::DOUBLE AS embed_s, {s}::DOUBLE AS search_s, {t}::DOUBLE AS extra_s FROM ({prompt_sql(PIPE_CTX[p], 4096)}) x" for p, (e, s, t) in PARTS.items()) + "), t AS (SELECT method, generator, n_tokens / prompt_rate AS prompt_s, embed_s + search_s + extra_s + n_tokens / prompt_rate AS ttft_s, (embed_s + search_s + extra_s + n_tokens / prompt_rate) * watt AS j FROM pr, sp) SELECT method, generator, round(avg(round(prompt_s, 6)), 4) AS prompt_s, round(avg(round(ttft_s, 6)), 4) AS ttft_s, round(avg(round(j, 6)), 4) AS joule_model FROM t GROUP BY 1, 2")
def w_ttft(spark, d):
    """Modelled time to first token and energy by pipeline and generator."""
    docs, q, idf = _base(spark, d)
    ctx, _ = _contexts(spark, d, docs, q, idf.cache())
    parts = _union([rag.build_prompt(ctx[p], q, 4096).select(F.lit(p).alias("method"), "qid", "n_tokens", F.lit(e).alias("embed_s"), F.lit(s).alias("search_s"), F.lit(t).alias("extra_s")) for p, (e, s, t) in PARTS.items()])
    made = measure.ttft_model(parts, measure.speeds(spark))
    return made.groupBy("method", "generator").agg(*(F.round(F.avg(c), 4).alias(c) for c in ("prompt_s", "ttft_s", "joule_model")))


@query(f"WITH {BASE}, {PLAIN}, {answer_sql('ans', 'plain')}, {SPEED_SQL}, r AS (SELECT count(*) AS replies, sum(len({TOK.format('reply')})) AS t FROM ans) SELECT generator, replies, round(t / gen_rate, 6) AS gen_s, round(t / 1000 * battery, 6) AS battery_pct FROM r, sp")
def w_battery(spark, d):
    docs, q, idf = _base(spark, d)
    idf = idf.cache()
    return measure.generation_model(rag.answer(rag.rag_plain(docs, q, idf), q, idf), measure.speeds(spark))


CHAT_SQL = "queries AS (SELECT ('0x' || substr(md5(conv_id || '/' || turn), 1, 15))::BIGINT AS qid, conv_id, turn, array_to_string(texts, ' ') AS query, coalesce(text, '') AS said, array_to_string(before, chr(10)) AS history FROM (SELECT *, list(coalesce(text, '')) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS texts, list(coalesce(text, '')) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 2 PRECEDING AND 1 PRECEDING) AS before FROM conversations) WHERE role = 'user')"
CHAT_N = f"len({TOK.format('said')}) + len({TOK.format('history')})"
CHAT_PROMPT = f"""pr AS (SELECT q.qid, array_to_string(list_filter([b.body, nullif(q.history, ''), q.said], lambda x: x IS NOT NULL), chr(10)) AS prompt, CAST(coalesce(b.ct, 0) + {CHAT_N} AS INTEGER) AS n_tokens FROM queries q LEFT JOIN
    (SELECT qid, string_agg(context, chr(10) ORDER BY rank) AS body, sum(t) AS ct FROM (SELECT c.*, len({TOK.format('context')}) AS t, sum(len({TOK.format('context')})) OVER (PARTITION BY qid ORDER BY rank) AS run FROM two c) JOIN (SELECT qid, {CHAT_N} AS qt FROM queries) USING (qid) WHERE run + qt <= 2048 GROUP BY qid) b USING (qid))"""


@query(f"WITH {IDF_SQL}, {CHAT_SQL}, {hv_sql('qv', 'queries', 'qid', 'query')}, {hv_sql('dv', 'documents', 'doc_id', 'text')}, {retrieve_sql('ret', 3)}, {SENTS_SQL}, {condense_sql()}, {TWO}, {answer_sql('ans', 'two')}, {CHAT_PROMPT} SELECT conv_id, turn, md5(prompt) AS prompt, n_tokens, md5(reply) AS reply, refs FROM queries JOIN pr USING (qid) JOIN ans USING (qid) LEFT JOIN (SELECT qid, list_sort(list(DISTINCT doc_id)) AS refs FROM two GROUP BY qid) USING (qid)")
def w_chat(spark, d):
    """Chat: each user turn with its history retrieves documents, which are condensed, prompted, answered from and named."""
    docs, _, idf = _base(spark, d)
    made = rag.chat(sources.table(spark, d, "conversations"), docs, idf)
    return made.select("conv_id", "turn", F.md5("prompt").alias("prompt"), "n_tokens", F.md5("reply").alias("reply"), "refs")


@query(f"WITH documents AS (SELECT * FROM main.documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)), {BASE}, {PLAIN} SELECT {CTX} FROM plain")
def w_filtered(spark, d):
    """Plain retrieval over the labelled, good documents only."""
    good = sources.table(spark, d, "labels").where("quality = 1")
    docs = corpus.select_corpus(docs_of(spark, d).select("doc_id", "text"), good)
    return _ctx(rag.rag_plain(docs, queries_of(spark, d), C.idf_table(docs).cache()))


def _pages_sql() -> str:
    body = "html"
    for tag in corpus.UNREAD:
        body = f"regexp_replace({body}, '(?is)<{tag}[^>]*>.*?</{tag}>', ' ', 'g')"
    text = f"trim(regexp_replace(regexp_replace({body}, '(?s)<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))"
    chunked = _chunk_sql(5).replace("FROM documents", f"FROM (SELECT page_id AS doc_id, {text} AS text FROM pages)")
    return f"SELECT doc_id, chunk_no, n_tokens FROM ({chunked})"


@query(_pages_sql())
def w_pages(spark, d):
    """Chunks of the web pages as a second document source."""
    return corpus.chunk(corpus.strip_pages(sources.table(spark, d, "pages")), 5).select("doc_id", "chunk_no", "n_tokens")
