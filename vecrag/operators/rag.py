"""Retrieval pipelines: plain, small chunks, compressed, re-ranked, disk-backed, iterative and two-tier.

`retrieve` is exact: blocks of query vectors are broadcast (their size is checked) and scored against the documents' sparse
vectors where those are, k rows a query and task go on. The two-tier pipeline searches an index over document vectors.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.functions import vector as V
from vecrag.operators import baselines, partition
from vecrag.operators import condense as C
from vecrag.operators import index as two_tier
from vecrag.session import checkpointed, shared_folder

#: Documents of a query, and candidates that are ranked again.
K, FETCH = 4, 10


def retrieve(owners: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, key: str = "doc_id", dim: int = C.DIM, vectors: DataFrame | None = None, ids: DataFrame | None = None) -> DataFrame:
    """(qid, key, score, rank): the k owners of highest cosine, by (score rounded to 6 falling, key).

    Owners that share no bucket with a query are no candidates of it. `vectors` are the owners' as `owner_vectors` makes them,
    `ids` are those of `condense.packed_owners`.
    """
    qv = C.packed_owners(queries, "qid", idf, dim, "query")
    ov = C.packed_owners(owners, key, idf, dim, ids=ids) if vectors is None else vectors
    most = max(1, QUERY_BYTES // (8 * dim))
    blocks = -(-queries.count() // most)
    if blocks <= 1:
        return top(_partials(ov, _collected(qv), k, dim, key), key, k)
    if vectors is None:  # every block of queries reads them again
        ov = checkpointed(ov)
    ov = ov.coalesce(max(owners.sparkSession.sparkContext.defaultParallelism, -(-ov.count() // SHARD)))
    dealt = checkpointed(qv.withColumn("_q", F.pmod(F.xxhash64("qid"), F.lit(blocks))))
    found: DataFrame | None = None
    for block in range(blocks):
        part = checkpointed(top(_partials(ov, _collected(dealt.where(F.col("_q") == block).drop("_q")), k, dim, key), key, k))
        found = part if found is None else found.unionByName(part)
    return found


def owner_vectors(owners: DataFrame, idf: DataFrame, key: str = "doc_id", dim: int = C.DIM) -> DataFrame:
    """(key, _b, _w) of all owners, made once for several pipelines over them."""
    return checkpointed(C.packed_owners(owners, key, idf, dim))


#: Bytes of dense query vectors that are broadcast, owners scored in one step, owners of a task where queries go in blocks.
QUERY_BYTES, BLOCK, SHARD = 32 << 20, 512, 100_000
#: A bound on the error of a cosine in 4-byte numbers and on what rounding to 6 places changes.
SLACK = 1e-4


def _collected(qv: DataFrame):
    """Broadcast packed vectors of queries; their number is bounded by the caller."""
    t = qv.select("qid", "_b", "_w").toArrow().combine_chunks()
    b, w = (t[c].combine_chunks() if t.num_rows else pa.array([], pa.list_(kind)) for c, kind in (("_b", pa.int32()), ("_w", pa.float64())))
    packed = (t["qid"].to_numpy(), b.value_lengths().to_numpy(), b.flatten().to_numpy(), w.flatten().to_numpy())
    return qv.sparkSession.sparkContext.broadcast(packed)


def _partials(owners: DataFrame, shared, k: int, dim: int, key: str) -> DataFrame:
    """(qid, key, score): the k best owners of each task for each of the broadcast queries."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, lengths, b, w = shared.value
        q = np.zeros((len(qids), dim))
        q[np.repeat(np.arange(len(qids)), lengths), b] = w
        best = _Best(q, k)
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK):
                best.meet(batch.slice(at, BLOCK), dim, key)
        yield from best.rows(qids, key)

    return owners.mapInArrow(scan, f"qid long, {key} {owners.schema[key].dataType.simpleString()}, score double")


class _Best:
    """The k best owners so far of each query, by (score rounded to 6 falling, key).

    Products in 4-byte numbers rule out, with SLACK, what cannot be among them; the rest is scored in 8 bytes.
    """

    def __init__(self, q: np.ndarray, k: int) -> None:
        self.q, self.short, self.used, self.k = q, q.astype(np.float32), None, k
        self.score = np.full((len(q), k), -np.inf)
        self.keys: list[np.ndarray] = []  # a column for each field of the key
        self.kind: pa.DataType | None = None

    def meet(self, batch: pa.RecordBatch, dim: int, key: str) -> None:
        n = batch.num_rows
        if not n or not len(self.q):
            return
        b, w, own = batch.column("_b"), batch.column("_w"), batch.column(key)
        d = np.zeros((n, dim))
        d[np.repeat(np.arange(n), b.value_lengths().to_numpy()), b.flatten().to_numpy()] = w.flatten().to_numpy()
        fields = [f.to_numpy() for f in (own.flatten() if pa.types.is_struct(own.type) else [own])]
        if not self.keys:
            self.kind, self.keys = own.type, [np.zeros(self.score.shape, f.dtype) for f in fields]
        near = self.short @ d.astype(np.float32).T
        limit = self.score[:, -1] - SLACK
        take = min(self.k, n)
        free = np.flatnonzero(limit == -np.inf)
        if len(free):  # the k-th best of these alone is a bound too, if it can't be one that shares nothing
            kth = np.partition(near[free], n - take, axis=1)[:, n - take] - 2 * SLACK
            limit[free] = np.where(kth > SLACK, kth, -np.inf) if take == self.k else -np.inf
        weak = np.flatnonzero(limit <= SLACK)
        if len(weak):  # owners without a common bucket are none of theirs
            if self.used is None:
                self.used = (self.q != 0).astype(np.float32)
            some = near[weak]
            some[(self.used[weak] @ (d != 0).astype(np.float32).T) == 0] = -np.inf
            near[weak] = some
            kth = np.partition(some, n - take, axis=1)[:, n - take] - 2 * SLACK
            limit[weak] = np.maximum(limit[weak], kth) if take == self.k else limit[weak]
        r, c = np.nonzero((near >= limit[:, None]) & (near > -np.inf))
        for at in range(0, len(r), PAIRS):  # few, but where many owners tie
            self._add(r[at : at + PAIRS], c[at : at + PAIRS], d, fields)

    def _add(self, r: np.ndarray, c: np.ndarray, d: np.ndarray, fields: list[np.ndarray]) -> None:
        score = np.round((self.q[r] * d[c]).sum(1), 6) + 0.0
        rows = np.unique(r)
        every = np.concatenate([r, np.repeat(rows, self.k)])
        scores = np.concatenate([score, self.score[rows].ravel()])
        keys = [np.concatenate([f[c], held[rows].ravel()]) for f, held in zip(fields, self.keys, strict=True)]
        order = np.lexsort([*reversed(keys), -scores, every])
        at = np.searchsorted(every[order], rows)
        chosen = order[at[:, None] + np.arange(self.k)]
        self.score[rows] = scores[chosen]
        for held, new in zip(self.keys, keys, strict=True):
            held[rows] = new[chosen]

    def rows(self, qids: np.ndarray, key: str) -> Iterator[pa.RecordBatch]:
        r, c = np.nonzero(self.score > -np.inf)
        for at in range(0, len(r), PAIRS):
            i, j = r[at : at + PAIRS], c[at : at + PAIRS]
            if pa.types.is_struct(self.kind):
                own = pa.StructArray.from_arrays([pa.array(f[i, j], t.type) for f, t in zip(self.keys, self.kind, strict=True)], fields=list(self.kind))
            else:
                own = pa.array(self.keys[0][i, j], self.kind)
            yield pa.RecordBatch.from_arrays([pa.array(qids[i], pa.int64()), own, pa.array(self.score[i, j])], ["qid", key, "score"])


#: Pairs of a query and an owner that are scored in 8 bytes at once.
PAIRS = 50_000


def top(scored: DataFrame, key: str, k: int) -> DataFrame:
    rank = F.row_number().over(W.partitionBy("qid").orderBy(F.desc("score"), key))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", key, "score", "rank")


def bm25(docs: DataFrame, queries: DataFrame, k: int = 10, k1: float = 1.2, b: float = 0.75, text: str = "text", pairs: DataFrame | None = None, texts: DataFrame | None = None) -> DataFrame:
    """(qid, doc_id, score, rank) of the k best documents by keyword; only postings of query terms are counted.

    With `pairs` (qid, doc_id) only those are scored and ranked, by the statistics of all documents; `texts` are the documents of the pairs.
    """
    lengths = docs.select("doc_id", V.token_count(text).alias("dl"))
    facts = lengths.agg(F.count("*").alias("n"), F.avg("dl").alias("avg_dl"))
    terms = queries.select("qid", F.explode(F.array_distinct(V.tokens("query"))).alias("token"))
    wanted = terms.select("token").distinct()
    df = docs.select(F.explode(F.array_distinct(V.tokens(text))).alias("token")).join(wanted, "token", "left_semi").groupBy("token").agg(F.count("*").alias("df"))
    if pairs is not None:
        docs = docs.join(pairs.select("doc_id").distinct(), "doc_id", "left_semi") if texts is None else texts
        lengths = docs.select("doc_id", V.token_count(text).alias("dl"))
    postings = docs.select("doc_id", F.explode(V.tokens(text)).alias("token")).join(wanted, "token", "left_semi").groupBy("doc_id", "token").agg(F.count("*").alias("tf"))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    weight = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("dl") / F.col("avg_dl")))
    scored = postings.join(df, "token").join(lengths, "doc_id").join(F.broadcast(facts)).select("token", "doc_id", weight.alias("w"))
    if pairs is not None:
        terms = terms.join(pairs.select("qid", F.col("doc_id").alias("_doc")), "qid")
        scored = scored.withColumn("_doc", F.col("doc_id"))
    met = terms.join(scored, ["token"] if pairs is None else ["token", "_doc"])
    return top(met.groupBy("qid", "doc_id").agg(F.round(F.sum("w"), 6).alias("score")), "doc_id", k)


# -- pipelines: (qid, doc_id, rank, context) ----------------------------------------------------------------------------
def with_text(ranked: DataFrame, docs: DataFrame) -> DataFrame:
    """Texts of retrieved ids."""
    return ranked.join(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("context")), "doc_id").select("qid", "doc_id", "rank", "context")


def rag_plain(docs: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K) -> DataFrame:
    """Whole documents in order of retrieval."""
    return with_text(retrieve(docs, queries, idf, k), docs)


def rag_small_chunks(chunks: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, ids: DataFrame | None = None) -> DataFrame:
    """Chunks instead of documents: `chunks` as made by corpus.chunk with a smaller ratio, of the documents `ids` if given."""
    keyed = chunks.withColumn("key", F.struct("doc_id", "chunk_no"))
    found = retrieve(keyed, queries, idf, k, key="key", ids=ids)
    return found.join(keyed.select("key", F.col("text").alias("context")), "key").select("qid", F.col("key.doc_id").alias("doc_id"), F.col("key.chunk_no").alias("chunk_no"), "rank", "context")


def rag_compressed(docs: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, keep: float = 0.5, dim: int = C.DIM, found: DataFrame | None = None) -> DataFrame:
    """Query-blind: the share `keep` of a document's sentences that lie closest to the document's own vector, in text order.

    `found` (qid, doc_id, rank) takes the place of the retrieval.
    """
    found = retrieve(docs, queries, idf, k) if found is None else found
    wanted = docs.join(found.select("doc_id").distinct(), "doc_id", "left_semi")
    sents = wanted.select("doc_id", F.posexplode(V.sentences("text")).alias("no", "text"))
    sv = C.sparse_vectors(sents, ["doc_id", "no"], idf, dim)
    dv = C.sparse_vectors(wanted, ["doc_id"], idf, dim).withColumnRenamed("w", "dw")
    near = sv.join(dv, ["doc_id", "bucket"]).groupBy("doc_id", "no").agg(F.sum(F.col("w") * F.col("dw")).alias("s"))
    scored = sents.join(near, ["doc_id", "no"], "left").withColumn("s", F.round(F.coalesce("s", F.lit(0.0)), 6))
    per = W.partitionBy("doc_id")
    kept = scored.withColumn("r", F.row_number().over(per.orderBy(F.desc("s"), "no"))).withColumn("n", F.count("*").over(per)).where(F.col("r") <= F.ceil(F.lit(keep) * F.col("n")))
    short = kept.groupBy("doc_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("no", "text"))), lambda x: x["text"]), " ").alias("context"))
    return found.join(short, "doc_id", "left").select("qid", "doc_id", "rank", F.coalesce("context", F.lit("")).alias("context"))


def rag_reranked(docs: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, fetch: int = FETCH, dim: int = C.DIM, found: DataFrame | None = None, texts: DataFrame | None = None) -> DataFrame:
    """`fetch` candidates ranked again by the mean of scaled BM25 and their best sentence's cosine.

    `found` (qid, doc_id) takes the place of the retrieval, `texts` has the found documents; BM25 still counts all of `docs`.
    """
    found = checkpointed((retrieve(docs, queries, idf, fetch) if found is None else found).select("qid", "doc_id"))
    wanted = docs.join(found.select("doc_id").distinct(), "doc_id", "left_semi") if texts is None else texts
    words = bm25(docs, queries, fetch, pairs=found, texts=wanted).select("qid", "doc_id", F.col("score").alias("kw"))
    best = C.best_windows(wanted, found, queries, idf, [(1, 0)], 1, dim).select("qid", "doc_id", F.col("score").alias("sem"))
    both = found.join(words, ["qid", "doc_id"], "left").join(best, ["qid", "doc_id"], "left").fillna(0.0, ["kw", "sem"])
    per = W.partitionBy("qid")
    low, high = F.min("kw").over(per), F.max("kw").over(per)
    scaled = F.when(high > low, (F.col("kw") - low) / (high - low)).otherwise(F.lit(0.0))
    ranked = top(both.withColumn("score", F.round((scaled + F.col("sem")) / 2, 6)), "doc_id", k)
    return with_text(ranked, wanted)


def rag_disk(docs: DataFrame, queries: DataFrame, idf: DataFrame, path: str, k: int = K, n_c: int = 8, n_p: int = 4, dim: int = C.DIM, vectors: DataFrame | None = None) -> DataFrame:
    """Inverted lists of document vectors written to `path`; only probed buckets are read, then whole documents.

    How many loads a cache of lists saves is reported by scale.cache_report.
    """
    spark = docs.sparkSession
    made = C.packed_owners(docs, "doc_id", idf, dim) if vectors is None else vectors
    dv = C.dense_of(made, ["doc_id"], dim).select(F.col("doc_id").alias("id"), "v")
    dv.write.mode("overwrite").parquet(f"{path}/vectors")  # made once, read by every pass over them
    dv = spark.read.parquet(f"{path}/vectors")
    cents = partition.fit_partitions(dv, n_c, rounds=1)
    baselines.save_lists(partition.assign(dv, cents), f"{path}/lists")
    qv = C.dense_vectors(C.sparse_vectors(queries, ["qid"], idf, dim, "query"), ["qid"], dim).select((-F.col("qid") - 1).alias("qid"), F.col("v").alias("qv"))
    found = baselines.ivf_disk_search(spark, f"{path}/lists", cents, qv, k, n_p, metric="overlap")  # ranks as in retrieve; query ids below 0: no document is taken for the query itself
    return with_text(found.select((-F.col("qid") - 1).alias("qid"), F.col("id").alias("doc_id"), "rank"), docs)


def rag_iterative(docs: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, rounds: int = 2) -> DataFrame:
    """Retrieval repeated with each query's best sentence so far appended to it."""
    asked = queries.select("qid", "query")
    for _ in range(rounds - 1):
        first = with_text(retrieve(docs, asked, idf, 1), docs)
        reply = answer(first, asked, idf)
        asked = asked.join(reply.select("qid", "reply"), "qid", "left").select("qid", F.concat_ws(" ", "query", "reply").alias("query"))
    return rag_plain(docs, asked, idf, k)


def document_index(docs: DataFrame, idf: DataFrame, path: str, n_c: int | None = None, rounds: int = 2, dim: int = C.DIM, vectors: DataFrame | None = None) -> two_tier.Index:
    """A saved two-tier index over unit document vectors (`vectors` as `owner_vectors` makes them, if given); documents without
    known tokens are not in it.
    """
    made = C.packed_owners(docs, "doc_id", idf, dim) if vectors is None else vectors
    dv = C.dense_of(made, ["doc_id"], dim).select(F.col("doc_id").alias("id"), "v")
    dv.write.mode("overwrite").parquet(f"{path}/vectors")  # made once, read by every pass over them
    dv = docs.sparkSession.read.parquet(f"{path}/vectors")
    return two_tier.save_index(two_tier.build_index(dv, n_c=n_c, rounds=rounds), f"{path}/index")


def rag_two_tier(docs: DataFrame, queries: DataFrame, idf: DataFrame, k: int = K, index: two_tier.Index | None = None, ranked: DataFrame | None = None, window: int = C.WINDOW, overlap: int = C.OVERLAP, ext: int = C.EXT, path: str | None = None, **width) -> DataFrame:
    """Search of a two-tier index over the documents, then condensation and new order.

    The index is built at `path` (or a folder of the session's) unless given; `ranked` (qid, doc_id, rank) takes the place
    of the search.
    """
    if ranked is None:
        index = document_index(docs, idf, path or shared_folder(docs.sparkSession)) if index is None else index
        ranked = index_ranks(index, queries, idf, k, **width)
    made = C.condense(ranked.select("qid", "doc_id", "rank"), docs, queries, idf, window, overlap, ext)
    return made.select("qid", "doc_id", F.col("new_rank").alias("rank"), F.col("text").alias("context"))


def query_vectors(queries: DataFrame, idf: DataFrame, dim: int = C.DIM) -> DataFrame:
    """(qid, qv): unit vectors of the queries with known tokens."""
    return checkpointed(C.dense_vectors(C.sparse_vectors(queries, ["qid"], idf, dim, "query"), ["qid"], dim).select("qid", F.col("v").alias("qv")))


def index_ranks(index: two_tier.Index, queries: DataFrame, idf: DataFrame, k: int = K, dim: int = C.DIM, **width) -> DataFrame:
    """(qid, doc_id, rank) from a two-tier index over unit document vectors: found by l2, ranked by cosine as `retrieve` does."""
    return two_tier.search(index, query_vectors(queries, idf, dim), k, skip_self=False, metric="overlap", **width).select("qid", F.col("id").alias("doc_id"), "rank")


# -- prompt and reply ------------------------------------------------------------------------------------------------------
def build_prompt(contexts: DataFrame, queries: DataFrame, budget: int = 2048, history: DataFrame | None = None) -> DataFrame:
    """(qid, prompt, n_tokens, n_contexts): contexts in order as long as their tokens fit the budget, then the turns of
    `history` (qid, history) if given, then the query; history and query count before the contexts.
    """
    asked = queries.select("qid", "query", F.lit(None).cast("string").alias("history")) if history is None else queries.select("qid", "query").join(history.select("qid", "history"), "qid", "left")
    asked = asked.withColumn("qt", V.token_count("query") + F.coalesce(V.token_count("history"), F.lit(0)))
    sized = contexts.withColumn("t", V.token_count("context"))
    run = F.sum("t").over(W.partitionBy("qid").orderBy("rank").rowsBetween(W.unboundedPreceding, 0))
    fits = sized.withColumn("run", run).join(asked.select("qid", "qt"), "qid").where(F.col("run") + F.col("qt") <= budget)
    body = fits.groupBy("qid").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rank", "context"))), lambda x: x["context"]), "\n").alias("body"), F.sum("t").alias("ct"), F.count("*").alias("n_contexts"))
    out = asked.join(body, "qid", "left")
    return out.select("qid", F.concat_ws("\n", "body", "history", "query").alias("prompt"), (F.coalesce("ct", F.lit(0)) + F.col("qt")).cast("int").alias("n_tokens"), F.coalesce("n_contexts", F.lit(0)).alias("n_contexts"))


def answer(contexts: DataFrame, queries: DataFrame, idf: DataFrame, dim: int = C.DIM) -> DataFrame:
    """(qid, reply, doc_id, score): the extractive default generator - the context sentence most similar to the query.

    Ties go to the context of lower rank, then the earlier sentence.
    """
    sents = contexts.select("qid", "doc_id", "rank", F.posexplode(V.sentences("context")).alias("no", "text"))
    sv = C.sparse_vectors(sents, ["qid", "rank", "no"], idf, dim)
    qv = C.sparse_vectors(queries, ["qid"], idf, dim, "query").withColumnRenamed("w", "qw")
    near = sv.join(qv, ["qid", "bucket"]).groupBy("qid", "rank", "no").agg(F.sum(F.col("w") * F.col("qw")).alias("s"))
    scored = sents.join(near, ["qid", "rank", "no"], "left").withColumn("s", F.round(F.coalesce("s", F.lit(0.0)), 6))
    best = scored.groupBy("qid").agg(F.min(F.struct((-F.col("s")).alias("low"), "rank", "no", "text", "doc_id")).alias("b"))
    return queries.select("qid").join(best, "qid", "left").select("qid", F.coalesce("b.text", F.lit("")).alias("reply"), "b.doc_id", F.round(-F.coalesce("b.low", F.lit(0.0)), 6).alias("score"))


def references(contexts: DataFrame) -> DataFrame:
    """(qid, refs): the documents a reply rests on."""
    return contexts.groupBy("qid").agg(F.array_sort(F.collect_set("doc_id")).alias("refs"))


def open_reference(docs: DataFrame, doc_id: int) -> DataFrame:
    return docs.where(F.col("doc_id") == doc_id).select("doc_id", "text")


def chat_queries(conversations: DataFrame, history: int = 2) -> DataFrame:
    """(qid, conv_id, turn, query, said, history): each user turn; `query` is what is searched for, the texts of the turn
    and of up to `history` turns before it; `said` is the turn by itself, `history` the turns before.

    qid is a hash of conversation and turn: no number of turns makes two of them meet.
    """
    order = W.partitionBy("conv_id").orderBy("turn")
    text = F.coalesce("text", F.lit(""))
    turns = conversations.withColumn("texts", F.collect_list(text).over(order.rowsBetween(-history, 0))).withColumn("before", F.collect_list(text).over(order.rowsBetween(-history, -1)))
    qid = F.conv(F.substring(F.md5(F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string"))), 1, 15), 16, 10).cast("long")
    return turns.where("role = 'user'").select(qid.alias("qid"), "conv_id", "turn", F.array_join("texts", " ").alias("query"), text.alias("said"), F.array_join("before", "\n").alias("history"))


def chat(conversations: DataFrame, docs: DataFrame, idf: DataFrame, k: int = 3, budget: int = 2048, history: int = 2, ranked: DataFrame | None = None) -> DataFrame:
    """(qid, conv_id, turn, prompt, n_tokens, reply, refs) of each user turn: the turn with its history retrieves documents,
    which are condensed, prompted with the history, answered from and named as references.
    """
    asked = checkpointed(chat_queries(conversations, history))
    found = retrieve(docs, asked, idf, k) if ranked is None else ranked
    contexts = checkpointed(rag_two_tier(docs, asked, idf, k, ranked=found))
    prompts = build_prompt(contexts, asked.select("qid", F.col("said").alias("query")), budget, asked.select("qid", F.when(F.col("history") != "", F.col("history")).alias("history")))
    replies = answer(contexts, asked, idf).select("qid", "reply")
    return asked.select("qid", "conv_id", "turn").join(prompts.select("qid", "prompt", "n_tokens"), "qid").join(replies, "qid").join(references(contexts), "qid", "left")


def normalised(text: Column) -> Column:
    """Lower-cased tokens joined by one space."""
    return F.array_join(V.tokens(text), " ")
