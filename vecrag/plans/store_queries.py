"""Registered queries of the store, the index source, the SQL surface and the streaming forms."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecrag import sources
from vecrag.functions import udf
from vecrag.operators import corpus, knn
from vecrag.operators import index as two_tier
from vecrag.operators.condense import split_sentences, windows
from vecrag.plans import ann_queries as A
from vecrag.plans import rag_queries as R
from vecrag.plans.shared import folder, query
from vecrag.sources import index_source, store
from vecrag.streaming import streams


def _store(spark, d) -> str:
    """A store of the documents whose ids are vectors' ids, without every tenth; those come as an update."""
    path = folder(spark)
    emb, doc, chunk = _tables(spark, d)
    first = F.col("doc_id") % 10 != 0
    store.write_tables(spark, path, emb.where(first), doc.where(first), chunk.where(first))
    late, gone = F.col("doc_id") % 10 == 0, doc.where("doc_id % 10 = 1")
    store.update_store(spark, path, {"emb": emb.where(late), "doc": doc.where(late), "chunk": chunk.where(late)}, gone)
    return path


def _tables(spark, d):
    docs = sources.table(spark, d, "documents").select("doc_id", "text", "source")
    emb = sources.vectors(spark, d).select(F.col("id").alias("vec_id"), F.col("id").alias("doc_id"), F.col("v").alias("embedding"))
    doc = docs.select("doc_id", F.concat_ws("/", "source", F.col("doc_id").cast("string")).alias("path"))
    chunk_id = F.xxhash64("doc_id", "chunk_no")  # no number of chunks makes two of them meet
    chunk = corpus.chunk(docs, 5).select(chunk_id.alias("chunk_id"), "doc_id", "offset")
    return emb, doc, chunk


@query("SELECT count(*) AS files, (SELECT count(*) FROM embeddings WHERE vec_id NOT IN (SELECT doc_id FROM documents WHERE doc_id % 10 = 1)) AS vectors, count(*) FILTER (WHERE doc_id % 10 = 0) AS new_files, (SELECT count(*) FROM embeddings WHERE vec_id % 10 = 0) AS new_vectors FROM documents WHERE doc_id % 10 <> 1")
def w_status(spark, d):
    """Index status after a build and an update."""
    return store.status(spark, _store(spark, d))


@query("SELECT doc_id, source || '/' || doc_id AS path FROM documents WHERE doc_id % 10 <> 1")
def store_documents(spark, d):
    path = _store(spark, d)
    return store.read_table(spark, path, "doc").select("doc_id", "path")


@query(A.IVF_SQL.replace(A.IVF_BODY, "SELECT a1.cluster_id, count(*) AS n FROM a1 WHERE cluster_id IN (1, 5, 9) GROUP BY 1"))
def index_source_pruned(spark, d):
    """The Python data source with a pushed filter: only the named lists' buckets are read."""
    idx, *_ = A._index(spark, d)
    saved = two_tier.save_index(idx, folder(spark))
    spark.dataSource.register(index_source.IndexSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    lists = spark.read.format("vecrag_index").option("path", f"{saved.path}/lists/v=0").option("buckets", saved.buckets).load()
    return lists.where(F.col("cluster_id").isin(1, 5, 9)).select("cluster_id", F.col("n").cast("long").alias("n"))


@query(f"WITH {A.E_SQL}, {A.Q_SQL} SELECT qid, id, d2, cos FROM (SELECT qid, id, round(list_distance(qv, v) ** 2, 6) AS d2, round(list_cosine_similarity(qv, v), 6) AS cos, row_number() OVER (PARTITION BY qid ORDER BY round(list_distance(qv, v) ** 2, 6), id) AS r FROM q JOIN e ON id <> qid) WHERE r <= 3")
def sql_functions(spark, d):
    """Vector functions from SQL, without Python: the three nearest of all vectors for the stated queries."""
    vectors = sources.vectors(spark, d)
    udf.register(spark, udf.only_size(vectors))
    vectors.createOrReplaceTempView("sf_vectors")
    pairs = "SELECT q.id AS qid, e.id, round(l2sq(q.v, e.v), 6) AS d2 FROM sf_vectors e JOIN sf_vectors q ON q.id % 50 = 0 AND e.id <> q.id"
    near = f"SELECT qid, id, d2 FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, id) AS r FROM ({pairs})) WHERE r <= 3"
    return spark.sql(f"SELECT n.qid, n.id, n.d2, round(vcosine(q.v, e.v), 6) AS cos FROM ({near}) n JOIN sf_vectors q ON q.id = n.qid JOIN sf_vectors e ON e.id = n.id")


@query(f"WITH {A.ONE_ROUND}, mm AS (SELECT cluster_id, j, count(*) AS n, avg(x) AS x FROM (SELECT cluster_id, generate_subscripts(v, 1) AS j, unnest(v) AS x FROM a1) GROUP BY 1, 2) SELECT cluster_id, max(n) AS n, round(sum(x * x), 6) AS sq FROM mm GROUP BY cluster_id")
def vec_mean(spark, d):
    """Mean vector of each list by the two-phase vector aggregate, as its squared length."""
    lists = A._lists(spark, d)[3]
    m = udf.vec_mean(lists, "cluster_id")
    return m.select(F.col("cluster_id").cast("int").alias("cluster_id"), "n", F.round(F.aggregate("mean", F.lit(0.0), lambda s, x: s + x * x), 6).alias("sq"))


@query(f"WITH sents AS (SELECT item_id AS doc_id, {R.SENT.format('text')} AS sents FROM benchmark), {R.windows_sql('w', 3, 1)} SELECT doc_id AS item_id, start, stop FROM w")
def udtf_windows(spark, d):
    """Windows by the table function, in a lateral join."""
    udf.register(spark)
    sources.table(spark, d, "benchmark").createOrReplaceTempView("uw_docs")
    return spark.sql("SELECT item_id, w.start, w.stop FROM uw_docs, LATERAL windows_of(text, 3, 2) w")


@query(f"WITH sents AS (SELECT item_id AS doc_id, {R.SENT.format('text')} AS sents FROM benchmark), {R.windows_sql('w', 3, 1)} SELECT doc_id AS item_id, start, stop FROM w")
def windows_of_benchmark(spark, d):
    items = sources.table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
    return windows(split_sentences(items)).select(F.col("doc_id").alias("item_id"), "start", "stop")


# -- streams: each runs over what is there and must equal its batch form --------------------------------------------------
def _events(spark, d):
    schema = sources.table(spark, d, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def _drained(spark, stream, mode: str = "append"):
    return streams.drain(stream, folder(spark), folder(spark), mode)


@query("SELECT time_bucket(INTERVAL 10 MINUTE, ts) AS start, count(*) AS n, CAST(count(*) AS DOUBLE) AS uj_model FROM events GROUP BY 1")
def stream_tumbling(spark, d):
    out = _drained(spark, streams.tumbling(_events(spark, d)), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "uj_model")


@query("SELECT s AS start, count(*) AS n FROM (SELECT unnest(generate_series(time_bucket(INTERVAL 10 MINUTE, ts) - INTERVAL 50 MINUTE, time_bucket(INTERVAL 10 MINUTE, ts), INTERVAL 10 MINUTE)) AS s FROM events) GROUP BY 1")
def stream_sliding(spark, d):
    out = _drained(spark, streams.sliding(_events(spark, d)), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), n AS (SELECT *, sum(s) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS n FROM n GROUP BY user_id, k")
def stream_sessions(spark, d):
    out = _drained(spark, streams.sessions(_events(spark, d)), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("stop").cast("timestamp_ntz").alias("stop"), "n")


@query("SELECT event_id, event_type FROM events")
def stream_once(spark, d):
    """Each event arrives twice and counts once."""
    twice = _events(spark, d).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    return _drained(spark, streams.once(twice)).select("event_id", "event_type")


@query("SELECT u.user_id, u.ts AS uts, q.ts AS qts FROM events u JOIN events q ON u.user_id = q.user_id AND u.event_type = 'signup' AND q.event_type = 'view' AND u.ts BETWEEN q.ts - INTERVAL 1 HOUR AND q.ts")
def stream_interval_join(spark, d):
    e = _events(spark, d)
    out = _drained(spark, streams.updates_before(e.where("event_type = 'signup'"), e.where("event_type = 'view'")))
    return out.select("user_id", F.col("uts").cast("timestamp_ntz").alias("uts"), F.col("qts").cast("timestamp_ntz").alias("qts"))


@query("SELECT user_id, count(*) AS n, CAST(sum(CASE WHEN event_type = p THEN 1 ELSE 0 END) AS BIGINT) AS hits FROM (SELECT *, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) GROUP BY user_id")
def stream_cache_hits(spark, d):
    """State per user: whether a request repeats the one before."""
    out = _drained_state(spark, streams.cache_hits(_events(spark, d)))
    return out.groupBy("user_id").agg(F.sum("n").alias("n"), F.sum("hits").alias("hits"))


def _drained_state(spark, stream):
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return _drained(spark, stream, "update")
    finally:
        spark.conf.set(key, before)


@query(f"WITH {A.E_SQL}, {A.Q_SQL}, {A.UPD_ALL_SQL}, {A.LIVE_SQL} {A.exact_sql('list_distance(qv, v)', rows='live')}")
def stream_updated_search(spark, d):
    """The whole log of updates arrives as a stream; the index must answer as after a batch update."""
    idx, e, q = A._index(spark, d)
    log = folder(spark)
    sources.update_log(spark, d).write.parquet(log)
    updates = spark.readStream.schema(spark.read.parquet(log).schema).parquet(log)
    updated = streams.stream_updates(idx, updates, folder(spark), folder(spark))
    return two_tier.search(updated, q, A.K, n_p=A.N_C, ef_c=A.WIDE, ef_l=A.WIDE)


@query(f"WITH {A.E_SQL}, {A.Q_SQL} {A.exact_sql('list_distance(qv, v)')}")
def stream_queries(spark, d):
    """Queries arrive as a stream and are answered per micro-batch."""
    idx, _, q = A._index(spark, d)
    asked, out = folder(spark), folder(spark)
    q.repartition(1).write.parquet(asked)
    saved = two_tier.save_index(idx, folder(spark))
    streams.stream_search(saved, spark.readStream.schema(q.schema).parquet(asked), out, folder(spark), A.K, n_p=A.N_C, ef_c=A.WIDE, ef_l=A.WIDE)
    return spark.read.parquet(out).select("qid", "id", "d", "rank")


@query("SELECT * FROM (VALUES ((SELECT count(*) * 4 // 200 FROM embeddings), 1, true), ((SELECT count(*) * 4 // 200 FROM embeddings), 2, true)) t(queries, n_p, enough)")
def expanded_recall(spark, d):
    """Recall of one and two probed lists on noisy copies of the vectors, which have clusters: at least 0.75 and 0.85. Each
    vector is in its four nearest lists, so that the number of lists, which grows with the table, takes no recall.
    """
    e = sources.expanded_embeddings(spark, d, 4).select("id", "v").cache()
    q = e.where("id % 200 = 0").select(F.col("id").alias("qid"), F.col("v").alias("qv"))
    truth = knn.knn_exact(e, q, 3).cache()
    idx = two_tier.save_index(two_tier.build_index(e, rounds=4, copies=4), folder(spark))
    from vecrag.operators.baselines import recall_at_k

    out = [recall_at_k(two_tier.search(idx, q, 3, n_p=n, ef_l=64), truth, 3).select("queries", F.lit(n).alias("n_p"), (F.col("recall") >= least).alias("enough")) for n, least in ((1, 0.75), (2, 0.85))]
    return out[0].unionByName(out[1])


@query("SELECT user_id, count(*) AS n, 0 AS late FROM events GROUP BY user_id")
def stream_late_rows(spark, d):
    """Rows that come too late are counted beside the windows; the events come in order, so none is."""
    out = streams.tumbling_with_late(_events(spark, d), streams.run_name("late"), folder(spark), folder(spark))
    late = out.agg(F.sum("late").cast("int").alias("late"))
    return sources.table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).join(late)


@query(None)
def stream_pending_updates(spark, d):
    """Updates wait by list and come out in groups of eight or more; here without a timer, so fewer stay in the state."""
    idx, *_ = A._index(spark, d)
    log = folder(spark)
    routed = two_tier.route(idx, A._ops(spark, d)).select(F.col("cluster_id").cast("long").alias("cluster_id"), F.col("id").alias("seq"), "op", "id")
    routed.repartition(1).write.parquet(log)
    return _drained_state(spark, streams.pending_updates(spark.readStream.schema(routed.schema).parquet(log), wait_ms=None))
