"""Registered queries of the vector methods, each with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecrag import sources
from vecrag.functions import udf
from vecrag.operators import baselines as B
from vecrag.operators import index as two_tier
from vecrag.operators import knn, partition
from vecrag.plans.shared import folder, query

N_C, N_P, K, WIDE = 16, 4, 10, two_tier.FULL

E_SQL = "e AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings)"
Q_SQL = "q AS (SELECT id AS qid, v AS qv FROM e WHERE id % 50 = 0)"
N_SQL = f"n AS (SELECT count(*) AS n, greatest(1, count(*) // {N_C}) AS step FROM e)"
C0_SQL = f"c0 AS (SELECT CAST(id // step AS INTEGER) AS cluster_id, v AS cv FROM e, n WHERE id % step = 0 AND id // step < {N_C})"


def assign_sql(name: str, cents: str, rows: str = "e") -> str:
    return f"""{name} AS (SELECT id, v, cluster_id, dist FROM (
        SELECT id, v, cluster_id, list_distance(v, cv) AS dist, row_number() OVER (PARTITION BY id ORDER BY round(list_distance(v, cv), 6), cluster_id) AS r FROM {rows}, {cents}) WHERE r = 1)"""


C1_SQL = """m1 AS (SELECT cluster_id, j, avg(x) AS x FROM (SELECT cluster_id, generate_subscripts(v, 1) AS j, unnest(v) AS x FROM a0) GROUP BY cluster_id, j),
    c1 AS (SELECT c0.cluster_id, coalesce(m.cv, c0.cv) AS cv FROM c0 LEFT JOIN (SELECT cluster_id, list(x ORDER BY j) AS cv FROM m1 GROUP BY cluster_id) m USING (cluster_id))"""
SEEDED = f"{E_SQL}, {Q_SQL}, {N_SQL}, {C0_SQL}, {assign_sql('a0', 'c0')}"
ONE_ROUND = f"{SEEDED}, {C1_SQL}, {assign_sql('a1', 'c1')}"


def probe_sql(name: str = "p", cents: str = "c1", n_p: int = N_P) -> str:
    return f"""{name} AS (SELECT qid, qv, cluster_id, c_dist, probe_rank FROM (
        SELECT qid, qv, cluster_id, round(list_distance(qv, cv), 6) AS c_dist, row_number() OVER (PARTITION BY qid ORDER BY round(list_distance(qv, cv), 6), cluster_id) AS probe_rank FROM q, {cents}) WHERE probe_rank <= {n_p})"""


def ranked_sql(source: str, k: int = K) -> str:
    """source gives qid, id, d (rounded)."""
    return f"SELECT qid, id, d, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d, id) AS rank FROM ({source})) WHERE rank <= {k}"


def exact_sql(expr: str, k: int = K, rows: str = "e") -> str:
    return ranked_sql(f"SELECT qid, id, round({expr}, 6) AS d FROM q JOIN {rows} ON qid <> id", k)


IVF_BODY = ranked_sql("SELECT qid, id, round(list_distance(qv, v), 6) AS d FROM p JOIN a1 USING (cluster_id) WHERE qid <> id")
IVF_SQL = f"WITH {ONE_ROUND}, {probe_sql()} {IVF_BODY}"


def _e(spark, d) -> tuple[DataFrame, DataFrame]:
    return sources.vectors(spark, d), sources.ann_queries(spark, d)


def _lists(spark, d) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    e, q = _e(spark, d)
    cents = partition.fit_partitions(e, N_C, rounds=1)
    return e, q, cents, partition.assign(e, cents)


def _index(spark, d) -> tuple[two_tier.Index, DataFrame, DataFrame]:
    e, q = _e(spark, d)
    return two_tier.build_index(e, n_c=N_C, rounds=1), e, q


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('list_distance(qv, v)')}")
def knn_exact_l2(spark: SparkSession, d: str) -> DataFrame:
    return knn.knn_exact(*_e(spark, d), K)


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('-list_dot_product(qv, v)')}")
def knn_exact_ip(spark, d):
    return knn.knn_exact(*_e(spark, d), K, "ip")


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('1 - list_cosine_similarity(qv, v)')}")
def knn_exact_cosine(spark, d):
    return knn.knn_exact(*_e(spark, d), K, "cosine")


@query(f"WITH {E_SQL}, {Q_SQL} SELECT qid, id, round(list_distance(qv, v), 6) AS d FROM q JOIN e ON qid <> id WHERE round(list_distance(qv, v), 6) <= 1.15")
def vec_range_search(spark, d):
    return knn.range_search(*_e(spark, d), 1.15)


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('list_distance(qv, v)', 3)}")
def vec_knn_join(spark, d):
    """k nearest by SQL alone: a lateral join with an ordered limit. Its pairs carry ids and distances, no vectors."""
    e, q = _e(spark, d)
    udf.register(spark, udf.only_size(e))
    e.createOrReplaceTempView("kj_vectors")
    q.createOrReplaceTempView("kj_queries")
    pairs = "SELECT q.qid, e.id, round(sqrt(l2sq(q.qv, e.v)), 6) AS d FROM kj_vectors e JOIN kj_queries q ON e.id <> q.qid"
    near = spark.sql(f"SELECT q.qid, n.id, n.d FROM (SELECT qid FROM kj_queries) q, LATERAL (SELECT p.id, p.d FROM ({pairs}) p WHERE p.qid = q.qid ORDER BY p.d, p.id LIMIT 3) n")
    return knn.merge_topk(near, 3)


@query(f"WITH {SEEDED} SELECT cluster_id, CAST(j - 1 AS INTEGER) AS j, round(x, 6) AS x FROM (SELECT cluster_id, generate_subscripts(cv, 1) AS j, unnest(cv) AS x FROM c0)")
def kmeans_seeded(spark, d):
    return _long(partition.fit_partitions(sources.vectors(spark, d), N_C, rounds=0))


@query(f"WITH {ONE_ROUND} SELECT cluster_id, CAST(j - 1 AS INTEGER) AS j, round(x, 6) AS x FROM (SELECT cluster_id, generate_subscripts(cv, 1) AS j, unnest(cv) AS x FROM c1)")
def kmeans_one_round(spark, d):
    return _long(partition.fit_partitions(sources.vectors(spark, d), N_C, rounds=1))


def _long(cents: DataFrame) -> DataFrame:
    return cents.select("cluster_id", F.posexplode("cv").alias("j", "x")).select("cluster_id", "j", F.round("x", 6).alias("x"))


@query(None)
def kmeans_parallel(spark, d):
    return _long(partition.fit_partitions(sources.vectors(spark, d), N_C, rounds=5, init="parallel"))


@query(None)
def kmeans_sample(spark, d):
    return _long(partition.fit_partitions(sources.vectors(spark, d), N_C, rounds=5, init="sample"))


@query(f"WITH {ONE_ROUND} SELECT id, cluster_id, round(dist, 6) AS dist FROM a1")
def assign_lists(spark, d):
    return _lists(spark, d)[3].select("id", "cluster_id", F.round("dist", 6).alias("dist"))


@query(f"WITH {ONE_ROUND} SELECT cluster_id, count(*) AS n, round(max(dist), 6) AS radius FROM a1 GROUP BY cluster_id")
def partition_stats(spark, d):
    return partition.partition_stats(_lists(spark, d)[3])


@query(f"WITH {ONE_ROUND} SELECT CAST(n // 10 * 10 AS BIGINT) AS bin_from, count(*) AS lists FROM (SELECT cluster_id, count(*) AS n FROM a1 GROUP BY cluster_id) GROUP BY 1")
def list_size_histogram(spark, d):
    return partition.list_size_histogram(_lists(spark, d)[3], 10)


@query(None)
def split_large(spark, d):
    return partition.partition_stats(partition.split_large(_lists(spark, d)[3], 40))


@query(f"WITH {ONE_ROUND}, {probe_sql()} SELECT qid, cluster_id, c_dist, CAST(probe_rank AS INTEGER) AS probe_rank FROM p")
def probe_full_width(spark, d):
    idx, _, q = _index(spark, d)
    return two_tier.probe(idx, q, N_P, WIDE).select("qid", "cluster_id", F.round("c_dist", 6).alias("c_dist"), "probe_rank")


@query(f"WITH {ONE_ROUND}, {probe_sql()} SELECT qid, cluster_id, c_dist FROM (SELECT *, min(c_dist) OVER (PARTITION BY qid) AS f FROM p) WHERE c_dist <= round(f * 1.02, 6)")
def probe_gate(spark, d):
    idx, _, q = _index(spark, d)
    probes = two_tier.probe(idx, q, N_P, WIDE).withColumn("c_dist", F.round("c_dist", 6))
    return two_tier.gate(probes, 1.02).select("qid", "cluster_id", "c_dist")


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('list_distance(qv, v)')}")
def two_tier_full_width(spark, d):
    """All lists, full widths: the index must give the exact answer."""
    idx, _, q = _index(spark, d)
    return two_tier.search(idx, q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE)


@query(IVF_SQL)
def two_tier_probed(spark, d):
    """Full widths, N_P lists: equals a scan of the same lists."""
    idx, _, q = _index(spark, d)
    return two_tier.search(idx, q, K, n_p=N_P, ef_c=WIDE, ef_l=WIDE)


@query(None)
def two_tier_default(spark, d):
    """The flagship: widths calibrated to a recall of 0.9 on a sample of the vectors."""
    idx, e, q = _index(spark, d)
    idx = two_tier.save_index(idx, folder(spark))
    return two_tier.search(idx, q, K, **two_tier.calibrate(idx, e, 0.9, K))


def clustered(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Expanded vectors (noisy copies, which have clusters), every 200th as a query, and the exact answer."""
    e = sources.expanded_embeddings(spark, d, 4).select("id", "v").cache()
    q = e.where("id % 200 = 0").select(F.col("id").alias("qid"), F.col("v").alias("qv")).cache()
    return e, q, knn.knn_exact(e, q, K).cache()


@query("SELECT (SELECT count(*) FROM embeddings WHERE vec_id % 50 = 0) AS queries, x.vectors, true AS reached FROM (VALUES ('given'), ('expanded')) x(vectors)")
def two_tier_recall(spark, d):
    """Whether calibrated searches reach a recall of 0.9, on the given and on the expanded vectors."""
    out = []
    idx, e, q = _index(spark, d)
    for name, (e, q, truth) in (("given", (e, q, knn.knn_exact(e, q, K))), ("expanded", clustered(spark, d))):
        idx = two_tier.save_index(two_tier.build_index(e, n_c=N_C, rounds=2), folder(spark))
        found = two_tier.search(idx, q, K, **two_tier.calibrate(idx, e, 0.95, K))
        out.append(B.recall_at_k(found, truth, K).select("queries", F.lit(name).alias("vectors"), (F.col("recall") >= 0.9).alias("reached")))
    return _union(out)


@query(IVF_SQL)
def two_tier_saved(spark, d):
    """The same from storage: only probed buckets are read."""
    idx, _, q = _index(spark, d)
    saved = two_tier.save_index(idx, folder(spark))
    return two_tier.search(saved, q, K, n_p=N_P, ef_c=WIDE, ef_l=WIDE)


@query(None)
def two_tier_counters(spark, d):
    idx, _, q = _index(spark, d)
    return two_tier.search_counters(idx, q)


@query(f"WITH {E_SQL}, {Q_SQL}, w AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings WHERE label % 2 = 0) {exact_sql('list_distance(qv, v)', rows='w')}")
def filtered_search(spark, d):
    """Search with a metadata predicate: lists are searched for matching vectors alone, more lists until k are found."""
    idx, _, q = _index(spark, d)
    keep = sources.table(spark, d, "embeddings").where("label % 2 = 0").select(F.col("vec_id").alias("id"))
    return two_tier.search(idx, q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE, where=keep)


@query(f"WITH {E_SQL}, {Q_SQL} SELECT qid, 10 AS n, true AS only_matching FROM q")
def filtered_search_narrow(spark, d):
    """A selective predicate and one probed list: still k results, all of them matching."""
    idx, _, q = _index(spark, d)
    keep = sources.table(spark, d, "embeddings").where("label = 3").select(F.col("vec_id").alias("id")).cache()
    found = two_tier.search(idx, q, K, n_p=1, where=keep)
    match = keep.withColumn("hit", F.lit(True))
    return found.join(match, "id", "left").groupBy("qid").agg(F.count("*").cast("int").alias("n"), F.coalesce(F.bool_and("hit") & (F.count("hit") == F.count("*")), F.lit(False)).alias("only_matching"))


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('list_distance(qv, v)')}")
def two_tier_bounded(spark, d):
    """Lists that the radius rules out are not loaded; at full width the answer stays exact."""
    idx, _, q = _index(spark, d)
    return two_tier.search(two_tier.save_index(idx, folder(spark)), q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE, bound=True)


@query(f"WITH {E_SQL}, {Q_SQL} {exact_sql('list_distance(qv, v)')}")
def graph_full_width(spark, d):
    """Baseline: one graph, at full width."""
    e, q = _e(spark, d)
    return B.graph_search(B.graph_index(e), q, K, WIDE)


@query(None)
def graph_default(spark, d):
    e, q = _e(spark, d)
    return B.graph_search(B.graph_index(e), q, K, 64)


@query(IVF_SQL)
def ivf_search(spark, d):
    _, q, cents, lists = _lists(spark, d)
    return B.ivf_search(lists, cents, q, K, N_P)


@query(IVF_SQL)
def ivf_salted(spark, d):
    _, q, cents, lists = _lists(spark, d)
    return B.search_salted(lists, B.probe_lists(q, cents, N_P), K)


@query(IVF_SQL)
def ivf_disk_search(spark, d):
    _, q, cents, lists = _lists(spark, d)
    B.save_lists(lists, path := folder(spark))
    return B.ivf_disk_search(spark, path, cents, q, K, N_P)


@query(IVF_SQL)
def ivf_graph_search(spark, d):
    e, q, cents, lists = _lists(spark, d)
    return B.ivf_graph_search(two_tier.build_index(e, centroids=cents), lists, q, K, N_P, WIDE)


M_PQ, BITS, WIDTH = 8, 4, 8
PQ_SQL = f"""pn AS (SELECT count(*) // {1 << BITS} AS step FROM e),
    book AS (SELECT sub, CAST(id // step AS INTEGER) AS code, list_slice(v, sub * {WIDTH} + 1, sub * {WIDTH} + {WIDTH}) AS cw FROM e, pn, range({M_PQ}) r(sub) WHERE id % step = 0 AND id // step < {1 << BITS}),
    enc AS (SELECT id, sub, code FROM (SELECT id, sub, code, row_number() OVER (PARTITION BY id, sub ORDER BY round(list_distance(list_slice(v, sub * {WIDTH} + 1, sub * {WIDTH} + {WIDTH}), cw) ** 2, 9), code) AS r FROM e, book) WHERE r = 1),
    lut AS (SELECT qid, sub, code, list_distance(list_slice(qv, sub * {WIDTH} + 1, sub * {WIDTH} + {WIDTH}), cw) ** 2 AS x FROM q, book)"""
PQ_NEAR = "SELECT p.qid, a1.id, round(sqrt(sum(x)), 6) AS d FROM p JOIN a1 USING (cluster_id) JOIN enc ON enc.id = a1.id JOIN lut ON lut.qid = p.qid AND lut.sub = enc.sub AND lut.code = enc.code WHERE p.qid <> a1.id GROUP BY p.qid, a1.id"
IVFPQ_SQL = f"WITH {ONE_ROUND}, {probe_sql()}, {PQ_SQL} {ranked_sql(PQ_NEAR)}"


def _coded(spark, d):
    e, q, cents, lists = _lists(spark, d)
    book = B.pq_fit(e, M_PQ, BITS)
    return e, q, cents, B.pq_encode(lists, book, M_PQ), book


@query(f"WITH {E_SQL}, {Q_SQL}, {PQ_SQL} SELECT id, list(code ORDER BY sub) AS codes FROM enc GROUP BY id")
def pq_codes(spark, d):
    e = sources.vectors(spark, d)
    return B.pq_encode(e, B.pq_fit(e, M_PQ, BITS), M_PQ).select("id", "codes")


@query(f"WITH {E_SQL}, {Q_SQL}, {PQ_SQL} SELECT qid, CAST(sub AS INTEGER) AS sub, code, round(x, 6) AS x FROM lut")
def pq_tables(spark, d):
    e, q = _e(spark, d)
    luts = B.pq_tables(q, B.pq_fit(e, M_PQ, BITS), M_PQ)
    return luts.select("qid", F.posexplode("luts").alias("sub", "lut")).select("qid", "sub", F.posexplode("lut").alias("code", "x")).select("qid", "sub", "code", F.round("x", 6).alias("x"))


@query(None)
def pq_trained(spark, d):
    e = sources.vectors(spark, d)
    return B.pq_fit(e, M_PQ, BITS, rounds=2)


@query(IVFPQ_SQL)
def ivfpq_search(spark, d):
    _, q, cents, coded, book = _coded(spark, d)
    return B.ivfpq_search(coded, cents, book, q, K, N_P, M_PQ)


@query(f"WITH {ONE_ROUND}, {probe_sql()}, {PQ_SQL}, f AS ({ranked_sql(PQ_NEAR, 30)}) {ranked_sql('SELECT f.qid, f.id, round(list_distance(qv, v), 6) AS d FROM f JOIN q ON q.qid = f.qid JOIN e ON e.id = f.id')}")
def ivfpq_reranked(spark, d):
    _, q, cents, coded, book = _coded(spark, d)
    return B.ivfpq_search(coded, cents, book, q, K, N_P, M_PQ, rerank=30)


@query(IVFPQ_SQL)
def ivfpq_disk_search(spark, d):
    _, q, cents, coded, book = _coded(spark, d)
    B.save_codes(coded, path := folder(spark))
    return B.ivfpq_disk_search(spark, path, cents, book, q, K, N_P, M_PQ)


@query(f"WITH {E_SQL}, {Q_SQL}, {PQ_SQL} {ranked_sql('SELECT q.qid, enc.id, round(sqrt(sum(x)), 6) AS d FROM q JOIN enc ON enc.id <> q.qid JOIN lut ON lut.qid = q.qid AND lut.sub = enc.sub AND lut.code = enc.code GROUP BY q.qid, enc.id')}")
def graph_pq_full_width(spark, d):
    e, q = _e(spark, d)
    return B.graph_pq_search(B.graph_index(e), e, B.pq_fit(e, M_PQ, BITS), q, K, WIDE, M_PQ)


UPD_SQL = """u0 AS (SELECT event_id AS seq, CASE WHEN event_type IN ('signup', 'purchase') THEN 'insert' WHEN event_type = 'error' THEN 'delete' END AS op, event_id % (SELECT count(*) FROM e) AS id FROM events),
    u AS (SELECT id, arg_max(op, seq) AS op FROM u0 WHERE op IS NOT NULL AND seq < 300 GROUP BY id)"""
#: The whole log, which nearly all ids meet.
UPD_ALL_SQL = UPD_SQL.replace(" AND seq < 300", "")


def _ops(spark, d) -> DataFrame:
    return sources.update_log(spark, d).where("seq < 300")


@query(f"WITH {ONE_ROUND}, {UPD_SQL} SELECT u.id, u.op, cluster_id FROM u JOIN a1 USING (id) WHERE op = 'insert' UNION ALL SELECT u.id, 'delete', cluster_id FROM u JOIN a1 USING (id)")
def update_route(spark, d):
    idx, *_ = _index(spark, d)
    return two_tier.route(idx, _ops(spark, d)).select("id", "op", "cluster_id")


@query(f"WITH {ONE_ROUND}, {UPD_SQL} SELECT a1.id, cluster_id FROM a1 LEFT JOIN u USING (id) WHERE op IS DISTINCT FROM 'delete'")
def two_tier_updated_members(spark, d):
    idx, *_ = _index(spark, d)
    return two_tier.members(two_tier.apply_updates(idx, _ops(spark, d))).select("id", "cluster_id")


LIVE_SQL = "live AS (SELECT e.* FROM e LEFT JOIN u USING (id) WHERE op IS DISTINCT FROM 'delete')"


@query(f"WITH {E_SQL}, {Q_SQL}, {UPD_ALL_SQL}, {LIVE_SQL} {exact_sql('list_distance(qv, v)', rows='live')}")
def two_tier_updated_search(spark, d):
    """Updates by the whole log; at full width the answer over what is live stays exact."""
    idx, _, q = _index(spark, d)
    return two_tier.search(two_tier.apply_updates(idx, sources.update_log(spark, d)), q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE)


@query(f"WITH {E_SQL}, {Q_SQL}, live AS (SELECT * FROM e WHERE id % 7 <> 0) {exact_sql('list_distance(qv, v)', rows='live')}")
def two_tier_flagged_search(spark, d):
    """Flag-only deletes: flagged vectors are crossed, never returned."""
    idx, e, q = _index(spark, d)
    return two_tier.search(two_tier.flag_deleted(idx, e.where("id % 7 = 0").select("id")), q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE)


@query(f"WITH {E_SQL}, {Q_SQL}, live AS (SELECT * FROM e WHERE id % 7 <> 0) {exact_sql('list_distance(qv, v)', rows='live')}")
def two_tier_purged_search(spark, d):
    idx, e, q = _index(spark, d)
    purged = two_tier.purge(two_tier.flag_deleted(idx, e.where("id % 7 = 0").select("id")))
    return two_tier.search(purged, q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE)


@query(f"WITH {ONE_ROUND}, {UPD_SQL} SELECT a1.id, cluster_id FROM a1 LEFT JOIN u USING (id) WHERE op IS DISTINCT FROM 'delete'")
def ivf_updated_members(spark, d):
    _, _, cents, lists = _lists(spark, d)
    last = two_tier.normalise_updates(_ops(spark, d))
    kept = B.ivf_delete(lists, last.where("op = 'delete'"))
    return B.ivf_insert(kept, cents, last.where("op = 'insert'").select("id", "v")).select("id", "cluster_id")


CURVE = (1, 2, 4, 8, 16)


def _recall_sql(n_p: int) -> str:
    return f"""SELECT {n_p} AS n_p, count(*) AS queries, round(avg(r), 6) AS recall FROM (SELECT t.qid, avg(CASE WHEN f.id IS NULL THEN 0.0 ELSE 1.0 END) AS r FROM t LEFT JOIN
        ({ranked_sql(f"SELECT qid, id, round(list_distance(qv, v), 6) AS d FROM p JOIN a1 USING (cluster_id) WHERE qid <> id AND probe_rank <= {n_p}")}) f ON f.qid = t.qid AND f.id = t.id GROUP BY t.qid)"""


@query(f"WITH {ONE_ROUND}, {probe_sql(n_p=N_C)}, t AS ({exact_sql('list_distance(qv, v)')}) {' UNION ALL '.join(_recall_sql(n) for n in CURVE)}")
def recall_curve_ivf(spark, d):
    """Recall@10 of inverted lists by number of probed lists."""
    e, q, cents, lists = _lists(spark, d)
    truth = knn.knn_exact(e, q, K).cache()
    out = [B.recall_at_k(B.ivf_search(lists, cents, q, K, n), truth, K).withColumn("n_p", F.lit(n)) for n in CURVE]
    return _union(out).select("n_p", "queries", "recall")


@query(f"WITH {ONE_ROUND}, {probe_sql(n_p=N_C)}, t AS ({exact_sql('list_distance(qv, v)')}) {' UNION ALL '.join(_recall_sql(n) for n in CURVE)}")
def recall_curve_two_tier(spark, d):
    """Recall@10 of the two-tier index by number of probed lists, at full widths."""
    idx, e, q = _index(spark, d)
    idx = two_tier.save_index(idx, folder(spark))
    truth = knn.knn_exact(e, q, K).cache()
    out = [B.recall_at_k(two_tier.search(idx, q, K, n, WIDE, WIDE), truth, K).withColumn("n_p", F.lit(n)) for n in CURVE]
    return _union(out).select("n_p", "queries", "recall")


@query(None)
def recall_curve_width(spark, d):
    """Recall@10 and counted distances by search width, on clustered vectors: four probed list graphs against one graph."""
    e, q, truth = clustered(spark, d)
    idx = two_tier.save_index(two_tier.build_index(e, n_c=N_C, rounds=2), folder(spark))
    one = two_tier.save_index(B.graph_index(e, mode="batch"), folder(spark))
    out = []
    for name, index, n_p in (("two_tier", idx, N_P), ("graph", one, 1)):
        for ef in (8, 16, 32, 64, 128, 256):
            parts = two_tier.search_partials(index, q, K, n_p, 32, ef)
            found = knn.merge_topk(parts.where("id is not null").select("qid", "id", "d"), K)
            work = parts.where("id is null").agg(F.sum("n_dist").alias("n_dist"))
            out.append(B.recall_at_k(found, truth, K).join(work).select(F.lit(name).alias("method"), F.lit(ef).alias("ef"), "recall", "n_dist"))
    return _union(out)


@query("SELECT (SELECT count(*) FROM embeddings WHERE vec_id % 50 = 0) AS queries, true AS near_rebuilt")
def recall_after_churn(spark, d):
    """Whether recall after updates is within 0.05 of a rebuilt index, at default list widths."""
    idx, e, q = _index(spark, d)
    log = _ops(spark, d)
    live = e.join(two_tier.normalise_updates(log).where("op = 'delete'").select("id"), "id", "left_anti")
    truth = knn.knn_exact(live, q, K).cache()
    updated, rebuilt = two_tier.apply_updates(idx, log), two_tier.build_index(live, centroids=partition.fit_partitions(e, N_C, rounds=1))
    a, b = (B.recall_at_k(two_tier.search(i, q, K, n_p=N_C), truth, K) for i in (updated, rebuilt))
    return a.join(b.select(F.col("recall").alias("again"))).select("queries", (F.col("recall") >= F.col("again") - 0.05).alias("near_rebuilt"))


@query(f"WITH {E_SQL}, {Q_SQL}, {UPD_ALL_SQL}, {LIVE_SQL} {exact_sql('list_distance(qv, v)', rows='live')}")
def two_tier_updated_saved(spark, d):
    """Updates of a saved index by the whole log: only buckets that hold touched lists are written."""
    idx, _, q = _index(spark, d)
    saved = two_tier.save_index(idx, folder(spark))
    return two_tier.search(two_tier.update_saved(saved, sources.update_log(spark, d)), q, K, n_p=N_C, ef_c=WIDE, ef_l=WIDE)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
