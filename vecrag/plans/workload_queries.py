"""Registered queries of the larger workloads: question sets, updates, power, retrieval cost, scale."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag import sources
from vecrag.functions import vector as V
from vecrag.operators import baselines as B
from vecrag.operators import condense as C
from vecrag.operators import corpus, cost, measure, partition, rag, scale
from vecrag.operators import index as two_tier
from vecrag.plans import ann_queries as A
from vecrag.plans import cost_queries as Q
from vecrag.plans import rag_queries as R
from vecrag.plans.shared import folder, query
from vecrag.session import checkpointed


# -- scale ---------------------------------------------------------------------------------------------------------------
@query(f"WITH {A.E_SQL}, {A.Q_SQL} {A.exact_sql('list_distance(qv, v)')}")
def three_tier_full_width(spark, d):
    """Three tiers at full width: the exact answer."""
    e, q = A._e(spark, d)
    idx = scale.build_three_tier(e, 4, 4, rounds=2)
    return scale.search_three_tier(idx, q, A.K, n_p1=4, n_p2=16, ef=A.WIDE)


@query(f"WITH {A.E_SQL}, {A.Q_SQL} {A.exact_sql('list_distance(qv, v)')}")
def rebalanced_search(spark, d):
    """Lists over 40 split, under 25 dissolved; at full width the answer stays exact."""
    idx, _, q = A._index(spark, d)
    out = scale.rebalance(two_tier.save_index(idx, folder(spark)), cap=40, floor=25)
    out = two_tier.save_index(out, folder(spark))
    return two_tier.search(out, q, A.K, n_p=out.n_c, ef_c=A.WIDE, ef_l=A.WIDE)


@query(None)
def rebalanced_sizes(spark, d):
    idx, *_ = A._index(spark, d)
    out = scale.rebalance(two_tier.save_index(idx, folder(spark)), cap=40, floor=25)
    return two_tier.members(out).groupBy("cluster_id").agg(F.count("*").alias("n"))


@query(f"WITH {A.ONE_ROUND}, {A.probe_sql()}, x AS (SELECT cluster_id % 4 AS worker, qid, probe_rank, cluster_id, row_number() OVER (PARTITION BY cluster_id % 4 ORDER BY qid, probe_rank) AS t FROM p), y AS (SELECT *, lag(t) OVER (PARTITION BY cluster_id ORDER BY t) AS before FROM x) SELECT CAST(worker AS INTEGER) AS worker, count(*) AS probes, count(*) FILTER (WHERE before IS NOT NULL AND (SELECT count(DISTINCT z.cluster_id) FROM x z WHERE z.worker = y.worker AND z.t > y.before AND z.t < y.t) < 2) AS hits FROM y GROUP BY worker")
def list_cache_hits(spark, d):
    """A cache of two lists on each of four workers, for the disk-resident form."""
    _, q, cents, _ = A._lists(spark, d)
    probes = B.probe_lists(q, cents, A.N_P)
    ranked = probes.withColumn("probe_rank", F.row_number().over(W.partitionBy("qid").orderBy("c_dist", "cluster_id")))
    return scale.cache_report(ranked, 2)


# -- vector workloads ------------------------------------------------------------------------------------------------------
def method_runs(spark, d) -> tuple[DataFrame, DataFrame, dict]:
    """(vectors, exact answer, runs by method): each run takes a width - lists for list methods, ef for graphs - and gives a
    ranked result; clustered vectors, one set of centroids and one codebook for all.
    """
    e, q, truth = A.clustered(spark, d)
    n_c = partition.choose_n_c(e.count(), 125)
    cents = partition.fit_partitions(e, n_c, rounds=3)
    lists = partition.assign(e, cents).cache()
    book = B.pq_fit(e, A.M_PQ, A.BITS, rounds=1)
    coded = B.pq_encode(lists, book, A.M_PQ).cache()
    idx = two_tier.save_index(two_tier.build_index(e, centroids=cents), folder(spark))
    one = two_tier.save_index(B.graph_index(e, mode="batch"), folder(spark))
    B.save_lists(lists.select("id", "v", "cluster_id"), flat := folder(spark))
    B.save_codes(coded, codes := folder(spark))
    k = A.K
    runs = {
        "ivf": lambda w: B.ivf_search(lists, cents, q, k, min(w, n_c)),
        "ivfpq": lambda w: B.ivfpq_search(coded, cents, book, q, k, min(w, n_c), A.M_PQ, rerank=40),
        "graph": lambda w: B.graph_search(one, q, k, max(k, 32 * w)),
        "graph_pq": lambda w: B.graph_pq_search(one, e, book, q, k, max(k, 32 * w), A.M_PQ, rerank=40),
        "ivf_disk": lambda w: B.ivf_disk_search(spark, flat, cents, q, k, min(w, n_c)),
        "ivfpq_disk": lambda w: B.ivfpq_disk_search(spark, codes, cents, book, q, k, min(w, n_c), A.M_PQ),
        "ivf_graph": lambda w: B.ivf_graph_search(idx, lists, q, k, min(w, n_c)),
        "two_tier": lambda w: two_tier.search(idx, q, k, n_p=min(w, n_c), ef_l=64),
    }
    return e, truth, runs


@query(None)
def w_recall_curve(spark, d):
    """Recall and measured queries per second of the eight methods, by width, on clustered vectors."""
    _, truth, runs = method_runs(spark, d)
    out = []
    for name, run in runs.items():
        for width in (1, 4, 16):
            began = time.time()
            found = spark.createDataFrame(run(width).collect(), "qid long, id long, d double, rank int")  # k rows a query, timed
            took = time.time() - began
            out.append(B.recall_at_k(found, truth, A.K).select(F.lit(name).alias("method"), F.lit(width).alias("width"), "recall", (F.col("queries") / F.lit(took)).alias("qps")))
    return A._union(out)


@query("SELECT method, true AS reached FROM (VALUES ('ivf'), ('graph'), ('ivf_disk'), ('ivf_graph'), ('two_tier')) t(method)")
def w_recall_reached(spark, d):
    """Whether each method that keeps whole vectors reaches the published recall of 0.93 at its widest setting."""
    _, truth, runs = method_runs(spark, d)
    return A._union([B.recall_at_k(run(16), truth, A.K).select(F.lit(name).alias("method"), (F.col("recall") >= 0.93).alias("reached")) for name, run in runs.items() if "pq" not in name])


@query(None)
def w_search_power(spark, d):
    """Modelled energy of a search from counted work: distances, lists and bytes of the eight methods."""
    idx, e, q = A._index(spark, d)
    idx = two_tier.save_index(idx, folder(spark))
    one = two_tier.save_index(B.graph_index(e, mode="batch"), folder(spark))
    _, _, cents, lists = A._lists(spark, d)
    dim, n = 64.0, float(e.count())
    sizes = lists.groupBy("cluster_id").agg(F.count("*").alias("n"))
    rows = B.probe_lists(q, cents, A.N_P).join(sizes, "cluster_id").groupBy("qid").agg(F.sum("n").alias("rows"), F.count("*").alias("lists"))
    scanned = rows.agg(F.avg("rows").alias("rows"), F.avg("lists").alias("lists"))
    centre = two_tier.probe(idx, q, A.N_P).groupBy("qid").agg(F.sum("n_dist").alias("n")).agg(F.avg("n").alias("centre"))
    share, table = A.M_PQ / dim * A.BITS / 8, float(1 << A.BITS)
    flat, code = 4 * dim + 8, A.M_PQ * A.BITS / 8 + 8
    both = scanned.join(centre)
    r, z = F.col("rows"), F.lit(0.0)
    own = {
        "ivf": (A.N_C + r, z, z), "ivfpq": (A.N_C + r * share + table, z, z), "ivf_disk": (A.N_C + r, F.col("lists"), r * flat),
        "ivfpq_disk": (A.N_C + r * share + table, F.col("lists"), r * code), "ivf_graph": (F.col("centre") + r, F.col("lists"), r * flat),
    }
    rows_of = lambda name, ops, seeks, size: F.struct(F.lit(name).alias("method"), ops.cast("double").alias("ops"), seeks.cast("double").alias("seeks"), size.cast("double").alias("bytes"))
    counted = both.select(F.explode(F.array(*(rows_of(k, *v) for k, v in own.items()))).alias("x")).select("x.*")
    mean = lambda i, **w: two_tier.search_counters(i, q, A.K, **w).agg(F.avg("n_dist").alias("ops"), F.avg("lists").alias("seeks"), F.avg("bytes_read").alias("bytes"))
    graph = mean(one, n_p=1, ef_l=64)
    more = [
        graph.select(F.lit("graph").alias("method"), "ops", F.lit(0.0).alias("seeks"), F.lit(0.0).alias("bytes")),
        graph.select(F.lit("graph_pq").alias("method"), (F.col("ops") * share + table).alias("ops"), F.lit(0.0).alias("seeks"), F.lit(0.0).alias("bytes")),
        mean(idx).select(F.lit("two_tier").alias("method"), "ops", "seeks", "bytes"),
    ]
    assert n
    return cost.power_report(A._union([counted, *more]))


@query("SELECT * FROM (VALUES ('modelled', true), ('resident', true), ('stored', true), ('largest_list', true)) t(what, sound)")
def w_memory_report(spark, d):
    """Modelled, resident and stored bytes of a real index: what is resident is a small part of what is stored."""
    idx, e, _ = A._index(spark, d)
    report = cost.memory_report(two_tier.save_index(idx, folder(spark)))
    stored = report.where("what = 'stored'").select(F.col("bytes").alias("all"))
    return report.join(stored).select("what", F.when(F.col("what") == "stored", F.col("bytes") > e.count() * 64 * 4).otherwise((F.col("bytes") > 0) & (2 * F.col("bytes") < F.col("all"))).alias("sound"))


@query(None)
def w_updates(spark, d):
    """Deletes and inserts of one vector in twenty: counted distances and measured ms per operation, by method. List methods
    find the list (by a scan of the centroids, or by the centroid graph) and rewrite its array; the two-tier index changes
    the list's graph besides.
    """
    from vecrag.operators.kernel import Graph

    idx, *_ = A._index(spark, d)
    e = A._lists(spark, d)[3].cache()
    hit = F.col("id") % 20 == 3
    shared = spark.sparkContext.broadcast(idx.centre)

    def change(t):
        import numpy as np
        import pyarrow as pa

        from vecrag.operators.knn import matrix

        centre = shared.value
        cents, c_ids = np.asarray(centre["exact"]), np.array(centre["ids"])
        near = Graph.from_row(centre)
        x, ids = matrix(t["v"]), t["id"].to_numpy()
        picked = [k for k, h in enumerate(t["hit"].to_pylist()) if h]
        graph, rows = Graph.build(ids.tolist(), x), []

        def timed(method: str, op: str, k: int, run) -> None:
            began = time.perf_counter()
            counted = run(k)
            rows.append((method, op, (time.perf_counter() - began) * 1000, counted))

        def by_scan(v) -> int:
            partition.nearest_centroid(v[None], c_ids, cents)
            return len(cents)

        def by_graph(v) -> int:
            return near.search(v, 1, two_tier.EF_C)[1]

        held = {"ivf": [x.copy(), ids.copy()], "ivf_graph": [x.copy(), ids.copy()]}

        def drop(method: str, k: int) -> int:
            keep = held[method][1] != ids[k]
            held[method] = [held[method][0][keep], held[method][1][keep]]
            return 0

        def add(method: str, k: int) -> int:
            n = (by_scan if method == "ivf" else by_graph)(x[k])
            held[method] = [np.vstack([held[method][0], x[k][None]]), np.append(held[method][1], ids[k])]
            return n

        def in_graph(op: str, k: int) -> int:
            before, found = graph.n_dist, 0
            if op == "delete":
                graph.delete(int(ids[k]))
            else:
                found = by_graph(x[k])
                graph.insert(int(ids[k]), x[k])
            return graph.n_dist - before + found

        for op, change_list in (("delete", drop), ("insert", add)):
            for k in picked:
                timed("two_tier", op, k, lambda k, op=op: in_graph(op, k))
                for method in held:
                    timed(method, op, k, lambda k, method=method, f=change_list: f(method, k))
        cols = list(zip(*rows, strict=True)) if rows else [[], [], [], []]
        return pa.table({"method": pa.array(cols[0], pa.string()), "op": pa.array(cols[1], pa.string()), "ms": pa.array(np.array(cols[2], float)), "n_dist": pa.array(np.array(cols[3], np.int64))})

    log = e.withColumn("hit", hit).groupBy("cluster_id").applyInArrow(change, "method string, op string, ms double, n_dist long")
    return measure.update_latency(log)


# -- question sets -----------------------------------------------------------------------------------------------------------
MULTI_SQL = r"""g0 AS (SELECT gold.qid, gold_docs, answer, query, row_number() OVER (ORDER BY gold.qid) AS k FROM gold JOIN longest USING (qid) JOIN queries USING (qid)),
    multi AS (SELECT a.qid, a.query || ' ' || b.query AS query, [a.answer, b.answer] AS answers FROM g0 a JOIN g0 b ON b.k = a.k + 1 WHERE a.k % 2 = 1)"""


def ranked(df: DataFrame, order: str) -> DataFrame:
    """`df` with its rank `k` by a column, from 1, without one task that sees all rows: ranks inside ranges plus offsets."""
    parts = checkpointed(df.repartitionByRange(order).withColumn("_p", F.spark_partition_id()))
    offsets, at = [], 0
    for r in parts.groupBy("_p").agg(F.count("*").alias("n"), F.min(order).alias("low")).orderBy("low").collect():  # one row a range
        offsets.append((r["_p"], at))
        at += r["n"]
    table = df.sparkSession.createDataFrame(offsets, "_p int, _at long")
    own = F.row_number().over(W.partitionBy("_p").orderBy(order))
    return parts.withColumn("_r", own).join(F.broadcast(table), "_p").withColumn("k", F.col("_r") + F.col("_at")).drop("_p", "_r", "_at")


def multi_set(spark, d, q: DataFrame | None = None, gold: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(queries, gold): two answerable items of consecutive rank joined into one question; `q` and `gold` of the items if given."""
    gold, q = R.gold_of(spark, d) if gold is None else gold, R.queries_of(spark, d) if q is None else q
    one = checkpointed(ranked(gold.join(q, "qid"), "qid"))
    b = one.select((F.col("k") - 1).alias("k"), F.col("query").alias("q2"), F.col("answers").alias("a2"), F.col("gold_docs").alias("g2"))
    both = one.where("k % 2 = 1").join(b, "k")
    return both.select("qid", F.concat_ws(" ", "query", "q2").alias("query")), both.select("qid", F.array_union("gold_docs", "g2").alias("gold_docs"), F.concat("answers", "a2").alias("answers"))


def fact_set(spark, d) -> tuple[DataFrame, DataFrame]:
    """(queries, gold): an 8-word fragment of the md5-chosen sentence of the documents of the stated query set (ids divisible by
    50), that sentence, and all documents that hold it.
    """
    own = R.docs_of(spark, d).select("doc_id", V.sentences("text").alias("all"))
    docs = own.where("doc_id % 50 = 0").select("doc_id", F.filter("all", lambda s: F.size(F.split(s, " ")) >= 8).alias("s")).where("size(s) > 0")
    at = F.pmod(F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long"), F.size("s")).cast("int")
    picked = checkpointed(docs.select(F.col("doc_id").alias("qid"), F.get("s", at).alias("answer")))
    holders = own.select("doc_id", F.explode(F.array_distinct("all")).alias("answer")).join(picked.select("answer").distinct(), "answer", "left_semi")
    gold = picked.join(holders, "answer").groupBy("qid", "answer").agg(F.array_sort(F.collect_set("doc_id")).alias("gold_docs"))
    q = picked.select("qid", F.array_join(F.slice(F.split("answer", " "), 1, 8), " ").alias("query"))
    return q, gold.select("qid", "gold_docs", F.array("answer").alias("answers"))


@query(f"WITH {R.QA_SQL}, {R.LONGEST}, {MULTI_SQL} SELECT qid, query, answers FROM multi")
def qa_multi(spark, d):
    q, gold = multi_set(spark, d)
    return q.join(gold, "qid").select("qid", "query", "answers")


FACT_SQL = f"""fs AS (SELECT doc_id, list_filter({R.SENT.format('text')}, lambda s: len(string_split(s, ' ')) >= 8) AS s, {R.SENT.format('text')} AS every FROM documents),
    fact AS (SELECT doc_id AS qid, s[1 + ('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8))::BIGINT % len(s)] AS answer FROM fs WHERE len(s) > 0 AND doc_id % 50 = 0)"""


@query(f"WITH {FACT_SQL} SELECT qid, array_to_string(list_slice(string_split(answer, ' '), 1, 8), ' ') AS query, [answer] AS answers, (SELECT list_sort(list(DISTINCT f.doc_id)) FROM fs f WHERE list_contains(f.every, answer)) AS gold_docs FROM fact")
def qa_fact(spark, d):
    q, gold = fact_set(spark, d)
    return q.join(gold, "qid").select("qid", "query", "answers", "gold_docs")


SETS = ("single", "multi", "fact")
#: Recall of the exact documents that the index's widths are calibrated to, on a sample of the questions.
TARGET = 0.95


def question_sets(spark, d) -> tuple[DataFrame, DataFrame]:
    """(queries, gold) of the three sets together: qid is 3 times the set's own plus the set's place in SETS."""
    one = R.queries_of(spark, d), checkpointed(R.gold_of(spark, d))
    sets = (one, multi_set(spark, d, *one), fact_set(spark, d))
    mixed = [A._union([x.withColumn("qid", F.col("qid") * len(SETS) + k) for k, x in enumerate(xs)]) for xs in zip(*sets, strict=True)]
    return checkpointed(mixed[0]), checkpointed(mixed[1])


def question_contexts(spark, docs: DataFrame, q: DataFrame, idf: DataFrame) -> dict[str, DataFrame]:
    """Contexts of the four pipelines for all questions. The two-tier one searches an index over the documents with calibrated
    widths; the documents' vectors are made once, and the exact retrieval is one for the pipelines that rest on it.
    """
    vectors = rag.owner_vectors(docs, idf)
    index = rag.document_index(docs, idf, path := folder(spark), vectors=vectors)
    widths = two_tier.calibrate(index, spark.read.parquet(f"{path}/vectors"), TARGET, rag.K, queries=rag.query_vectors(q, idf), metric="overlap")
    probed = checkpointed(rag.index_ranks(index, q, idf, **widths))
    fetched = checkpointed(rag.retrieve(docs, q, idf, rag.FETCH, vectors=vectors))
    wanted = probed.select("doc_id").unionByName(fetched.select("doc_id")).distinct()
    texts = checkpointed(docs.join(wanted, "doc_id", "left_semi"))
    made = {
        "plain": rag.with_text(fetched.where(F.col("rank") <= rag.K), texts), "disk": rag.rag_disk(docs, q, idf, folder(spark), vectors=vectors),
        "two_tier": rag.rag_two_tier(texts, q, idf, ranked=probed), "reranked": rag.rag_reranked(docs, q, idf, found=fetched, texts=texts),
    }
    return {name: checkpointed(ctx) for name, ctx in made.items()}


@query(None)
def w_question_sets(spark, d):
    """Accuracy, evidence and modelled times of four pipelines on three question sets, each pipeline run once over all sets."""
    docs = R.docs_of(spark, d).select("doc_id", "text")
    idf = C.idf_table(docs).cache()
    q, gold = question_sets(spark, d)
    rates, out = measure.speeds(spark), []
    of = F.pmod("qid", F.lit(len(SETS)))
    for pipe, ctx in question_contexts(spark, docs, q, idf).items():
        replies = checkpointed(rag.answer(ctx, q, idf))
        e, s, t = R.PARTS[pipe]
        parts = rag.build_prompt(ctx, q, 4096).select("qid", "n_tokens", F.lit(e).alias("embed_s"), F.lit(s).alias("search_s"), F.lit(t).alias("extra_s"))
        timed = checkpointed(measure.ttft_model(parts, rates))
        for k, name in enumerate(SETS):
            mine = gold.where(of == k)
            acc = checkpointed(measure.answer_accuracy(replies, mine).join(measure.evidence_report(ctx, mine).select("in_context", "gold_in_top", "mrr")))
            times = timed.where(of == k).groupBy("generator").agg(F.round(F.avg("ttft_s"), 4).alias("ttft_s"), F.round(F.avg("joule_model"), 4).alias("joule_model"))
            out.append(times.join(acc).select(F.lit(name).alias("dataset"), F.lit(pipe).alias("method"), "generator", "queries", "accuracy", "in_context", "gold_in_top", "mrr", "ttft_s", "joule_model"))
    return A._union(out)


RATIOS = (1.0, 0.9, 0.8, 0.6)


def _cost_sql() -> str:
    count = lambda per: f"(SELECT count(*) FROM (SELECT doc_id, unnest(generate_series(0, len(sents) - 1, {per})) FROM sents WHERE len(sents) > 0))"
    shapes = " UNION ALL ".join(f"SELECT 'ratio {r}' AS name, {count(max(1, round(5 * r)))}::DOUBLE AS N" for r in RATIOS)
    p = "p AS (SELECT name, N, 384.0 AS d, greatest(1, round(N / 250))::DOUBLE AS Nc, 16.0 AS M, 8.0 AS M2, 48.0 AS m_pq, 8.0 AS nbits, 4.0 AS nP, 64.0 AS ef_H, 16.0 AS ef_c, 16.0 AS ef_L FROM sh)"
    return f"WITH {R.SENTS_SQL}, sh AS ({shapes}), {p}, {Q.latency_sql()}, m AS ({Q.memory_sql()}) SELECT name, method, round(bytes, 3) AS bytes, round(ms, 9) AS ms, round(uj, 9) AS uj FROM m JOIN l USING (name, method) JOIN j USING (name, method) WHERE method IN ('ivf', 'ivf_disk', 'two_tier')"


@query(_cost_sql())
def w_retrieval_cost(spark, d):
    """Modelled memory and energy of retrieval: small chunks by ratio, disk lists and the two-tier index, with real counts."""
    docs = R.docs_of(spark, d).select("doc_id", "text")
    rows = []
    for ratio in RATIOS:
        n = float(corpus.chunk(docs, 5, ratio=ratio).count())
        n_c = float(partition.choose_n_c(int(n)))
        rows.append((f"ratio {ratio}", n, 384.0, n_c, 16.0, 8.0, 48.0, 8.0, 4.0, 64.0, 16.0, 16.0))
    p = cost.parameters(spark, rows)
    times = cost.latency_model(p)
    joined = cost.memory_model(p).join(times, ["name", "method"]).join(cost.energy_model(times), ["name", "method"])
    return joined.where("method in ('ivf', 'ivf_disk', 'two_tier')").select("name", "method", F.round("bytes", 3).alias("bytes"), F.round("ms", 9).alias("ms"), F.round("uj", 9).alias("uj"))


@query("SELECT * FROM (VALUES (1, 3, 'before', 'S2'), (2, 3, 'core', 'S3'), (3, 3, 'after', 'S4')) t(k, best, part, text)")
def w_walkthrough(spark, d):
    """The condensation example: scores .3 .4 .9 .5 .2, extension 1."""
    sents = spark.createDataFrame([(1, [f"S{k}" for k in range(1, 6)])], "doc_id long, sents array<string>")
    scored = spark.createDataFrame([(1, 1, i, i, s) for i, s in enumerate((0.3, 0.4, 0.9, 0.5, 0.2), 1)], "qid long, doc_id long, start int, stop int, score double")
    parts = C.extend(C.best_window(scored), sents, 1).select("start", F.posexplode("parts").alias("k", "p"))
    return parts.select((F.col("k") + 1).alias("k"), F.col("start").alias("best"), "p.part", "p.text")
