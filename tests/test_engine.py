"""Worked examples, golden values of the models, edges and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecrag import schema, sources
from vecrag.functions import vector as V
from vecrag.operators import baselines as B
from vecrag.operators import condense as C
from vecrag.operators import corpus, cost, knn, measure, partition, rag
from vecrag.operators import index as two_tier
from vecrag.sources import store

SF = "/root/testdata/sf0.001"
GOLDEN = {
    "published": (522048000, 26179072, 691911480, 735776992, 10048512, 10179088, 10448933.5, 10449033.6),
    "small": (136096, 77632, 178052.7, 269746.8, 8352, 73640, 9338.3, 9400.0),
}
OPS = {"published": (8000, 4756, 4096, 768, 8000, 4756, 4512, 4608), "small": (141, 287.62, 1024, 384, 141, 287.62, 253, 640)}


@pytest.mark.parametrize("shape", list(GOLDEN))
def test_golden_models(spark, shape):
    p = cost.parameters(spark)
    mem = {r["method"]: r["bytes"] for r in cost.memory_model(p).where(F.col("name") == shape).collect()}
    assert [mem[m] for m in cost.METHODS] == pytest.approx(GOLDEN[shape], rel=1e-5)
    ops = {r["method"]: r["ops"] for r in cost.ops_model(p).where(F.col("name") == shape).collect()}
    assert [ops[m] for m in cost.METHODS] == pytest.approx(OPS[shape], abs=0.01)
    assert cost.t_op_ms() == pytest.approx(2.083e-4, rel=1e-3)


def frames(spark, n=5):
    docs = spark.createDataFrame([(1, " ".join(f"Word{i} here." for i in range(1, n + 1)))], "doc_id long, text string")
    return docs, C.split_sentences(docs)


def test_windows_example(spark):
    _, sents = frames(spark)
    got = [(r["start"], r["stop"]) for r in C.windows(sents, 3, 2).orderBy("start").collect()]
    assert got == [(1, 3), (2, 4), (3, 5)]
    with pytest.raises(ValueError):
        C.windows(sents, 2, 2)


def test_best_extend_merge_example(spark):
    _, sents = frames(spark)
    scored = spark.createDataFrame([(1, 1, i, i, s) for i, s in enumerate((0.3, 0.4, 0.9, 0.5, 0.2), 1)], "qid long, doc_id long, start int, stop int, score double")
    best = C.best_window(scored)
    assert best.first()["start"] == 3
    out = C.extend(best, sents, 1).select(C.merge(F.col("parts")).alias("t"), "parts").first()
    assert out["t"] == "Word2 here. Word3 here. Word4 here."
    assert [p["part"] for p in out["parts"]] == ["before", "core", "after"]
    wide = C.extend(C.best_window(scored, 2), sents, 1).select(C.merge(F.col("parts")).alias("t")).first()
    assert wide["t"] == "Word2 here. Word3 here. Word4 here. Word5 here."


def test_reorder_example(spark):
    rows = spark.createDataFrame([(1, 10, 1, 0.5), (1, 20, 2, 0.9), (1, 30, 3, 0.1)], "qid long, doc_id long, rank int, score double")
    assert [r["doc_id"] for r in C.reorder(rows).orderBy("new_rank").collect()] == [20, 10, 30]


def test_condense_keeps_every_document(spark):
    texts = [(1, "alpha beta. gamma delta. alpha again! the end?"), (2, ""), (3, None), (4, "no terminator\nonly lines\nalpha"), (5, "zzz yyy.")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    q = spark.createDataFrame([(7, "alpha")], "qid long, query string")
    idf = C.idf_table(docs)
    ret = spark.createDataFrame([(7, i, i) for i in range(1, 6)], "qid long, doc_id long, rank int")
    out = {r["doc_id"]: r for r in C.condense(ret, docs, q, idf).collect()}
    assert set(out) == {1, 2, 3, 4, 5} and out[2]["text"] == out[3]["text"] == ""
    assert sorted(r["new_rank"] for r in out.values()) == [1, 2, 3, 4, 5]
    assert "alpha" in out[4]["text"] and out[5]["score"] == 0.0


def test_token_cuts(spark):
    for before, after, cut in ((155, 90, 41.9), (309, 287, 7.1), (287, 198, 31.0)):
        a = spark.createDataFrame([(1, 1, "w " * before)], "qid long, doc_id long, context string")
        b = spark.createDataFrame([(1, 1, "w " * after)], "qid long, doc_id long, context string")
        assert measure.token_report(a, b).first()["reduction"] == pytest.approx(cut, abs=0.06)


def test_store_rows_and_rerun(spark, tmp_path):
    path = f"file://{tmp_path}/s"
    emb = lambda i, d: spark.createDataFrame([(i, d, [0.425, 1.0])], schema.EMBEDDING)
    doc = lambda d: spark.createDataFrame([(d, f"/A/File{d}.txt")], schema.DOCUMENT)
    chunk = lambda c, d, o: spark.createDataFrame([(c, d, o)], schema.CHUNK)
    store.write_tables(spark, path, emb(38, 123), doc(123), chunk(1872, 123, 5348))
    new = {"emb": emb(82, 913), "doc": doc(913), "chunk": chunk(1900, 913, 0)}
    none = spark.createDataFrame([], "doc_id long")
    assert store.update_store(spark, path, new, none, 1) == 1
    assert store.update_store(spark, path, new, none, 1) == 1
    assert store.status(spark, path).first().asDict() == {"files": 2, "vectors": 2, "new_files": 1, "new_vectors": 1}
    assert store.read_table(spark, path, "chunk").where("chunk_id = 1872").first()["offset"] == 5348
    store.update_store(spark, path, {k: v.limit(0) for k, v in new.items()}, spark.createDataFrame([(123,)], "doc_id long"))
    assert [r["doc_id"] for r in store.read_table(spark, path, "doc").collect()] == [913]


def test_schema_is_checked(spark):
    with pytest.raises(ValueError):
        schema.require(spark.range(1), schema.DOCUMENT)
    df = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0, None]), (4, [1.0]), (5, [float("nan"), 1.0])], "vec_id long, embedding array<double>")
    good, bad = schema.vectors(df, dim=2)
    assert [r["id"] for r in good.collect()] == [1]
    assert {r["id"]: r["reason"] for r in bad.collect()} == {2: "null vector", 3: "non-finite component", 4: "wrong dimension", 5: "non-finite component"}


def test_knn_edges(spark):
    e = sources.vectors(spark, SF)
    q = sources.ann_queries(spark, SF)
    assert knn.knn_exact(e, q.limit(0), 5).count() == 0
    assert knn.knn_exact(e, q, 0).count() == 0
    n = e.count()
    assert knn.knn_exact(e, q, n + 5).count() == q.count() * (n - 1)
    with pytest.raises(ValueError):
        knn.knn_exact(e, q, -1)
    zero = spark.createDataFrame([(1, [0.0, 0.0]), (2, [1.0, 0.0])], "id long, v array<double>")
    asks = spark.createDataFrame([(9, [1.0, 1.0])], "qid long, qv array<double>")
    assert [round(r["d"], 6) for r in knn.knn_exact(zero, asks, 2, "cosine").orderBy("rank").collect()] == [0.292893, 1.0]


def test_knn_blocks_equal_broadcast(spark, monkeypatch):
    e, q = sources.vectors(spark, SF), sources.ann_queries(spark, SF)
    want = sorted(knn.knn_exact(e, q, 7).collect())
    monkeypatch.setattr(knn, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(knn, "BLOCK", 3)
    monkeypatch.setattr(knn, "SHARDS_ROWS", 150)
    assert sorted(knn.knn_exact(e, q, 7).collect()) == want


def test_partition_edges(spark):
    e = sources.vectors(spark, SF)
    n = e.count()
    with pytest.raises(ValueError):
        partition.seeded_centroids(e, n + 1)
    assert partition.assign(e, partition.seeded_centroids(e, 1)).select("cluster_id").distinct().count() == 1
    own = partition.assign(e, partition.seeded_centroids(e, n))
    assert own.where("id <> cluster_id or dist > 1e-6").isEmpty()
    assert partition.choose_n_c(1000) == 4 and partition.choose_n_c(1) == 1
    lists = partition.assign(e, partition.seeded_centroids(e, 4))
    cut = partition.split_large(lists, 60)
    assert cut.count() == n and cut.select("id").distinct().count() == n
    assert cut.groupBy("cluster_id").count().agg(F.max("count")).first()[0] < lists.groupBy("cluster_id").count().agg(F.max("count")).first()[0]


def test_lloyd_cost_falls(spark):
    e = sources.vectors(spark, SF)
    costs = [partition.assign(e, partition.fit_partitions(e, 8, r)).agg(F.sum(F.col("dist") ** 2)).first()[0] for r in (0, 1, 3)]
    assert costs[0] >= costs[1] >= costs[2]


def test_search_one_equals_batch(spark, tmp_path):
    e, q = sources.vectors(spark, SF), sources.ann_queries(spark, SF).limit(2)
    idx = two_tier.save_index(two_tier.build_index(e, n_c=8, rounds=1), f"file://{tmp_path}/i")
    for r in q.collect():
        want = [x["id"] for x in two_tier.search(idx, q.where(F.col("qid") == r["qid"]), 10, 8, 4096, 4096, skip_self=False).orderBy("rank").collect()]
        got, facts = two_tier.search_one(idx, r["qv"], 10, 8, 4096, 4096)
        assert [i for _, i in got] == want and facts["peak_lists"] == 1 and facts["lists"] <= 8
        assert [i for _, i in two_tier.search_one(idx, r["qv"], 10, 8, 4096, 4096, sequential=False)[0]] == want


def test_results_do_not_depend_on_partitions(spark):
    e, q = sources.vectors(spark, SF), sources.ann_queries(spark, SF)
    out = [sorted(two_tier.search(two_tier.build_index(e.repartition(p), n_c=8, rounds=1), q.repartition(p), 5).collect()) for p in (1, 7)]
    assert out[0] == out[1]


def test_degenerate_indexes(spark):
    e = sources.vectors(spark, SF).where("id < 40")
    q = sources.ann_queries(spark, SF)
    truth = sorted(knn.knn_exact(e, q, 5).collect())
    for n_c in (1, 40):
        assert sorted(two_tier.search(two_tier.build_index(e, n_c=n_c, rounds=0), q, 5, n_p=n_c, ef_c=4096, ef_l=4096).collect()) == truth
    with pytest.raises(ValueError):
        two_tier.probe(two_tier.build_index(e, n_c=2, rounds=0), q, 0)
    assert two_tier.search(two_tier.build_index(e, n_c=2, rounds=0), q.limit(0), 5).count() == 0


def test_updates_are_idempotent_and_local(spark):
    e = sources.vectors(spark, SF)
    idx = two_tier.build_index(e, n_c=8, rounds=1)
    log = spark.createDataFrame([(1, "delete", 7, None), (2, "delete", 99999, None), (3, "insert", 5000, [0.1] * 64), (4, "delete", 8, None), (5, "insert", 8, [0.2] * 64)], "seq long, op string, id long, v array<double>")
    once = two_tier.apply_updates(idx, log)
    twice = two_tier.apply_updates(once, log)
    ids = lambda i: sorted(r["id"] for r in two_tier.members(i).collect())
    assert ids(once) == ids(twice) == sorted(set(range(e.count())) - {7} | {5000})
    touched = {r["cluster_id"] for r in two_tier.route(idx, log).collect()}
    for r in once.lists.select("cluster_id", "version").collect():
        assert (r["version"] == 1) == (r["cluster_id"] in touched)


def test_saved_index_prunes_buckets(spark, tmp_path):
    e = sources.vectors(spark, SF)
    idx = two_tier.save_index(two_tier.build_index(e, n_c=16, rounds=1), f"file://{tmp_path}/p")
    plan = idx.lists.where("bucket = 3 and cluster_id = 3")._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(bucket" in plan
    assert len(idx.lists.where("bucket = 3").inputFiles()) >= 1


def test_no_row_at_a_time_python(spark):
    q = C.idf_table(sources.table(spark, SF, "documents"))
    plan = q._jdf.queryExecution().toString()
    assert "BatchEvalPython" not in plan and "ReadSchema: struct<text:string>" in plan


def test_accuracy_and_negative_control(spark):
    gold = spark.createDataFrame([(1, [5], ["The Answer is 42."]), (2, [6], ["nowhere"]), (3, [7], [])], "qid long, gold_docs array<long>, answers array<string>")
    said = spark.createDataFrame([(1, "well: the answer, IS 42!"), (2, "else")], "qid long, reply string")
    r = measure.answer_accuracy(said, gold).first()
    assert r["queries"] == 3 and r["accuracy"] == pytest.approx(100 / 3, abs=1e-5)


def test_prompt_budget(spark):
    ctx = spark.createDataFrame([(1, 1, 1, "a b c"), (1, 2, 2, "d e f g"), (1, 3, 3, "h")], "qid long, doc_id long, rank int, context string")
    q = spark.createDataFrame([(1, "x y"), (2, "z")], "qid long, query string")
    out = {r["qid"]: r for r in rag.build_prompt(ctx, q, 6).collect()}
    assert out[1]["prompt"] == "a b c\nx y" and out[1]["n_tokens"] == 5 and out[2]["prompt"] == "z"


def test_chunk_offsets(spark):
    docs = spark.createDataFrame([(1, "One two. Three four. Five."), (2, ""), (3, None)], "doc_id long, text string")
    rows = corpus.chunk(docs, 2).orderBy("chunk_no").collect()
    joined = "One two. Three four. Five."
    assert [joined[r["offset"] :].startswith(r["text"]) for r in rows] == [True, True] and {r["doc_id"] for r in rows} == {1}
    with pytest.raises(ValueError):
        corpus.chunk(docs, 2, overlap=2)


def test_vector_functions(spark):
    r = spark.sql("select array(1D, 2D) a, array(3D, -1D) b, array(0D, 0D) z").select(V.dot("a", "b").alias("d"), V.l2sq("a", "b").alias("s"), V.cosine("a", "z").alias("c")).first()
    assert (r["d"], r["s"], r["c"]) == (1.0, 13.0, 0.0)


def test_pq_checks(spark):
    e = sources.vectors(spark, SF)
    with pytest.raises(ValueError):
        B.pq_fit(e, 7, 4)
    with pytest.raises(ValueError):
        B.pq_fit(e, 8, 12)


def test_expanded_vectors_have_clusters(spark):
    x = sources.expanded_embeddings(spark, SF, 3)
    assert x.count() == 3 * sources.vectors(spark, SF).count()
    lengths = np.array([r[0] for r in x.select(V.norm("v")).collect()])
    assert np.allclose(lengths, 1)


def places(folder):
    return sorted(str(p.relative_to(folder)) for p in folder.rglob("bucket=*") if p.is_dir())


def test_saved_updates_write_touched_buckets_only(spark, tmp_path):
    e, q = sources.vectors(spark, SF), sources.ann_queries(spark, SF)
    idx = two_tier.save_index(two_tier.build_index(e, n_c=16, rounds=1), f"file://{tmp_path}/i")
    log = spark.createDataFrame([(1, "delete", 7, None), (2, "insert", 5000, [0.1] * 64)], "seq long, op string, id long, v array<double>")
    touched = {r["cluster_id"] for r in two_tier.route(idx, log).collect()}
    new = two_tier.update_saved(idx, log)
    assert places(tmp_path / "i" / "lists" / "v=1") == sorted(f"bucket={c % idx.buckets}" for c in touched)
    assert len(places(tmp_path / "i" / "homes" / "v=1")) <= 2
    assert {b: v for b, v in new.at["lists"].items() if v == 1}.keys() == {c % idx.buckets for c in touched}
    ids = sorted(r["id"] for r in two_tier.members(new).collect())
    assert ids == sorted(set(range(e.count())) - {7} | {5000}) == sorted(r["id"] for r in new.homes.select("id").collect())
    assert sorted(r["id"] for r in two_tier.members(two_tier.load_index(spark, idx.path, 0)).collect()) == list(range(e.count()))  # readers keep their version
    want = sorted(two_tier.search(two_tier.apply_updates(idx, log), q, 5, 16, 4096, 4096).collect())
    assert sorted(two_tier.search(new, q, 5, 16, 4096, 4096).collect()) == want
    nothing = two_tier.update_saved(new, log.limit(0))
    assert not (tmp_path / "i" / "lists" / "v=2").exists() and nothing.version == 2


def test_a_search_reads_probed_buckets_only(spark, tmp_path):
    idx = two_tier.save_index(two_tier.build_index(sources.vectors(spark, SF), n_c=16, rounds=1), f"file://{tmp_path}/i")
    blocks = two_tier.block_queries(two_tier.probe(idx, sources.ann_queries(spark, SF).limit(1), 2))
    plan = two_tier.load_graphs(idx, blocks)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters" in plan and "PushedFilters: [In(cluster_id" in plan or "cluster_id" in plan.split("PushedFilters")[1][:200]


def test_bucket_count_follows_the_lists():
    assert two_tier.choose_buckets(16) == 16 and two_tier.choose_buckets(1_000_000) == 400


def test_store_updates_write_touched_buckets_only(spark, tmp_path):
    path = f"file://{tmp_path}/s"
    emb = spark.createDataFrame([(i, i, [0.5]) for i in range(40)], schema.EMBEDDING)
    doc = spark.createDataFrame([(i, f"/f{i}") for i in range(40)], schema.DOCUMENT)
    chunk = spark.createDataFrame([(i, i, 0) for i in range(40)], schema.CHUNK)
    store.write_tables(spark, path, emb, doc, chunk)
    none = {"emb": emb.limit(0), "doc": doc.limit(0), "chunk": chunk.limit(0)}
    store.update_store(spark, path, none, spark.createDataFrame([(9,)], "doc_id long"))
    assert places(tmp_path / "s" / "doc" / "v=1") == ["bucket=1"]
    assert sorted(r["doc_id"] for r in store.read_table(spark, path, "doc").collect()) == [i for i in range(40) if i != 9]
    assert store.read_table(spark, path, "doc", 0).count() == 40


def test_lists_send_k_rows_a_query(spark, monkeypatch):
    e, q = sources.vectors(spark, SF), sources.ann_queries(spark, SF)
    cents = partition.fit_partitions(e, 8, 1)
    lists, seen = partition.assign(e, cents), []
    monkeypatch.setattr(B, "merge_topk", lambda partials, k: seen.append(partials.count()) or knn.merge_topk(partials, k))
    B.ivf_search(lists, cents, q, 5, 3).collect()
    assert 0 < seen[0] <= q.count() * 3 * 5
    with pytest.raises(ValueError):
        monkeypatch.setattr(B, "GRAPH_BYTES", 10)
        B.graph_index(e)


def test_one_graph_is_linked_in_blocks(spark, monkeypatch):
    e = sources.vectors(spark, SF)
    n, seen, whole = e.count(), [], two_tier.link_in_blocks
    rows = lambda idx: [r.asDict() for r in idx.lists.drop("n_dist_build").collect()]
    one = rows(B.graph_index(e))
    monkeypatch.setattr(two_tier, "LINKED", n // 3)
    monkeypatch.setattr(two_tier, "link_in_blocks", lambda *a, **k: seen.append(whole(*a, **k)) or seen[-1])
    assert rows(B.graph_index(e)) == one
    assert seen[0].count() == n and seen[0].where("array_contains(near, id) or size(near) = 0 or size(near) > 16").isEmpty()


def test_query_blocks_equal_broadcasts(spark, monkeypatch):
    docs = sources.table(spark, SF, "documents").select("doc_id", "text")
    q = spark.createDataFrame([(k, r["text"][:80]) for k, r in enumerate(docs.limit(6).collect())], "qid long, query string")
    idf = C.idf_table(docs).cache()
    want = sorted(rag.retrieve(docs, q, idf).collect())
    monkeypatch.setattr(rag, "QUERY_BYTES", 2 * 8 * C.DIM)
    monkeypatch.setattr(rag, "SHARD", 90)
    assert sorted(rag.retrieve(docs, q, idf).collect()) == want
    e, asks = sources.vectors(spark, SF), sources.ann_queries(spark, SF)
    near = sorted(knn.range_search(e, asks, 1.2).collect())
    monkeypatch.setattr(knn, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(knn, "BLOCK", 3)
    assert sorted(knn.range_search(e, asks, 1.2).collect()) == near


def test_retrieval_plan_has_no_join_of_buckets(spark):
    docs = sources.table(spark, SF, "documents").select("doc_id", "text")
    q = spark.createDataFrame([(1, "the")], "qid long, query string")
    plan = rag.retrieve(docs, q, C.idf_table(docs).cache())._jdf.queryExecution().toString()
    assert "bucket#" not in "".join(x for x in plan.splitlines() if "Join" in x)


def test_late_rows_are_counted(spark, tmp_path):
    from vecrag.streaming import streams

    for n, rows in enumerate(([("2024-01-01 10:00:00",), ("2024-01-01 12:00:00",)], [("2024-01-01 10:30:00",), ("2024-01-01 11:30:00",)])):
        spark.createDataFrame(rows, "t string").select(F.to_timestamp("t").alias("ts")).coalesce(1).write.parquet(f"file://{tmp_path}/in/part{n}")
    stream = spark.readStream.schema("ts timestamp").option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/in")
    got = {r["batch"]: (r["late"], r["on_time"]) for r in streams.tumbling_with_late(stream, "late_test", f"file://{tmp_path}/out", f"file://{tmp_path}/ck").collect()}
    assert got == {0: (0, 2), 1: (1, 1)}


def test_prompt_with_history(spark):
    ctx = spark.createDataFrame([(1, 1, 1, "a b c")], "qid long, doc_id long, rank int, context string")
    q, h = spark.createDataFrame([(1, "x y"), (2, "z")], "qid long, query string"), spark.createDataFrame([(1, "before it")], "qid long, history string")
    out = {r["qid"]: (r["prompt"], r["n_tokens"]) for r in rag.build_prompt(ctx, q, 50, h).collect()}
    assert out == {1: ("a b c\nbefore it\nx y", 7), 2: ("z", 1)}


@pytest.mark.parametrize("name", ["two_tier_updated_search", "two_tier_updated_saved", "stream_updated_search"])
def test_updates_take_the_whole_log(spark, name):
    """An id's last operation counts, wherever in the log it is; what is live is all that is searched, and all of it."""
    from vecrag.queries import QUERIES

    d = "/root/testdata/sf0.001"
    n = sources.vectors(spark, d).count()
    last = {}
    for r in sources.table(spark, d, "events").select("event_id", "event_type").orderBy("event_id").collect():
        if r["event_type"] in ("signup", "purchase", "error"):
            last[r["event_id"] % n] = r["event_type"]
    gone = {i for i, op in last.items() if op == "error"}
    vecs = {r["id"]: np.array(r["v"]) for r in sources.vectors(spark, d).collect()}
    got = {}
    for r in sorted(QUERIES[name](spark, d).collect(), key=lambda r: (r["qid"], r["rank"])):
        got.setdefault(r["qid"], []).append(r["id"])
    want = lambda q: [i for _, i in sorted((round(float(np.linalg.norm(vecs[q] - v)), 6), i) for i, v in vecs.items() if i != q and i not in gone)][:10]
    assert gone and got == {q: want(q) for q in vecs if q % 50 == 0}
