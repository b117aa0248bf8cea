"""Pipelines over the same documents share their vectors and one retrieval."""

from pyspark.sql import functions as F

from vecrag.operators import condense as C
from vecrag.operators import rag
from vecrag.plans import rag_queries as R


def test_pipelines_retrieve_once(spark, monkeypatch):
    docs, q, idf = R._base(spark, "/root/testdata/sf0.001")
    whole, calls = rag.retrieve, []
    monkeypatch.setattr(rag, "retrieve", lambda *a, **k: calls.append(k) or whole(*a, **k))
    contexts, near = R._contexts(spark, "/root/testdata/sf0.001", docs, q, idf)
    assert len(calls) == 1 and calls[0]["vectors"] is not None
    own = {"plain": rag.rag_plain(docs, q, idf), "reranked": rag.rag_reranked(docs, q, idf)}
    for name, want in own.items():
        assert sorted(contexts[name].collect()) == sorted(want.collect())
    assert 0 < near.count() < idf.count() or near.join(idf, ["token", "idf"]).count() == idf.count()


def test_idf_of_met_tokens(spark):
    idf = spark.createDataFrame([("a", 1.0), ("b", 2.0), ("c", 3.0)], "token string, idf double")
    texts = spark.createDataFrame([("A a d",), (None,)], "text string")
    assert [tuple(r) for r in C.idf_of(idf, texts, texts.select(F.lit("c").alias("query"))).orderBy("token").collect()] == [("a", 1.0), ("c", 3.0)]


def test_question_sets_search_the_index(spark, monkeypatch):
    """The two-tier pipeline of the question sets takes its documents from a search of the document index."""
    from vecrag.plans import workload_queries as Q

    d = "/root/testdata/sf0.001"
    docs, idf = R.docs_of(spark, d).select("doc_id", "text"), R._base(spark, d)[2]
    q, gold = Q.question_sets(spark, d)
    assert {r["qid"] % 3 for r in gold.collect()} == {0, 1, 2} and q.count() == q.select("qid").distinct().count()
    searched, built = [], []
    search, build = rag.index_ranks, rag.document_index
    monkeypatch.setattr(rag, "index_ranks", lambda *a, **k: searched.append(search(*a, **k)) or searched[-1])
    monkeypatch.setattr(rag, "document_index", lambda *a, **k: built.append(k) or build(*a, **k))
    found = Q.question_contexts(spark, docs, q, idf)
    assert len(searched) == len(built) == 1
    pairs = lambda df: sorted(map(tuple, df.select("qid", "doc_id").collect()))
    assert pairs(found["two_tier"]) == pairs(searched[0])


def test_windows_are_scored_where_texts_are(spark, monkeypatch):
    """Best windows without a shuffle of terms are those of `score_windows`, for texts longer than a step too."""
    docs, q, idf, ret = R._retrieved(spark, "/root/testdata/sf0.001")
    monkeypatch.setattr(C, "STEP", 5)
    cells = [(1, 0), (3, 2), (4, 1), (5, 0)]
    made = C.best_windows(docs, ret, q, idf, cells, 2)
    plan = made._jdf.queryExecution().toString()
    assert "Join" not in "".join(x for x in plan.splitlines() if "token#" in x)
    for w, o in cells:
        want = C.best_window(C.score_windows(C.windows(C.split_sentences(docs), w, o), ret, q, idf), 2).select("qid", "doc_id", "start", "stop", "score")
        got = made.where((F.col("window") == w) & (F.col("overlap") == o)).select(want.columns)
        assert sorted(got.collect()) == sorted(want.collect())


def test_owners_are_packed_in_place(spark, monkeypatch):
    """The same vectors with a lookup, without one, and where an id comes twice."""
    docs = R.docs_of(spark, "/root/testdata/sf0.001").select("doc_id", "text").repartition(3)
    idf = C.idf_table(docs).cache()
    flat = lambda df: sorted((r["doc_id"], b, round(w, 9)) for r in df.collect() for b, w in zip(r["_b"], r["_w"], strict=True) if round(w, 9))
    own = C.packed_owners(docs, "doc_id", idf)
    assert "hashpartitioning" not in own._jdf.queryExecution().executedPlan().toString()
    assert flat(own) == flat(C.packed_vectors(C.sparse_vectors(docs, ["doc_id"], idf), ["doc_id"]))
    twice = docs.unionByName(docs.where("doc_id = 3").withColumn("text", F.lit("another text")))
    assert C.packed_owners(twice, "doc_id", idf).groupBy("doc_id").count().where("count > 1").isEmpty()
    monkeypatch.setattr(C, "LOOKUP_TOKENS", 3)
    assert flat(C.packed_owners(docs, "doc_id", C.idf_table(docs).cache())) == flat(own)


def test_the_best_of_ties_and_of_none():
    """Ties go to the smaller key however owners come; an owner without a common bucket is none of a query's."""
    import numpy as np
    import pyarrow as pa

    rng = np.random.default_rng(5)
    d = np.where(rng.random((400, 8)) < 0.4, rng.integers(-2, 3, (400, 8)), 0).astype(float)
    q = np.vstack([d[:20], -d[:5], np.zeros((1, 8)), np.eye(8)])
    unit = lambda x: x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    d, q, keys = unit(d), unit(q), rng.permutation(400)
    best = rag._Best(q, 3)
    for at in range(0, 400, 30):
        rows = [np.flatnonzero(x) for x in d[at : at + 30]]
        cols = [pa.array(keys[at : at + 30]), pa.array([r.tolist() for r in rows], pa.list_(pa.int32())), pa.array([x[r].tolist() for x, r in zip(d[at : at + 30], rows, strict=True)], pa.list_(pa.float64()))]
        best.meet(pa.RecordBatch.from_arrays(cols, ["key", "_b", "_w"]), 8, "key")
    got = {}
    for b in best.rows(np.arange(len(q)), "key"):
        for i, k, s in zip(*(c.to_pylist() for c in b.columns), strict=True):
            got.setdefault(i, []).append((-s, k))
    score = np.round(q @ d.T, 6) + 0.0
    want = {i: sorted((-score[i, j], int(keys[j])) for j in range(400) if ((q[i] != 0) & (d[j] != 0)).any())[:3] for i in range(len(q))}
    assert {i: sorted(v) for i, v in got.items()} == {i: v for i, v in want.items() if v}
