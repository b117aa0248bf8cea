"""Full widths, bounded memory and ranks of the search."""

import numpy as np
from vecrag.operators import kernel
from vecrag.operators.kernel import Graph, packed, unpacked
from vecrag.operators.knn import best_of, nearest


def test_full_width_starts_at_the_entry():
    """Node 2 hangs on the entry alone, and upper levels lead the walk away from it."""
    g = Graph(dim=1, vecs=np.array([[0.0], [9.0], [8.0]]), ids=[0, 1, 2], levels=[1, 1, 0], links=[[[2, 1], [1]], [[], []], [[]]], deleted=[False] * 3, entry=0, max_level=1)
    assert [i for _, i in g.search(np.array([9.0]), 3, 4096)[0]] == [1]
    assert g.crossed()[0].tolist() == [0, 1, 2]


def test_width_of_queries_is_over_any_list():
    from vecrag.plans import ann_queries

    assert ann_queries.WIDE > 1_000_000_000


def test_links_do_not_depend_on_the_block(monkeypatch):
    x = np.random.default_rng(3).normal(size=(150, 6))
    x[40:60] = x[0]
    whole = Graph.build(list(range(150)), x)
    monkeypatch.setattr(kernel, "BLOCK_BYTES", 8 * 150 * 7)
    parts = Graph.build(list(range(150)), x)
    assert whole.links == parts.links and len(whole.reachable()) == 150


def test_stored_vectors_lose_nothing():
    x = np.random.default_rng(4).normal(size=(5, 3))
    assert (unpacked(packed(x), 5, 3) == x).all()
    assert len(packed(x.astype("<f4").astype(float))) == 60


def test_overlap_ranks_by_rounded_score_among_sharing_rows():
    x = np.array([[0.0, 0.0, 1.0], [0.6, 0.8, 0.0], [0.6 + 1e-8, 0.8, 0.0], [-1.0, 0.0, 0.0]])
    qid, i, d = nearest(np.array([-1]), np.array([[1.0, 0.0, 0.0]]), np.array([5, 9, 7, 3]), x, 4, "overlap", True)
    assert i.tolist() == [7, 9, 3] and d.tolist() == [-0.6, -0.6, 1.0]


def test_best_of_counts_an_id_once():
    got = best_of(np.array([1, 1, 1, 2]), np.array([4, 4, 3, 4]), np.array([0.5, 0.2, 0.2, 0.1]), 2)
    assert [x.tolist() for x in got] == [[1, 1, 2], [3, 4, 4], [0.2, 0.2, 0.1]]


def test_copies_put_a_vector_in_several_lists(spark):
    """Neighbours that a border parts meet in one list, and an id is found once."""
    from pyspark.sql import functions as F

    from vecrag import sources
    from vecrag.operators import index, knn, partition
    from vecrag.operators.baselines import recall_at_k

    e = sources.expanded_embeddings(spark, "/root/testdata/sf0.001", 4).select("id", "v").cache()
    q = e.where("id % 8 = 0").select(F.col("id").alias("qid"), F.col("v").alias("qv"))
    cents = partition.fit_partitions(e, 40, rounds=2)
    assert {r["count"] for r in partition.assign(e, cents, 3).groupBy("id").count().collect()} == {3}
    truth, recall = knn.knn_exact(e, q, 3).cache(), []
    for copies in (1, 3):
        found = index.search(index.build_index(e, centroids=cents, copies=copies), q, 3, n_p=1, ef_l=64).cache()
        assert found.count() == found.select("qid", "id").distinct().count()
        recall.append(recall_at_k(found, truth, 3).first()["recall"])
    assert recall[1] > recall[0] + 0.03
