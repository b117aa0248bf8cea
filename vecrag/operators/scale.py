"""Forms for very large tables: a third tier, re-balancing after drift, list caches."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag import schema
from vecrag.operators import index as two_tier
from vecrag.operators import partition
from vecrag.operators.kernel import Graph, unpacked
from vecrag.operators.knn import matrix, merge_topk
from vecrag.session import checkpointed

#: Vectors of a coarse partition that its fine centroids are fitted on, for each fine centroid.
SAMPLE_PER_FINE, ASSIGN_ROWS = 100, 50_000


@dataclass(frozen=True)
class ThreeTier:
    """coarse: resident graph row; middle: a graph over fine centroids for each coarse partition; lists: list graphs.

    Ids of the middle graphs are the lists' cluster ids: coarse * n_fine + fine.
    """

    coarse: dict
    middle: DataFrame
    lists: DataFrame
    buckets: int


def build_three_tier(emb: DataFrame, n_coarse: int, n_fine: int, rounds: int = 4, m: int = 16, m_c: int = 8, buckets: int = two_tier.BUCKETS, seed: int = 42) -> ThreeTier:
    """Coarse centroids are broadcast; fine ones are fitted on a bounded sample of each coarse partition, in its task;
    all vectors are then assigned in groups of bounded size.
    """
    coarse = partition.fit_partitions(emb, n_coarse, rounds)
    assigned = partition.assign(emb, coarse).select("id", "v", F.col("cluster_id").alias("coarse"))
    sizes = assigned.groupBy("coarse").agg(F.count("*").alias("n"))
    share = F.least(F.lit(1.0), F.lit(float(SAMPLE_PER_FINE * n_fine)) / F.col("n"))
    picked = F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(1 << 30)) < share * F.lit(1 << 30)
    sample = assigned.join(F.broadcast(sizes), "coarse").where(picked).select("coarse", "id", "v")

    def fit(t: pa.Table) -> pa.Table:
        order = np.argsort(t["id"].to_numpy(), kind="stable")
        x, cid = matrix(t["v"])[order], t["coarse"][0].as_py()
        k = min(n_fine, len(x))
        c = x[np.linspace(0, len(x) - 1, k).astype(int)]
        for _ in range(rounds):
            near, _d = partition.nearest_centroid(x, np.arange(k), c)
            c = np.array([x[near == j].mean(0) if (near == j).any() else c[j] for j in range(k)])
        graph = Graph.build([cid * n_fine + j for j in range(k)], c, m=m_c)
        return two_tier._table(graph, cid, buckets, 0, 0.0)

    middle = sample.groupBy("coarse").applyInArrow(fit, schema.GRAPH)
    parts = F.ceil(F.col("n") / ASSIGN_ROWS).cast("int")
    dealt = assigned.join(F.broadcast(sizes), "coarse").select("coarse", "id", "v", F.pmod(F.xxhash64("id"), parts).cast("int").alias("part"))
    fine = middle.select(F.col("cluster_id").alias("coarse"), "ids", "vecs", "n", "dim").join(F.broadcast(sizes.withColumnRenamed("n", "rows")), "coarse")
    fine = fine.withColumn("part", F.explode(F.sequence(F.lit(0), F.ceil(F.col("rows") / ASSIGN_ROWS).cast("int") - 1))).drop("rows")

    def place(rows: pa.Table, books: pa.Table) -> pa.Table:
        ids = np.array(books["ids"][0].as_py(), np.int64)
        c = unpacked(books["vecs"][0].as_py(), len(ids), books["dim"][0].as_py())
        near, d = partition.nearest_centroid(matrix(rows["v"]), ids, c)
        return pa.table({"id": rows["id"], "v": rows["v"], "cluster_id": pa.array(near.astype(np.int32)), "dist": pa.array(d)})

    placed = dealt.groupBy("coarse", "part").cogroup(fine.groupBy("coarse", "part")).applyInArrow(place, "id long, v array<double>, cluster_id int, dist double")
    lists = two_tier.build_partition_graphs(placed, m, buckets=buckets)
    return ThreeTier(two_tier.build_centroid_graph(coarse, m_c), middle, lists, buckets)


def search_three_tier(index: ThreeTier, queries: DataFrame, k: int = 10, n_p1: int = 4, n_p2: int = 8, ef: int = 32, skip_self: bool = True) -> DataFrame:
    """Probe the resident graph, then the stored middle graphs, then the lists: a few rows of a very large table."""
    spark = queries.sparkSession
    top = two_tier.Index(spark, index.coarse, {}, index.middle, index.buckets)
    blocks = two_tier.block_queries(two_tier.probe(top, queries, n_p1, max(ef, n_p1)))
    fine = two_tier.search_lists(two_tier.load_graphs(top, blocks), n_p2, ef, skip_self=False).where("id is not null")
    probes = merge_topk(fine.select("qid", "id", "d"), n_p2).join(queries.select("qid", "qv"), "qid")
    probes = probes.select("qid", "qv", F.col("id").cast("int").alias("cluster_id"), F.col("d").alias("c_dist"), F.col("rank").alias("probe_rank"))
    low = two_tier.Index(spark, index.coarse, {}, index.lists, index.buckets)
    found = two_tier.search_lists(two_tier.load_graphs(low, two_tier.block_queries(probes)), k, ef, skip_self).where("id is not null")
    return merge_topk(found.select("qid", "id", "d"), k)


def stored_vectors(index: two_tier.Index) -> DataFrame:
    """(cluster_id, id, v) of all vectors that are not flagged, from the list graphs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                keep = ~np.array(r["deleted"], bool)
                x = unpacked(r["vecs"], r["n"], r["dim"])[keep]
                ids = np.array(r["ids"], np.int64)[keep]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), r["cluster_id"], np.int32)), pa.array(ids), pa.array(list(x), pa.list_(pa.float64()))], ["cluster_id", "id", "v"])

    return index.lists.select("cluster_id", "n", "dim", "ids", "vecs", "deleted").mapInArrow(run, "cluster_id int, id long, v array<double>")


def rebalance(index: two_tier.Index, cap: int = partition.CAP, floor: int = 20, m: int = 16) -> two_tier.Index:
    """Split lists over `cap`, dissolve lists under `floor` into their neighbours; other lists stay as they are."""
    sizes = checkpointed(index.lists.select("cluster_id", F.size(F.filter("deleted", lambda d: ~d)).alias("n")))
    ids, exact = list(index.centre["ids"]), np.asarray(index.centre["exact"])
    odd = sizes.where((F.col("n") > cap) | (F.lit(len(ids) > 1) & (F.col("n") < floor)))
    if odd.where(F.col("n") <= cap).count() == len(ids):  # all are small: the largest of them stays
        odd = odd.join(odd.orderBy(F.desc("n"), "cluster_id").limit(1).select("cluster_id"), "cluster_id", "left_anti")
    odd = checkpointed(odd)
    if odd.isEmpty():
        return index
    vectors = stored_vectors(index)
    loose = checkpointed(vectors.join(odd.select("cluster_id", "n"), "cluster_id"))
    gone = {r[0] for r in odd.select("cluster_id").collect()}  # at most as many as there are centroids, which are here
    kept = [(c, v) for c, v in zip(ids, exact, strict=True) if c not in gone]
    parts = partition.split_large(loose.where(F.col("n") > cap).drop("n").withColumn("dist", F.lit(0.0)), cap)
    means = parts.select("cluster_id", F.posexplode("v").alias("j", "x")).groupBy("cluster_id", "j").agg(F.avg("x").alias("x"))
    rows = means.groupBy("cluster_id").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("s")).orderBy("cluster_id").select("s.x").collect()
    free = iter(range(max(ids) + 1, max(ids) + 1 + len(rows)))
    kept += [(next(free), np.array(r[0])) for r in rows]
    centroids = partition.as_table(index.spark, np.array([c for c, _ in kept]), np.array([v for _, v in kept]))
    moved = checkpointed(partition.assign(loose.select("id", "v"), centroids))
    hit = checkpointed(moved.select("cluster_id").distinct())
    stay = vectors.join(hit, "cluster_id", "left_semi").join(odd.select("cluster_id"), "cluster_id", "left_anti")
    again = partition.assign(stay.select("id", "v"), centroids).select("id", "v", "dist").join(stay.select("id", "cluster_id"), "id").select("id", "v", "cluster_id", "dist")
    rebuilt = two_tier.build_partition_graphs(moved.unionByName(again), m, buckets=index.buckets, version=index.version + 1)
    left = index.lists.join(hit.unionByName(odd.select("cluster_id")).distinct(), "cluster_id", "left_anti").select(*index.lists.columns)
    out = replace(index, centre=two_tier.build_centroid_graph(centroids, index.centre["m"]), lists=left.unionByName(rebuilt), version=index.version + 1, path=None, homes=None, at=None)
    return two_tier.refresh(out)


def cache_report(probes: DataFrame, capacity: int, workers: int = 4) -> DataFrame:
    """(worker, probes, hits): loads saved by a least-recently-used cache of `capacity` lists on each worker.

    Lists belong to workers by id, and a worker sees its probes in order of query and rank.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        caches: dict[int, OrderedDict] = {}
        count: dict[int, list[int]] = {}
        for batch in batches:
            for w, c in zip(batch.column("worker").to_pylist(), batch.column("cluster_id").to_pylist(), strict=True):
                cache, tally = caches.setdefault(w, OrderedDict()), count.setdefault(w, [0, 0])
                tally[0] += 1
                if c in cache:
                    tally[1] += 1
                    cache.move_to_end(c)
                elif capacity > 0:
                    cache[c] = True
                    if len(cache) > capacity:
                        cache.popitem(last=False)
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(list(count), pa.int32()), pa.array([x[0] for x in count.values()]), pa.array([x[1] for x in count.values()])], ["worker", "probes", "hits"])

    dealt = probes.select(F.pmod("cluster_id", F.lit(workers)).cast("int").alias("worker"), "qid", "probe_rank", "cluster_id")
    return dealt.repartition("worker").sortWithinPartitions("worker", "qid", "probe_rank").mapInArrow(run, "worker int, probes long, hits long")
