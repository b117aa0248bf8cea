"""The two-tier index: a graph over centroids that is broadcast, and a graph of each list that is read on demand."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag import schema
from vecrag.operators import partition
from vecrag.operators.kernel import Graph, chosen_links, packed, unpacked
from vecrag.operators.knn import BROADCAST_BYTES, best_of, knn_exact, matrix, merge_topk, nearest
from vecrag.session import checkpointed

N_P, EF_C, EF_L, M_C, BLOCK = 4, 32, 32, 8, 1024
#: Width that no list reaches: a search of it visits all that the links reach.
FULL = 1 << 30
#: Members of a single large list whose links one task chooses, and the parts of a list at most: each holds all its vectors.
LINKED, LINKED_PARTS = 4096, 32
#: Probes of a batch that goes to the JVM, and results that a task of a search holds before it merges them.
ROWS, HELD = 50_000, 1 << 19
#: Buckets of a small index; a larger one has as many as keep LISTS_PER_BUCKET lists (about 1 GB at 384 dimensions) in each.
BUCKETS, LISTS_PER_BUCKET = 16, 2500
#: Probed lists up to which their ids are pushed to the scan as literals.
LITERALS = 1000


def choose_buckets(n_c: int) -> int:
    return max(BUCKETS, -(-n_c // LISTS_PER_BUCKET))


@dataclass(frozen=True)
class Index:
    """centre: the centroid graph's stored row (bounded by n_c); radii by cluster; lists: the list graphs' table.

    A saved index also has `homes`, the list of each id by buckets of ids, and `at`: which version's files hold each bucket
    of lists and of homes.
    """

    spark: SparkSession
    centre: dict
    radii: dict[int, float]
    lists: DataFrame
    buckets: int = BUCKETS
    version: int = 0
    path: str | None = None
    homes: DataFrame | None = None
    at: dict[str, dict[int, int]] | None = None

    @property
    def n_c(self) -> int:
        return self.centre["n"]


def build_centroid_graph(centroids: DataFrame, m: int = M_C, ef_build: int = 64, alpha: float = 1.2, mode: str | None = None) -> dict:
    """Stored row of the graph over the centroids; without a mode, batch up to 1000 of them, incremental beyond."""
    ids, c = partition.local(centroids)
    mode = mode or ("batch" if len(ids) <= 1000 else "incremental")
    row = Graph.build(ids, c, mode=mode, m=m, ef_build=ef_build, alpha=alpha).to_row()
    return row | {"exact": c}


def build_partition_graphs(assigned: DataFrame, m: int = 16, ef_build: int = 64, alpha: float = 1.2, mode: str = "batch", buckets: int = BUCKETS, version: int = 0) -> DataFrame:
    """One graph row for each list, all independent; a list is bounded by CAP vectors (split_large)."""

    def build(t: pa.Table) -> pa.Table:
        chosen = None
        if "near" in t.column_names:
            t = t.sort_by("id")
            near = t["near"].combine_chunks()
            chosen = np.split(np.searchsorted(t["id"].to_numpy(), near.flatten().to_numpy()), np.cumsum(near.value_lengths().to_numpy())[:-1])
        return _table(Graph.build(t["id"].to_pylist(), matrix(t["v"]), mode=mode, m=m, ef_build=ef_build, alpha=alpha, chosen=chosen), t["cluster_id"][0].as_py(), buckets, version, max(t["dist"].to_pylist()))

    return assigned.select("cluster_id", "id", "v", "dist", *(["near"] if "near" in assigned.columns else [])).groupBy("cluster_id").applyInArrow(build, schema.GRAPH)


def link_in_blocks(assigned: DataFrame, size: int, m: int = 16, ef_build: int = 64, alpha: float = 1.2, block: int | None = None) -> DataFrame:
    """The members of lists of up to `size` vectors with the ids `near` that each links to on level 0: about `block` (LINKED) members
    a task, which looks at all vectors of their list. Building a list's graph in batch mode then takes time linear in its size.
    """
    parts = min(LINKED_PARTS, max(1, -(-size // (block or LINKED))))

    def choose(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids, wanted = t["id"].to_numpy(), np.flatnonzero(t["own"].to_numpy() == t["part"][0].as_py())
        links = chosen_links(matrix(t["v"]), wanted, m, ef_build, alpha)
        near = pa.ListArray.from_arrays(np.cumsum([0, *map(len, links)]), pa.array(ids[np.concatenate([np.zeros(0, int), *links])]))
        return pa.table({"id": t["id"].take(pa.array(wanted)), "cluster_id": t["cluster_id"].take(pa.array(wanted)), "near": near.cast(pa.list_(pa.int64()))})

    own = F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int").alias("own")
    dealt = assigned.select("cluster_id", "id", "v", own, F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))
    kind = assigned.schema["cluster_id"].dataType.simpleString()
    found = dealt.groupBy("cluster_id", "part").applyInArrow(choose, f"id long, cluster_id {kind}, near array<long>")
    return assigned.join(checkpointed(found), ["cluster_id", "id"])


_KINDS = {"cluster_id": pa.int32(), "bucket": pa.int32(), "version": pa.int64(), "n": pa.int32(), "dim": pa.int32(), "m": pa.int32(), "ids": pa.list_(pa.int64()), "vecs": pa.binary(), "levels": pa.list_(pa.int32()), "link_ptr": pa.list_(pa.int32()), "link_to": pa.list_(pa.int32()), "entry": pa.int32(), "max_level": pa.int32(), "deleted": pa.list_(pa.bool_()), "radius": pa.float64(), "n_dist_build": pa.int64()}


def _table(graph: Graph, cluster_id: int, buckets: int, version: int, radius: float) -> pa.Table:
    row = graph.to_row() | {"cluster_id": cluster_id, "bucket": cluster_id % buckets, "version": version, "radius": float(radius)}
    return pa.table({c: pa.array([row[c]], kind) for c, kind in _KINDS.items()})


def build_index(emb: DataFrame, n_c: int | None = None, rounds: int = 8, init: str = "seeded", m: int = 16, m_c: int = M_C, alpha: float = 1.2, ef_build: int = 64, mode: str = "batch", cap: int | None = None, centroids: DataFrame | None = None, buckets: int | None = None, copies: int = 1, size: int = 0) -> Index:
    """Partition, then build both tiers. With `size`, the length of the longest list, lists over LINKED are linked in blocks. With `cap`, oversize lists are split and their means become centroids. With `copies`
    a vector is in as many lists, those of its nearest centroids: neighbours that a border parts still meet in one list.
    """
    spark = emb.sparkSession
    if centroids is None:
        centroids = partition.fit_partitions(emb, n_c or partition.choose_n_c(emb.count()), rounds, init)
    assigned = partition.assign(emb, centroids)
    if cap:
        assigned = partition.split_large(assigned, cap)
        per = assigned.select("cluster_id", F.posexplode("v").alias("j", "x")).groupBy("cluster_id", "j").agg(F.avg("x").alias("x"))
        centroids = per.groupBy("cluster_id").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("s")).select("cluster_id", F.col("s.x").alias("cv"))
    if cap or copies > 1:
        assigned = partition.assign(emb, centroids, copies)
    centre = build_centroid_graph(centroids, m_c, ef_build, alpha)
    buckets = buckets or choose_buckets(centre["n"])
    linked = link_in_blocks(assigned, size, m, ef_build, alpha) if mode == "batch" and size > LINKED else assigned
    lists = build_partition_graphs(linked, m, ef_build, alpha, mode, buckets)
    radii = {r["cluster_id"]: r["radius"] for r in partition.partition_stats(assigned).collect()}
    return Index(spark, centre, radii, lists, buckets)


# -- search --------------------------------------------------------------------------------------------------------
def probe(index: Index, queries: DataFrame, n_p: int = N_P, ef_c: int = EF_C, carry: bool = True) -> DataFrame:
    """(qid, qv, cluster_id, c_dist, probe_rank, n_dist) of each query's n_p nearest centroids, by the resident graph; without
    `carry` no qv.
    """
    if n_p < 1:
        raise ValueError("n_p must be at least 1")
    shared = index.spark.sparkContext.broadcast(index.centre)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = Graph.from_row(shared.value)
        exact = shared.value.get("exact")
        if exact is not None:
            graph.vecs = np.asarray(exact)
        ids, width = np.array(graph.ids, np.int64), max(n_p, ef_c)
        every = graph.crossed() if width >= len(ids) else None
        step = max(1, ROWS // n_p)
        for batch in batches:
            for at in range(0, batch.num_rows, step):
                part = batch.slice(at, step)
                q, qids = matrix(part.column("qv")), part.column("qid").to_numpy()
                place = np.arange(len(q))
                if every is not None:
                    r, c, d = nearest(place, q, ids[every[0]], graph.vecs[every[0]], n_p, "l2", False)
                    n = np.full(len(q), every[1])
                else:
                    found = [graph.candidates(v, width) for v in q]
                    near = [nearest(place[k : k + 1], q[k : k + 1], ids[f[0]], graph.vecs[f[0]], n_p, "l2", False) for k, f in enumerate(found)]
                    r, c, d = (np.concatenate(x) for x in zip(*near, strict=True))
                    n = np.array([f[1] for f in found])
                rank = np.arange(len(r)) - np.searchsorted(r, r) + 1
                cols = [pa.array(qids[r]), pa.array(c.astype(np.int32)), pa.array(d), pa.array(rank.astype(np.int32)), pa.array(np.where(rank == 1, n[r], 0))]
                names = ["qid", "cluster_id", "c_dist", "probe_rank", "n_dist"]
                if carry:
                    cols, names = [cols[0], part.column("qv").take(pa.array(r)), *cols[1:]], ["qid", "qv", *names[1:]]
                yield pa.RecordBatch.from_arrays(cols, names)

    return queries.select("qid", "qv").mapInArrow(run, f"qid long, {'qv array<double>, ' if carry else ''}cluster_id int, c_dist double, probe_rank int, n_dist long")


def gate(probes: DataFrame, ratio: float | None = None) -> DataFrame:
    """Only promising probes: centroid distance at most `ratio` times the query's nearest one."""
    if ratio is None:
        return probes
    first = F.min("c_dist").over(W.partitionBy("qid"))
    return probes.withColumn("first", first).where(F.round("c_dist", 6) <= F.round(F.col("first") * ratio, 6)).drop("first")


def block_queries(probes: DataFrame, block: int = BLOCK) -> DataFrame:
    """One row for each list and block of at most about `block` queries, so that a list is loaded once a block. Probes without
    qv give ids of queries alone.
    """
    sizes = probes.groupBy("cluster_id").agg(F.ceil(F.count("*") / block).alias("parts"))
    dealt = probes.join(sizes, "cluster_id").withColumn("part", F.pmod(F.xxhash64("qid"), F.col("parts")).cast("int"))
    asked = F.struct("qid", "qv") if "qv" in probes.columns else F.col("qid")
    return dealt.groupBy("cluster_id", "part").agg(F.collect_list(asked).alias("asked"))


def search_lists(loaded: DataFrame, k: int, ef_l: int, skip_self: bool = True, metric: str = "l2", shared=None, merged: bool = False) -> DataFrame:
    """(qid, id, d, cluster_id, n_dist) of each list graph's k nearest to its block of queries by (d rounded to 6, id), and a
    row without id that counts the distances; one list in memory.

    `shared` is a broadcast (sorted ids, vectors) of all queries, for blocks that name ids alone. With `merged` a task sends k
    rows of a query for all its lists together, and no counts.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0
        for batch in batches:
            for r in range(batch.num_rows):
                row = {c: batch.column(c)[r].as_py() for c in batch.schema.names if c != "asked"}
                graph = Graph.from_row(row)
                ids, asked = np.array(graph.ids, np.int64), batch.column("asked")[r].values
                if shared is None:
                    qids, q = asked.field("qid").to_numpy(), matrix(asked.field("qv"))
                else:
                    qids = asked.to_numpy()
                    q = shared.value[1][np.searchsorted(shared.value[0], qids)]
                width = max(ef_l, k + skip_self)
                if width >= len(ids):
                    nodes, n = graph.crossed()
                    step = max(1, (4 << 20) // max(1, len(nodes)))
                    got = [nearest(qids[at : at + step], q[at : at + step], ids[nodes], graph.vecs[nodes], k, metric, skip_self) for at in range(0, len(qids), step)]
                    counts = np.full(len(qids), n)
                else:
                    found = [graph.candidates(v, width) for v in q]
                    got = [nearest(qids[i : i + 1], q[i : i + 1], ids[f[0]], graph.vecs[f[0]], k, metric, skip_self) for i, f in enumerate(found)]
                    counts = np.array([f[1] for f in found])
                near = tuple(np.concatenate(x) for x in zip(*got, strict=True))
                if merged:
                    held.append(near)
                    size += len(near[0])
                    if size > HELD:
                        held = [best_of(*(np.concatenate(x) for x in zip(*held, strict=True)), k)]
                        size = len(held[0][0])
                        if 2 * size > HELD:  # more queries than a task can keep
                            yield from _found(*held[0])
                            held, size = [], 0
                    continue
                yield from _found(*near, row["cluster_id"])
                none = pa.nulls(len(qids), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(qids), none, none.cast(pa.float64()), pa.array(np.full(len(qids), row["cluster_id"], np.int32)), pa.array(counts.astype(np.int64))], _FOUND)
        if held:
            yield from _found(*best_of(*(np.concatenate(x) for x in zip(*held, strict=True)), k))

    cols = ["cluster_id", "n", "dim", "m", "ids", "vecs", "levels", "link_ptr", "link_to", "entry", "max_level", "deleted", "asked"]
    return loaded.select(*cols).mapInArrow(run, "qid long, id long, d double, cluster_id int, n_dist long")


_FOUND = ["qid", "id", "d", "cluster_id", "n_dist"]


def _found(qids: np.ndarray, ids: np.ndarray, d: np.ndarray, cluster_id: int | None = None) -> Iterator[pa.RecordBatch]:
    for at in range(0, len(qids), ROWS):
        n = len(qids[at : at + ROWS])
        lists = pa.nulls(n, pa.int32()) if cluster_id is None else pa.array(np.full(n, cluster_id, np.int32))
        yield pa.RecordBatch.from_arrays([*(pa.array(x[at : at + ROWS]) for x in (qids, ids, d)), lists, pa.array(np.zeros(n, np.int64))], _FOUND)


def share_queries(queries: DataFrame):
    """Broadcast (sorted ids, vectors) of queries that fit BROADCAST_BYTES, else None."""
    n, dim, once = queries.agg(F.count("*"), F.max(F.size("qv")), F.count_distinct("qid")).first()
    if not n or once < n or n * (dim or 1) * 8 > BROADCAST_BYTES:
        return None
    rows = sorted((r[0], r[1]) for r in queries.select("qid", "qv").collect())
    return queries.sparkSession.sparkContext.broadcast((np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], float)))


def load_graphs(index: Index, blocks: DataFrame) -> DataFrame:
    """Graph rows of probed lists only, with their queries: the join prunes bucket directories of a saved index, and few
    probed lists are named to the scan, which then skips row groups.
    """
    asked = blocks.withColumn("bucket", F.pmod(F.col("cluster_id"), F.lit(index.buckets)).cast("int"))
    lists = index.lists
    if index.path:
        wanted = [r[0] for r in blocks.select("cluster_id").distinct().limit(LITERALS + 1).collect()]
        if len(wanted) <= LITERALS:
            lists = lists.where(F.col("cluster_id").isin(wanted) & F.col("bucket").isin(sorted({c % index.buckets for c in wanted})))
    return lists.join(asked, ["bucket", "cluster_id"])


def only(loaded: DataFrame, allowed: DataFrame) -> DataFrame:
    """Graph rows in which all vectors but the allowed ids are flagged: they are crossed, never returned."""
    ids = loaded.select("cluster_id", "ids").dropDuplicates(["cluster_id"]).select("cluster_id", F.posexplode("ids").alias("pos", "id"))
    open_ = ids.join(allowed.select("id").distinct(), "id", "left_semi").groupBy("cluster_id").agg(F.collect_set("pos").alias("open"))
    flags = F.transform("deleted", lambda d, i: d | ~F.array_contains("open", i))
    return loaded.join(open_, "cluster_id").withColumn("deleted", flags).drop("open")


def search(index: Index, queries: DataFrame, k: int = 10, n_p: int = N_P, ef_c: int = EF_C, ef_l: int = EF_L, ratio: float | None = None, skip_self: bool = True, where: DataFrame | None = None, bound: bool = False, metric: str = "l2") -> DataFrame:
    """Ranked result (qid, id, d, rank).

    `where` (id) keeps matching vectors only: lists are searched for those alone, and queries that got fewer than k are
    asked again with twice as many lists until all are probed. With `bound` the lists after the first are skipped where
    centroid distance less radius exceeds the k-th distance found in the first (`gate_by_radius`). `metric` ranks what the
    lists' graphs find; the graphs are walked by l2.
    """
    if where is None:
        return merge_topk(search_partials(index, queries, k, n_p, ef_c, ef_l, ratio, skip_self, bound, merged=True, metric=metric).where("id is not null").select("qid", "id", "d"), k)
    allowed = checkpointed(where.select("id").distinct())
    found, left, width = None, queries, min(n_p, index.n_c)
    while True:
        part = search_partials(index, left, k, width, max(ef_c, width), ef_l, ratio, skip_self, False, allowed).where("id is not null")
        got = checkpointed(merge_topk(part.select("qid", "id", "d"), k))
        full = got.groupBy("qid").agg(F.count("*").alias("n")).where(F.col("n") >= k).select("qid")
        if width >= index.n_c:
            return got if found is None else found.unionByName(got)
        done = got.join(full, "qid", "left_semi")
        found = done if found is None else found.unionByName(done)
        left = checkpointed(left.select("qid", "qv").join(full, "qid", "left_anti"))
        if left.isEmpty():
            return found
        width = min(2 * width, index.n_c)


def gate_by_radius(index: Index, probes: DataFrame, first: DataFrame, k: int) -> DataFrame:
    """Probes whose list can still hold one of the k nearest, given the results (qid, id, d) of each query's first list."""
    order = W.partitionBy("qid").orderBy("d", "id")
    kth = first.withColumn("r", F.row_number().over(order)).where(F.col("r") == k).select("qid", F.col("d").alias("kth"))
    radii = index.spark.createDataFrame([(int(c), float(r)) for c, r in index.radii.items()], "cluster_id int, radius double")
    near = probes.join(F.broadcast(radii), "cluster_id", "left").join(kth, "qid", "left")
    return near.where(F.col("kth").isNull() | (F.col("c_dist") - F.coalesce("radius", F.lit(0.0)) <= F.col("kth") + 1e-5)).select(*probes.columns)


def search_partials(index: Index, queries: DataFrame, k: int, n_p: int, ef_c: int, ef_l: int, ratio: float | None = None, skip_self: bool = True, bound: bool = False, allowed: DataFrame | None = None, merged: bool = False, metric: str = "l2") -> DataFrame:
    shared = share_queries(queries)
    probes = checkpointed(gate(probe(index, queries, min(n_p, index.n_c), ef_c, shared is None), ratio))

    def inside(some: DataFrame) -> DataFrame:
        load = load_graphs(index, block_queries(some))
        return search_lists(load if allowed is None else only(load, allowed), k, ef_l, skip_self, metric, shared, merged)

    if not bound:
        return inside(probes)
    first = checkpointed(inside(probes.where("probe_rank = 1")))
    rest = gate_by_radius(index, probes.where("probe_rank > 1"), first.where("id is not null"), k)
    return first.unionByName(inside(checkpointed(rest)))


def calibrate(index: Index, emb: DataFrame, target: float = 0.9, k: int = 10, sample: int = 48, most: int = 256, ef_l: int | None = None, seed: int = 42, queries: DataFrame | None = None, metric: str = "l2") -> dict[str, int]:
    """Widths (n_p, ef_c, ef_l) that reach a recall on a hashed sample of the vectors, or of `queries` (qid, qv), measured
    against exact neighbours.

    One search of the most lists gives the recall of all fewer ones. If none reaches the target, the lists are searched
    twice as wide, up to their full width, and at last the widest setting is returned.
    """
    asked = emb.select(F.col("id").alias("qid"), F.col("v").alias("qv")) if queries is None else queries.select("qid", "qv")
    picked = checkpointed(asked.orderBy(F.xxhash64(F.lit(seed), "qid"), "qid").limit(sample))
    widest, ef_l = min(index.n_c, most), ef_l or max(EF_L, 6 * k)
    widths = sorted({min(widest, 1 << b) for b in range(widest.bit_length() + 1)})
    probes = checkpointed(probe(index, picked, widest, max(EF_C, 2 * widest)))
    truth = checkpointed(knn_exact(emb, picked, k, metric, queries is None))
    n, largest = truth.count(), index.lists.agg(F.max("n")).first()[0] or 0
    while True:
        parts = search_lists(load_graphs(index, block_queries(probes)), k, ef_l, queries is None, metric).where("id is not null")
        ranked = parts.join(probes.select("qid", "cluster_id", "probe_rank"), ["qid", "cluster_id"])
        each = ranked.withColumn("n_p", F.explode(F.filter(F.array(*(F.lit(w) for w in widths)), lambda w: w >= F.col("probe_rank"))))
        best = each.withColumn("r", F.row_number().over(W.partitionBy("qid", "n_p").orderBy(F.round("d", 6), "id"))).where(F.col("r") <= k)
        hits = {r["n_p"]: r["n"] for r in best.join(truth.select("qid", "id"), ["qid", "id"]).groupBy("n_p").agg(F.count("*").alias("n")).collect()}
        n_p = next((w for w in widths if hits.get(w, 0) >= target * n), None)
        if n_p or ef_l >= largest:
            n_p = n_p or widest
            return {"n_p": n_p, "ef_c": max(EF_C, 2 * n_p), "ef_l": ef_l}
        ef_l *= 2


def search_counters(index: Index, queries: DataFrame, k: int = 10, n_p: int = N_P, ef_c: int = EF_C, ef_l: int = EF_L) -> DataFrame:
    """(qid, lists, n_dist, bytes_read): measured work of each query. Counters travel with rows, so retries count once."""
    probes = probe(index, queries, min(n_p, index.n_c), ef_c)
    inner = search_lists(load_graphs(index, block_queries(probes)), k, ef_l).where("id is null").groupBy("qid").agg(F.count("*").alias("lists"), F.sum("n_dist").alias("in_lists"))
    sizes = index.lists.select("cluster_id", (F.length("vecs") + 4 * F.size("link_to") + 8 * F.size("ids")).alias("bytes"))
    outer = probes.join(sizes, "cluster_id").groupBy("qid").agg(F.sum("n_dist").alias("in_centre"), F.sum("bytes").alias("bytes_read"))
    return inner.join(outer, "qid").select("qid", "lists", (F.col("in_lists") + F.col("in_centre")).alias("n_dist"), "bytes_read")


def search_one(index: Index, qv, k: int = 10, n_p: int = N_P, ef_c: int = EF_C, ef_l: int = EF_L, sequential: bool = True) -> tuple[list[tuple[float, int]], dict]:
    """Interactive search of one vector: lists are loaded one after the other, nearest first, and released.

    A list whose centroid distance minus radius exceeds the k-th distance so far cannot help and is not loaded.
    """
    q = np.asarray(qv, float)
    graph = Graph.from_row(index.centre)
    graph.vecs = index.centre.get("exact", graph.vecs)
    found, n_dist = graph.search(q, min(n_p, index.n_c), max(n_p, ef_c))
    best: list[tuple[float, int]] = []
    loaded = 0
    wanted = [(d, c) for d, c in found]
    together = None if sequential else {r["cluster_id"]: r.asDict(True) for r in index.lists.where(F.col("cluster_id").isin([c for _, c in wanted])).collect()}
    for d, c in wanted:
        if len(best) >= k and d - index.radii.get(c, 0.0) > best[k - 1][0] + 1e-6:
            continue
        row = together.get(c) if together is not None else next((r.asDict(True) for r in index.lists.where((F.col("bucket") == c % index.buckets) & (F.col("cluster_id") == c)).collect()), None)
        if row is None:
            continue
        part, n = Graph.from_row(row).search(q, k, max(ef_l, k))
        n_dist, loaded = n_dist + n, loaded + 1
        best = sorted({i: x for x, i in [*best, *part]}.items(), key=lambda p: (round(p[1], 6), p[0]))
        best = [(x, i) for i, x in best][:k]
    return best, {"lists": loaded, "n_dist": n_dist, "peak_lists": 1 if sequential else loaded}


# -- storage ---------------------------------------------------------------------------------------------------------
HOMES = "id long, cluster_id int, bucket int"


def _write(rows: DataFrame, folder: str, keys: tuple[str, ...]) -> None:
    """Rows by bucket directories; small row groups, so that a probe reads little besides its lists."""
    rows.repartition("bucket").sortWithinPartitions("bucket", *keys).write.mode("overwrite").partitionBy("bucket").option("parquet.block.size", 1 << 20).parquet(folder)


def _read(spark: SparkSession, path: str, table: str, at: dict[int, int], kind: str) -> DataFrame:
    """A table whose buckets may lie in files of different versions."""
    names = [c.split()[0] for c in kind.split(", ")]
    if not at:
        return spark.createDataFrame([], kind)
    if len(set(at.values())) == 1:
        return spark.read.schema(kind).parquet(f"{path}/{table}/v={next(iter(at.values()))}").select(*names)
    places = [f"{path}/{table}/v={v}/bucket={b}" for b, v in sorted(at.items())]
    return spark.read.schema(kind).option("basePath", f"{path}/{table}").parquet(*places).select(*names)


def home_bucket(index: Index, of: str = "id"):
    return F.pmod(F.xxhash64(of), F.lit(index.buckets)).cast("int")


def _commit(index: Index, path: str, version: int, at: dict[str, dict[int, int]]) -> Index:
    """The manifest says which version's files hold each bucket; it is written last, which makes the version visible."""
    c = index.centre
    exact = [float(x) for x in np.asarray(c["exact"] if "exact" in c else unpacked(c["vecs"], c["n"], c["dim"])).ravel()]
    places = [(t, int(b), int(v)) for t, of in at.items() for b, v in of.items()]
    row = (version, index.buckets, c["n"], c["dim"], c["m"], [int(i) for i in c["ids"]], exact, c["levels"], c["link_ptr"], c["link_to"], c["entry"], c["max_level"], sorted((int(k), float(r)) for k, r in index.radii.items()), places)
    kind = "version long, buckets int, n int, dim int, m int, ids array<bigint>, vecs array<double>, levels array<int>, link_ptr array<int>, link_to array<int>, entry int, max_level int, radii array<struct<c:int,r:double>>, at array<struct<t:string,b:int,v:long>>"
    index.spark.createDataFrame([row], kind).coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest/v={version}")
    return load_index(index.spark, path, version)


def _buckets_of(spark: SparkSession, folder: str, kind: str) -> list[int]:
    """Buckets that a written version has rows in; their number is that of the index's directories."""
    return [r[0] for r in spark.read.schema(kind).parquet(folder).select("bucket").distinct().collect()]


def save_index(index: Index, path: str, version: int | None = None) -> Index:
    """All lists by bucket and sorted by cluster, the list of each id, and the manifest."""
    version = index.version if version is None else version
    spark = index.spark
    _write(index.lists.withColumn("version", F.lit(version).cast("long")), f"{path}/lists/v={version}", ("cluster_id",))
    lists = spark.read.schema(schema.GRAPH).parquet(f"{path}/lists/v={version}")
    _write(lists.select(F.explode("ids").alias("id"), "cluster_id").withColumn("bucket", home_bucket(index)), f"{path}/homes/v={version}", ("id",))
    at = {t: dict.fromkeys(_buckets_of(spark, f"{path}/{t}/v={version}", kind), version) for t, kind in (("lists", schema.GRAPH), ("homes", HOMES))}
    return _commit(index, path, version, at)


def load_index(spark: SparkSession, path: str, version: int | None = None) -> Index:
    """A version of a saved index (the newest by default); readers keep the version they opened."""
    if version is None:
        version = spark.read.option("basePath", f"{path}/manifest").parquet(f"{path}/manifest").agg(F.max("version")).first()[0]
    r = spark.read.parquet(f"{path}/manifest/v={version}").first()
    exact = np.array(r["vecs"]).reshape(r["n"], r["dim"])
    centre = {c: r[c] for c in ("n", "dim", "m", "ids", "levels", "link_ptr", "link_to", "entry", "max_level")} | {"vecs": packed(exact), "deleted": [False] * r["n"], "exact": exact}
    at: dict[str, dict[int, int]] = {"lists": {}, "homes": {}}
    for x in r["at"]:
        at[x["t"]][x["b"]] = x["v"]
    lists, homes = _read(spark, path, "lists", at["lists"], schema.GRAPH), _read(spark, path, "homes", at["homes"], HOMES)
    return Index(spark, centre, {x["c"]: x["r"] for x in r["radii"]}, lists, r["buckets"], r["version"], path, homes, at)


def update_saved(index: Index, updates: DataFrame, version: int | None = None, **options) -> Index:
    """A new version of a saved index: only buckets that hold a touched list, or a touched id's home, are written."""
    version, spark, path = index.version + 1 if version is None else version, index.spark, index.path
    routed = checkpointed(route(index, updates))
    touched = checkpointed(routed.select("cluster_id").distinct())
    places = [r[0] for r in touched.select(F.pmod("cluster_id", F.lit(index.buckets)).cast("int")).distinct().collect()]
    at = {t: dict(of) for t, of in index.at.items()}
    if places:
        near = index.lists.where(F.col("bucket").isin(places))
        changed = _changed(near, routed, index.buckets, version, **options)
        kept = near.join(touched, "cluster_id", "left_anti")
        _write(kept.unionByName(changed), f"{path}/lists/v={version}", ("cluster_id",))
        at["lists"] |= dict.fromkeys(_buckets_of(spark, f"{path}/lists/v={version}", schema.GRAPH), version)
        new = routed.where("op = 'insert'").select("id", "cluster_id").withColumn("bucket", home_bucket(index))
        ids = checkpointed(routed.select("id").distinct().withColumn("bucket", home_bucket(index)))
        houses = [r[0] for r in ids.select("bucket").distinct().collect()]
        old = index.homes.where(F.col("bucket").isin(houses)).join(ids.select("id"), "id", "left_anti").select("id", "cluster_id", "bucket")
        _write(old.unionByName(new), f"{path}/homes/v={version}", ("id",))
        written = _buckets_of(spark, f"{path}/homes/v={version}", HOMES)
        at["homes"] = {b: v for b, v in at["homes"].items() if b not in houses} | dict.fromkeys(written, version)
        radii = {r["cluster_id"]: r["radius"] for r in spark.read.schema(schema.GRAPH).parquet(f"{path}/lists/v={version}").join(F.broadcast(touched), "cluster_id", "left_semi").select("cluster_id", "radius").collect()}
        index = replace(index, radii=index.radii | radii)
    return _commit(index, path, version, at)


# -- updates ---------------------------------------------------------------------------------------------------------
def normalise_updates(updates: DataFrame) -> DataFrame:
    """Last operation of each id by seq, an insert before a delete on ties, then the larger vector: (id, op, v, seq)."""
    return updates.groupBy("id").agg(F.max_by(F.struct("op", "v", "seq"), F.struct("seq", "op", "v")).alias("u")).select("id", "u.op", "u.v", "u.seq")


def route(index: Index, updates: DataFrame) -> DataFrame:
    """(cluster_id, id, op, v, seq): inserts go to the nearest centroid, every touched id also leaves its old list."""
    last = checkpointed(normalise_updates(updates))  # a row an id of the log, met three times below
    table = partition.as_table(index.spark, np.array(index.centre["ids"]), np.asarray(index.centre["exact"]))
    new = partition.assign(last.where("op = 'insert'").select("id", "v"), table).select("cluster_id", "id", F.lit("insert").alias("op"), "v", "dist")
    asked = last.select("id")
    if index.homes is None:
        homes = index.lists.select("cluster_id", F.explode("ids").alias("id")).join(asked, "id")
    else:  # only the touched buckets of ids are read
        homes = index.homes.join(asked.withColumn("bucket", home_bucket(index)), ["bucket", "id"])
    old = homes.select("cluster_id", "id", F.lit("delete").alias("op"), F.lit(None).cast("array<double>").alias("v"), F.lit(None).cast("double").alias("dist"))
    return old.unionByName(new)


def _changed(lists: DataFrame, routed: DataFrame, buckets: int, version: int, m: int = 16, ef_build: int = 64, alpha: float = 1.2) -> DataFrame:
    """The touched lists' new graphs: deletes first, then inserts, each in order of id."""
    ops = routed.select(F.col("cluster_id").alias("target"), F.col("id").alias("uid"), "op", F.col("v").alias("uv"), F.col("dist").alias("udist"))

    def change(old: pa.Table, ops: pa.Table) -> pa.Table:
        if old.num_rows:
            row = {c: old[c][0].as_py() for c in old.schema.names}
            graph, cid, radius = Graph.from_row(row, ef_build=ef_build, alpha=alpha), row["cluster_id"], row["radius"]
        else:
            cid, radius = ops["target"][0].as_py(), 0.0
            dim = next((len(v) for v in ops["uv"].to_pylist() if v is not None), 0)
            graph = Graph(dim=dim, m=m, ef_build=ef_build, alpha=alpha)
        rows = ops.to_pylist()
        graph.delete_many([r["uid"] for r in rows if r["op"] == "delete"])
        for r in sorted((r for r in rows if r["op"] == "insert"), key=lambda r: r["uid"]):
            graph.insert(r["uid"], r["uv"])
            radius = max(radius, r["udist"])
        graph.repair()
        return _table(graph, cid, buckets, version, radius)

    hit = F.col("cluster_id") == F.col("target")
    mine = lists.join(ops.select("target").distinct(), hit, "left_semi")
    return mine.groupBy("cluster_id").cogroup(ops.groupBy("target")).applyInArrow(change, schema.GRAPH)


def apply_updates(index: Index, updates: DataFrame, m: int = 16, ef_build: int = 64, alpha: float = 1.2) -> Index:
    """A new version in which only touched lists are changed, not yet written; see update_saved for a saved index."""
    routed = checkpointed(route(index, updates))
    version = index.version + 1
    changed = _changed(index.lists, routed, index.buckets, version, m, ef_build, alpha)
    kept = index.lists.join(routed.select("cluster_id").distinct(), "cluster_id", "left_anti").select(*index.lists.columns)
    return replace(index, lists=kept.unionByName(changed), version=version, path=None, homes=None, at=None)


def refresh(index: Index) -> Index:
    """Radii read from the lists again (after updates)."""
    return replace(index, radii={r["cluster_id"]: r["radius"] for r in index.lists.select("cluster_id", "radius").collect()})


def flag_deleted(index: Index, ids: DataFrame) -> Index:
    """Flag-only delete: flagged vectors are crossed but never returned until purge()."""
    gone = ids.select(F.col("id")).distinct()
    homes = index.lists.select("cluster_id", F.posexplode("ids").alias("pos", "id")).join(gone, "id").groupBy("cluster_id").agg(F.collect_set("pos").alias("flags"))
    flagged = F.transform("deleted", lambda d, i: d | F.array_contains(F.coalesce("flags", F.array().cast("array<int>")), i))
    return replace(index, lists=index.lists.join(homes, "cluster_id", "left").withColumn("deleted", flagged).drop("flags"), path=None)


def purge(index: Index) -> Index:
    """Remove flagged vectors from the touched lists."""
    flagged = index.lists.where(F.exists("deleted", lambda d: d))
    ops = flagged.select(F.explode(F.filter(F.transform("ids", lambda i, k: F.when(F.get("deleted", k), i)), lambda i: i.isNotNull())).alias("id"))
    return apply_updates(index, ops.select("id", F.lit("delete").alias("op"), F.lit(None).cast("array<double>").alias("v"), F.lit(0).cast("long").alias("seq")))


def members(index: Index) -> DataFrame:
    """(cluster_id, id) of all vectors that are not flagged."""
    return index.lists.select("cluster_id", F.explode(F.arrays_zip("ids", "deleted")).alias("x")).where(~F.col("x.deleted")).select("cluster_id", F.col("x.ids").alias("id"))
