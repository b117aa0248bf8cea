"""Baselines of the index: inverted lists, product quantisation, one graph, disk-resident forms, and their updates."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.functions.vector import l2sq
from vecrag.operators import index as two_tier
from vecrag.operators import partition
from vecrag.operators.knn import exact_distance, matrix, merge_topk, nearest
from vecrag.session import checkpointed

#: Rows of a part of a list and queries of a block that meet in one task.
PART, BLOCK = 50_000, 1024
#: Bytes of the vectors of a single graph.
GRAPH_BYTES = 1 << 30


# -- inverted lists ------------------------------------------------------------------------------------------------
def probe_lists(queries: DataFrame, centroids: DataFrame, n_p: int) -> DataFrame:
    """(qid, qv, cluster_id, c_dist): each query's n_p nearest centroids by a scan of all of them (broadcast, checked)."""
    if n_p < 1:
        raise ValueError("n_p must be at least 1")
    shared = queries.sparkSession.sparkContext.broadcast(partition.local(centroids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, c = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            q = matrix(batch.column("qv"))
            r, k = np.divmod(np.arange(len(q) * len(c)), len(c))
            d = np.round(exact_distance(q[r], c[k], "l2"), 6)
            order = np.lexsort((ids[k], d, r)).reshape(len(q), len(c))[:, :n_p].ravel()
            yield pa.RecordBatch.from_arrays([batch.column("qid").take(pa.array(r[order])), batch.column("qv").take(pa.array(r[order])), pa.array(ids[k[order]].astype(np.int32)), pa.array(d[order])], ["qid", "qv", "cluster_id", "c_dist"])

    return queries.select("qid", "qv").mapInArrow(run, "qid long, qv array<double>, cluster_id int, c_dist double")


def _top_of_lists(rows: DataFrame, probes: DataFrame, k: int, near: Callable[[pa.Table, pa.Table, int], tuple[np.ndarray, np.ndarray, np.ndarray]], sizes: DataFrame | None = None) -> DataFrame:
    """Ranked result of probed lists: the parts of a list (cluster_id, id, ..) meet the blocks of its queries (qid, cluster_id,
    ..) in tasks of bounded size, and each sends its k best of every query. Lists that no query probes are not moved.
    """
    asked = probes.groupBy("cluster_id").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    sizes = rows.groupBy("cluster_id").agg(F.count("*").alias("n")) if sizes is None else sizes
    shape = asked.join(sizes, "cluster_id").select("cluster_id", "blocks", F.ceil(F.col("n") / PART).cast("int").alias("parts"))
    left = rows.join(F.broadcast(shape), "cluster_id").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    right = probes.join(F.broadcast(shape), "cluster_id").withColumn("block", F.pmod(F.xxhash64("qid"), F.col("blocks")).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        got = near(a, b, k) if a.num_rows and b.num_rows else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"qid": got[0], "id": got[1], "d": got[2]})

    keys = ["cluster_id", "part", "block"]
    partials = left.drop("parts", "blocks").groupBy(*keys).cogroup(right.drop("parts", "blocks").groupBy(*keys)).applyInArrow(meet, "qid long, id long, d double")
    return merge_topk(partials, k)


def _by_vectors(a: pa.Table, b: pa.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return _by_metric("l2", a, b, k)


def _by_metric(metric: str, a: pa.Table, b: pa.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return nearest(b["qid"].to_numpy(), matrix(b["qv"]), a["id"].to_numpy(), matrix(a["v"]), k, metric, True)


def _by_codes(a: pa.Table, b: pa.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Asymmetric distances: the square roots of summed table entries."""
    ids, qids, codes = a["id"].to_numpy(), b["qid"].to_numpy(), matrix(a["codes"]).astype(int)
    sub = np.arange(codes.shape[1])
    out: list[tuple[np.ndarray, ...]] = []
    for q, lut in zip(qids, b["luts"].to_pylist(), strict=True):
        d = np.round(np.sqrt(np.array(lut)[sub, codes].sum(1)), 6)
        d[ids == q] = np.inf
        best = np.lexsort((ids, d))[:k]
        best = best[np.isfinite(d[best])]
        out.append((np.full(len(best), q), ids[best], d[best]))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def search_flat(lists: DataFrame, probes: DataFrame, k: int) -> DataFrame:
    """Scan of the probed lists (cluster_id, id, v): k rows of a query and list are shuffled, not its distances."""
    return _top_of_lists(lists.select("cluster_id", "id", "v"), probes.select("qid", "qv", "cluster_id"), k, _by_vectors)


def ivf_search(assigned: DataFrame, centroids: DataFrame, queries: DataFrame, k: int, n_p: int) -> DataFrame:
    """Inverted lists in memory: n_p nearest lists, scanned."""
    return search_flat(assigned, probe_lists(queries, centroids, n_p), k)


def save_lists(assigned: DataFrame, path: str, buckets: int = two_tier.BUCKETS) -> None:
    """Lists on disk: by bucket directories, sorted by cluster, and their sizes."""
    rows = assigned.withColumn("bucket", F.pmod("cluster_id", F.lit(buckets)).cast("int"))
    rows.repartition(buckets, "bucket").sortWithinPartitions("bucket", "cluster_id").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/lists")
    assigned.groupBy("cluster_id").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{path}/sizes")


def probed(spark, path: str, schema: str, probes: DataFrame, buckets: int) -> DataFrame:
    """Rows of the probed lists only: bucket directories are pruned at run time, row groups by cluster."""
    asked = probes.select("cluster_id", F.pmod("cluster_id", F.lit(buckets)).cast("int").alias("bucket")).distinct()
    return spark.read.schema(schema).parquet(f"{path}/lists").join(F.broadcast(asked), ["bucket", "cluster_id"], "left_semi")


def ivf_disk_search(spark, path: str, centroids: DataFrame, queries: DataFrame, k: int, n_p: int, buckets: int = two_tier.BUCKETS, metric: str = "l2") -> DataFrame:
    """Inverted lists on disk: only the probed buckets are read (dynamic partition pruning). Lists are probed by l2, their
    vectors ranked by `metric`.
    """
    probes = checkpointed(probe_lists(queries, centroids, n_p))
    lists = probed(spark, path, "id long, v array<double>, cluster_id int, bucket int", probes, buckets)
    return _top_of_lists(lists.select("cluster_id", "id", "v"), probes.select("qid", "qv", "cluster_id"), k, partial(_by_metric, metric), spark.read.parquet(f"{path}/sizes"))


def ivf_graph_search(index: two_tier.Index, assigned: DataFrame, queries: DataFrame, k: int, n_p: int, ef_c: int = two_tier.EF_C) -> DataFrame:
    """Centroid graph with flat lists."""
    return search_flat(assigned, two_tier.probe(index, queries, n_p, ef_c), k)


def graph_index(emb: DataFrame, m: int = 16, ef_build: int = 64, mode: str = "batch") -> two_tier.Index:
    """One graph over all vectors (a single list): a baseline for tables that fit one task, which is checked. In batch mode
    blocks of nodes choose their links in tasks of their own; `incremental` inserts one vector after the other in one task.
    """
    n, dim = emb.agg(F.count("*"), F.max(F.size("v"))).first()
    if n * (dim or 0) * 8 > GRAPH_BYTES:
        raise ValueError(f"{n} vectors are too many for one graph in one task; use a two-tier index")
    first = emb.orderBy("id").limit(1).select(F.lit(0).alias("cluster_id"), F.col("v").alias("cv"))
    return two_tier.build_index(emb, centroids=first, m=m, ef_build=ef_build, mode=mode, size=n)


def graph_search(index: two_tier.Index, queries: DataFrame, k: int, ef: int) -> DataFrame:
    return two_tier.search(index, queries, k, n_p=1, ef_l=ef)


# -- product quantisation --------------------------------------------------------------------------------------------
def pq_fit(emb: DataFrame, m_pq: int, nbits: int, rounds: int = 0) -> DataFrame:
    """Codebook (sub, code, cw): sub-vectors of the ids at every (N div 2^nbits)-th place, then Lloyd rounds."""
    n, dim = emb.count(), emb.select(F.max(F.size("v"))).first()[0]
    if not dim or dim % m_pq:
        raise ValueError("the dimension must be a multiple of m_pq")
    codes, width = 1 << nbits, dim // m_pq
    if codes > n:
        raise ValueError("more codes than vectors")
    step = n // codes
    at = F.floor(F.col("id") / step)
    seeds = emb.where((F.col("id") % step == 0) & (at < codes)).select(at.cast("int").alias("code"), "v")
    book = seeds.select(F.explode(F.sequence(F.lit(0), F.lit(m_pq - 1))).alias("sub"), "code", "v").select("sub", "code", F.slice("v", F.col("sub") * width + 1, width).alias("cw"))
    for _ in range(rounds):
        coded = pq_encode(emb, book, m_pq).select("v", F.posexplode("codes").alias("sub", "code"))
        parts = coded.select("sub", "code", F.posexplode(F.slice("v", F.col("sub") * width + 1, width)).alias("j", "x")).groupBy("sub", "code", "j").agg(F.avg("x").alias("x"))
        means = parts.groupBy("sub", "code").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("s")).select("sub", "code", F.col("s.x").alias("nw"))
        book = book.join(means, ["sub", "code"], "left").select("sub", "code", F.coalesce("nw", "cw").alias("cw"))
        book = emb.sparkSession.createDataFrame(book.collect(), "sub int, code int, cw array<double>")  # m_pq * 2^nbits rows
    return book


def _book(codebook: DataFrame, m_pq: int) -> list[np.ndarray]:
    rows = codebook.orderBy("sub", "code").collect()
    return [np.array([r["cw"] for r in rows if r["sub"] == s], float) for s in range(m_pq)]


def pq_encode(emb: DataFrame, codebook: DataFrame, m_pq: int) -> DataFrame:
    """(.., codes): nearest codeword of each sub-vector by (squared distance rounded to 9 places, code)."""
    shared = emb.sparkSession.sparkContext.broadcast(_book(codebook, m_pq))
    names = emb.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column("v"))
            width = x.shape[1] // m_pq
            codes = np.empty((len(x), m_pq), np.int32)
            for s, words in enumerate(book):
                part = x[:, s * width : (s + 1) * width]
                d = (part**2).sum(1)[:, None] + (words**2).sum(1)[None, :] - 2 * part @ words.T
                r, c = np.nonzero(d <= d.min(1)[:, None] + 1e-8)  # those that may be nearest, measured without cancellation
                exact = np.round(((part[r] - words[c]) ** 2).sum(1), 9)
                order = np.lexsort((c, exact, r))
                codes[:, s] = c[order][np.append(True, r[order][1:] != r[order][:-1])]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(list(codes), pa.list_(pa.int32()))], [*names, "codes"])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in emb.schema.fields)
    return emb.mapInArrow(run, f"{kinds}, codes array<int>")


def pq_tables(queries: DataFrame, codebook: DataFrame, m_pq: int) -> DataFrame:
    """(qid, qv, luts): squared distances of a query's sub-vectors to all codewords, sub by sub."""
    width = F.floor(F.size("qv") / m_pq).cast("int")
    books = codebook.groupBy("sub").agg(F.array_sort(F.collect_list(F.struct("code", "cw"))).alias("b"))
    each = queries.join(F.broadcast(books)).select("qid", "qv", "sub", F.transform("b.cw", lambda cw: l2sq(F.slice("qv", F.col("sub") * width + 1, width), cw)).alias("lut"))
    return each.groupBy("qid").agg(F.first("qv").alias("qv"), F.array_sort(F.collect_list(F.struct("sub", "lut"))).alias("t")).select("qid", "qv", F.col("t.lut").alias("luts"))


def adc(codes, luts):
    """Asymmetric distance: the square root of the summed table entries."""
    return F.sqrt(F.aggregate(F.zip_with(luts, codes, lambda lut, c: F.get(lut, c)), F.lit(0.0), lambda s, x: s + x))


def ivfpq_search(coded: DataFrame, centroids: DataFrame, codebook: DataFrame, queries: DataFrame, k: int, n_p: int, m_pq: int, rerank: int = 0) -> DataFrame:
    """Inverted lists of codes (cluster_id, id, codes, v): table distances; the best `rerank` are ranked exactly again."""
    probes = probe_lists(queries, centroids, n_p).join(pq_tables(queries, codebook, m_pq).select("qid", "luts"), "qid")
    found = _top_of_lists(coded.select("cluster_id", "id", "codes"), probes.select("qid", "cluster_id", "luts"), max(k, rerank), _by_codes)
    return _rerank(found, coded, queries, k) if rerank else found


def _rerank(found: DataFrame, vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    exact = found.select("qid", "id").join(vectors.select("id", "v"), "id").join(queries.select("qid", "qv"), "qid")
    return merge_topk(exact.select("qid", "id", F.sqrt(l2sq("qv", "v")).alias("d")), k)


def graph_pq_search(index: two_tier.Index, emb: DataFrame, codebook: DataFrame, queries: DataFrame, k: int, ef: int, m_pq: int, rerank: int = 0) -> DataFrame:
    """One graph searched for ef candidates, ranked by coded distance (then exactly, with `rerank`)."""
    found = two_tier.search(index, queries, ef, n_p=1, ef_l=ef).select("qid", "id")
    coded = pq_encode(emb, codebook, m_pq).select("id", "codes", "v")
    near = found.join(coded, "id").join(pq_tables(queries, codebook, m_pq).select("qid", "luts"), "qid").select("qid", "id", adc("codes", "luts").alias("d"))
    return _rerank(merge_topk(near, max(k, rerank)), coded, queries, k) if rerank else merge_topk(near, k)


def save_codes(coded: DataFrame, path: str, buckets: int = two_tier.BUCKETS) -> None:
    save_lists(coded.select("id", "codes", "cluster_id"), path, buckets)


def ivfpq_disk_search(spark, path: str, centroids: DataFrame, codebook: DataFrame, queries: DataFrame, k: int, n_p: int, m_pq: int, buckets: int = two_tier.BUCKETS) -> DataFrame:
    """Codes on disk: only the probed buckets are read."""
    probes = checkpointed(probe_lists(queries, centroids, n_p)).join(pq_tables(queries, codebook, m_pq).select("qid", "luts"), "qid")
    lists = probed(spark, path, "id long, codes array<int>, cluster_id int, bucket int", probes, buckets)
    return _top_of_lists(lists.select("cluster_id", "id", "codes"), probes.select("qid", "cluster_id", "luts"), k, _by_codes, spark.read.parquet(f"{path}/sizes"))


# -- updates of lists --------------------------------------------------------------------------------------------------
def ivf_insert(assigned: DataFrame, centroids: DataFrame, new: DataFrame) -> DataFrame:
    """Append to the nearest list; an id that is there already is replaced."""
    return ivf_delete(assigned, new.select("id")).unionByName(partition.assign(new, centroids))


def ivf_delete(assigned: DataFrame, ids: DataFrame) -> DataFrame:
    return assigned.join(ids.select("id").distinct(), "id", "left_anti")


def recall_at_k(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(queries, recall): share of the exact k nearest that a result has, mean over the queries of the truth."""
    want = truth.where(F.col("rank") <= k).select("qid", "id")
    got = result.where(F.col("rank") <= k).select("qid", "id").withColumn("hit", F.lit(1))
    per = want.join(got, ["qid", "id"], "left").groupBy("qid").agg((F.count("hit") / F.count("*")).alias("r"))
    return per.agg(F.count("*").alias("queries"), F.round(F.avg("r"), 6).alias("recall"))


def search_salted(assigned: DataFrame, probes: DataFrame, k: int, part: int = 8) -> DataFrame:
    """search_flat for skewed lists, in parts of about `part` rows each."""
    sizes = assigned.groupBy("cluster_id").agg((F.count("*") * F.ceil(F.lit(PART) / part)).alias("n"))
    return _top_of_lists(assigned.select("cluster_id", "id", "v"), probes.select("qid", "qv", "cluster_id"), k, _by_vectors, sizes)
