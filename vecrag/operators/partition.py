"""Partitions of the vectors: k-means, assignment, list statistics, balancing."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecrag.operators.knn import BROADCAST_BYTES, exact_distance, matrix, nearest

#: A list holds about TARGET vectors; one over CAP is split.
TARGET, CAP = 250, 1000


def choose_n_c(n: int, target: int = TARGET) -> int:
    return max(1, round(n / target))


def seeded_centroids(emb: DataFrame, n_c: int) -> DataFrame:
    """Vectors at every (N div n_c)-th id of a table with ids 0..N-1: (cluster_id, cv)."""
    n = emb.count()
    if not 1 <= n_c <= max(1, n):
        raise ValueError("1 <= n_c <= N is required")
    step = max(1, n // n_c)
    at = F.floor(F.col("id") / step)
    return emb.where((F.col("id") % step == 0) & (at < n_c)).select(at.cast("int").alias("cluster_id"), F.col("v").alias("cv"))


def local(centroids: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Centroid ids and matrix on the driver; their number is chosen (n_c), and their size is checked before they come."""
    n, dim = centroids.agg(F.count("*"), F.max(F.size("cv"))).first()
    if n * (dim or 0) * 8 > BROADCAST_BYTES * 8:
        raise ValueError("too many centroids for one tier; use scale.build_three_tier")
    rows = centroids.orderBy("cluster_id").collect()
    ids, c = np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], float)
    return ids, c.reshape(len(ids), -1)


def as_table(spark: SparkSession, ids: np.ndarray, c: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(int(i), [float(x) for x in v]) for i, v in zip(ids, c, strict=True)], "cluster_id int, cv array<double>")


def nearest_centroid(x: np.ndarray, ids: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cluster_id, distance) by (distance rounded to 6 places, cluster_id), in blocks of bounded size."""
    out_i, out_d = np.empty(len(x), np.int64), np.empty(len(x))
    step = max(1, (4 << 20) // max(1, len(c)))
    for at in range(0, len(x), step):
        part = x[at : at + step]
        d = np.sqrt(np.maximum(0, (part**2).sum(1)[:, None] + (c**2).sum(1)[None, :] - 2 * part @ c.T))
        r, k = np.nonzero(d <= d.min(1)[:, None] + 2e-6)
        exact = exact_distance(part[r], c[k], "l2")
        order = np.lexsort((ids[k], np.round(exact, 6), r))
        first = order[np.append(True, r[order][1:] != r[order][:-1])]
        out_i[at : at + step], out_d[at : at + step] = ids[k[first]], exact[first]
    return out_i, out_d


def assign(emb: DataFrame, centroids: DataFrame, copies: int = 1) -> DataFrame:
    """(id, v, cluster_id, dist): each vector with its nearest centroid, or with its `copies` nearest ones. The centroids are
    broadcast (checked).
    """
    if copies < 1:
        raise ValueError("a vector must be in a list")
    shared = emb.sparkSession.sparkContext.broadcast(local(centroids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, c = shared.value
        for batch in batches:
            if batch.num_rows and copies > 1:
                step = max(1, (4 << 20) // max(1, len(c)))
                for at in range(0, batch.num_rows, step):
                    part = batch.slice(at, step)
                    r, near, d = nearest(np.arange(part.num_rows), matrix(part.column("v")), ids, c, copies, "l2", False)
                    yield pa.RecordBatch.from_arrays([part.column("id").take(pa.array(r)), part.column("v").take(pa.array(r)), pa.array(near.astype(np.int32)), pa.array(d)], ["id", "v", "cluster_id", "dist"])
            elif batch.num_rows:
                near, d = nearest_centroid(matrix(batch.column("v")), ids, c)
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("v"), pa.array(near.astype(np.int32)), pa.array(d)], ["id", "v", "cluster_id", "dist"])

    return emb.select("id", "v").mapInArrow(run, "id long, v array<double>, cluster_id int, dist double")


def lloyd(emb: DataFrame, centroids: DataFrame, rounds: int) -> DataFrame:
    """`rounds` of Lloyd's algorithm; a list that becomes empty keeps its centroid.

    A round sends n_c x d sums of each task, not vectors; the driver keeps only the centroids.
    """
    ids, c = local(centroids)
    spark = emb.sparkSession
    for _ in range(rounds):
        shared = spark.sparkContext.broadcast((ids, c))

        def sums(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ids, c = shared.value
            count, acc = np.zeros(len(ids), np.int64), np.zeros(c.shape)
            at = {int(i): k for k, i in enumerate(ids)}
            for batch in batches:
                if batch.num_rows:
                    x = matrix(batch.column("v"))
                    near = np.array([at[int(i)] for i in nearest_centroid(x, ids, c)[0]])
                    count += np.bincount(near, minlength=len(ids))
                    np.add.at(acc, near, x)
            some = np.flatnonzero(count)
            yield pa.RecordBatch.from_arrays([pa.array(ids[some].astype(np.int32)), pa.array(count[some]), pa.array(list(acc[some]), pa.list_(pa.float64()))], ["cluster_id", "n", "s"])

        parts = emb.select("v").mapInArrow(sums, "cluster_id int, n long, s array<double>")
        per = parts.select("cluster_id", "n", F.posexplode("s").alias("j", "x")).groupBy("cluster_id", "j").agg((F.sum("x") / F.sum("n")).alias("x"))
        means = per.groupBy("cluster_id").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("s")).select("cluster_id", "s.x").collect()
        c = c.copy()
        at = {int(i): k for k, i in enumerate(ids)}
        for r in means:
            c[at[r[0]]] = r[1]
    return as_table(spark, ids, c)


def fit_partitions(emb: DataFrame, n_c: int, rounds: int = 8, init: str = "seeded", seed: int = 42) -> DataFrame:
    """Centroids by k-means: `seeded` (every N/n_c-th id), `sample` (n_c ids of smallest hash) or `parallel` (k-means||)."""
    if init == "seeded":
        return lloyd(emb, seeded_centroids(emb, n_c), rounds)
    if init == "sample":
        picked = emb.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(n_c).collect()
        return lloyd(emb, as_table(emb.sparkSession, np.arange(len(picked)), np.array([r["v"] for r in picked])), rounds)
    if init == "parallel":
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.functions import array_to_vector

        data = emb.select(array_to_vector("v").alias("features"))
        found = KMeans(k=n_c, seed=seed, maxIter=max(1, rounds), initMode="k-means||").fit(data).clusterCenters()
        return as_table(emb.sparkSession, np.arange(len(found)), np.array(found))
    raise ValueError(f"no such init: {init}")


def partition_stats(assigned: DataFrame) -> DataFrame:
    """(cluster_id, n, radius): members of each list and the largest distance to its centroid."""
    return assigned.groupBy("cluster_id").agg(F.count("*").alias("n"), F.round(F.max("dist"), 6).alias("radius"))


def list_size_histogram(assigned: DataFrame, width: int = 50) -> DataFrame:
    """(bin_from, lists): number of lists by size."""
    sizes = assigned.groupBy("cluster_id").agg(F.count("*").alias("n"))
    return sizes.groupBy((F.floor(F.col("n") / width) * width).cast("long").alias("bin_from")).agg(F.count("*").alias("lists"))


def split_large(assigned: DataFrame, cap: int = CAP, rounds: int = 4) -> DataFrame:
    """Lists over `cap` become several of about `cap` / 2, by k-means inside each of them.

    A list too large for one task is first dealt by hash; parts of a list never meet, so memory stays bounded.
    """
    sizes = assigned.groupBy("cluster_id").agg(F.count("*").alias("n"))
    limit = 50 * cap
    rows = assigned.join(sizes, "cluster_id").withColumn("part", F.when(F.col("n") > limit, F.pmod(F.xxhash64("id"), F.ceil(F.col("n") / limit))).otherwise(F.lit(0)).cast("int"))

    def split(t: pa.Table) -> pa.Table:
        x, n = matrix(t["v"]), t.num_rows
        k = 1 if t["n"][0].as_py() <= cap else max(1, math.ceil(2 * n / cap))
        order = np.argsort(t["id"].to_numpy(), kind="stable")
        c = x[order[np.linspace(0, n - 1, k).astype(int)]]
        for _ in range(rounds if k > 1 else 0):
            near, _d = nearest_centroid(x, np.arange(k), c)
            c = np.array([x[near == j].mean(0) if (near == j).any() else c[j] for j in range(k)])
        near, d = nearest_centroid(x, np.arange(k), c)
        if k == 1:
            d = t["dist"].to_numpy()
        return pa.table({"id": t["id"], "v": t["v"], "parent": t["cluster_id"], "part": t["part"], "sub": pa.array(near.astype(np.int32)), "dist": pa.array(d)})

    out = rows.groupBy("cluster_id", "part").applyInArrow(split, "id long, v array<double>, parent int, part int, sub int, dist double")
    names = out.select("parent", "part", "sub").distinct()
    from pyspark.sql import Window as W

    numbered = names.withColumn("k", F.row_number().over(W.partitionBy("parent").orderBy("part", "sub")))
    many = assigned.agg(F.max("cluster_id")).first()[0]
    new_id = F.when(F.col("k") == 1, F.col("parent").cast("long")).otherwise((F.col("k").cast("long") - 1) * F.lit((many or 0) + 1) + F.col("parent"))
    return out.join(numbered, ["parent", "part", "sub"]).select("id", "v", new_id.cast("int").alias("cluster_id"), "dist")
