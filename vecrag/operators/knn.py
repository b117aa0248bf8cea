"""Exact nearest neighbours (the truth for recall), top-k merging and the blocked form for large query sets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Bytes of query vectors that may be broadcast; more go in blocks that meet the vectors by shard.
BROADCAST_BYTES = 64 << 20
BLOCK, SHARDS_ROWS = 4096, 200_000


def matrix(column) -> np.ndarray:
    """Rows of an Arrow list column as a dense matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), float).reshape(n, -1) if n else np.zeros((0, 0))


def block_distances(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Queries x vectors; smaller is nearer."""
    prod = q @ x.T
    if metric == "l2":
        return np.sqrt(np.maximum(0.0, (q**2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * prod))
    if metric == "ip":
        return -prod
    if metric == "overlap":  # inner product of sparse vectors: those that share no place with the query are none of its candidates
        return np.where((q != 0).astype(np.float32) @ (x != 0).astype(np.float32).T > 0, -prod, np.inf)
    if metric == "cosine":
        lengths = np.sqrt((q**2).sum(1))[:, None] * np.sqrt((x**2).sum(1))[None, :]
        return 1 - np.divide(prod, lengths, out=np.zeros_like(prod), where=lengths > 0)
    raise ValueError(f"no such metric: {metric}")


def exact_distance(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Row by row, without the cancellation of the block form."""
    if metric == "l2":
        return np.sqrt(((q - x) ** 2).sum(1))
    prod = (q * x).sum(1)
    if metric in ("ip", "overlap"):
        return -prod
    lengths = np.sqrt((q**2).sum(1) * (x**2).sum(1))
    return 1 - np.divide(prod, lengths, out=np.zeros_like(prod), where=lengths > 0)


def nearest(qids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int, metric: str, skip_self: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(qid, id, d) of each query's k nearest by (d rounded to 6 places, id)."""
    if not len(q) or not len(x) or k <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    d = block_distances(q, x, metric)
    if skip_self:
        d[qids[:, None] == ids[None, :]] = np.inf
    take = min(k, len(ids))
    limit = np.partition(d, take - 1, axis=1)[:, take - 1] + 2e-6
    r, c = np.nonzero((d <= limit[:, None]) & np.isfinite(d))
    exact = np.round(exact_distance(q[r], x[c], metric), 6) + 0.0
    order = np.lexsort((ids[c], exact, r))
    r, c, exact = r[order], c[order], exact[order]
    place = np.arange(len(r)) - np.searchsorted(r, r)
    keep = place < k
    return qids[r[keep]], ids[c[keep]], exact[keep]


def best_of(qids: np.ndarray, ids: np.ndarray, d: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best (qid, id, d) of each query by (d, id); an id counts once."""
    order = np.lexsort((d, ids, qids))
    qids, ids, d = qids[order], ids[order], d[order]
    once = np.append(True, (np.diff(qids) != 0) | (np.diff(ids) != 0))[: len(qids)]
    qids, ids, d = qids[once], ids[once], d[once]
    order = np.lexsort((ids, d, qids))
    qids, ids, d = qids[order], ids[order], d[order]
    keep = np.arange(len(qids)) - np.searchsorted(qids, qids) < k
    return qids[keep], ids[keep], d[keep]


def merge_topk(partials: DataFrame, k: int, extra: tuple[str, ...] = ()) -> DataFrame:
    """Ranked result (qid, id, d, rank) of partial lists, by (d rounded to 6, id); an id counts once."""
    once = partials.groupBy("qid", "id").agg(F.min("d").alias("d"), *(F.max(c).alias(c) for c in extra))
    rank = F.row_number().over(W.partitionBy("qid").orderBy(F.round("d", 6), "id"))
    return once.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", "id", F.round("d", 6).alias("d"), "rank", *extra)


def knn_exact(emb: DataFrame, queries: DataFrame, k: int, metric: str = "l2", skip_self: bool = True) -> DataFrame:
    """Each query's k nearest of `emb` (id, v) for `queries` (qid, qv), by a scan.

    The query set is broadcast where its size is under BROADCAST_BYTES, else it goes in blocks of BLOCK queries that
    each meet every shard of the vectors: bounded memory either way, and k rows of each pair are shuffled.
    """
    if k < 0:
        raise ValueError("k must not be negative")
    shape = queries.agg(F.count("*"), F.max(F.size("qv"))).first()
    if shape[0] * (shape[1] or 1) * 8 <= BROADCAST_BYTES:
        rows = queries.select("qid", "qv").collect()
        qids, q = np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], float)
        shared = emb.sparkSession.sparkContext.broadcast((qids, q.reshape(len(qids), shape[1] or 0)))

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            qid, qv = shared.value
            for batch in batches:
                if batch.num_rows and len(qid):
                    for at in range(0, len(qid), BLOCK):
                        got = nearest(qid[at : at + BLOCK], qv[at : at + BLOCK], batch.column("id").to_numpy(), matrix(batch.column("v")), k, metric, skip_self)
                        yield pa.RecordBatch.from_arrays([pa.array(c) for c in got], ["qid", "id", "d"])

        partials = emb.select("id", "v").mapInArrow(scan, "qid long, id long, d double")
    else:
        def meet(a: pa.Table, b: pa.Table) -> pa.Table:
            got = nearest(b["qid"].to_numpy(), matrix(b["qv"]), a["id"].to_numpy(), matrix(a["v"]), k, metric, skip_self)
            return pa.table({"qid": got[0], "id": got[1], "d": got[2]})

        partials = _in_shards(emb, queries, shape[0], meet)
    return merge_topk(partials, k)


def range_search(emb: DataFrame, queries: DataFrame, radius: float) -> DataFrame:
    """(qid, id, d) of all other vectors within an l2 radius. Queries are broadcast up to BROADCAST_BYTES; more of them meet
    the shards of the vectors in blocks.
    """

    def within(qid: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        r, c = np.nonzero((block_distances(q, x, "l2") <= radius + 1e-5) & (qid[:, None] != ids[None, :]))
        d = np.round(exact_distance(q[r], x[c], "l2"), 6)
        keep = d <= radius
        return qid[r[keep]], ids[c[keep]], d[keep]

    n, dim = queries.agg(F.count("*"), F.max(F.size("qv"))).first()
    if n * (dim or 1) * 8 <= BROADCAST_BYTES:
        rows = queries.select("qid", "qv").collect()
        shared = emb.sparkSession.sparkContext.broadcast((np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], float)))

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            qid, q = shared.value
            for batch in batches:
                for at in range(0, len(qid) if batch.num_rows else 0, BLOCK):
                    got = within(qid[at : at + BLOCK], q[at : at + BLOCK], batch.column("id").to_numpy(), matrix(batch.column("v")))
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in got], ["qid", "id", "d"])

        return emb.select("id", "v").mapInArrow(scan, "qid long, id long, d double")

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        got = within(b["qid"].to_numpy(), matrix(b["qv"]), a["id"].to_numpy(), matrix(a["v"])) if a.num_rows and b.num_rows else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table(dict(zip(("qid", "id", "d"), got, strict=True)))

    return _in_shards(emb, queries, n, meet)


def _in_shards(emb: DataFrame, queries: DataFrame, n: int, meet) -> DataFrame:
    """Every shard of the vectors meets every block of the n queries, each pair in a task of bounded size."""
    blocks, shards = -(-n // BLOCK), max(1, -(-emb.count() // SHARDS_ROWS))
    left = emb.select("id", "v", F.pmod(F.xxhash64("id"), F.lit(shards)).alias("shard"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    right = queries.select("qid", "qv", F.pmod(F.xxhash64("qid"), F.lit(blocks)).alias("block"), F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"))
    return left.groupBy("shard", "block").cogroup(right.groupBy("shard", "block")).applyInArrow(meet, "qid long, id long, d double")
