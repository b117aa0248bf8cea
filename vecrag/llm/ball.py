"""Exact top-k by inner product: ball-tree branch and bound in every shard.

Vectors are dealt to shards by a hash of their row; a shard's ball tree, built once and stored with it, halves its members
at the median along the direction between two far members, and a node keeps the mean and radius of its members. For a
block of queries the
nodes wait in order of their upper bound |q . centre| + |q| * radius; a query is dropped from a node whose bound is
under its current k-th score. A first pass gives each query the k best of one shard; that k-th score is shared with
all shards from then on, and within a task it keeps rising from shard to shard.

Defined results: vectors that are null, empty, or hold a null or non-finite component take no part; inner products
exist between vectors of one length only; rows that repeat an id are candidates, and queries, of their own (a row is only
no candidate of itself); rows without an id take no part; ties go to smaller ids.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.llm.common import checkpointed

LEAF, SHARD, BLOCK, TOP = 128, 4096, 1024, 5
#: Blocks of queries that come to a shard together.
BUNDLE = 16
_NOBODY = np.iinfo(np.int64).max


@dataclass
class Tree:
    rows: np.ndarray  # what tells a row from all others
    ids: np.ndarray
    vectors: np.ndarray
    nodes: list[tuple[int, int, int, int]]  # first row, row after the last, left node, right node (-1: leaf)
    centres: np.ndarray
    radii: np.ndarray


def build(ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF, rows: np.ndarray | None = None) -> Tree:
    rows = ids if rows is None else rows
    order = np.lexsort((rows, ids))
    nodes: list[tuple[int, int, int, int]] = []
    centres, radii = [], []

    def node(lo: int, hi: int) -> int:
        at = len(nodes)
        part = vectors[order[lo:hi]]
        centre = part.mean(0)
        away = np.sqrt(((part - centre) ** 2).sum(1))
        nodes.append((lo, hi, -1, -1))
        centres.append(centre)
        radii.append(away.max(initial=0.0) * (1 + 1e-12))
        if hi - lo > leaf and radii[at] > 0:
            far = part[int(away.argmax())]
            other = part[int(((part - far) ** 2).sum(1).argmax())]
            side = np.argsort(part @ (other - far), kind="stable")
            order[lo:hi] = order[lo:hi][side]
            mid = (lo + hi) // 2
            a = node(lo, mid)
            b = node(mid, hi)
            nodes[at] = (lo, hi, a, b)
        return at

    node(0, len(ids))
    return Tree(rows[order], ids[order], vectors[order], nodes, np.array(centres), np.array(radii))


def search(tree: Tree, qid: np.ndarray, q: np.ndarray, k: int, best: np.ndarray | None = None, who: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, int]:
    """The k best (scores, ids) of each query over `best`/`who` and the tree, and the number of products computed. qid is
    the query's own row.

    Rows are sorted by falling score, then rising id; -inf stands for a missing one. Columns may exceed k - an incoming
    k-th score without its id (-1) is a bound only.
    """
    best = np.full((len(q), k), -np.inf) if best is None else best.copy()
    who = np.full((len(q), k), _NOBODY) if who is None else who.copy()
    length = np.sqrt((q**2).sum(1))
    bound = q @ tree.centres.T + length[:, None] * tree.radii[None, :] + 1e-6
    heap = [(-bound[:, 0].max(initial=-np.inf), 0)]
    products = 0
    while heap:
        _, at = heapq.heappop(heap)
        alive = np.flatnonzero(bound[:, at] >= best[:, k - 1])
        if not len(alive):
            continue
        lo, hi, left, right = tree.nodes[at]
        if left >= 0:
            for child in (left, right):
                heapq.heappush(heap, (-bound[alive, child].max(), child))
            continue
        score = q[alive] @ tree.vectors[lo:hi].T
        ids = tree.ids[lo:hi]
        products += score.size
        score[qid[alive][:, None] == tree.rows[lo:hi][None, :]] = -np.inf
        take = min(k, hi - lo)
        # order by (score, -id): equal scores at the edge must keep the smaller ids
        floor = np.partition(score, hi - lo - take, axis=1)[:, hi - lo - take]
        hits = (score >= np.maximum(floor, best[alive, k - 1])[:, None]) & (score > -np.inf)
        for r in np.flatnonzero(hits.any(1)):
            cols = np.flatnonzero(hits[r])
            s = np.concatenate([best[alive[r]], score[r, cols]])
            i = np.concatenate([who[alive[r]], ids[cols]])
            keep = np.lexsort((i, -s))[:k]
            best[alive[r]], who[alive[r]] = s[keep], i[keep]
    return best, who, products


def quantised(vector: str, scale: int = 256) -> Column:
    """floor(scale * x) of every component as double; null where the vector takes no part."""
    v = F.col(vector).cast("array<double>")
    sound = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.when(sound, F.transform(v, lambda x: F.floor(x * F.lit(float(scale))).cast("double")))


def _matrix(column: pa.Array) -> np.ndarray:
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(np.float64) if n else np.zeros((0, 0))


_TREE = {"rows": "<i8", "ids": "<i8", "vectors": "<f8", "nodes": "<i4", "centres": "<f8", "radii": "<f8"}
TREE = ", ".join(f"{c} binary" for c in _TREE)
ASKED = "qrows binary, qids binary, qbody binary, floor binary"


def _trees(placed: DataFrame) -> DataFrame:
    """(dim, shard, tree): the ball tree of each shard, of bounded size, as packed bytes."""

    def pack(t: pa.Table) -> pa.Table:
        tree = build(t["id"].to_numpy(), _matrix(t["v"].combine_chunks()), rows=t["row"].to_numpy())
        out = {g: pa.array([t[g][0].as_py()], pa.int32()) for g in ("dim", "shard")}
        return pa.table(out | {c: pa.array([np.asarray(getattr(tree, c)).astype(kind).tobytes()], pa.binary()) for c, kind in _TREE.items()})

    return placed.select("dim", "shard", "id", "row", "v").groupBy("dim", "shard").applyInArrow(pack, f"dim int, shard int, {TREE}")


def _blocks(queries: DataFrame) -> DataFrame:
    """(dim, block, rows, ids, vectors and k-th scores so far) of each block of queries, as packed bytes."""

    def pack(t: pa.Table) -> pa.Table:
        t = t.sort_by("row").combine_chunks()
        out = {g: pa.array([t[g][0].as_py()], pa.int32()) for g in ("dim", "block")}
        packed = (t["row"].to_numpy().astype("<i8"), t["id"].to_numpy().astype("<i8"), _matrix(t["v"].combine_chunks()).astype("<f8"), t["floor"].to_numpy(zero_copy_only=False).astype("<f8"))
        return pa.table(out | {c.split()[0]: pa.array([x.tobytes()], pa.binary()) for c, x in zip(ASKED.split(", "), packed, strict=True)})

    return queries.select("dim", "block", "row", "id", "v", "floor").groupBy("dim", "block").applyInArrow(pack, f"dim int, block int, {ASKED}")


def _visit(trees: DataFrame, blocks: DataFrame, k: int) -> DataFrame:
    """Search each tree for the bundle of query blocks that meets it at (dim, shard, bundle).

    One tree and at most BUNDLE blocks are in memory; k-th scores found in a task are kept for what it comes to next.
    """
    known: dict[int, float] = {}

    def run(shard: pa.Table, asked: pa.Table) -> pa.Table:
        out: list[tuple[np.ndarray, ...]] = []
        if shard.num_rows and asked.num_rows:
            dim = shard["dim"][0].as_py()
            parts = {c: np.frombuffer(shard[c][0].as_py(), kind) for c, kind in _TREE.items()}
            tree = Tree(parts["rows"], parts["ids"], parts["vectors"].reshape(-1, dim), [tuple(x) for x in parts["nodes"].reshape(-1, 4).tolist()], parts["centres"].reshape(-1, dim), parts["radii"])
            for r in range(asked.num_rows):
                rows, ids, floor = (np.frombuffer(asked[c][r].as_py(), kind) for c, kind in (("qrows", "<i8"), ("qids", "<i8"), ("floor", "<f8")))
                q = np.frombuffer(asked["qbody"][r].as_py(), "<f8").reshape(-1, dim)
                floor = np.maximum(floor, [known.get(x, -np.inf) for x in rows.tolist()])
                best, who, _ = search(tree, rows, q, k, np.repeat(floor[:, None], k, axis=1), np.full((len(q), k), _NOBODY))
                if len(known) > 1 << 20:
                    known.clear()
                known.update(zip(rows.tolist(), best[:, k - 1].tolist(), strict=True))
                at, col = np.nonzero(who != _NOBODY)
                out.append((rows[at], ids[at], who[at, col], best[at, col].astype(np.int64)))
        cols = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64)] * 4
        return pa.table(dict(zip(("row", "query_id", "vec_id", "score"), cols, strict=True)))

    keys = ["dim", "shard", "bundle"]
    return trees.groupBy(*keys).cogroup(blocks.groupBy(*keys)).applyInArrow(run, "row long, query_id long, vec_id long, score long")


def top_k(df: DataFrame, is_query: Column, vec_id: str = "vec_id", vector: str = "embedding", k: int = TOP, scale: int = 256) -> DataFrame:
    """query_id, rank, vec_id, score: each query row's k best candidates over all other rows."""
    given = df.select(F.col(vec_id).cast("long").alias("id"), quantised(vector, scale).alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    given = given.where("v is not null and id is not null").withColumns({"dim": F.size("v"), "row": F.monotonically_increasing_id()})
    given = checkpointed(given)  # from here on a row keeps its number
    sizes = {r["dim"]: (r["n"], r["q"]) for r in given.groupBy("dim").agg(F.count("*").alias("n"), F.sum(F.col("asks").cast("long")).alias("q")).collect()}
    if not sizes:
        return df.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    many = lambda col, per: F.element_at(F.create_map(*(F.lit(x) for d, c in sizes.items() for x in (d, max(1, -(-c[col] // per))))), F.col("dim"))
    placed = given.withColumn("shard", F.pmod(F.xxhash64(F.lit(1), "row"), many(0, SHARD)).cast("int"))
    trees = checkpointed(_trees(placed))
    queries = placed.where("asks").drop("shard").withColumn("block", F.pmod(F.xxhash64(F.lit(2), "row"), many(1, BLOCK)).cast("int"))
    # first pass: one shard for each block, the same for all of its queries
    home = F.pmod(F.col("block"), many(0, SHARD)).cast("int")
    one = F.lit(0).alias("bundle")
    seeds = _blocks(queries.withColumn("floor", F.lit(float("-inf")))).withColumn("shard", home).select("*", one)
    first = checkpointed(_visit(trees.where(F.col("shard") < many(1, BLOCK)).select("*", one), seeds, k))
    nth = W.partitionBy("row").orderBy(F.desc("score"), "vec_id")
    kth = first.withColumn("r", F.row_number().over(nth)).where(F.col("r") == k).select("row", F.col("score").cast("double").alias("floor"))
    blocks = checkpointed(_blocks(queries.join(kth, "row", "left").withColumn("floor", F.coalesce("floor", F.lit(float("-inf"))))))
    bundles = F.ceil(many(1, BLOCK) / BUNDLE).cast("int")
    asked = blocks.withColumn("bundle", F.pmod("block", bundles).cast("int")).withColumn("shard", F.explode(F.sequence(F.lit(0), many(0, SHARD) - 1))).where(F.col("shard") != home)
    rest = _visit(trees.withColumn("bundle", F.explode(F.sequence(F.lit(0), bundles - 1))), asked, k)
    merged = first.unionByName(rest)
    return merged.withColumn("rank", F.row_number().over(nth)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
