"""SQL surface: temporary functions with SQL bodies, Arrow UDFs and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, udtf

from vecrag.operators.kernel import Graph

#: Places up to which a distance is written out term by term.
WIDEST = 128
SQL_FUNCTIONS = {
    "l2sq(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
    "vdot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vcosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "coalesce(vdot(a, b) / nullif(sqrt(vdot(a, a) * vdot(b, b)), 0D), 0D)",
    "text_tokens(t STRING) RETURNS ARRAY<STRING>": r"regexp_extract_all(lower(coalesce(t, '')), '([\\p{L}\\p{N}]+)')",
    "token_count(t STRING) RETURNS INT": "size(text_tokens(t))",
}


def unrolled_l2sq(dim: int) -> str:
    """Body of l2sq for vectors of up to `dim` places, term by term in the same order: compiled code instead of lambdas."""
    each = (f"(get(a, {i}) - get(b, {i}))" for i in range(dim))
    return "0D + " + " + ".join(f"{x} * {x}" for x in each)


def only_size(vectors: DataFrame, v: str = "v") -> int | None:
    """The size of all vectors if they have the same one of up to WIDEST places and no null in them, else None."""
    low, high, gaps = vectors.agg(F.min(F.size(v)), F.max(F.size(v)), F.bool_or(F.exists(v, lambda x: x.isNull()))).first()
    return high if low == high and high and 0 < high <= WIDEST and not gaps else None


def register(spark: SparkSession, dim: int | None = None) -> None:
    """Make l2sq, vdot, vcosine, text_tokens, token_count, windows_of and neighbours known to SQL.

    With `dim`, the size of all vectors, l2sq is compiled for it: it is what scans of all pairs spend their time on.
    """
    for signature, body in SQL_FUNCTIONS.items():
        if dim and signature.startswith("l2sq("):
            body = unrolled_l2sq(dim)
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURN {body}")
    spark.udtf.register("windows_of", windows_of)
    spark.udtf.register("neighbours", neighbours)


@udtf(returnType="start int, stop int, text string")
class windows_of:  # noqa: N801 - a table function's SQL name
    """Sliding windows of a text's sentences."""

    def eval(self, text: str, window: int, overlap: int):
        import re

        body = text or ""
        marked = re.sub(r"([.!?])\s+", "\\1\u0001", body)
        parts = marked.split("\u0001") if "\u0001" in marked else body.split("\n")
        sents = [s.strip() for s in parts if s.strip()]
        n, step = len(sents), window - overlap
        if step < 1:
            raise ValueError("a window must move forward")
        starts = [1] if 0 < n <= window else list(range(1, n - window + 2, step)) if n else []
        if n > window and starts[-1] < n - window + 1:
            starts.append(n - window + 1)
        for s in starts:
            yield s, min(n, s + window - 1), " ".join(sents[s - 1 : s - 1 + window])


@udtf(returnType="id bigint, level int, other bigint")
class neighbours:  # noqa: N801
    """Links of a stored graph row, given as its columns."""

    def eval(self, row: Row):
        graph = Graph.from_row(row.asDict(True))
        for at, node in enumerate(graph.links):
            for level, links in enumerate(node):
                for n in links:
                    yield graph.ids[at], level, graph.ids[n]


def graph_search_udf(k: int, ef: int):
    """Arrow UDF: ids of the k nearest in a graph (its row as a struct) to a query vector."""

    @arrow_udf("array<bigint>")
    def search(graphs: pa.Array, queries: pa.Array) -> pa.Array:
        out = []
        for row, q in zip(graphs.to_pylist(), queries.to_pylist(), strict=True):
            found, _ = Graph.from_row(row).search(np.array(q, float), k, ef)
            out.append([i for _, i in found])
        return pa.array(out, pa.list_(pa.int64()))

    return search


def vec_mean(df, group: str, vec: str = "v"):
    """(group, n, mean): two-phase mean of vectors: sums of each batch, then of the groups."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from vecrag.operators.knn import matrix

        for batch in batches:
            if batch.num_rows:
                keys, at = np.unique(batch.column("g").to_numpy(zero_copy_only=False), return_inverse=True)
                x = matrix(batch.column("v"))
                acc = np.zeros((len(keys), x.shape[1]))
                np.add.at(acc, at, x)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.bincount(at)), pa.array(list(acc), pa.list_(pa.float64()))], ["g", "n", "s"])

    parts = df.select(F.col(group).cast("long").alias("g"), F.col(vec).alias("v")).mapInArrow(sums, "g long, n long, s array<double>")
    per = parts.select("g", "n", F.posexplode("s").alias("j", "x")).groupBy("g", "j").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    return per.groupBy("g").agg(F.max("n").alias("n"), F.array_sort(F.collect_list(F.struct("j", (F.col("x") / F.col("n")).alias("m")))).alias("t")).select(F.col("g").alias(group), "n", F.col("t.m").alias("mean"))
