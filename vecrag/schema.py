"""Explicit schemas of the engine's tables; readers check them, writers never infer."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

EMBEDDING = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("doc_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.DoubleType()))])
DOCUMENT = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("path", T.StringType())])
CHUNK = T.StructType([T.StructField("chunk_id", T.LongType()), T.StructField("doc_id", T.LongType()), T.StructField("offset", T.LongType())])
GRAPH = (
    "cluster_id int, bucket int, version long, n int, dim int, m int, ids array<bigint>, vecs binary, levels array<int>, link_ptr array<int>, "
    "link_to array<int>, entry int, max_level int, deleted array<boolean>, radius double, n_dist_build long"
)
RESULT = "qid long, id long, d double, rank int"


def require(df: DataFrame, wanted: T.StructType) -> DataFrame:
    """The wanted columns, or ValueError where one is missing or of another kind."""
    have = {f.name: f.dataType for f in df.schema.fields}
    for f in wanted.fields:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise ValueError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df.select(*wanted.fieldNames())


def vectors(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", dim: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(sound rows as id, v double array; rejects with a reason): null, ragged or non-finite vectors are reported."""
    v = F.col(vec_col).cast("array<double>")
    reason = (
        F.when(F.col(id_col).isNull(), "null id")
        .when(v.isNull(), "null vector")
        .when(F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), "non-finite component")
        .when((F.size(v) != dim) if dim else (F.size(v) == 0), "wrong dimension")
    )
    all_rows = df.select(F.col(id_col).cast("long").alias("id"), v.alias("v"), reason.alias("reason"))
    return all_rows.where("reason is null").select("id", "v"), all_rows.where("reason is not null").select("id", "reason")
