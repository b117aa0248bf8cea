"""Document store: embedding, document and chunk tables by bucket, with versions, updates and status."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecrag import schema
from vecrag.session import checkpointed

TABLES = {"emb": schema.EMBEDDING, "doc": schema.DOCUMENT, "chunk": schema.CHUNK}
KEYS = {"emb": "vec_id", "doc": "doc_id", "chunk": "chunk_id"}
BUCKETS = 8


def _bucketed(df: DataFrame, version: int, buckets: int) -> DataFrame:
    return df.withColumn("added", F.lit(version).cast("long")).withColumn("bucket", F.pmod("doc_id", F.lit(buckets)).cast("int"))


def _write(rows: DataFrame, folder: str) -> list[int]:
    """Write bucket directories; the buckets that have rows."""
    rows.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(folder)
    found = rows.sparkSession.read.schema(rows.schema).parquet(folder).select("bucket").distinct()
    return [r[0] for r in found.collect()]  # at most one row a bucket


def write_tables(spark: SparkSession, path: str, emb: DataFrame, doc: DataFrame, chunk: DataFrame, buckets: int = BUCKETS) -> None:
    """Version 0 of the three tables; `buckets` should give files of about 1 GB."""
    at = {}
    for name, df in (("emb", emb), ("doc", doc), ("chunk", chunk)):
        rows = _bucketed(schema.require(df, TABLES[name]), 0, buckets)
        at[name] = dict.fromkeys(_write(rows, f"{path}/{name}/v=0"), 0)
    commit(spark, path, 0, at, buckets)


def commit(spark: SparkSession, path: str, version: int, at: dict[str, dict[int, int]], buckets: int) -> None:
    """The manifest names the version that holds each bucket; it is written last, which makes the version visible."""
    rows = [(name, b, v, buckets) for name, of in at.items() for b, v in of.items()] + [("", 0, version, buckets)]
    spark.createDataFrame(rows, "name string, bucket int, held_by long, buckets int").coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest/v={version}")


def current(spark: SparkSession, path: str) -> int:
    return spark.read.option("basePath", f"{path}/manifest").parquet(f"{path}/manifest").agg(F.max("v")).first()[0]


def places(spark: SparkSession, path: str, version: int) -> tuple[dict[str, dict[int, int]], int]:
    """Which version's files hold each bucket of each table, and the number of buckets."""
    rows = spark.read.parquet(f"{path}/manifest/v={version}").collect()
    at: dict[str, dict[int, int]] = {name: {} for name in TABLES}
    for r in rows:
        if r["name"]:
            at[r["name"]][r["bucket"]] = r["held_by"]
    return at, rows[0]["buckets"]


def read_table(spark: SparkSession, path: str, name: str, version: int | None = None) -> DataFrame:
    at, _ = places(spark, path, current(spark, path) if version is None else version)
    names = [*TABLES[name].fieldNames(), "added", "bucket"]
    kinds = schema.T.StructType([*TABLES[name].fields, schema.T.StructField("added", schema.T.LongType()), schema.T.StructField("bucket", schema.T.IntegerType())])
    if not at[name]:
        return spark.createDataFrame([], kinds)
    folders = [f"{path}/{name}/v={v}/bucket={b}" for b, v in sorted(at[name].items())]
    return spark.read.schema(kinds).option("basePath", f"{path}/{name}").parquet(*folders).select(*names)


def update_store(spark: SparkSession, path: str, added: dict[str, DataFrame], removed: DataFrame, version: int | None = None) -> int:
    """A new version without the `removed` doc_ids and with the `added` rows; an id that is added again is replaced.

    Only buckets that lose or gain rows are written. A version that exists already is returned as it is, so a repeated
    run changes nothing.
    """
    old = current(spark, path)
    version = old + 1 if version is None else version
    if version <= old:
        return old
    at, buckets = places(spark, path, old)
    gone = checkpointed(removed.select("doc_id").distinct())
    for name, kind in TABLES.items():
        rows, key = read_table(spark, path, name, old), KEYS[name]
        new = checkpointed(_bucketed(schema.require(added[name], kind), version, buckets))
        lost = rows.join(gone, "doc_id", "left_semi").unionByName(rows.join(new.select(key), key, "left_semi").select(*rows.columns))
        touched = [r[0] for r in lost.select("bucket").unionByName(new.select("bucket")).distinct().collect()]  # at most one a bucket
        if touched:
            kept = rows.where(F.col("bucket").isin(touched)).join(gone, "doc_id", "left_anti").join(new.select(key), key, "left_anti").select(*rows.columns)
            written = _write(kept.unionByName(new.select(*rows.columns)), f"{path}/{name}/v={version}")
            at[name] = {b: v for b, v in at[name].items() if b not in touched} | dict.fromkeys(written, version)
    commit(spark, path, version, at, buckets)
    return version


def status(spark: SparkSession, path: str, since: int | None = None) -> DataFrame:
    """(files, vectors, new_files, new_vectors) of the current version; new: added after version `since`."""
    version = current(spark, path)
    since = version - 1 if since is None else since
    count = lambda name, alias: read_table(spark, path, name, version).agg(F.count("*").alias(alias), F.sum((F.col("added") > since).cast("long")).alias(f"new_{alias}"))
    both = count("doc", "files").join(count("emb", "vectors"))
    return both.select("files", "vectors", F.coalesce("new_files", F.lit(0)).alias("new_files"), F.coalesce("new_vectors", F.lit(0)).alias("new_vectors"))
