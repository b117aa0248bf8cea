"""Readers of the engine's inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given parquet tables, by a path that only Spark has to understand."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, v) of the embeddings in double."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))


def ann_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, qv): every vector whose id is divisible by 50."""
    return vectors(spark, sf_dir).where("id % 50 = 0").select(F.col("id").alias("qid"), F.col("v").alias("qv"))


def event_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with ts as a zoned timestamp, which watermarks need."""
    return table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def update_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(seq, op, id, v) from events: signup and purchase insert, error deletes, id = event_id % N."""
    e = vectors(spark, sf_dir)
    n = e.count()
    op = F.when(F.col("event_type").isin("signup", "purchase"), "insert").when(F.col("event_type") == "error", "delete")
    ops = table(spark, sf_dir, "events").select(F.col("event_id").alias("seq"), op.alias("op"), (F.col("event_id") % n).alias("id")).where("op is not null")
    return ops.join(e, "id").select("seq", "op", "id", F.when(F.col("op") == "insert", F.col("v")).alias("v"))


def expanded_embeddings(spark: SparkSession, sf_dir: str, r: int, sigma: float = 0.5) -> DataFrame:
    """(id, v, parent_id): each vector and r - 1 noisy copies, renormalised; noise depends on (parent, copy, place) only."""
    base = vectors(spark, sf_dir).select(F.col("id").alias("parent_id"), "v", F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("copy"))
    key = lambda j, s: (F.pmod(F.xxhash64("parent_id", "copy", j, F.lit(s)), F.lit(1 << 30)) + 1) / F.lit(float(1 << 30))
    gauss = lambda j: F.sqrt(-2 * F.log(key(j, 1))) * F.cos(2 * 3.141592653589793 * key(j, 2))
    noisy = F.transform("v", lambda x, j: F.when(F.col("copy") == 0, x).otherwise(x + sigma / F.sqrt(F.size("v")) * gauss(j)))
    length = F.sqrt(F.aggregate("w", F.lit(0.0), lambda s, x: s + x * x))
    return base.withColumn("w", noisy).select((F.col("parent_id") * r + F.col("copy")).alias("id"), F.transform("w", lambda x: x / length).alias("v"), "parent_id")
