"""Accuracy, token, time-to-first-token, energy and battery measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.functions import vector as V
from vecrag.operators.rag import normalised

#: Generators: prompt tokens/s, generated tokens/s, battery % per 1000 tokens (fixed values).
SPEEDS = (("S-0.5B", 90.0, 14.5, 0.10), ("M-1.5B", 50.0, 10.0, 0.30), ("R-1.5B", 35.0, 9.0, 0.36))
#: Joules per second of time to first token, of each generator (fixed values, from the published table).
WATT = {"S-0.5B": 4.74, "M-1.5B": 7.55, "R-1.5B": 5.4}


def speeds(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(*r, WATT[r[0]]) for r in SPEEDS], "generator string, prompt_rate double, gen_rate double, battery double, watt double")


def gain_at_recall(curve: DataFrame, recall: float = 0.93, base: str = "two_tier") -> DataFrame:
    """(method, qps, gain): QPS interpolated at one recall along each method's curve, and `base`'s ratio to it."""
    w = W.partitionBy("method").orderBy("recall")
    steps = curve.withColumn("r0", F.lag("recall").over(w)).withColumn("q0", F.lag("qps").over(w))
    crossing = steps.where((F.col("recall") >= recall) & ((F.col("r0") < recall) | F.col("r0").isNull()))
    share = (recall - F.col("r0")) / (F.col("recall") - F.col("r0"))
    at = crossing.select("method", F.when(F.col("r0").isNull(), F.col("qps")).otherwise(F.col("q0") + share * (F.col("qps") - F.col("q0"))).alias("qps"))
    own = at.where(F.col("method") == base).select(F.col("qps").alias("own"))
    return at.join(F.broadcast(own)).select("method", F.round("qps", 6).alias("qps"), F.round(F.col("own") / F.col("qps"), 6).alias("gain"))


def width_for_recall(curve: DataFrame, recall: float) -> DataFrame:
    """(method, ef): the smallest width that reaches a recall."""
    return curve.where(F.col("recall") >= recall).groupBy("method").agg(F.min("ef").alias("ef"))


def throughput(times: DataFrame) -> DataFrame:
    """(method, qps, p50, p95) of measured (method, ms) per query."""
    return times.groupBy("method").agg(F.round(1000 * F.count("*") / F.sum("ms"), 6).alias("qps"), F.round(F.percentile("ms", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("ms", F.lit(0.95)), 6).alias("p95"))


def update_latency(log: DataFrame) -> DataFrame:
    """(method, op, n, mean_ms, p95_ms, n_dist) of measured updates."""
    return log.groupBy("method", "op").agg(F.count("*").alias("n"), F.round(F.avg("ms"), 6).alias("mean_ms"), F.round(F.percentile("ms", F.lit(0.95)), 6).alias("p95_ms"), F.sum("n_dist").alias("n_dist"))


def answer_accuracy(replies: DataFrame, gold: DataFrame) -> DataFrame:
    """(queries, accuracy): % of queries whose reply contains all normalised gold answers; a missing gold is wrong."""
    joined = gold.select("qid", "answers").join(replies.select("qid", normalised(F.col("reply")).alias("reply")), "qid", "left")
    right = (F.size("answers") > 0) & F.forall("answers", lambda a: F.contains(F.coalesce("reply", F.lit("")), normalised(a)) & (normalised(a) != ""))
    return joined.agg(F.count("*").alias("queries"), F.round(100 * F.avg(right.cast("double")), 6).alias("accuracy"))


def evidence_report(contexts: DataFrame, gold: DataFrame) -> DataFrame:
    """(queries, in_context, gold_in_top, mrr): gold answer in the context, gold document retrieved, reciprocal rank."""
    per = contexts.join(gold, "qid").groupBy("qid").agg(
        F.max(F.forall("answers", lambda a: F.contains(normalised(F.col("context")), normalised(a))).cast("double")).alias("hit"),
        F.min(F.when(F.array_contains("gold_docs", F.col("doc_id")), F.col("rank"))).alias("first"),
    )
    all_q = gold.select("qid").join(per, "qid", "left")
    return all_q.agg(F.count("*").alias("queries"), F.round(F.avg(F.coalesce("hit", F.lit(0.0))), 6).alias("in_context"), F.round(F.avg(F.when(F.col("first").isNotNull(), 1.0).otherwise(0.0)), 6).alias("gold_in_top"), F.round(F.avg(F.coalesce(1.0 / F.col("first"), F.lit(0.0))), 6).alias("mrr"))


def token_report(before: DataFrame, after: DataFrame) -> DataFrame:
    """(documents, before, after, reduction): mean tokens of (qid, doc_id, context) pairs and the cut in %."""
    a = before.select("qid", "doc_id", V.token_count("context").alias("b"))
    b = after.select("qid", "doc_id", V.token_count("context").alias("a"))
    both = a.join(b, ["qid", "doc_id"]).agg(F.count("*").alias("documents"), F.avg("b").alias("before"), F.avg("a").alias("after"))
    return both.select("documents", F.round("before", 6).alias("before"), F.round("after", 6).alias("after"), F.round(100 * (1 - F.col("after") / F.col("before")), 6).alias("reduction"))


def ttft_model(parts: DataFrame, rates: DataFrame) -> DataFrame:
    """(.., generator, prompt_s, ttft_s, joule_model): embed, search and extra seconds plus prompt tokens / speed."""
    made = parts.join(F.broadcast(rates))
    prompt = F.col("n_tokens") / F.col("prompt_rate")
    ttft = F.col("embed_s") + F.col("search_s") + F.col("extra_s") + prompt
    return made.select(*parts.columns, "generator", F.round(prompt, 6).alias("prompt_s"), F.round(ttft, 6).alias("ttft_s"), F.round(ttft * F.col("watt"), 6).alias("joule_model"))


def generation_model(replies: DataFrame, rates: DataFrame) -> DataFrame:
    """(generator, replies, gen_s, battery_pct): time and battery share of the generated tokens."""
    made = replies.select(V.token_count("reply").alias("t")).agg(F.count("*").alias("replies"), F.sum("t").alias("t"))
    return made.join(F.broadcast(rates)).select("generator", "replies", F.round(F.col("t") / F.col("gen_rate"), 6).alias("gen_s"), F.round(F.col("t") / 1000 * F.col("battery"), 6).alias("battery_pct"))


def relative_gain(table: DataFrame, base: str) -> DataFrame:
    """(generator, dataset, method, measure, cut_pct, ratio) of each method against `base`."""
    b = table.where(F.col("method") == base).select("generator", "dataset", "measure", F.col("value").alias("b"))
    joined = table.where(F.col("method") != base).join(b, ["generator", "dataset", "measure"])
    return joined.select("generator", "dataset", "method", "measure", F.round(100 * (1 - F.col("value") / F.col("b")), 6).alias("cut_pct"), F.round(F.col("b") / F.col("value"), 6).alias("ratio"))
