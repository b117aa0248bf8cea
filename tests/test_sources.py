"""Sources and sinks: round trips, pruning, overwriting by partition."""

import json

import pytest
from pyspark.sql import functions as F

from vecrag import sources
from vecrag.operators import index as two_tier
from vecrag.sources import index_source

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("kind", ["json", "csv", "orc", "parquet"])
def test_round_trip(spark, tmp_path, kind):
    df = sources.table(spark, SF, "events").select("event_id", "user_id", "event_type", "value", "props")
    options = {"header": True, "escape": '"', "quote": '"'} if kind == "csv" else {}
    df.write.format(kind).options(**options).save(f"file://{tmp_path}/x")
    back = spark.read.format(kind).options(**options).schema(df.schema).load(f"file://{tmp_path}/x")
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, df.collect()))


def test_text_and_binary(spark, tmp_path):
    df = sources.table(spark, SF, "events").select("props")
    df.write.text(f"file://{tmp_path}/t")
    assert sorted(r["value"] for r in spark.read.text(f"file://{tmp_path}/t").collect()) == sorted(r["props"] for r in df.collect())
    blobs = spark.read.format("binaryFile").option("pathGlobFilter", "*.txt").load(f"file://{tmp_path}/t").select("content").collect()
    assert sum(len(json.loads(line)) for b in blobs for line in bytes(b["content"]).decode().splitlines()) == df.count()


def test_only_touched_partitions_are_overwritten(spark, tmp_path):
    path = f"file://{tmp_path}/p"
    spark.range(20).withColumn("bucket", F.col("id") % 4).write.partitionBy("bucket").parquet(path)
    files = lambda: {r[0] for r in spark.read.parquet(path).where("bucket <> 2").select(F.input_file_name()).distinct().collect()}
    before = files()
    new = spark.range(100, 103).withColumn("bucket", F.lit(2).cast("long"))
    new.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("bucket").parquet(path)
    out = spark.read.parquet(path)
    assert before == files()
    assert sorted(r["id"] for r in out.where("bucket = 2").collect()) == [100, 101, 102]


def test_pushed_filter_names_the_buckets(spark):
    from pyspark.sql.datasource import EqualTo, GreaterThan, In

    reader = index_source.IndexReader({"path": "/x", "buckets": "8"})
    left = list(reader.pushFilters([In(("cluster_id",), (1, 9, 3)), GreaterThan(("n",), 5)]))
    assert left == [GreaterThan(("n",), 5)]
    assert [(p.bucket, p.clusters) for p in reader.partitions()] == [(1, (1, 9)), (3, (3,))]
    list(reader.pushFilters([EqualTo(("cluster_id",), 9)]))
    assert [(p.bucket, p.clusters) for p in reader.partitions()] == [(1, (9,))]


def test_probed_search_prunes_at_run_time(spark, tmp_path):
    idx = two_tier.save_index(two_tier.build_index(sources.vectors(spark, SF), n_c=16, rounds=1), f"file://{tmp_path}/i")
    blocks = two_tier.block_queries(two_tier.probe(idx, sources.ann_queries(spark, SF), 1))
    plan = two_tier.load_graphs(idx, blocks)._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and "Cartesian" not in plan and "BatchEvalPython" not in plan


def test_events_are_zoned(spark):
    assert dict(sources.event_times(spark, SF).dtypes)["ts"] == "timestamp"
