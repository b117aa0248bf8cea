"""Streams leave their rows in files, not on the driver."""

from pyspark.sql import functions as F

from vecrag.streaming import streams


def test_drained_rows_lie_in_files(spark, tmp_path):
    """Complete mode gives the last batch's rows, append mode those of all batches; no table is kept in the driver's memory."""
    given = str(tmp_path / "in")
    for k in range(2):
        spark.range(4).select((F.col("id") + 4 * k).alias("id"), (F.col("id") % 2).alias("g")).coalesce(1).write.mode("append").parquet(given)
    stream = streams.file_stream(spark, given, "id long, g long")
    views = {t.name for t in spark.catalog.listTables()}
    counted = streams.drain(stream.groupBy("g").count(), str(tmp_path / "n"), str(tmp_path / "c1"), "complete")
    assert sorted(map(tuple, counted.collect())) == [(0, 4), (1, 4)]
    rows = streams.drain(stream, str(tmp_path / "r"), str(tmp_path / "c2"))
    assert sorted(r["id"] for r in rows.collect()) == list(range(8)) and len(rows.inputFiles()) >= 2
    assert {t.name for t in spark.catalog.listTables()} == views


def test_a_drained_stream_without_rows_is_empty(spark, tmp_path):
    spark.range(0).write.parquet(str(tmp_path / "in"))
    got = streams.drain(streams.file_stream(spark, str(tmp_path / "in"), "id long"), str(tmp_path / "r"), str(tmp_path / "c"))
    assert got.columns == ["id"] and got.count() == 0
