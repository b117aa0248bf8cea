"""Queries that read the given tables, and tables that repeat their keys."""

from vecrag import sources
from vecrag.queries import QUERIES

SF = "/root/testdata/sf0.001"


def test_cost_models_take_their_shapes_from_the_vectors(spark):
    n = {f"label {r['label']}": r["count"] for r in sources.table(spark, SF, "embeddings").groupBy("label").count().collect()}
    found = {r["name"]: r["bytes"] for r in QUERIES["memory_model"](spark, SF).where("method = 'ivf'").collect()}
    assert found == {k: 4 * 64 + 8 * v + 4 * 64 * v for k, v in n.items()}


def test_gain_is_of_the_events(spark):
    kinds = {r[0] for r in sources.table(spark, SF, "events").select("event_type").distinct().collect()}
    rows = {r["method"]: r["gain"] for r in QUERIES["gain_at_recall"](spark, SF).collect()}
    assert set(rows) == kinds and rows["click"] == 1.0


def test_lateral_gives_two_orders_of_a_repeated_key(spark, tmp_path):
    kind = "c_custkey long", "o_orderkey long, o_custkey long, o_totalprice double"
    spark.createDataFrame([(1,), (1,), (2,)], kind[0]).write.parquet(str(tmp_path / "customer.parquet"))
    spark.createDataFrame([(10, 1, 5.0), (11, 1, 7.0), (12, 1, 1.0), (13, 2, 2.0)], kind[1]).write.parquet(str(tmp_path / "orders.parquet"))
    assert sorted(tuple(r) for r in QUERIES["rel_lateral"](spark, str(tmp_path)).collect()) == [(1, 11), (1, 11), (2, 13)]
