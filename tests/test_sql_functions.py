"""Distances of all pairs from SQL: compiled, and without vectors in what is sorted."""

import pytest

from vecrag.functions import udf
from vecrag.queries import QUERIES


def test_compiled_distance_has_the_same_bits(spark):
    rows = spark.createDataFrame([([0.1 * i, 1 / (i + 3), -2.0], [1.0 / (i + 7), 0.3 * i, 5.5]) for i in range(20)], "a array<double>, b array<double>")
    rows.createOrReplaceTempView("cd_rows")
    got = []
    for dim in (None, udf.only_size(rows, "a")):
        udf.register(spark, dim)
        got.append([r[0] for r in spark.sql("SELECT l2sq(a, b) FROM cd_rows").collect()])
    udf.register(spark)
    assert got[0] == got[1]


def test_only_whole_vectors_of_one_size_are_compiled(spark):
    made = lambda *v: udf.only_size(spark.createDataFrame([(x,) for x in v], "v array<double>"))
    assert made([1.0, 2.0], [3.0, 4.0]) == 2
    assert made([1.0, 2.0], [3.0]) is None and made([1.0, None]) is None and made([]) is None and made(None) is None
    assert made([0.0] * (udf.WIDEST + 1)) is None


@pytest.mark.parametrize("name", ["vec_knn_join", "sql_functions"])
def test_sorted_pairs_carry_no_vectors(spark, name):
    plan = QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    limits = [line for line in plan.split("\n") if "WindowGroupLimit" in line]
    assert limits and "Partial" in "".join(limits) and not any("qv#" in line or " v#" in line for line in limits)
    assert "lambda" not in plan.split("Window")[-1].split("Cartesian")[0]
