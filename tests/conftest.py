"""One local session for all tests."""

import os
import sys
from pathlib import Path

import pytest

REPO = str(Path(__file__).resolve().parents[1])
sys.path.insert(0, REPO)
os.environ["PYTHONPATH"] = f"{REPO}:{os.environ.get('PYTHONPATH', '')}"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    shared = tmp_path_factory.mktemp("shared")
    session = (
        SparkSession.builder.master("local[4]").appName("tests").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", f"file://{shared}").config("spark.driver.memory", "6g")
        .config("spark.sql.warehouse.dir", str(shared / "warehouse")).getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


def same_rows(rows, columns, other, other_columns) -> bool:
    """Equal sets of rows with columns sorted by name; floats to 9 places."""

    def norm(v):
        if isinstance(v, float):
            return repr(round(v, 9) + 0.0)
        if hasattr(v, "asDict"):
            return [norm(x) for x in v]
        if isinstance(v, dict):
            return [norm(x) for x in v.values()]
        if isinstance(v, (list, tuple)):
            return [norm(x) for x in v]
        return str(v)

    def prepared(rs, cs):
        order = sorted(range(len(cs)), key=lambda i: cs[i])
        return sorted(str([norm(r[i]) for i in order]) for r in rs)

    return sorted(columns) == sorted(other_columns) and prepared(rows, columns) == prepared(other, other_columns)
