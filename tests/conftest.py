import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
TINY, SMALL = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
    at = tmp_path_factory.mktemp("spark")
    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.local.dir", str(at)).getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    def connect(sf_dir):
        con = duckdb.connect()
        for p in Path(sf_dir).glob("*.parquet"):
            con.sql(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
        return con

    return connect


def values(rows, columns):
    """Rows as sorted tuples, with numbers rounded: equal whichever engine made them."""

    def plain(v):
        if v is None or v != v:
            return "null"
        if isinstance(v, bool) or type(v).__name__ == "bool":
            return str(bool(v))
        try:
            return repr(round(float(v), 5) + 0.0)
        except (TypeError, ValueError):
            return str(v)

    return sorted(tuple(plain(r[c]) for c in columns) for r in rows)


def same(a, b) -> bool:
    """Whether two results of values() agree, numbers within 2e-5."""

    def close(x, y):
        try:
            return x == y or abs(float(x) - float(y)) <= 2e-5
        except ValueError:
            return False

    return len(a) == len(b) and all(all(map(close, r, s)) for r, s in zip(a, b, strict=True))
