import os
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "4")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf_dir():
    return SF


@pytest.fixture(scope="session")
def duck(sf_dir):
    import duckdb

    c = duckdb.connect()
    for f in sorted(Path(sf_dir).glob("*.parquet")):
        c.sql(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    return c


@pytest.fixture(scope="session")
def same():
    """Rows of a Spark result and of a DuckDB result, in any order, with numbers as doubles."""

    def rows(pdf):
        cols = sorted(pdf.columns)
        out = []
        for r in pdf[cols].astype(object).where(pdf[cols].notna(), None).itertuples(index=False):
            out.append(tuple(float(x) if isinstance(x, (int, float)) and not isinstance(x, bool) or type(x).__module__ == "numpy" and not hasattr(x, "isoformat") and str(x) not in ("True", "False") else (None if x is None else str(x)) for x in r))
        return cols, sorted(out, key=repr)

    def check(df, relation):
        got, want = rows(df.toPandas()), rows(relation.df())
        assert got[0] == want[0]
        assert len(got[1]) == len(want[1])
        assert got[1] == want[1]

    return check
