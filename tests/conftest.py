import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .config("spark.checkpoint.dir", "file://" + str(tmp_path_factory.mktemp("shared")))
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    from probgraph.runtime import ship

    ship(s)
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return SF


def duck(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    for p in sorted(Path(sf_dir).glob("*.parquet")):
        con.execute(f"create view {p.stem} as select * from read_parquet('{p}/*.parquet')" if p.is_dir() else f"create view {p.stem} as select * from read_parquet('{p}')")
    return con


def rows(df) -> list[tuple]:
    """Rows in column-name order, numbers rounded (whole ones alike, whatever their type), sorted."""
    import pandas as pd

    pdf = df if isinstance(df, pd.DataFrame) else df.toPandas()
    pdf = pdf[sorted(pdf.columns)]

    def one(v):
        if v is None or v is pd.NA or v is pd.NaT or isinstance(v, float) and v != v:
            return "null"
        if isinstance(v, float):
            v = round(v, 6)
            return str(int(v)) if v == int(v) else repr(float(v))
        return str(v)

    return sorted(tuple(one(v) for v in r) for r in pdf.itertuples(index=False, name=None))
