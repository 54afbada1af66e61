import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    from stationlink.plans.shipping import ship

    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    ship(session)
    return session


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for f in Path(SMALL).glob("*.parquet"):
        c.sql(f"create view {f.stem} as select * from '{f}'")
    return c


def rows_of(frame):
    """Sorted rows with columns by name; floats to 9 digits."""
    names = sorted(frame.columns)
    plain = lambda x: None if x is None or x != x else round(float(x), 9) if isinstance(x, float) else str(x)
    return sorted(([plain(r[n]) for n in names] for r in frame.to_dict("records")), key=repr)


@pytest.fixture(scope="session")
def same(spark, duck):
    def check(name, query, sql):
        import pandas as pd

        a, b = query(spark, SMALL).toPandas(), duck.sql(sql).df()
        a, b = (x.astype(object).where(pd.notna(x), None) for x in (a, b))
        for x in (a, b):
            for c in x.columns:
                x[c] = [float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v for v in x[c]]
        assert sorted(a.columns) == sorted(b.columns), name
        assert rows_of(a) == rows_of(b), name

    return check
