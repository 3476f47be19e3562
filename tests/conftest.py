import os
import sys

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        path = f"{SF}/{t}.parquet"
        con.sql(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def plain(rows):
    """Rows as a sorted list of comparable tuples, columns by name; floats to 9 digits."""
    def one(v):
        if isinstance(v, float):
            return f"{v:.9g}"
        return str(v)

    return sorted(tuple(one(r[c]) for c in sorted(r)) for r in rows)


@pytest.fixture(scope="session")
def same(spark, duck):
    def check(query, sql, sf=SF):
        import warnings

        with warnings.catch_warnings():
            warnings.simplefilter("ignore")
            got = [r.asDict() for r in query(spark, sf).collect()]
            rel = duck.sql(sql)
            want = [dict(zip(rel.columns, r)) for r in rel.fetchall()]
        assert plain(got) == plain(want)

    return check
