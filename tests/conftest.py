import os
import sys
from pathlib import Path

import pytest

ROOT = str(Path(__file__).resolve().parent.parent)
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, os.environ.get("PYTHONPATH", "")])


@pytest.fixture(scope="session")
def spark():
    from framepatterns import session

    s = session.start("local[4]", "tests", **{"spark.sql.shuffle.partitions": "4", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.driver.memory": "4g", "spark.sql.adaptive.coalescePartitions.enabled": "true"})
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def duck(sf):
    import duckdb

    con = duckdb.connect()
    for f in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM read_parquet('{f}')")
    return con


@pytest.fixture(scope="session")
def same_as_sql(spark, sf, duck):
    """Whether a registered query's rows equal its SQL twin's, in any order."""

    def check(query, sql):
        df = query(spark, sf)
        cols = df.columns
        mine = sorted(repr(tuple(r)) for r in df.collect())
        res = duck.execute(sql)
        names = [x[0] for x in res.description]
        assert sorted(names) == sorted(cols)
        at = [names.index(c) for c in cols]
        theirs = sorted(repr(tuple(r[i] for i in at)) for r in res.fetchall())
        assert mine == theirs

    return check
