import os
import sys

os.environ.setdefault("OMP_NUM_THREADS", "1")
sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

import pytest  # noqa: E402

from meshprofile.session import local_session  # noqa: E402

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    s = local_session("4", 4)
    s.sparkContext.setLogLevel("ERROR")
    s.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("shared")))
    return s


@pytest.fixture(scope="session")
def sf():
    return SF


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for t in os.listdir(SF):
        c.execute(f"create view {t.removesuffix('.parquet')} as select * from '{SF}/{t}'")
    return c


def same(spark_df, relation):
    """Both results as sorted rows of plain values."""

    def rows(frame):
        cols = sorted(frame.columns)
        return sorted(tuple("" if v is None or v != v else (repr(float(v) + 0.0) if isinstance(v, float) else str(v)) for v in r) for r in frame[cols].itertuples(index=False))

    a, b = spark_df.toPandas(), relation.fetchdf()
    assert sorted(a.columns) == sorted(b.columns)
    assert rows(a) == rows(b)
