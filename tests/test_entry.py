"""The driver contract, and each workload against its SQL at the smallest size."""

import duckdb
import pytest

import __spark_entry__
from turnwise.sources.io import NAMES

PLAIN = {k for w in __spark_entry__.WORKLOADS for k in w.ORACLES}


def cell(v):
    return None if v is None or v != v else round(float(v), 6) if isinstance(v, float) or type(v).__name__ == "Decimal" else v


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    for n in NAMES:
        c.execute(f"create view {n} as select * from read_parquet('{small}/{n}.parquet')")
    return c


def test_entry(spark):
    assert {r.subtype for r in __spark_entry__.entry(spark).collect()} <= {"not_drift", "value", "constraint", "projection", "reject"}


@pytest.mark.parametrize("name", sorted(PLAIN))
def test_equals_sql(spark, small, con, name):
    df = __spark_entry__.queries()[name](spark, small)
    cols = sorted(df.columns)
    got = sorted(str([cell(r[c]) for c in cols]) for r in df.collect())
    res = con.execute(__spark_entry__.oracle_sql()[name])
    names = [d[0] for d in res.description]
    assert sorted(names) == cols
    want = sorted(str([cell(r[names.index(c)]) for c in cols]) for r in res.fetchall())
    assert got == want
