"""Plans on tables that are cut into several ranges, and the size of what the driver has to describe."""

import duckdb
import pytest

from turnwise.plans import construction, panels


@pytest.fixture()
def many_ranges(spark):
    """Ranges of a few kB stay apart, as they do on large tables."""
    names = ("spark.sql.adaptive.advisoryPartitionSizeInBytes", "spark.sql.adaptive.coalescePartitions.minPartitionSize", "spark.sql.shuffle.partitions")
    before = {n: spark.conf.get(n) for n in names}
    for n, v in zip(names, ("1k", "1k", "200"), strict=True):
        spark.conf.set(n, v)
    yield
    for n, v in before.items():
        spark.conf.set(n, v)


def test_next_part_across_ranges(spark, small, tmp_path, many_ranges):
    con = duckdb.connect()
    con.execute(f"COPY (SELECT * REPLACE (p_partkey + 1000 * i AS p_partkey) FROM '{small}/part.parquet', range(100) t(i) ORDER BY p_partkey) TO '{tmp_path}/part.parquet' (ROW_GROUP_SIZE 2048)")
    con.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet'")
    for name in ("chain_qualified", "chain_verdict"):
        got = panels.QUERIES[name](spark, str(tmp_path))
        want = con.execute(panels.ORACLES[name])
        columns = [d[0] for d in want.description]
        assert sorted(map(tuple, got.select(*columns).collect())) == sorted(want.fetchall())


def test_parts_without_key_or_name(spark, tmp_path):
    con = duckdb.connect()
    con.execute(f"COPY (SELECT * FROM (VALUES (2, 'b c'), (NULL, 'c d'), (1, 'a b'), (3, NULL), (4, 'd e')) t(p_partkey, p_name)) TO '{tmp_path}/part.parquet'")
    rows = panels.chain_qualified(spark, str(tmp_path)).collect()
    assert {(r.part_key, r.verdict) for r in rows if r.part_key in (1, 2, 4)} == {(1, "transformed"), (4, "transformed")}  # 2: the next part has no name


@pytest.mark.parametrize("name", ["triplets", "triplet_violations", "audit_sample"])
def test_plans_of_construction_are_short(spark, small, name):
    """The driver describes every plan again at each of its steps: what is cut off must not be told again."""
    plan = construction.QUERIES[name](spark, small)._jdf.queryExecution().toString()
    assert len(plan) < 300_000
