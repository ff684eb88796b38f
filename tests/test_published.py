"""The audit reads given tables, and the same arithmetic holds for the figures of the paper."""

from pyspark.sql import functions as F

from turnwise.plans import published


def test_audit_reads_given_tables(spark, small):
    audited = published.published_audit(spark, small)
    files = {f.rsplit("/", 1)[-1] for f in audited.inputFiles()}
    assert {"lineitem.parquet", "orders.parquet", "customer.parquet"} <= files
    checks = {r.check: r for r in audited.collect()}
    assert len(checks) == 17 and all(r.ok for r in checks.values())


def test_audit_finds_a_wrong_figure(spark, small):
    right = published.accuracy(spark, small).localCheckpoint()
    wrong = right.withColumn("t_d", F.col("t_d") - F.when(F.col("agent") == "steady", 30).otherwise(0))
    n = right.count()
    assert {r.check: r.computed for r in published.audit(right).collect()}["weighted"] == n
    assert {r.check: r.computed for r in published.audit(wrong).collect()}["weighted"] == n - 1


def test_figures_of_the_paper(spark):
    cells = ["c", "dv", "dc", "dp", "d", "jv", "jc", "jp", "j"]
    sizes = dict(zip("vcp", published.SIZES, strict=True))
    rows = [(agent, *[round(10 * x) for x in figures]) for agent, *figures in published.ACCURACY]
    t = spark.createDataFrame(rows, "agent string, " + ", ".join(f"t_{c} long" for c in cells))
    t = t.select("*", *[F.lit(sizes[c[1]] if len(c) == 2 else sum(sizes.values())).alias(f"n_{c}") for c in cells])
    t = t.select("*", *[(F.col(f"t_{c}") * F.col(f"n_{c}") / 1000).alias(f"k_{c}") for c in cells])
    got = {r.check: round(r.computed, 1) for r in published.audit(t).collect()}
    assert got == {"ordered": 12.0, "weighted": 12.0, "drop_min": 13.2, "drop_max": 17.9, "excess_min": 9.8, "excess_max": 13.4, "spread_c": 10.0, "spread_d": 8.5, "spread_j": 8.5}
    assert all(round(100 * kept / entered, 1) == rate for _, entered, kept, rate in published.FUNNEL)
    assert all(abs(sum(parts) / 3 - whole) < 0.06 for parts, whole in published.AUDIT.values())
