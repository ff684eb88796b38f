"""Streams give what the batch forms give."""

from pyspark.sql import functions as F

from turnwise.sources.io import table
from turnwise.streaming import live


def _stream(spark, small, tmp_path):
    src = str(tmp_path / "events")
    table(spark, small, "events").repartition(1).write.parquet(src)
    return live.acts(spark.readStream.schema(spark.read.parquet(src).schema).parquet(src))


def _run(df, name, mode, tmp_path):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    q.stop()


def test_closed_sessions_equal_batch(spark, small, tmp_path):
    s = live.session_runs(_stream(spark, small, tmp_path), watermark="1 hour")
    _run(s, "sessions", "append", tmp_path)
    batch = live.session_runs(live.acts(table(spark, small, "events")))
    got = spark.table("sessions")
    assert got.exceptAll(batch).isEmpty() and 0 < got.count() <= batch.count()


def test_run_machine_equals_batch(spark, small, tmp_path):
    _run(live.live_runs(_stream(spark, small, tmp_path)), "runs", "update", tmp_path)
    got = {r.run_id: r for r in spark.table("runs").collect()}
    rows = {}
    for r in live.acts(table(spark, small, "events")).orderBy("ts", "event_id").collect():
        rows.setdefault(r.run_id, []).append(r.act)
    for run, acts in rows.items():
        acts = acts[: acts.index("END")] if "END" in acts else acts
        sql = [i for i, a in enumerate(acts) if a == "SQL"]
        want = (acts.count("ASK"), len(sql), sum(1 for i, a in enumerate(acts) if a == "DRIFT" and sql and i > sql[0]), acts.count("BROKEN"))
        assert (got[run].asks, got[run].n_sql, got[run].drifts, got[run].broken) == want


def test_sinks(spark, tmp_path):
    write = live.upsert(str(tmp_path / "out"))
    df = spark.createDataFrame([(1, 5), (2, 6)], "run_id int, x int")
    write(df, 0)
    write(df.withColumn("x", F.col("x") + 1), 1)
    write(df.withColumn("x", F.col("x") + 1), 1)  # a repeated batch
    got = {r.run_id: r.x for r in live.latest(spark.read.parquet(str(tmp_path / "out"))).collect()}
    assert got == {1: 6, 2: 7}
