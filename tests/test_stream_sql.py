"""Streams against batches, SQL access, readers."""

import time

import pytest
from pyspark.sql import functions as F

from flowrings import streaming
from flowrings.operators import graph
from flowrings.params import LouvainParams, Period, ScreenParams
from flowrings.plans.pipeline import Settings
from flowrings.plans.sql import register
from flowrings.sources import ledger
from flowrings.sources.planted import planted

PERIOD = Period("2024-01-01", "2024-01-08")


@pytest.fixture(scope="module")
def rows(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("ledger") / "t")
    planted(spark, PERIOD, accounts=60, noise=300, rings=2).coalesce(1).write.parquet(path)
    return path


def finish(query):
    query.awaitTermination(120)


def test_windows_match_batch(spark, rows, tmp_path):
    got = []
    edges = streaming.windowed_edges(streaming.read_stream(spark, rows), "1 day", lateness="1 hour")
    finish(streaming.detect_on_close(edges, lambda df, n: got.extend(df.collect()), str(tmp_path / "c")))
    table = ledger.read_transfers(spark, rows)
    last = table.agg(F.max("ts")).first()[0]
    closed = {r.window.start for r in got}
    assert closed and all(r.window.end <= last for r in got)
    day = min(closed)
    batch = graph.merge_transfers(table.filter(F.to_date("ts") == F.lit(day.date())))
    assert {(r.src, r.dst, r.money, r.times) for r in got if r.window.start == day} == {(r.src, r.dst, r.money, r.times) for r in batch.collect()}


@pytest.mark.parametrize("make", [streaming.account_sessions, streaming.deduplicated, lambda s: streaming.hops(s, s)])
def test_other_streams_run(spark, rows, tmp_path, make):
    seen = []
    q = make(streaming.read_stream(spark, rows)).writeStream.outputMode("append").option("checkpointLocation", str(tmp_path)).foreachBatch(lambda df, n: seen.append(df.count())).trigger(availableNow=True).start()
    finish(q)
    assert sum(seen) > 0


def test_running_profiles(spark, rows, tmp_path):
    seen = []
    q = streaming.running_profiles(streaming.read_stream(spark, rows)).writeStream.outputMode("update").option("checkpointLocation", str(tmp_path)).foreachBatch(lambda df, n: seen.extend(df.collect())).trigger(availableNow=True).start()
    finish(q)
    table = ledger.read_transfers(spark, rows)
    assert sum(r.n_in for r in seen) == table.count() == sum(r.n_out for r in seen)


def test_idle_accounts_leave_the_state(spark, tmp_path):
    """An account that comes back after the idle time starts anew; one that stays keeps its totals."""
    rows = [(0, 1, "2024-01-01"), (0, 1, "2024-01-02"), (5, 6, "2024-03-01"), (5, 6, "2024-03-02"), (0, 1, "2024-03-03"), (5, 6, "2024-03-03")]
    for i, (a, b, day) in enumerate(rows):
        spark.createDataFrame([(a, b, 1.0, float(i), day, i)], "src long, dst long, amount double, t_sec double, d string, tx_id long").selectExpr(
            "src", "dst", "cast(amount as decimal(18,2)) amount", "t_sec", "cast(d as timestamp) ts", "cast(d as date) day", "tx_id").coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / f"f{i:02d}"))
    seen = []
    stream = streaming.read_stream(spark, str(tmp_path / "in" / "*"), files_per_batch=1)
    q = streaming.running_profiles(stream, "1 hour", 5 * 86_400).writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "c")).foreachBatch(lambda df, n: seen.extend(df.collect())).trigger(availableNow=True).start()
    finish(q)
    out = {v: [r.n_out for r in seen if r.v == v] for v in (0, 5)}
    assert out == {0: [1, 2, 1], 5: [1, 2, 3]}


def test_generated_stream(spark, tmp_path):
    seen = []
    q = streaming.windowed_edges(streaming.rate_stream(spark, 50, 20), "1 day").writeStream.outputMode("update").option("checkpointLocation", str(tmp_path)).foreachBatch(lambda df, n: seen.append(df.count())).start()
    try:
        for _ in range(120):
            if sum(seen) > 0:
                break
            time.sleep(0.5)
    finally:
        q.stop()
    assert sum(seen) > 0


def test_period_and_sinks(spark, tmp_path):
    rows = planted(spark, PERIOD, accounts=60, noise=300, rings=2)
    part = Period("2024-01-03", "2024-01-05")
    kept = ledger.in_period(rows, part)
    want = rows.filter("ts >= '2024-01-03' AND ts < '2024-01-05'")
    assert 0 < kept.count() == want.count() < rows.count()
    assert kept.agg(F.min("t_sec") >= 0, F.max("t_sec") < 2 * 86_400).first()[:] == (True, True)
    merged = graph.merge_transfers(rows)
    spark.sql("DROP TABLE IF EXISTS edges_test")
    ledger.write_edges(merged, "edges_test", 4)
    try:
        table = spark.table("edges_test")
        assert table.count() == merged.count()
        plan = table.groupBy("src").count()._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
    finally:
        spark.sql("DROP TABLE edges_test")
    ledger.write_results(merged.withColumn("level", F.col("src") % 3), str(tmp_path / "out"), "level")
    assert sorted(p.name for p in (tmp_path / "out").iterdir() if p.is_dir()) == ["level=0", "level=1", "level=2"]
    assert spark.read.parquet(str(tmp_path / "out")).count() == merged.count()


def test_sql_views_and_functions(spark, rows):
    table = ledger.read_transfers(spark, rows)
    register(spark, table, PERIOD, Settings(screen=ScreenParams(2, 5000, 1, 0), louvain=LouvainParams(strategy="local")))
    n = spark.sql("SELECT count(*) FROM communities").first()[0]
    assert n > 0 and spark.sql("SELECT entropy_bits(array(2, 1, 1))").first()[0] == 1.5
    assert spark.sql("SELECT entropy_of(x) FROM VALUES (1), (1), (2), (3) AS t(x)").first()[0] == 1.5
    levels = spark.sql("SELECT * FROM louvain_levels(TABLE(SELECT mcs, src, dst, w_e FROM edges) PARTITION BY mcs)")
    assert levels.select("v").distinct().count() == n


def test_csv_reader(spark, tmp_path):
    spark.createDataFrame([(1, 2, 5.5, 0.0, "2024-01-01 00:00:00", "2024-01-01", 7)], "a long, dst long, amount double, t_sec double, ts string, day string, tx_id long").write.option("header", True).csv(str(tmp_path / "x"))
    got = ledger.read_transfers(spark, str(tmp_path / "x"), "csv", {"src": "a"}, "a long, dst long, amount decimal(18,2), t_sec double, ts timestamp, day date, tx_id long").first()
    assert (got.src, got.dst, float(got.amount)) == (1, 2, 5.5)
    bad = spark.createDataFrame([(1, None, 5.0, None)], "src long, dst long, amount double, ts timestamp")
    assert ledger.rejected(bad, src=F.col("src"), dst=F.col("dst"), amount=F.col("amount"), ts="ts").first().reason == "dst,ts"
