"""Ledgers and merged graphs."""

from __future__ import annotations

from pyspark.sql import functions as F

from flowrings.operators import drilldown, graph
from flowrings.queries.common import EVENT_HOURS, EVENT_WEEK, MERGE, RELAY, TRADE_YEAR, event_sql, relay_sql, shown, trade_sql
from flowrings.scratch import materialize, scratch_path
from flowrings.sources import ledger

_EDGES = "SELECT src, dst, CAST(money AS DOUBLE) AS money, times, round(t, 6) AS t FROM e"


def stream_windows_event(spark, sf_dir):
    """Daily graphs of the week's events, read as a stream; days whose end the watermark has passed."""
    from flowrings import streaming

    path = scratch_path(spark, "event-stream")
    ledger.event(spark, sf_dir, EVENT_WEEK).repartition(1).sortWithinPartitions("ts").write.parquet(path)
    edges = streaming.windowed_edges(streaming.read_stream(spark, path), "1 day", lateness="1 hour")
    out = scratch_path(spark, "closed-windows")
    spark.createDataFrame([], "day string, src bigint, dst bigint, money double, times bigint").write.parquet(out)

    def keep(batch, _):
        batch.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "src", "dst", F.col("money").cast("double").alias("money"), "times").write.mode("append").parquet(out)

    streaming.detect_on_close(edges, keep, scratch_path(spark, "stream-checkpoint")).awaitTermination()
    return spark.read.schema("day string, src bigint, dst bigint, money double, times bigint").parquet(out).groupBy("day").agg(
        F.count(F.lit(1)).alias("edges"), F.sum("times").alias("transfers"), F.round(F.sum("money"), 2).alias("money")
    )


def _hops(spark, sf_dir):
    rows = materialize(ledger.event(spark, sf_dir, EVENT_WEEK), "events")
    return shown(drilldown.hop_pairs(rows, 3600.0))


QUERIES = {
    "merge_relay": lambda s, d: shown(graph.merge_transfers(ledger.relay(s, d, RELAY))),
    "merge_trade": lambda s, d: shown(graph.merge_transfers(ledger.trade(s, d, TRADE_YEAR))),
    "merge_event": lambda s, d: shown(graph.merge_transfers(ledger.event(s, d, EVENT_WEEK)), 3),
    "profile_relay": lambda s, d: shown(graph.vertex_profile(graph.merge_transfers(ledger.relay(s, d, RELAY)))),
    "profile_event": lambda s, d: shown(graph.vertex_profile(graph.merge_transfers(ledger.event(s, d, EVENT_HOURS))), 3),
    "counterparties_event": lambda s, d: drilldown.counterparties(graph.merge_transfers(ledger.event(s, d, EVENT_WEEK))),
    "hops_event": _hops,
    "bursts_event": lambda s, d: shown(drilldown.burst_profile(ledger.event(s, d, EVENT_WEEK), 6.0)),
    "stream_windows_event": stream_windows_event,
    "threads_conversations": lambda s, d: ledger.threads(s, d).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")),
    "similarity_embeddings": lambda s, d: ledger.similarity(s, d, 10, 100).groupBy("src").agg(F.count(F.lit(1)).alias("n"), F.round(F.min("w"), 4).alias("least")),
    "hyperlinks_pages": lambda s, d: ledger.hyperlinks(s, d).agg(F.count(F.lit(1)).alias("edges"), F.sum("times").alias("links")),
}

_NODES = """
nd AS (SELECT v, count(*) AS deg, count(*) FILTER (i = 1) AS deg_in, count(*) FILTER (i = 0) AS deg_out, CAST(sum(money) AS DOUBLE) AS money, CAST(sum(times) AS BIGINT) AS times,
       round(sum(t * times) FILTER (i = 1) / sum(times) FILTER (i = 1), {n}) AS t_in, round(sum(t * times) FILTER (i = 0) / sum(times) FILTER (i = 0), {n}) AS t_out
       FROM (SELECT src AS v, 0 AS i, * FROM e UNION ALL SELECT dst, 1, * FROM e) GROUP BY 1)"""

ORACLES = {
    "merge_relay": f"WITH {relay_sql()} {_EDGES}",
    "merge_trade": f"WITH {trade_sql(TRADE_YEAR)} {_EDGES}",
    "merge_event": f"WITH {event_sql(EVENT_WEEK)} {_EDGES.replace('round(t, 6)', 'round(t, 3)')}",
    "profile_relay": f"WITH {relay_sql()}, {_NODES.format(n=6)} SELECT * FROM nd",
    "profile_event": f"WITH {event_sql(EVENT_HOURS)}, {_NODES.format(n=3)} SELECT * FROM nd",
    "counterparties_event": f"WITH {event_sql(EVENT_WEEK)} SELECT v, count(DISTINCT u) AS n FROM (SELECT src AS v, dst AS u FROM e UNION ALL SELECT dst, src FROM e) GROUP BY 1",
    "hops_event": f"""WITH {event_sql(EVENT_WEEK)} SELECT a.dst AS account, a.tx_id AS in_tx, b.tx_id AS out_tx, round(b.t_sec - a.t_sec, 6) AS gap
        FROM tr a JOIN tr b ON a.dst = b.src WHERE b.t_sec - a.t_sec BETWEEN 0 AND 3600""",
    "bursts_event": f"""WITH {event_sql(EVENT_WEEK)} SELECT src, tx_id, round(t_sec, 6) AS t_sec, CAST(sum(amount) OVER w AS DOUBLE) AS volume, count(*) OVER w AS n FROM tr
        WINDOW w AS (PARTITION BY src ORDER BY CAST(floor(t_sec) AS BIGINT) RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW)""",
    "stream_windows_event": f"""WITH {event_sql(EVENT_WEEK).replace(MERGE, "x AS (SELECT 1)")},
        m AS (SELECT strftime(ts, '%Y-%m-%d') AS day, src, dst, sum(amount) AS money, count(*) AS times FROM tr GROUP BY 1, 2, 3)
        SELECT day, count(*) AS edges, CAST(sum(times) AS BIGINT) AS transfers, round(CAST(sum(money) AS DOUBLE), 2) AS money FROM m
        WHERE CAST(day AS TIMESTAMP) + INTERVAL 1 DAY <= (SELECT max(ts) FROM tr) - INTERVAL 1 HOUR GROUP BY 1""",
    "threads_conversations": """SELECT src, dst, count(*) AS n FROM (SELECT role AS src, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations)
        WHERE dst IS NOT NULL GROUP BY 1, 2""",
    "hyperlinks_pages": r"""WITH l AS (SELECT regexp_extract(url, '//([^/?#:]+)', 1) AS host, unnest(regexp_extract_all(html, 'href="([^"#?]+)', 1)) AS target FROM pages),
        g AS (SELECT host, target, count(*) AS n FROM l GROUP BY 1, 2) SELECT count(*) AS edges, CAST(sum(n) AS BIGINT) AS links FROM g""",
    "similarity_embeddings": """WITH p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) AS w
        FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 100 = 0),
        r AS (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM p) SELECT src, count(*) AS n, round(min(w), 4) AS least FROM r WHERE r <= 10 GROUP BY 1""",
}
