"""The same ledger as a stream: graphs per window, bursts, running profiles, hops, detection on closed windows."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from flowrings.schema import TRANSFER


def read_stream(spark: SparkSession, path: str, fmt: str = "parquet", files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.format(fmt).schema(TRANSFER)
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).load(path)


def rate_stream(spark: SparkSession, rows_per_batch: int = 1000, accounts: int = 1000, seed: int = 1) -> DataFrame:
    """Generated transfers between hashed accounts, a fixed number of rows a batch: for tests and load trials."""
    rows = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).option("startTimestamp", 0).load()
    pick = lambda salt: F.pmod(F.xxhash64("value", F.lit(seed), F.lit(salt)), F.lit(accounts))
    ts = F.col("timestamp")
    return rows.select(
        pick("src").alias("src"), pick("dst").alias("dst"), (F.lit(1) + pick("amount")).cast("decimal(18,2)").alias("amount"), (F.unix_micros(ts) / 1e6).alias("t_sec"),
        ts.alias("ts"), F.to_date(ts).alias("day"), F.col("value").alias("tx_id"),
    )


def windowed_edges(stream: DataFrame, period: str = "7 days", step: str | None = None, lateness: str = "1 day") -> DataFrame:
    """Merged edges per tumbling window, or per sliding one with ``step``; rows later than ``lateness`` are dropped.

    t is the mean time since the window's start.
    """
    w = F.window("ts", period, step) if step else F.window("ts", period)
    own = stream.filter("src <> dst").withWatermark("ts", lateness)
    merged = own.groupBy(w.alias("window"), "src", "dst").agg(
        F.sum("amount").cast("decimal(28,2)").alias("money"), F.count(F.lit(1)).alias("times"), F.avg(F.unix_micros("ts") / 1e6).alias("at")
    )
    return merged.select("window", "src", "dst", "money", "times", (F.col("at") - F.unix_micros("window.start") / 1e6).alias("t"))


def account_sessions(stream: DataFrame, gap: str = "6 hours", lateness: str = "1 day") -> DataFrame:
    """Bursts of each payer: transfers with no pause longer than ``gap``."""
    s = F.session_window("ts", gap)
    return stream.withWatermark("ts", lateness).groupBy(s.alias("session"), "src").agg(F.count(F.lit(1)).alias("n"), F.sum("amount").cast("decimal(28,2)").alias("money"))


def deduplicated(stream: DataFrame, lateness: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["tx_id"])


def with_accounts(stream: DataFrame, accounts: DataFrame, key: str = "src") -> DataFrame:
    """Attributes of the account (v, ...) at each transfer: a join with a static table."""
    return stream.join(accounts.withColumnRenamed("v", key), key, "left")


def hops(incoming: DataFrame, outgoing: DataFrame, within: str = "1 hour", lateness: str = "1 day") -> DataFrame:
    """Money passed on: transfers in and out of one account within a time band, both sides streams."""
    got = incoming.withWatermark("ts", lateness).select(F.col("dst").alias("account"), F.col("ts").alias("got_at"), F.col("tx_id").alias("in_tx"))
    sent = outgoing.withWatermark("ts", lateness).select(F.col("src").alias("payer"), F.col("ts").alias("sent_at"), F.col("tx_id").alias("out_tx"))
    band = (F.col("account") == F.col("payer")) & (F.col("sent_at") >= F.col("got_at")) & (F.col("sent_at") <= F.col("got_at") + F.expr(f"INTERVAL {within}"))
    return got.join(sent, band).select("account", "in_tx", "out_tx", "got_at", "sent_at")


def running_profiles(stream: DataFrame, lateness: str = "1 day", idle_seconds: int = 30 * 86_400) -> DataFrame:
    """(v, n_in, n_out, money_in, money_out, last_t): each account's totals so far, updated with every batch.

    The totals of an account are dropped once the watermark is ``idle_seconds`` past its last transfer, so the
    state holds the accounts of that time only; an account that comes back starts anew.
    """
    ends = stream.withWatermark("ts", lateness).select(F.explode(F.array(F.struct(F.col("dst").alias("v"), F.lit(1).alias("into")), F.struct(F.col("src").alias("v"), F.lit(0).alias("into")))).alias("x"), "amount", "t_sec", "ts")
    ends = ends.select("x.v", "x.into", F.col("amount").cast("double").alias("amount"), "t_sec", "ts", F.unix_millis("ts").alias("ms"))

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n_in, n_out, m_in, m_out, last, ms = state.get if state.exists else (0, 0, 0.0, 0.0, 0.0, 0)
        for part in parts:
            into = part["into"] == 1
            n_in, n_out = n_in + int(into.sum()), n_out + int((~into).sum())
            m_in, m_out = m_in + float(part.amount[into].sum()), m_out + float(part.amount[~into].sum())
            last, ms = max(last, float(part.t_sec.max())), max(ms, int(part.ms.max()))
        state.update((n_in, n_out, m_in, m_out, last, ms))
        state.setTimeoutTimestamp(max(ms + idle_seconds * 1000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"v": [key[0]], "n_in": [n_in], "n_out": [n_out], "money_in": [m_in], "money_out": [m_out], "last_t": [last]})

    fields = "n_in bigint, n_out bigint, money_in double, money_out double, last_t double"
    return ends.groupBy("v").applyInPandasWithState(update, f"v bigint, {fields}", f"{fields}, ms bigint", "update", GroupStateTimeout.EventTimeTimeout)


def detect_on_close(edges: DataFrame, detect: Callable[[DataFrame, int], None], checkpoint: str):
    """Hand every batch of closed windows' edges (append mode) to ``detect(edges, batch_id)``; returns the query."""
    return edges.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(detect).trigger(availableNow=True).start()
