"""Transfer ledgers: adapters from tables to (src, dst, amount, t_sec, ts, day, tx_id)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from flowrings.params import Period
from flowrings.schema import TRANSFER, require_columns

MONEY = "decimal(18,2)"


def _within(ts: str, period: Period) -> Column:
    """A predicate on a zoneless timestamp column that reaches the scan."""
    return (F.col(ts) >= F.lit(period.start).cast("timestamp_ntz")) & (F.col(ts) < F.lit(period.end).cast("timestamp_ntz"))


def _seconds(ts: Column, period: Period) -> Column:
    """Seconds since the period began: small numbers, whose sums stay exact."""
    start = F.lit(period.start).cast("timestamp_ntz").cast("timestamp")
    return (F.unix_micros(ts) - F.unix_micros(start)) / F.lit(1e6)


def transfers(df: DataFrame, period: Period, *, src: Column, dst: Column, amount: Column, ts: str, tx_id: Column) -> DataFrame:
    """Map any table to transfers.  Rows without payer, payee, amount or time are left out (see ``rejected``)."""
    at = F.col(ts).cast("timestamp")
    out = df.select(
        src.cast("bigint").alias("src"), dst.cast("bigint").alias("dst"), amount.cast(MONEY).alias("amount"), _seconds(at, period).alias("t_sec"),
        at.alias("ts"), F.to_date(at).alias("day"), tx_id.cast("bigint").alias("tx_id"),
    )
    return out.dropna(subset=["src", "dst", "amount", "ts"])


def rejected(df: DataFrame, *, src: Column, dst: Column, amount: Column, ts: str) -> DataFrame:
    """The rows that ``transfers`` leaves out, with the reason."""
    reason = F.concat_ws(",", *(F.when(c.isNull(), n) for n, c in (("src", src), ("dst", dst), ("amount", amount), ("ts", F.col(ts)))))
    return df.withColumn("reason", reason).filter(F.col("reason") != "")


def in_period(ledger: DataFrame, period: Period) -> DataFrame:
    """Transfers of the period; t_sec is counted from its start anew."""
    require_columns(ledger, "ts", "day")
    lo, hi = F.lit(period.start).cast("timestamp"), F.lit(period.end).cast("timestamp")
    kept = ledger.filter((F.col("day") >= F.to_date(lo)) & (F.col("day") <= F.to_date(hi)) & (F.col("ts") >= lo) & (F.col("ts") < hi))
    return kept.withColumn("t_sec", (F.unix_micros("ts") - F.unix_micros(lo)) / F.lit(1e6))


def relay(spark: SparkSession, sf_dir: str, period: Period) -> DataFrame:
    """Hand-overs of a part between customers: each order of a part pays on to the next one's customer."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").filter(_within("l_shipdate", period)).select(
        "l_partkey", "l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", "l_shipdate"
    )
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey")
    turn = Window.partitionBy("l_partkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice")
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey).withColumn("payee", F.lead("o_custkey").over(turn))
    found = transfers(
        rows, period, src=F.col("o_custkey"), dst=F.col("payee"), amount=F.col("l_extendedprice"), ts="l_shipdate",
        tx_id=F.col("l_orderkey") * 10 + F.col("l_linenumber"),
    )
    return found.filter("src <> dst")


def trade(spark: SparkSession, sf_dir: str, period: Period) -> DataFrame:
    """Customers (even ids) pay suppliers (odd ids); returned goods are paid back."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").filter(_within("l_shipdate", period)).select(
        "l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", "l_discount", "l_returnflag", "l_shipdate"
    )
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey")
    buyer, seller = F.col("o_custkey") * 2, F.col("l_suppkey") * 2 + 1
    back = F.col("l_returnflag") == "R"
    amount = F.round(F.col("l_extendedprice").cast("decimal(14,2)") * (F.lit(1).cast("decimal(4,2)") - F.col("l_discount").cast("decimal(4,2)")), 2)
    return transfers(
        lines.join(orders, lines.l_orderkey == orders.o_orderkey), period, src=F.when(back, seller).otherwise(buyer),
        dst=F.when(back, buyer).otherwise(seller), amount=amount, ts="l_shipdate", tx_id=F.col("l_orderkey") * 10 + F.col("l_linenumber"),
    )


def event(spark: SparkSession, sf_dir: str, period: Period) -> DataFrame:
    """Events as transfers from the user to the account in the properties."""
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").filter(_within("ts", period)).select("event_id", "ts", "user_id", "value", "props")
    found = transfers(
        rows, period, src=F.col("user_id"), dst=F.get_json_object("props", "$.k"), amount=F.col("value"), ts="ts", tx_id=F.col("event_id")
    )
    return found.filter("src <> dst")


def similarity(spark: SparkSession, sf_dir: str, neighbours: int = 10, queries_every: int = 100) -> DataFrame:
    """Edges (src, dst, w) from each vector to its nearest by cosine; the classes are the truth.

    The queries are a stated set, the vectors whose id ``queries_every`` divides; they meet all vectors, and
    each task passes on its ``neighbours`` best for a query only (Spark limits ranks before the shuffle).
    """
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x * x))
    vectors = vectors.withColumn("embedding", F.col("embedding").cast("array<double>"))
    unit = vectors.withColumn("e", F.transform("embedding", lambda x: x / norm)).select("vec_id", "e")
    asked = unit.filter(F.col("vec_id") % queries_every == 0).select(F.col("vec_id").alias("src"), F.col("e").alias("q"))
    cosine = F.aggregate(F.zip_with("q", "e", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    pairs = asked.join(unit.withColumnRenamed("vec_id", "dst"), F.col("src") != F.col("dst")).select("src", "dst", cosine.alias("w"))
    best = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return pairs.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= neighbours).select("src", "dst", "w")


def hyperlinks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges (src, dst, times) between hosts and link targets of pages; ids are hashes of the strings."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("url", "html")
    links = pages.select(F.regexp_extract("url", r"//([^/?#:]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"#?]+)'), 1)).alias("to"))
    return links.groupBy(F.xxhash64("host").alias("src"), F.xxhash64("to").alias("dst")).agg(F.count(F.lit(1)).alias("times"))


def threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordinal-time edges from each turn's role to the next one's: (conv_id, src, dst, t_sec)."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role")
    following = F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))
    return turns.withColumn("to", following).dropna(subset=["to"]).select("conv_id", F.col("role").alias("src"), F.col("to").alias("dst"), F.col("turn").cast("double").alias("t_sec"))


def read_transfers(spark: SparkSession, path: str, fmt: str = "parquet", mapping: dict[str, str] | None = None, schema: str | None = None) -> DataFrame:
    """Transfers from files of any built-in format; ``mapping`` gives the source column of each of ours."""
    reader = spark.read.format(fmt)
    if schema or fmt in ("csv", "json"):
        reader = reader.schema(schema or TRANSFER)
    raw = (reader.option("header", True) if fmt == "csv" else reader).load(path)
    mapping = mapping or {}
    fields = [x.strip().split(" ", 1) for x in TRANSFER.replace("(18,2)", "(18;2)").split(",")]
    return raw.select(*(F.col(mapping.get(n, n)).cast(t.replace(";", ",")).alias(n) for n, t in fields))


def write_edges(edges: DataFrame, table: str, buckets: int = 64) -> None:
    """Keep merged edges as a table bucketed by payer, so later joins on it need no shuffle."""
    edges.write.mode("overwrite").format("parquet").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def write_results(df: DataFrame, path: str, by: str) -> None:
    """Results as Parquet, partitioned by a column of few values (period, level, component bucket)."""
    df.repartition(by).write.mode("overwrite").partitionBy(by).parquet(path)
