"""Looking closer at accounts and transfers around the found communities."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def hop_pairs(transfers: DataFrame, max_gap: float) -> DataFrame:
    """(account, in_tx, out_tx, gap): transfers in that are followed by one out within ``max_gap`` seconds.

    A range join on equal account and close times: each transfer in looks into its own time bin and the
    next one, so the join stays an equi-join and no account's transfers all meet each other.
    """
    bin_of = lambda c: F.floor(F.col(c) / F.lit(float(max_gap))).cast("bigint")
    got = transfers.select(F.col("dst").alias("account"), F.col("tx_id").alias("in_tx"), F.col("t_sec").alias("t_in"))
    got = got.withColumn("bin", F.explode(F.array(bin_of("t_in"), bin_of("t_in") + 1)))
    sent = transfers.select(F.col("src").alias("account"), F.col("tx_id").alias("out_tx"), F.col("t_sec").alias("t_out"), bin_of("t_sec").alias("bin"))
    near = got.join(sent, ["account", "bin"]).withColumn("gap", F.col("t_out") - F.col("t_in"))
    return near.filter((F.col("gap") >= 0) & (F.col("gap") <= max_gap)).select("account", "in_tx", "out_tx", "gap")


def burst_profile(transfers: DataFrame, hours: float) -> DataFrame:
    """Each transfer with its payer's volume and number of transfers over the trailing hours."""
    span = int(hours * 3600)
    trailing = Window.partitionBy("src").orderBy(F.col("t_sec").cast("bigint")).rangeBetween(-span, 0)
    return transfers.select("src", "tx_id", "t_sec", F.sum("amount").over(trailing).cast("decimal(28,2)").alias("volume"), F.count(F.lit(1)).over(trailing).alias("n"))


def risk_rollup(levels: DataFrame, members: DataFrame, accounts: DataFrame, places: DataFrame) -> DataFrame:
    """(region, nation, level, communities, accounts): grouping sets over where the members of communities live.

    ``levels`` (comm, level), ``members`` (v, comm), ``accounts`` (v, nation_key), ``places`` (nation_key, nation, region).
    """
    wide = members.join(levels.select("comm", "level"), "comm").join(accounts, "v").join(F.broadcast(places), "nation_key")
    return wide.rollup("region", "nation", "level").agg(F.countDistinct("comm").alias("communities"), F.countDistinct("v").alias("accounts"))


def volume_cube(edges: DataFrame, accounts: DataFrame, places: DataFrame) -> DataFrame:
    """(payer, payee, edges, money): money between regions, by payer, by payee and in all (a cube)."""
    side = lambda key, name: accounts.join(F.broadcast(places), "nation_key").select(F.col("v").alias(key), F.col("region").alias(name))
    wide = edges.join(side("src", "payer"), "src").join(side("dst", "payee"), "dst")
    return wide.cube("payer", "payee").agg(F.count(F.lit(1)).alias("edges"), F.sum("money").cast("decimal(28,2)").alias("money"))


def level_sets(levels: DataFrame) -> DataFrame:
    """(mcs, level, communities, top_psi): grouping sets by component and by level, without their combinations."""
    count, top = F.count(F.lit(1)).alias("communities"), F.max("psi").alias("top_psi")
    return levels.groupingSets([["mcs"], ["level"]], "mcs", "level").agg(count, top)


def counterparties(edges: DataFrame, approximate: bool = False) -> DataFrame:
    """(v, n): distinct accounts that an account has dealt with, exact or by sketch."""
    both = edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x")).select("x.*")
    return both.groupBy("v").agg((F.approx_count_distinct("u") if approximate else F.countDistinct("u")).alias("n"))


def sample_components(edges: DataFrame, percent: int) -> DataFrame:
    """Whole components by a hash of their id: sampling edges would break them."""
    return edges.filter(F.pmod(F.xxhash64("mcs"), F.lit(100)) < percent)
