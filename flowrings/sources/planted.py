"""Generated ledgers with known rings: the only source with ground truth.

Noise is transfers between hashed accounts at hashed times.  A ring gathers money into a collector,
hands it to a distributor and scatters it, in that order of time; a decoy has the same edges with
hashed times.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.params import Period


def _unit(*keys) -> Column:
    """A hashed number in [0, 1)."""
    return F.pmod(F.xxhash64(*keys), F.lit(1_000_003)) / F.lit(1_000_003.0)


def planted(
    spark: SparkSession, period: Period, *, accounts: int = 2000, noise: int = 4000, rings: int = 12, decoys: int = 0, ring_size: int = 14, seed: int = 1
) -> DataFrame:
    """Transfers; rings use account ids from ``accounts`` on, one block of ``ring_size`` ids each."""
    span = period.seconds
    start = F.lit(period.start).cast("timestamp_ntz").cast("timestamp")
    pick = lambda salt: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(salt)), F.lit(accounts))
    base = spark.range(noise).select(
        pick("src").alias("src"), pick("dst").alias("dst"), (F.lit(10.0) + 500 * _unit("id", F.lit(seed), F.lit("amount"))).alias("amount"),
        (span * _unit("id", F.lit(seed), F.lit("t"))).alias("t_sec"),
    )
    half = (ring_size - 2) // 2
    steps = spark.range(rings + decoys).withColumnRenamed("id", "ring").crossJoin(spark.range(2 * half + 3).withColumnRenamed("id", "step"))
    first = F.lit(accounts) + F.col("ring") * ring_size
    gather, scatter = F.col("step") < half, (F.col("step") >= half) & (F.col("step") < 2 * half)
    src = F.when(gather, first + 2 + F.col("step")).when(scatter, first + 1).otherwise(first)
    dst = F.when(gather, first).when(scatter, first + 2 + F.col("step")).otherwise(first + 1)
    begin = 0.1 + 0.6 * _unit("ring", F.lit(seed), F.lit("begin"))
    phase = F.when(gather, 0.0).when(scatter, 0.10).otherwise(0.05) + 0.03 * _unit("ring", "step", F.lit(seed))
    when = F.when(F.col("ring") < rings, begin + phase).otherwise(_unit("ring", "step", F.lit(seed), F.lit("shuffled")))
    inside = steps.select(src.alias("src"), dst.alias("dst"), F.when(gather | scatter, 2000.0).otherwise(2000.0 * half).alias("amount"), (F.lit(span) * when).alias("t_sec"))
    # one thread ties each ring to the noise
    tie = spark.range(rings + decoys).select(
        F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(accounts)).alias("src"), (F.lit(accounts) + F.col("id") * ring_size + 2).alias("dst"),
        F.lit(50.0).alias("amount"), F.lit(span * 0.02).alias("t_sec"),
    )
    rows = base.unionByName(inside).unionByName(tie).filter("src <> dst")
    ts = F.timestamp_micros((F.unix_micros(start) + F.col("t_sec") * 1e6).cast("bigint"))
    return rows.select(
        "src", "dst", F.col("amount").cast("decimal(18,2)").alias("amount"), "t_sec", ts.alias("ts"), F.to_date(ts).alias("day"),
        F.xxhash64("src", "dst", "t_sec").alias("tx_id"),
    )


def planted_truth(spark: SparkSession, *, accounts: int = 2000, rings: int = 12, decoys: int = 0, ring_size: int = 14) -> DataFrame:
    """(v, ring, timed): the ring of each of its accounts, and whether its times follow the pattern."""
    return spark.range((rings + decoys) * ring_size).select(
        (F.lit(accounts) + F.col("id")).alias("v"), F.floor(F.col("id") / ring_size).alias("ring"), (F.floor(F.col("id") / ring_size) < rings).alias("timed")
    )


def component_graph(spark: SparkSession, *, components: int = 74, vertices: int = 415, edges: int = 1828, groups: int = 8, seed: int = 1) -> DataFrame:
    """(mcs, src, dst, w_b, w_e): components of one size with denser groups inside, for timing searches.

    The defaults have the size of the published screened graph: 74 components, about 30,700 vertices
    and 135,000 edges.  Three quarters of the edges stay in a group of their component.
    """
    size = -(-vertices // groups)
    pick = lambda salt, n: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(salt)), n)
    rows = spark.range(components * edges).withColumn("mcs", F.col("id") % components)
    group = pick("group", F.lit(groups))
    near = lambda salt: F.least(group * size + pick(salt, F.lit(size)), F.lit(vertices - 1))
    inner = pick("inner", F.lit(4)) < 3
    ends = rows.select(
        "mcs", (F.col("mcs") * vertices + F.when(inner, near("s")).otherwise(pick("s", F.lit(vertices)))).alias("src"),
        (F.col("mcs") * vertices + F.when(inner, near("d")).otherwise(pick("d", F.lit(vertices)))).alias("dst"),
        F.exp(2 * _unit("id", F.lit(seed), F.lit("b"))).alias("w_b"), F.exp(3 * _unit("id", F.lit(seed), F.lit("e"))).alias("w_e"),
    )
    return ends.filter("src <> dst").groupBy("mcs", "src", "dst").agg(F.sum("w_b").alias("w_b"), F.sum("w_e").alias("w_e"))
