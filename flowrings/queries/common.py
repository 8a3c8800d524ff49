"""Ledgers, settings and SQL that the workloads share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.operators import graph, weights
from flowrings.params import SMALL_DATA, Period, WeightParams
from flowrings.plans.pipeline import Settings, weighted_graph
from flowrings.sources import ledger

RELAY = Period("1998-06-01", "1998-08-30")
TRADE = Period("1998-06-01", "1998-08-30")
TRADE_YEAR = Period("1998-01-01", "1999-01-01")
EVENT_HOURS = Period("2024-01-08", "2024-01-08 06:00:00")
EVENT_WEEK = Period("2024-01-08", "2024-01-15")
SMALL = Settings(screen=SMALL_DATA)
#: Published thresholds; standardised values are clipped, so that no single edge holds most of the weight.
SPREAD = Settings(weight=WeightParams(z_cap=3.0))


def relay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.relay(spark, sf_dir, RELAY)


def relay_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Merged edges with base weights."""
    return weights.base_weight(graph.merge_transfers(relay(spark, sf_dir)))


def relay_connected(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.drop_isolated_edges(relay_base(spark, sf_dir))


def relay_screened(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Screened edges with all weights, thresholds for small data."""
    return weighted_graph(relay(spark, sf_dir), RELAY, SMALL)[0]


def trade_screened(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ninety days of trade, screened by the published thresholds, with clipped weights."""
    return weighted_graph(ledger.trade(spark, sf_dir, TRADE), TRADE, SPREAD)[0]


def nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, comm): the account's nation, a partition that SQL can name."""
    return spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("v"), F.col("c_nationkey").cast("bigint").alias("comm"))


def shown(df: DataFrame, digits: int = 6) -> DataFrame:
    """Decimals as doubles and doubles rounded, so that results compare by value."""
    kinds = dict(df.dtypes)
    return df.select(*(F.round(F.col(c).cast("double"), digits).alias(c) if kinds[c] == "double" or kinds[c].startswith("decimal") else F.col(c) for c in df.columns))


def relay_sql(period: Period = RELAY) -> str:
    """CTEs tr (transfers) and e (merged edges)."""
    return f"""
li AS (SELECT * FROM lineitem WHERE l_shipdate >= TIMESTAMP '{period.start}' AND l_shipdate < TIMESTAMP '{period.end}'),
raw AS (SELECT o_custkey AS src, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_suppkey, l_extendedprice) AS dst,
        CAST(l_extendedprice AS DECIMAL(18,2)) AS amount, epoch(l_shipdate) - epoch(TIMESTAMP '{period.start}') AS t_sec FROM li JOIN orders ON l_orderkey = o_orderkey),
tr AS (SELECT * FROM raw WHERE dst IS NOT NULL AND src <> dst),
{MERGE}"""


def trade_sql(period: Period = TRADE) -> str:
    return f"""
raw AS (SELECT 2 * o_custkey AS c, 2 * l_suppkey + 1 AS s, l_returnflag = 'R' AS back, l_orderkey * 10 + l_linenumber AS tx_id,
        round(CAST(l_extendedprice AS DECIMAL(14,2)) * (CAST(1 AS DECIMAL(4,2)) - CAST(l_discount AS DECIMAL(4,2))), 2) AS amount,
        epoch(l_shipdate) - epoch(TIMESTAMP '{period.start}') AS t_sec
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate >= TIMESTAMP '{period.start}' AND l_shipdate < TIMESTAMP '{period.end}'),
tr AS (SELECT CASE WHEN back THEN s ELSE c END AS src, CASE WHEN back THEN c ELSE s END AS dst, CAST(amount AS DECIMAL(18,2)) AS amount, t_sec, tx_id FROM raw),
{MERGE}"""


def event_sql(period: Period) -> str:
    return f"""
raw AS (SELECT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, CAST(value AS DECIMAL(18,2)) AS amount,
        (epoch_us(ts) - epoch_us(TIMESTAMP '{period.start}')) / 1e6 AS t_sec, event_id AS tx_id, ts
        FROM events WHERE ts >= TIMESTAMP '{period.start}' AND ts < TIMESTAMP '{period.end}'),
tr AS (SELECT * FROM raw WHERE src <> dst AND dst IS NOT NULL AND amount IS NOT NULL),
{MERGE}"""


MERGE = "e AS (SELECT src, dst, sum(amount) AS money, count(*) AS times, avg(t_sec) AS t FROM tr GROUP BY 1, 2)"


def z_sql(col: str, table: str, cap: float | None = None) -> str:
    """A standardised column as an expression over one table."""
    x = f"CAST({col} AS DOUBLE)"
    z = f"coalesce(({x} - (SELECT avg({x}) FROM {table})) / nullif((SELECT stddev_pop({x}) FROM {table}), 0), 0)"
    return z if cap is None else f"greatest(-{cap}, least({cap}, {z}))"


def base_sql(cap: float | None = None) -> str:
    return f"""
ew AS (SELECT *, exp(lw) AS w_b FROM (SELECT *, 0.5 * {z_sql('money', 'e', cap)} + 0.5 * {z_sql('times', 'e', cap)} AS lw FROM e))"""


BASE = base_sql()

ISOLATION = """
ends AS (SELECT src AS v FROM ew UNION ALL SELECT dst FROM ew),
d0 AS (SELECT v, count(*) AS deg FROM ends GROUP BY 1),
k AS (SELECT ew.* FROM ew JOIN d0 a ON a.v = src JOIN d0 b ON b.v = dst WHERE NOT (a.deg = 1 AND b.deg = 1))"""

#: From edges k: comp (v, mcs). A label spreads only to larger ids, which the least one always can.
COMPONENTS = """
links AS (SELECT src AS v, dst AS u FROM k UNION SELECT dst, src FROM k),
reach AS (SELECT DISTINCT v, v AS r FROM links UNION SELECT links.u, reach.r FROM reach JOIN links ON links.v = reach.v WHERE reach.r < links.u),
comp AS (SELECT v, min(r) AS mcs FROM reach GROUP BY 1)"""

PROFILE = """
d1 AS (SELECT v, count(*) AS deg FROM (SELECT src AS v FROM k UNION ALL SELECT dst FROM k) GROUP BY 1),
prof AS (SELECT mcs, count(*) AS n_vertices, CAST(sum(deg) // 2 AS BIGINT) AS n_edges, count(*) FILTER (deg > 3) AS n_hubs FROM comp JOIN d1 USING (v) GROUP BY 1),
kept AS (SELECT * FROM prof WHERE n_vertices > 10 AND n_vertices < 2000 AND n_hubs > 0),
se AS (SELECT k.*, mcs FROM k JOIN comp ON comp.v = src JOIN kept USING (mcs))"""


def nodes_sql(table: str, name: str = "nd") -> str:
    """Node profiles of a table of edges, transfer-weighted mean times."""
    return f"""
{name} AS (SELECT v, count(*) AS deg, count(*) FILTER (i = 1) AS deg_in, count(*) FILTER (i = 0) AS deg_out, sum(money) AS money, CAST(sum(times) AS BIGINT) AS times,
       sum(t * times) FILTER (i = 1) / sum(times) FILTER (i = 1) AS t_in, sum(t * times) FILTER (i = 0) / sum(times) FILTER (i = 0) AS t_out
       FROM (SELECT src AS v, 0 AS i, * FROM {table} UNION ALL SELECT dst, 1, * FROM {table}) GROUP BY 1)"""


def final_sql(seconds: float, cap: float | None = None) -> str:
    """From screened edges se: nd, nf (nodes), fw (edges with all weights)."""
    return nodes_sql("se") + f""",
nf AS (SELECT *, {z_sql('money', 'nd', cap)} / 3 + {z_sql('times', 'nd', cap)} / 3 + {z_sql('deg', 'nd', cap)} / 3 AS ls, (deg_in - deg_out) / CAST(deg_in + deg_out AS DOUBLE) AS beta FROM nd),
tp AS (SELECT se.*, lw + s.ls + d.ls AS lwn, s.beta AS sb, d.beta AS db,
       CASE WHEN s.beta > 0 AND t <> s.t_in THEN s.beta * greatest(-10, least(10, {seconds} / nullif(t - s.t_in, 0))) ELSE 0 END AS xs,
       CASE WHEN d.beta < 0 AND t <> d.t_out THEN d.beta * greatest(-10, least(10, {seconds} / nullif(t - d.t_out, 0))) ELSE 0 END AS xd
       FROM se JOIN nf s ON s.v = src JOIN nf d ON d.v = dst),
fw AS (SELECT *, exp(lwn) AS w_n, exp(lwn + xs + xd) AS w_e,
       CASE WHEN sb > 0 AND db < 0 THEN 'both' WHEN sb > 0 THEN 'gather_then_send' WHEN db < 0 THEN 'gather_before_scatter' ELSE 'none' END AS kind FROM tp)"""


TO_SCREENED = ", ".join((relay_sql(), BASE, ISOLATION, COMPONENTS, PROFILE))
TO_FINAL = f"{TO_SCREENED}, {final_sql(RELAY.seconds)}"
TRADE_PROFILE = PROFILE.replace("deg > 3", "deg > 20").replace("n_hubs > 0", "n_hubs > 7")
TRADE_TO_FINAL = ", ".join((trade_sql(), base_sql(3.0), ISOLATION, COMPONENTS, TRADE_PROFILE, final_sql(TRADE.seconds, 3.0)))
