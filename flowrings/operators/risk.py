"""Risk of communities: volume, structure and how concentrated their transfers are in time."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from flowrings.functions.stats import scaled_exp, share_bound, share_sum, standardise
from flowrings.operators.graph import vertex_profile
from flowrings.params import RiskParams
from flowrings.scratch import materialize

#: Communities that one task ranks; beyond it they are ranked range by range, with the same result.
ONE_TASK = 1_000_000


def inside(rows: DataFrame, labels: DataFrame) -> DataFrame:
    """Transfers or edges with both ends in one community, with column comm."""
    side = lambda end: labels.select(F.col("v").alias(end), F.col("comm").alias(f"__{end}"))
    both = rows.join(side("src"), "src").join(side("dst"), "dst").filter("__src = __dst")
    return both.select(*rows.columns, F.col("__src").alias("comm"))


def segment_of(gap: Column, segments: int | list[float], seconds: float) -> Column:
    """The segment of a time gap: equal parts of the period, or the given inner bounds; the last one is open."""
    if isinstance(segments, int):
        return F.least(F.floor(gap / F.lit(seconds / segments)), F.lit(segments - 1)).cast("int")
    return F.aggregate(F.array(*(F.lit(float(b)) for b in segments)), F.lit(0), lambda n, b: n + (gap >= b).cast("int"))


def segment_shares(transfers: DataFrame, labels: DataFrame, seconds: float, segments: int | list[float] = 7) -> DataFrame:
    """(comm, segment, n, p): transfers of each community by their distance from its mean time."""
    own = inside(transfers.select("src", "dst", "t_sec"), labels)
    mean = own.groupBy("comm").agg(F.avg("t_sec").alias("mean_t"), F.count(F.lit(1)).alias("total"))
    gap = F.abs(F.col("t_sec") - F.col("mean_t"))
    counted = own.join(mean, "comm").groupBy("comm", segment_of(gap, segments, seconds).alias("segment")).agg(F.count(F.lit(1)).alias("n"), F.max("total").alias("total"))
    return counted.select("comm", "segment", "n", (F.col("n") / F.col("total")).alias("p"))


def time_entropy(transfers: DataFrame, labels: DataFrame, seconds: float, segments: int | list[float] = 7) -> DataFrame:
    """(comm, h): temporal entropy in bits; 0 if all transfers lie in one segment."""
    shares = segment_shares(transfers, labels, seconds, segments)
    return shares.groupBy("comm").agg((-F.sum(F.col("p") * F.log2("p")) + 0.0).alias("h"))


def community_features(edges: DataFrame, labels: DataFrame, degree_scope: str = "inside") -> DataFrame:
    """(comm, v, e, m, d): vertices, inner edges, inner money, mean degree.

    Degrees count inner edges, or all edges of the graph with ``degree_scope='graph'``.
    """
    inner = inside(edges, labels).groupBy("comm").agg(F.count(F.lit(1)).alias("e"), F.sum("money").cast("decimal(28,2)").alias("m"))
    sizes = labels.groupBy("comm").agg(F.count(F.lit(1)).alias("v"))
    if degree_scope == "graph":
        degrees = vertex_profile(edges).select("v", "deg").join(labels, "v").groupBy("comm").agg(F.avg("deg").alias("d"))
        out = sizes.join(inner, "comm", "left").join(degrees, "comm", "left")
    else:
        out = sizes.join(inner, "comm", "left").withColumn("d", 2 * F.coalesce("e", F.lit(0)) / F.col("v"))
    zero = F.lit(0).cast("decimal(28,2)")
    return out.select("comm", "v", F.coalesce("e", F.lit(0)).alias("e"), F.coalesce("m", zero).alias("m"), F.coalesce("d", F.lit(0.0)).alias("d"))


def risk_scores(features: DataFrame, params: RiskParams = RiskParams()) -> DataFrame:
    """Add psi = exp of the share-weighted standardised v, e, m, d, h.  ``entropy_sign=-1`` rewards low entropy."""
    names = ["v", "e", "m", "d", "h"]
    z = standardise(features, names, tops=True).withColumn("z_h", F.col("z_h") * params.entropy_sign)
    return z.withColumn("psi", scaled_exp(share_sum(params.shares.of), share_bound(params.shares.of))).drop(*(f"{p}_{c}" for p in ("z", "top") for c in names))


def community_risk(transfers: DataFrame, edges: DataFrame, labels: DataFrame, seconds: float, params: RiskParams = RiskParams()) -> DataFrame:
    """(comm, v, e, m, d, h, psi) of every community; without inner transfers h is 0."""
    h = time_entropy(transfers, labels, seconds, params.segments)
    f = community_features(edges, labels, params.degree_scope).join(h, "comm", "left").withColumn("h", F.coalesce("h", F.lit(0.0)))
    return risk_scores(f, params)


def _by_range(scores: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows with __part, ranges in descending order of psi, and __n, the place in the range; and a row for each range.

    Ranges have (__part, before, first, n_first, following): rows before it, its largest psi and how often,
    the largest psi of the next one.
    """
    parts = int(scores.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cut = materialize(scores.repartitionByRange(parts, F.desc("psi"), F.asc("comm")).withColumn("__part", F.spark_partition_id()), "ranges")
    rows = cut.withColumn("__n", F.row_number().over(Window.partitionBy("__part").orderBy(F.desc("psi"), "comm")).cast("bigint"))
    sizes = cut.groupBy("__part", "psi").agg(F.count(F.lit(1)).alias("n")).groupBy("__part").agg(F.sum("n").alias("n"), F.max(F.struct("psi", "n")).alias("first"))
    w = Window.orderBy("__part")
    before = F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows, sizes.select("__part", before.alias("before"), F.col("first.psi").alias("first"), F.col("first.n").alias("n_first"), F.lead("first.psi").over(w).alias("following"))


def risk_curve(scores: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """Add rank (1 = riskiest, ties by community id) and slope, the forward difference of psi by rank."""
    scores = materialize(scores, "scores")
    if scores.count() <= one_task:
        w = Window.orderBy(F.desc("psi"), "comm")
        return scores.select("*", F.row_number().over(w).cast("bigint").alias("rank"), (F.lead("psi").over(w) - F.col("psi")).alias("slope"))
    rows, ranges = _by_range(scores)
    ahead = F.lead("psi").over(Window.partitionBy("__part").orderBy("__n"))
    wide = rows.withColumn("__ahead", ahead).join(F.broadcast(ranges), "__part")
    return wide.select(*scores.columns, (F.col("before") + F.col("__n")).alias("rank"), (F.coalesce("__ahead", "following") - F.col("psi")).alias("slope"))


def risk_levels(scores: DataFrame, cuts: tuple[float, float, float] = (0.95, 0.90, 0.80), exact: bool = True, one_task: int = ONE_TASK) -> DataFrame:
    """Add pct (percentile rank of psi, equal for ties) and level: 1, 2, 3 from the cuts down, else 0.

    ``exact=False`` compares with approximate percentiles instead of ranking all rows; pct is then null.
    """
    if exact:
        scores = materialize(scores, "scores")
        n = scores.count()
        if n <= one_task:
            ranked = scores.withColumn("pct", F.percent_rank().over(Window.orderBy("psi")))
        else:
            rows, ranges = _by_range(scores)
            # the last place of a tie: here, or in a later range that begins with it
            here = rows.withColumn("__last", F.max("__n").over(Window.partitionBy("__part", "psi"))).join(F.broadcast(ranges.select("__part", "before")), "__part")
            later = ranges.groupBy(F.col("first").alias("psi")).agg(F.max(F.col("before") + F.col("n_first")).alias("__later"))
            last = F.greatest(F.col("before") + F.col("__last"), F.col("__later"))
            ranked = here.join(F.broadcast(later), "psi", "left").select(*scores.columns, ((F.lit(n) - last) / F.lit(max(1, n - 1))).alias("pct"))
        at = [F.col("pct") >= c for c in cuts]
        return ranked.withColumn("level", F.when(at[0], 1).when(at[1], 2).when(at[2], 3).otherwise(0))
    bounds = scores.agg(F.percentile_approx("psi", [float(c) for c in cuts], 100_000).alias("__b"))
    wide = scores.crossJoin(F.broadcast(bounds)).withColumn("pct", F.lit(None).cast("double"))
    at = [F.col("psi") >= F.col("__b")[i] for i in range(3)]
    return wide.withColumn("level", F.when(at[0], 1).when(at[1], 2).when(at[2], 3).otherwise(0)).drop("__b")


def turning_point(curve: DataFrame, tol: float = 0.05) -> int | None:
    """The first rank from which no slope exceeds ``tol`` of the steepest one: the one after the last that does."""
    known = curve.filter("slope IS NOT NULL")
    top = known.agg(F.max(F.abs("slope")).alias("top"))
    steep = F.when(F.abs("slope") > tol * F.col("top"), F.col("rank"))
    first, last, steepest = known.crossJoin(F.broadcast(top)).agg(F.min("rank"), F.max("rank"), F.max(steep)).first()
    point = first if steepest is None else steepest + 1
    return None if point is None or point > last else int(point)


def suspicious_components(levels: DataFrame, min_count: int = 2, level: int = 2) -> DataFrame:
    """(mcs, n_risky, n_communities, top_psi) of components with at least ``min_count`` communities of levels 1..level."""
    risky = F.col("level").between(1, level)
    return (
        levels.groupBy("mcs").agg(F.count_if(risky).alias("n_risky"), F.count(F.lit(1)).alias("n_communities"), F.max("psi").alias("top_psi"))
        .filter(F.col("n_risky") >= min_count)
    )


def report_nodes(edges: DataFrame, mcs: DataFrame, top: int = 10, weight: str = "w_e") -> DataFrame:
    """(mcs, v, weight, rank): the ``top`` vertices of largest attached weight in each given component."""
    own = edges.join(mcs.select("mcs"), "mcs", "left_semi")
    ends = own.select("mcs", F.explode(F.array("src", "dst")).alias("v"), F.col(weight).alias("w")).groupBy("mcs", "v").agg(F.sum("w").alias("weight"))
    ranked = ends.withColumn("rank", F.row_number().over(Window.partitionBy("mcs").orderBy(F.desc("weight"), "v")))
    return ranked.filter(F.col("rank") <= top)
