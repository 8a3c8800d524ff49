"""Which components are worth a search, and where to put the thresholds.

A curve over all integer thresholds only changes at the distinct sizes (or degrees, or hub counts).  Sweeps
so keep the thresholds next to those alone; between two of them the curve is flat.  N vertices have at most
sqrt(2 N) distinct sizes or degrees, which bounds the rows that the windows without partitions see (some
45,000 for 10**9 vertices), whatever the largest size is.  ``every_threshold`` fills the gaps for plots.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from flowrings.operators.graph import component_profile, vertex_profile
from flowrings.params import ScreenParams


def screen_components(mcs: DataFrame, params: ScreenParams = ScreenParams()) -> DataFrame:
    """Components of v_lo < vertices < v_hi with more than n_hubs hubs (counted by ``component_profile``)."""
    return mcs.filter((F.col("n_vertices") > params.v_lo) & (F.col("n_vertices") < params.v_hi) & (F.col("n_hubs") > params.n_hubs))


def hubs(vertices: DataFrame, hub_degree: int = 20) -> DataFrame:
    return vertices.filter(F.col("deg") > hub_degree)


def apply_screen(edges: DataFrame, labels: DataFrame, kept: DataFrame) -> DataFrame:
    """Edges of the kept components, with column mcs."""
    ours = labels.join(kept.select("mcs"), "mcs", "left_semi")
    return edges.join(ours.select(F.col("v").alias("src"), "mcs"), "src").select(*edges.columns, "mcs")


def _tail(histogram: DataFrame, value: str, sums: dict[str, str]) -> DataFrame:
    """For threshold 0 and the integers next to each value, up to the largest: sums over values above it."""
    top = histogram.agg(F.coalesce(F.max(value), F.lit(0)).cast("long").alias("top"))
    near = histogram.select(F.explode(F.array(*(F.col(value).cast("long") + i for i in (-1, 0, 1)))).alias("threshold"))
    grid = top.select(F.lit(0).cast("long").alias("threshold")).union(near).distinct().crossJoin(F.broadcast(top)).filter("threshold between 0 and top").drop("top")
    above = Window.orderBy(F.desc("threshold")).rowsBetween(Window.unboundedPreceding, -1)
    wide = grid.join(histogram, F.col("threshold") == F.col(value), "left")
    return wide.select("threshold", *(F.coalesce(F.sum(c).over(above), F.lit(0)).alias(n) for n, c in sums.items()))


def every_threshold(curve: DataFrame) -> DataFrame:
    """A curve with a row for every integer threshold: flat, and without differences, between the rows it has."""
    upto = F.coalesce(F.lead("threshold").over(Window.orderBy("threshold")) - 1, F.col("threshold"))
    wide = curve.withColumn("__all", F.sequence("threshold", upto)).select("*", F.posexplode("__all").alias("__at", "__threshold"))
    flat = lambda c: F.when(F.col("__at") > 0, F.lit(0.0)).otherwise(F.col(c)) if c in ("d1", "d2") else F.col(c)
    return wide.select(F.col("__threshold").alias("threshold"), *(flat(c).alias(c) for c in curve.columns if c != "threshold"))


def sweep_sizes(mcs: DataFrame) -> DataFrame:
    """(threshold, v_remain, m_remain, v_avg): what is left of components larger than the threshold."""
    sizes = mcs.groupBy("n_vertices").agg(F.count(F.lit(1)).alias("m")).withColumn("total", F.col("m") * F.col("n_vertices"))
    curve = _tail(sizes, "n_vertices", {"v_remain": "total", "m_remain": "m"})
    return curve.withColumn("v_avg", F.coalesce(F.col("v_remain") / F.when(F.col("m_remain") > 0, F.col("m_remain")), F.lit(0.0)))


def sweep_degrees(vertices: DataFrame) -> DataFrame:
    """(threshold, v_remain): vertices of a degree above the threshold."""
    return _tail(vertices.groupBy("deg").agg(F.count(F.lit(1)).alias("n")), "deg", {"v_remain": "n"})


def sweep_hub_counts(mcs: DataFrame) -> DataFrame:
    """(threshold, m_remain): components with more hubs than the threshold."""
    return _tail(mcs.groupBy("n_hubs").agg(F.count(F.lit(1)).alias("n")), "n_hubs", {"m_remain": "n"})


def second_difference(curve: DataFrame, y: str) -> DataFrame:
    """Add d1 (forward difference) and d2 (second difference) of a column over unit steps; null at the ends.

    Where the curve has no row for the next integer, or the one before, it is flat there.
    """
    w, t = Window.orderBy("threshold"), F.col("threshold")
    side = lambda f, step: F.when(f("threshold").over(w) == t + step, f(y).over(w)).when(f("threshold").over(w).isNotNull(), F.col(y))
    ahead, behind = side(F.lead, 1), side(F.lag, -1)
    return curve.select("*", (ahead - F.col(y)).cast("double").alias("d1"), (ahead - 2 * F.col(y) + behind).cast("double").alias("d2"))


def settling_point(curve: DataFrame, tol: float = 0.01, run: int = 5) -> int | None:
    """The first threshold from which |d2|, relative to its largest value, stays within ``tol`` for ``run`` steps.

    It is the first with a d2, or follows one that is too large; the next too large one must be ``run`` steps away.
    """
    ends = curve.agg((F.min("threshold") + 1).alias("low"), (F.max("threshold") - 1).alias("high"), F.max(F.abs("d2")).alias("top")).filter("low <= high")
    large = curve.crossJoin(F.broadcast(ends)).filter(F.abs("d2") > tol * F.col("top")).select("threshold")
    stops = large.unionByName(ends.select((F.col("high") + run + 1).alias("threshold")))
    calm = stops.withColumn("before", F.lag("threshold").over(Window.orderBy("threshold"))).crossJoin(F.broadcast(ends))
    start = F.coalesce(F.col("before") + 1, F.col("low"))
    row = calm.filter((F.col("threshold") >= start + run) & (start <= F.col("high"))).agg(F.min(start)).first()
    return None if row[0] is None else int(row[0])


def choose_thresholds(edges: DataFrame, labels: DataFrame, tol: float = 0.01, run: int = 5, default: ScreenParams = ScreenParams()) -> ScreenParams:
    """Thresholds where the curves settle, in the order size, degree, hub count; defaults where they never do."""
    pick = lambda curve, y, other: other if (x := settling_point(second_difference(curve, y), tol, run)) is None else x
    mcs = component_profile(edges, labels, 0)
    sizes = sweep_sizes(mcs)
    v_lo, v_hi = pick(sizes, "v_remain", default.v_lo), pick(sizes, "v_avg", default.v_hi)
    hub_degree = pick(sweep_degrees(vertex_profile(edges)), "v_remain", default.hub_degree)
    n_hubs = pick(sweep_hub_counts(component_profile(edges, labels, hub_degree)), "m_remain", default.n_hubs)
    return ScreenParams(v_lo, max(v_hi, v_lo + 2), hub_degree, n_hubs)
