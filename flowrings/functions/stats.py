"""Standardisation and shared expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Logarithm up to which exponentials are taken as they are: sums over 10**12 rows, and their squares, stay finite.
LARGEST_LOG = 300.0


def standardise(df: DataFrame, cols: list[str], by: str | None = None, cap: float | None = None, prefix: str = "z_", tops: bool = False) -> DataFrame:
    """Add ``z_<col>``: (value - mean) / population deviation, over all rows or within ``by``.

    Without spread, and for a null value, it is 0.  The whole-table form broadcasts one row of statistics;
    with ``tops`` it also adds ``top_<col>``, the largest absolute z of the column, from the same statistics.
    """
    value = {c: F.col(c).cast("double") for c in cols}
    if by is None:
        kinds = [("mean", F.avg), ("sd", F.stddev_pop), *([("min", F.min), ("max", F.max)] if tops else [])]
        stats = df.agg(*(f(value[c]).alias(f"__{n}_{c}") for c in cols for n, f in kinds))
        if tops:
            stats = stats.select("*", *(F.greatest(*(F.abs(_z(F.col(f"__{n}_{c}"), c, cap)) for n in ("min", "max"))).alias(f"top_{c}") for c in cols))
            stats = stats.drop(*(f"__{n}_{c}" for c in cols for n in ("min", "max")))
        wide = df.crossJoin(F.broadcast(stats))
    else:
        over = Window.partitionBy(by)
        wide = df.select("*", *(f(value[c]).over(over).alias(f"__{n}_{c}") for c in cols for n, f in (("mean", F.avg), ("sd", F.stddev_pop))))
    names = [f"__{n}_{c}" for c in cols for n in ("mean", "sd")]
    return wide.select("*", *(_z(value[c], c, cap).alias(prefix + c) for c in cols)).drop(*names)


def _z(value: Column, c: str, cap: float | None) -> Column:
    sd = F.col(f"__sd_{c}")
    z = F.coalesce(F.when(sd > 0, (value - F.col(f"__mean_{c}")) / sd), F.lit(0.0))
    return z if cap is None else F.greatest(F.lit(-cap), F.least(F.lit(cap), z))


def share_sum(shares: dict[str, float], prefix: str = "z_") -> Column:
    """The share-weighted sum of standardised columns."""
    total = F.lit(0.0)
    for name, share in shares.items():
        total = total + F.lit(share) * F.col(prefix + name)
    return total


def share_bound(shares: dict[str, float], prefix: str = "top_") -> Column:
    """A bound of ``share_sum`` over all rows, from ``standardise(..., tops=True)``."""
    return share_sum({name: abs(share) for name, share in shares.items()}, prefix)


def scaled_exp(log: Column, bound: Column) -> Column:
    """exp(log), divided by one constant for all rows where ``bound`` on the logarithms says that it could overflow."""
    return F.exp(log - F.greatest(F.lit(0.0), bound - LARGEST_LOG))
