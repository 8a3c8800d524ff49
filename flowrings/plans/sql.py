"""The engine for SQL users: temporary views of every stage, a table function and an aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.operators.kernel import serial_louvain
from flowrings.params import Period
from flowrings.plans.pipeline import RingReport, Settings, detect_rings


def register(spark: SparkSession, transfers: DataFrame, period: Period, settings: Settings = Settings()) -> RingReport:
    """Views transfers, edges, mcs, communities, risk, suspicious; functions louvain_levels, entropy_bits and entropy_of."""
    report = detect_rings(transfers, period, settings)
    views = {"transfers": transfers, "edges": report.edges, "mcs": report.mcs, "communities": report.labels, "risk": report.risk, "suspicious": report.suspicious}
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    spark.udtf.register("louvain_levels", louvain_levels())
    spark.udf.register("entropy_bits", entropy_bits())
    spark.udf.register("entropy_of", entropy_of())
    return report


def louvain_levels():
    """A table function: SELECT * FROM louvain_levels(TABLE(edges) PARTITION BY mcs), with columns src, dst, w_e."""

    @F.udtf(returnType="v: bigint, level: int, comm: bigint")
    class Levels:
        def __init__(self):
            self.rows: list[tuple[int, int, float]] = []

        def eval(self, row) -> None:
            self.rows.append((row["src"], row["dst"], row["w_e"]))

        def terminate(self) -> Iterator[tuple[int, int, int]]:
            if self.rows:
                src, dst, w = (np.array(x) for x in zip(*sorted(self.rows)))
                ids, levels = serial_louvain(src, dst, w)
                for n, comm in enumerate(levels):
                    yield from ((int(v), n, int(c)) for v, c in zip(ids, comm))

    return Levels


def entropy_bits():
    """A scalar over an array of counts: its entropy in bits."""

    @F.pandas_udf("double")
    def bits(counts: pd.Series) -> pd.Series:
        def one(c):
            p = np.asarray(c, float)
            p = p[p > 0] / max(p.sum(), 1e-300)
            return float(-(p * np.log2(p)).sum()) + 0.0

        return counts.map(one)

    return bits


def entropy_of():
    """An aggregate over a column of values (time segments, say): the entropy of their frequencies in bits.

    It gathers the values of a group in one task; the engine's own entropies count first, with built-in functions.
    """

    @F.pandas_udf("double")
    def bits(values: pd.Series) -> float:
        p = values.value_counts(normalize=True).to_numpy()
        return float(-(p * np.log2(p)).sum()) + 0.0

    return bits
