"""Bounded samples of labelled documents for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sample_ids(rows: DataFrame, at_most: int, id_col: str = "doc_id") -> DataFrame:
    """At most ``at_most`` rows, the first by a hash of the id: the same rows however the table is cut.

    Rows above a hash limit that leaves about twice the wanted number go before the sort, so no task
    or driver holds more than a few times ``at_most`` rows.
    """
    h = F.xxhash64(id_col)
    total = rows.count()
    if total > 2 * at_most:
        share = 2 * at_most / total
        rows = rows.filter(F.shiftrightunsigned(h, 1) < F.lit(int(share * (1 << 63))))
    return rows.withColumn("__order", h).orderBy("__order", id_col).limit(at_most)
