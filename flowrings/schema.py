"""Fixed schemas of the engine and the check that callers' frames have them."""

from __future__ import annotations

from pyspark.sql import DataFrame

TRANSFER = "src bigint, dst bigint, amount decimal(18,2), t_sec double, ts timestamp, day date, tx_id bigint"
EDGE = "src bigint, dst bigint, money decimal(28,2), times bigint, t double"
LABELS = "v bigint, comm bigint"


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}; there are {', '.join(df.columns)}")
    return df
