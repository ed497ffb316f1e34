"""Grouped forms that Spark's own functions do not have."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F


def heavy_summary(spark=None):
    """Grouped aggregate over degrees: the share of all rows that the heaviest tenth of the keys has."""
    @F.pandas_udf("double")
    def heavy_share(deg: pd.Series) -> float:
        top = deg.sort_values(ascending=False)
        return float(top.head(max(1, len(top) // 10)).sum() / max(1, top.sum()))

    return heavy_share
