"""Entry for SQL users: natural joins of catalog tables by the cover-bounded methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .operators import planner
from .plans.model import JoinQuery
from .plans.parse import parse_natural
from .sources.relations import from_catalog


def cover_join(spark: SparkSession, text: str, strategy: str = "auto", **how) -> DataFrame:
    """``A NATURAL JOIN B NATURAL JOIN C`` over tables or views, as sets."""
    return planner.join(JoinQuery([from_catalog(spark, t) for t in parse_natural(text)]), strategy, **how)
