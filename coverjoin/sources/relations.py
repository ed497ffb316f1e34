"""Relations out of tables and files, and where results go."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.model import Relation


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def relation(df: DataFrame, attrs: Mapping[str, str | Column] | Sequence[str], name: str = "") -> Relation:
    """Project, rename, and drop repeated rows: relations are sets."""
    cols = [F.col(a) for a in attrs] if not isinstance(attrs, Mapping) else [(F.col(e) if isinstance(e, str) else e).alias(a) for a, e in attrs.items()]
    return Relation(name, df.select(*cols).distinct())


def keyed(df: DataFrame, attrs: Mapping[str, str | Column] | Sequence[str], name: str = "") -> Relation:
    """Like relation(), where the caller knows that the projection holds a key: no shuffle to drop repeated rows."""
    cols = [F.col(a) for a in attrs] if not isinstance(attrs, Mapping) else [(F.col(e) if isinstance(e, str) else e).alias(a) for a, e in attrs.items()]
    return Relation(name, df.select(*cols))


def from_catalog(spark: SparkSession, table: str) -> Relation:
    return relation(spark.table(table), spark.table(table).columns, table)


def read(spark: SparkSession, fmt: str, path: str, schema: str) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet with a fixed schema."""
    r = spark.read.format(fmt).schema(schema)
    return (r.option("header", "true") if fmt == "csv" else r).load(path)


def json_attr(col: str, path: str, kind: str = "int") -> Column:
    return F.get_json_object(col, f"$.{path}").cast(kind)


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: Sequence[str] = (), sort_by: Sequence[str] = ()) -> None:
    w = (df.sortWithinPartitions(*sort_by) if sort_by else df).write.format(fmt).mode(mode)
    w = w.option("header", "true") if fmt == "csv" else w
    (w.partitionBy(*partition_by) if partition_by else w).save(path)
