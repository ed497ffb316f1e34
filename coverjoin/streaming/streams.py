"""Streaming forms over the events table: windows, late data, set semantics, joins that keep up with new edges."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import anchored
from ..plans.model import JoinQuery, Relation
from ..storage import delete, scratch, settle


def source(spark: SparkSession, sf_dir: str, table: str = "events", per_batch: int = 1) -> DataFrame:
    """A Parquet table as a stream, its event time as a timestamp (watermarks need one; the session's zone should be UTC)."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in s.columns else s


def drain(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream to its present end and give its rows, from files in the shared folder: they never meet in the driver. In
    complete mode the last batch has all rows."""
    spark, at, last = df.sparkSession, scratch(df.sparkSession, name), []
    w = df.writeStream.queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", checkpoint or scratch(spark, f"{name}-state"))
    if mode == "append":
        w.format("parquet").start(at).awaitTermination()
        return spark.read.schema(df.schema).parquet(at)

    def put(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/{i}")
        if last and mode == "complete" and last[-1] != i:
            delete(spark, f"{at}/{last.pop()}")
        last.append(i)

    w.foreachBatch(put).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(*(f"{at}/{i}" for i in dict.fromkeys(last))) if last else spark.createDataFrame([], df.schema)


def each_batch(df: DataFrame, step: Callable[[DataFrame, int], None], checkpoint: str | None = None) -> None:
    w = df.writeStream.foreachBatch(step).trigger(availableNow=True)
    (w.option("checkpointLocation", checkpoint) if checkpoint else w).start().awaitTermination()


def tumbling(df: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w"), "event_type").agg(F.count("*").alias("n_events")).select(F.col("w.start").alias("start"), "event_type", "n_events")


def sliding(df: DataFrame, length: str = "1 hour", step: str = "15 minutes", late: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", late).groupBy(F.window("ts", length, step).alias("w")).agg(F.count("*").alias("n_events")).select(F.col("w.start").alias("start"), "n_events")


def sessions(df: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_events")).select("user_id", F.col("w.start").alias("start"), "n_events")


def as_set(df: DataFrame, cols: list[str], late: str = "1 hour") -> DataFrame:
    """Rows once each, as long as copies come within the watermark."""
    return df.withWatermark("ts", late).dropDuplicatesWithinWatermark(cols)


def heavy_per_window(df: DataFrame, tau: int, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Keys of degree above tau in each window."""
    return df.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w"), "user_id").agg(F.count("*").alias("degree")).filter(F.col("degree") > tau).select(F.col("w.start").alias("start"), "user_id", "degree")


def delta_join(old: JoinQuery | None, new: JoinQuery) -> DataFrame:
    """Rows that the join gains by adding ``new`` (rows not in ``old``) to the relations: term i joins the new rows of relation i
    with old rows of the relations before it and all rows of those behind it, so that no row comes twice."""
    if old is None:
        return anchored.join(new)
    both = [Relation(a.name, a.df.unionByName(b.df)) for a, b in zip(old.relations, new.relations)]
    out = None
    for i, n in enumerate(new.relations):
        rels = [old.relations[j] if j < i else n if j == i else both[j] for j in range(len(both))]
        term = anchored.join(JoinQuery(rels, new.attrs))
        out = term if out is None else out.unionByName(term)
    return out


def delta_triangle(edges: DataFrame, name: str) -> DataFrame:
    """Triangles of a stream of edges (x < y, each edge once), batch by batch. Tables of edges and triangles grow by what a batch
    adds; only the new terms are joined."""
    spark = edges.sparkSession
    found: dict[str, list[DataFrame]] = {"edges": [], "rows": []}

    def three(e: DataFrame) -> JoinQuery:
        return JoinQuery([Relation("R", e.toDF("a", "b")), Relation("S", e.toDF("b", "c")), Relation("T", e.toDF("a", "c"))])

    def step(batch: DataFrame, _: int) -> None:
        new = batch.select("x", "y").distinct()
        old = found["edges"][-1] if found["edges"] else None
        new = settle(new if old is None else new.join(old, ["x", "y"], "left_anti"))
        rows = delta_join(three(old) if old is not None else None, three(new))
        found["rows"].append(settle(rows))
        found["edges"].append(settle(new if old is None else old.unionByName(new)))

    each_batch(edges, step)
    out = found["rows"][0] if found["rows"] else spark.createDataFrame([], "a long, b long, c long")
    for r in found["rows"][1:]:
        out = out.unionByName(r)
    return out


def static_triangle(edges: DataFrame, static: DataFrame) -> DataFrame:
    """Triangles that a streamed edge closes with two static ones: stream-static joins on a prepared edge table."""
    s = static.select(F.col("x").alias("x"), F.col("y").alias("z"))
    t = static.select(F.col("x").alias("z"), F.col("y").alias("y"))
    return edges.select("x", "y").join(s, "x").join(t.withColumnRenamed("z", "z2"), "y").filter("z = z2").select("x", "z", "y")


def last_user(df: DataFrame) -> DataFrame:
    """Hand-offs between consecutive users of one type of event within a batch and across batches, by per-key state."""
    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        users = pd.concat(list(frames)).sort_values(["ts", "event_id"])["user_id"].to_numpy(np.int64)
        before = np.concatenate([[state.get[0] if state.exists else users[0]], users[:-1]])
        change = users != before
        state.update((int(users[-1]),))
        yield pd.DataFrame({"event_type": key[0], "x": np.minimum(users, before)[change], "y": np.maximum(users, before)[change]})

    return df.groupBy("event_type").applyInPandasWithState(step, "event_type string, x long, y long", "last long", "append", GroupStateTimeout.NoTimeout)
