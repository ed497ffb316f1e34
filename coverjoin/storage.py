"""Tables in the shared folder: what cuts lineage, survives a lost executor, and keeps plans short."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A set of at most this many rows, whose columns have a fixed width, may be broadcast.
BROADCAST_ROWS = 200_000
#: Rows that a cross product may have.
PRODUCT_ROWS = 50_000_000
_RUN = uuid.uuid4().hex
_own_dir: list[str] = []
#: Spark's switch to delete an execution's shuffle files as it ends, else they stay until the driver collects its garbage.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_lock = threading.Lock()
_writing: list[str] = []  # the switch as it was before, once for each write under way
_passing: list[list[str]] = []  # the tables settled in each passing() under way


class ProductTooLarge(ValueError):
    """A cross product would have more than PRODUCT_ROWS rows."""


def shared_dir(spark: SparkSession) -> str:
    """Folder seen by the driver and all executors: spark.checkpoint.dir. Where that is unset a local session gets a temporary
    folder; on a cluster it is an error, as executors do not share local folders."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_dir:
        _own_dir.append(tempfile.mkdtemp(prefix="coverjoin-"))
        atexit.register(shutil.rmtree, _own_dir[0], ignore_errors=True)
    return f"file://{_own_dir[0]}"


def scratch(spark: SparkSession, what: str) -> str:
    """A new path below this process's folder."""
    return f"{shared_dir(spark)}/coverjoin/{_RUN}/{what}-{uuid.uuid4().hex}"


def delete(spark: SparkSession, at: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Delete all tables that this process has settled. DataFrames made from them cannot be read any more."""
    delete(spark, f"{shared_dir(spark)}/coverjoin/{_RUN}")


def _storable(kind: T.DataType) -> bool:
    if isinstance(kind, T.StructType):
        return all(_storable(f.dataType) for f in kind.fields)
    if isinstance(kind, T.ArrayType):
        return _storable(kind.elementType)
    return not isinstance(kind, (T.NullType, T.CalendarIntervalType))


@contextmanager
def freeing(spark: SparkSession) -> Iterator[None]:
    """What is planned and executed meanwhile leaves no shuffle files behind. Writes may overlap; the last one puts the switch back."""
    with _lock:
        _writing.append(spark.conf.get(_CLEANUP, "false") if not _writing else _writing[0])
        spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        with _lock:
            before = _writing.pop()
            if not _writing:
                spark.conf.set(_CLEANUP, before)


def sized(df: DataFrame, rows: int) -> DataFrame:
    """The same rows, not to be broadcast if they are too many. Spark goes by the size of files, and a table of few
    different values is small on disk whatever its number of rows."""
    return df.hint("merge") if rows > BROADCAST_ROWS else df


def settle(df: DataFrame, what: str = "table") -> DataFrame:
    """The same rows, written to the shared folder and read back: later plans start at the table. Rows with columns that
    Parquet lacks are persisted."""
    if not _storable(df.schema):
        return df.persist(StorageLevel.MEMORY_AND_DISK)
    spark, at, seen = df.sparkSession, scratch(df.sparkSession, what), Observation()
    for made in _passing:
        made.append(at)
    with freeing(spark):
        df.observe(seen, F.count(F.lit(1)).alias("rows")).write.parquet(at)
    out = sized(spark.read.schema(df.schema).parquet(at), seen.get["rows"])
    out._settled_at = at
    return out


def settle_all(dfs: Sequence[DataFrame], what: str = "table") -> list[DataFrame]:
    """Several tables, written at the same time."""
    if len(dfs) < 2:
        return [settle(d, what) for d in dfs]
    with ThreadPoolExecutor(min(4, len(dfs))) as pool:
        return list(pool.map(lambda d: settle(d, what), dfs))


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Tables settled and shuffle files made meanwhile are deleted in the end: for figures about rows that nothing reads afterwards."""
    made: list[str] = []
    _passing.append(made)
    try:
        with freeing(spark):
            yield
    finally:
        _passing[:] = [x for x in _passing if x is not made]
        for at in made:
            delete(spark, at)


def drop(df: DataFrame) -> None:
    """Delete a settled table that nothing reads any more."""
    if at := getattr(df, "_settled_at", None):
        delete(df.sparkSession, at)


def drop_unread(dfs: Sequence[DataFrame], readers: Sequence[DataFrame]) -> None:
    """Delete the settled tables among ``dfs`` that none of ``readers`` reads."""
    read = [f for d in readers for f in d.inputFiles()]
    for d in dfs:
        at = getattr(d, "_settled_at", None)
        if at and not any(at.rsplit("/", 1)[-1] in f for f in read):
            drop(d)


def shuffles(df: DataFrame) -> bool:
    """Whether making these rows moves data: a bare scan with projections and filters does not."""
    return "Exchange" in df._jdf.queryExecution().executedPlan().toString()


def narrow(df: DataFrame) -> bool:
    """Whether all columns have a fixed width, so that a number of rows bounds the bytes."""
    return all(isinstance(f.dataType, (T.NumericType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)) for f in df.schema.fields)


def small(df: DataFrame, rows: int) -> DataFrame:
    """Marked for broadcast if ``rows``, a count or a bound of its rows, and its columns allow it."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS and narrow(df) else df


def product(a: DataFrame, b: DataFrame, rows_a: int | None = None, rows_b: int | None = None) -> DataFrame:
    """Cross product of two sets of counted size; refused above PRODUCT_ROWS."""
    rows_a = a.count() if rows_a is None else rows_a
    rows_b = b.count() if rows_b is None else rows_b
    if rows_a * rows_b > PRODUCT_ROWS:
        raise ProductTooLarge(f"{rows_a} x {rows_b} rows; no relation links the two sides")
    return a.crossJoin(small(b, rows_b)) if rows_b <= rows_a else small(a, rows_a).crossJoin(b)
