"""Cutting lineage with tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from typing import TypeVar

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

T = TypeVar("T")
_local_root: str | None = None


def shared_root(spark: SparkSession) -> str:
    """The cluster's shared folder (spark.checkpoint.dir). Only a session whose executors run
    in the driver's own process may leave it unset; it then gets a temporary folder."""
    global _local_root
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    master = spark.conf.get("spark.master", "local")
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    if _local_root is None:
        _local_root = tempfile.mkdtemp(prefix="starwatch-")
    return f"file://{_local_root}"


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
        jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)
    except Exception:  # the session may already be closed at exit
        return


ROWS_PER_FILE = 500_000


def materialise(df: DataFrame, name: str, rows: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    ``rows``: a known bound on its narrow rows, which spares a small table many small files. ``by``: columns of few values; a reader
    of one of their values opens its files only. A value's rows go to a file, or to several if they are many.

    The table survives lost executors (unlike a local checkpoint). It is deleted by ``free``, at the
    latest when the driver's Python ends.
    """
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    if rows is not None:
        df = df.coalesce(1 + rows // ROWS_PER_FILE)
    (df.hint("rebalance", *by) if by else df).write.option("compression", "zstd").partitionBy(*by).parquet(path)
    atexit.register(_remove, spark, path)
    table = spark.read.schema(df.schema).parquet(path)
    table = table.select(df.columns) if by else table
    table._stored_at = path
    return table


def side_by_side(*calls: Callable[[], T]) -> list[T]:
    """The results of calls that do not need each other: on little data most of a job is waiting."""
    with ThreadPoolExecutor(len(calls)) as pool:
        return [x.result() for x in [pool.submit(f) for f in calls]]


#: Written tables that stand as one before they are written anew.
PIECES = 8


def grown(old: DataFrame, new: DataFrame, name: str) -> DataFrame:
    """The rows of a written table and of another beside it; only now and then is all of it written anew."""
    both, pieces = old.unionByName(new), old.__dict__.get("_pieces", 1) + 1
    if pieces > PIECES:
        return materialise(both, name)
    both._pieces = pieces
    return both


def small(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    """A table of a few rows known to the driver, as a part of the plan: reading it takes no job."""
    fields = StructType.fromDDL(schema)
    columns = list(zip(*rows, strict=True)) or [()] * len(fields)
    arrow = to_arrow_schema(fields)
    return spark.createDataFrame(pa.table([pa.array(c, f.type) for c, f in zip(columns, arrow, strict=True)], schema=arrow), fields)


def free(*tables: DataFrame | None) -> None:
    """Delete tables that ``materialise`` wrote, once all that reads them is itself written.

    Shuffle files of finished plans go when the driver's JVM collects the plans, so it is asked to.
    """
    stored = [t for t in tables if getattr(t, "_stored_at", None)]
    for t in stored:
        _remove(t.sparkSession, t._stored_at)
        t._stored_at = None
    if stored:
        drop_shuffles(stored[0].sparkSession)


def drop_shuffles(spark: SparkSession) -> None:
    """Let the executors delete the shuffle files of plans that nobody holds any more."""
    gc.collect()
    spark._jvm.System.gc()
