"""Logical times of an epoch's records."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def numbered_epoch(batch: DataFrame, after: int) -> DataFrame:
    """Updates (seq, ts, op, u, v, elabel) with seq after + 1, after + 2, ... in the order
    (ts, deletions first, u, v): a row number per second plus the rows of earlier seconds."""
    e = batch.filter("u <> v").withColumn("_s", F.date_trunc("second", "ts")).withColumn("_o", F.when(F.col("op") == "-", 0).otherwise(1))
    n = e.groupBy("_s").agg(F.count(F.lit(1)).alias("_n"))
    before = n.select("_s", F.coalesce(F.sum("_n").over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_s").orderBy("ts", "_o", "u", "v"))
    return e.withColumn("_rank", rank).join(before, "_s").select((F.lit(after) + F.col("_before") + F.col("_rank")).alias("seq"), "ts", "op", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "elabel")
