"""Structured Streaming: monitoring by epochs, stateful histograms, rates, sessions and late rows."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model import EDGE_LIFE, VERTICES, BuildParams
from ..operators.monitor import Monitor
from ..operators.refine import OUT
from ..plans.patterns import Patterns
from ..sources.io import RECORD, upsert_epoch
from ..storage import materialise, shared_root
from .numbering import numbered_epoch


class StreamMonitor:
    """Feeds a Monitor from a stream of update records, one epoch per trigger.

    Within a trigger the order is (ts, op, u, v) with deletions before insertions of the same
    time. Records older than the newest time seen less ``late_seconds`` do not rewrite history; they go to
    the table ``late``. Records that give a vertex another label than it has go to ``rejected`` and are not applied.

    ``store``: a folder on which everything is kept by epoch: edges, vertices, answers, late and rejected
    records, and last of all a row that says the epoch is done. A monitor made anew on the same folder goes on from
    the last such row, and a batch it names is skipped, so a restart neither repeats nor loses an epoch. Unset: a
    folder of this run.
    """

    TABLES = {"edge_life": EDGE_LIFE, "vertices": VERTICES, "answers": OUT}

    def __init__(self, spark: SparkSession, patterns: Patterns, vertices: DataFrame, params: BuildParams | None = None, late_seconds: int = 0, sink: str | None = None, store: str | None = None):
        self.spark, self.sink, self.late_seconds = spark, sink, late_seconds
        self.store = store or f"{shared_root(spark)}/stream-{uuid.uuid4().hex}"
        self.monitor = Monitor(None, vertices, patterns, params)
        self.last_batch, self.newest = -1, None
        self._resume()

    def _table(self, name: str, schema: str) -> DataFrame:
        """One of the epoch tables; empty until it is first written."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.store}/{name}")
        there = path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path)
        return self.spark.read.schema(f"{schema}, epoch BIGINT").parquet(f"{self.store}/{name}") if there else self.spark.createDataFrame([], f"{schema}, epoch BIGINT")

    def _resume(self) -> None:
        done = self._table("done", DONE).orderBy(F.desc("epoch")).first()
        if done is None:
            return
        m = self.monitor
        m.edge_life, m.vertices, m.state = (self._table(n, s).filter(F.col("epoch") == done.epoch).drop("epoch") for n, s in self.TABLES.items())
        m.now, self.newest, self.last_batch = done.now, done.newest, done.epoch

    def _write(self, df: DataFrame, name: str, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.store}/{name}/epoch={batch_id}")

    @property
    def late(self) -> DataFrame:
        return self._table("late", RECORD)

    @property
    def rejected(self) -> DataFrame:
        return self._table("rejected", RECORD)

    @property
    def late_rows(self) -> int:
        return self.late.count()

    def epoch(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last_batch:
            return
        batch = materialise(batch, "batch")  # read several times
        m = self.monitor
        if self.newest is not None:
            limit = F.lit(self.newest) - F.expr(f"INTERVAL {self.late_seconds} SECONDS")
            self._write(batch.filter(F.col("ts") < limit), "late", batch_id)
            batch = batch.filter(F.col("ts") >= limit)
        newest = batch.agg(F.max("ts")).first()[0]
        if newest is not None:
            self.newest = max(newest, self.newest) if self.newest else newest
            ends = batch.select(F.col("u").alias("v"), F.col("u_label").alias("label")).unionByName(batch.select("v", F.col("v_label").alias("label"))).filter("label IS NOT NULL").groupBy("v").agg(F.min("label").alias("label"))
            fresh = ends.join(m.vertices, "v", "left_anti").select("v", "label")
            known = materialise(m.vertices.select("v", "label").unionByName(fresh), "vertices")
            a, b = (known.select(F.col("v").alias(x), F.col("label").alias(f"_{x}")) for x in "uv")
            judged = materialise(batch.join(a, "u", "left").join(b, "v", "left").withColumn("_bad", F.coalesce((F.col("u_label") != F.col("_u")) | (F.col("v_label") != F.col("_v")), F.lit(False))).select(*batch.columns, "_bad"), "judged")
            self._write(judged.filter("_bad").drop("_bad"), "rejected", batch_id)
            m.vertices = known
            m.apply(numbered_epoch(judged.filter("NOT _bad").drop("_bad"), m.now))
        for name, df in zip(self.TABLES, (m.edge_life, m.vertices, m.state), strict=True):
            self._write(df, name, batch_id)
        self._write(self.spark.createDataFrame([(m.now, self.newest)], DONE), "done", batch_id)
        self.last_batch = batch_id
        if self.sink:
            upsert_epoch(m.answers(), self.sink, batch_id)

    def start(self, source: DataFrame, checkpoint: str, available_now: bool = True) -> StreamingQuery:
        writer = source.writeStream.foreachBatch(self.epoch).option("checkpointLocation", checkpoint)
        return (writer.trigger(availableNow=True) if available_now else writer).start()


DONE = "now BIGINT, newest TIMESTAMP"


def update_rates(updates: DataFrame, size: str = "1 day", slide: str | None = None, delay: str = "2 days") -> DataFrame:
    """Updates per tumbling (or sliding) window and operation; late rows beyond ``delay`` are left out."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    src = updates.withWatermark("ts", delay) if updates.isStreaming else updates
    return src.groupBy(w.alias("w"), "op").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "op", "n")


def user_sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Sessions of each user: events closer than ``gap``."""
    src = events.withWatermark("ts", gap) if events.isStreaming else events
    return src.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def without_repeats(updates: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Repeated deliveries of a record within ``delay`` are dropped."""
    return updates.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["ts", "op", "u", "v"])


HIST = "v long, nlabel int, cnt long"


def stateful_histogram(updates: DataFrame) -> DataFrame:
    """Streaming neighbour histogram: the counter of each (v, neighbour label) after each trigger."""
    both = updates.select("op", F.col("u").alias("v"), F.col("v_label").alias("nlabel")).unionAll(updates.select("op", "v", F.col("u_label").alias("nlabel")))

    def add(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = state.get[0] if state.exists else 0
        for f in frames:
            n += int((f["op"] == "+").sum() - (f["op"] == "-").sum())
        state.update((n,))
        yield pd.DataFrame({"v": [key[0]], "nlabel": [key[1]], "cnt": [n]})

    return both.groupBy("v", "nlabel").applyInPandasWithState(add, HIST, "n long", "update", GroupStateTimeout.NoTimeout)


def run_to_end(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a streaming frame over all that is there now, into a memory table."""
    spark = df.sparkSession
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{shared_root(spark)}/stream-{uuid.uuid4().hex}").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)
