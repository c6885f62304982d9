"""Reading updates from files and streams, and writing answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A streamed record carries the labels of its ends, so new vertices are defined by it.
RECORD = "ts TIMESTAMP, op STRING, u BIGINT, v BIGINT, u_label INT, v_label INT, elabel INT"
KAFKA = "key BINARY, value BINARY, topic STRING, partition INT, offset BIGINT, timestamp TIMESTAMP, timestampType INT"


def read_updates(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Update records from Parquet, CSV (with header) or JSON lines; the schema is fixed, never inferred."""
    reader = spark.read.schema(RECORD)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path) if fmt == "json" else reader.parquet(path)


def stream_updates(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(RECORD).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def from_kafka_shape(df: DataFrame) -> DataFrame:
    """Records from a frame of the Kafka source's shape whose value is JSON."""
    return df.select(F.from_json(F.col("value").cast("string"), RECORD).alias("r")).select("r.*")


def rate_updates(spark: SparkSession, rows_per_second: int, vertices: int) -> DataFrame:
    """A load generator: hashed edges over ``vertices`` vertices from the rate source."""
    r = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    u, v = F.col("value") * 7919 % vertices, (F.col("value") * 104729 + 13) % vertices
    return r.filter(u != v).select(F.col("timestamp").alias("ts"), F.lit("+").alias("op"), F.least(u, v).alias("u"), F.greatest(u, v).alias("v"), (F.least(u, v) % 15 + 1).cast("int").alias("u_label"), (F.greatest(u, v) % 15 + 1).cast("int").alias("v_label"), F.lit(1).alias("elabel"))


def write_answers(answers: DataFrame, path: str) -> None:
    answers.write.mode("overwrite").partitionBy("query_id").parquet(path)


def export_json(answers: DataFrame, path: str) -> None:
    answers.write.mode("overwrite").json(path)


def upsert_epoch(answers: DataFrame, path: str, epoch: int) -> None:
    """One directory per epoch, overwritten if the epoch is run again, so a restart adds nothing twice."""
    answers.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")
