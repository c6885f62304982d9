"""Written tables in the shared folder (the library's own helper), and Arrow batches fit for texts."""

from pyspark.sql import SparkSession

from ..storage import drop_shuffles, free, materialise, shared_root

__all__ = ["drop_shuffles", "free", "materialise", "shared_root", "small_batches"]

BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    """Batches of at most BATCH_ROWS rows between the JVM and its Python workers, if the session allows more.

    Rows here are whole texts of some kilobytes: the usual 10,000 of them stand several times over in
    the executor's memory outside the heap, and in the worker's."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name, "10000")) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))
