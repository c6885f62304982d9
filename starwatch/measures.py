"""Measures: pruning power, selectivity, work counters, times and exactness."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans.patterns import Patterns


def pruning_power(cand: DataFrame, star: DataFrame, patterns: Patterns) -> DataFrame:
    """query_id, qv, n_cand, n_vertices, pruned_share: the share of vertices ruled out."""
    q = patterns.q_vertex(star.sparkSession).select("query_id", "qv")
    n = cand.groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("n_cand"))
    total = star.agg(F.count(F.lit(1)).alias("n_vertices"))
    rows = q.join(n, ["query_id", "qv"], "left").fillna(0, ["n_cand"]).join(F.broadcast(total))
    return rows.withColumn("pruned_share", F.round(1 - F.col("n_cand") / F.col("n_vertices"), 6))


def pruning_cube(by_stage: dict[str, DataFrame], star: DataFrame, patterns: Patterns) -> DataFrame:
    """Candidates by stage and pattern with all subtotals (nulls stand for all)."""
    out = None
    for stage, cand in by_stage.items():
        rows = cand.select(F.lit(stage).alias("stage"), "query_id")
        out = rows if out is None else out.unionAll(rows)
    return out.cube("stage", "query_id").agg(F.count(F.lit(1)).alias("n_cand"))


def selectivity_box(cand: DataFrame, patterns: Patterns) -> DataFrame:
    """Minimum, quartiles and maximum of the candidate counts over all pattern vertices."""
    q = patterns.q_vertex(cand.sparkSession).select("query_id", "qv")
    n = q.join(cand.groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("n")), ["query_id", "qv"], "left").fillna(0, ["n"])
    return n.agg(F.min("n").alias("least"), *[F.expr(f"percentile(n, {x})").alias(name) for x, name in ((0.25, "lower"), (0.5, "middle"), (0.75, "upper"))], F.max("n").alias("most"))


def exactness(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: n_found, n_true, n_common, precision, recall of two sets of equal columns."""
    cols = sorted(truth.columns)
    a, b = found.select(*cols).distinct(), truth.select(*cols).distinct()
    both = a.withColumn("_f", F.lit(1)).join(b.withColumn("_t", F.lit(1)), cols, "full_outer")
    n = both.agg(F.coalesce(F.sum("_f"), F.lit(0)).alias("n_found"), F.coalesce(F.sum("_t"), F.lit(0)).alias("n_true"), F.count_if(F.col("_f").isNotNull() & F.col("_t").isNotNull()).alias("n_common"))
    share = lambda d: F.when(F.col(d) == 0, 1.0).otherwise(F.col("n_common") / F.col(d))
    return n.withColumn("precision", share("n_found")).withColumn("recall", share("n_true"))


class Timer:
    """Wall clock by phase; rows (graph, workload, method, phase, metric, value)."""

    def __init__(self, graph: str, workload: str):
        self.graph, self.workload, self.rows = graph, workload, []

    def run(self, method: str, phase: str, f: Callable[[], DataFrame]) -> int:
        began = time.time()
        n = f().count()
        self.rows += [(self.graph, self.workload, method, phase, "seconds", time.time() - began), (self.graph, self.workload, method, phase, "rows", float(n))]
        return n

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "graph string, workload string, method string, phase string, metric string, value double")

    def seconds(self, method: str) -> float:
        return sum(r[5] for r in self.rows if r[2] == method and r[4] == "seconds")


def per_edge_cost(seconds: float, n_ops: int) -> float:
    """Microseconds per update."""
    return 1e6 * seconds / max(1, n_ops)


def speedup_log10(ours: float, theirs: float) -> float:
    """Orders of magnitude between two times."""
    return math.log10(theirs / ours)


def work_counters(stages: dict[str, DataFrame]) -> list[tuple[str, int]]:
    """Rows of each named stage: cells visited, vertices compared, partial matches and so on."""
    return [(name, df.count()) for name, df in stages.items()]
