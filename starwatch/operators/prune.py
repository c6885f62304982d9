"""Candidate vertices: cell filter, dominance pruning, box pruning, and baseline filters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import all_of, dominates, in_box
from ..model import BuildParams
from ..plans.patterns import Patterns, embed_patterns
from .synopsis import Index

STAGES = ("cell", "label", "dominance", "box")


def banded_queries(index: Index, patterns: Patterns) -> DataFrame:
    """Embedded pattern vertices with the band of their degree and their key (sum of squares)."""
    spark = index.star.sparkSession
    p = index.params
    q = embed_patterns(spark, patterns, p)
    q = q.join(F.broadcast(index.bands), (F.col("deg") > F.col("lo_excl")) & (F.col("deg") <= F.col("hi_incl"))).drop("lo_excl", "hi_incl")
    key = F.expr(" + ".join(f"CAST(q{k} AS DOUBLE) * CAST(q{k} AS DOUBLE)" for k in p.dims))
    return q.withColumnRenamed("label", "q_label").withColumnRenamed("deg", "q_deg").withColumn("q_key", key)


def cells_visited(index: Index, patterns: Patterns) -> DataFrame:
    """query_id, qv, n_cells, n_in_cells: occupied cells that survive the key and corner tests."""
    p = index.params
    q = patterns.hinted(banded_queries(index, patterns).withColumnRenamed("band", "q_band"))
    ok = (F.col("band") == F.col("q_band")) & (F.col("cell_key") >= F.col("q_key")) & all_of([F.col(f"cu{k}") >= F.col(f"q{k}") for k in p.dims])
    return index.cells().join(q, ok).groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("n_cells"), F.sum("n_vertices").alias("n_in_cells"))


def candidates(index: Index, patterns: Patterns, stages: tuple[str, ...] = STAGES) -> DataFrame:
    """cand(query_id, qv, v): vertices that survive the given stages.

    One broadcast join does cells, labels and dominance (an equality on band, and on label where
    asked, with comparisons left over), a second the boxes. A vertex's degree must reach the
    pattern vertex's in any case that uses boxes.
    """
    p = index.params
    q = patterns.hinted(banded_queries(index, patterns).withColumnRenamed("band", "q_band"))
    tests = [F.col("band") == F.col("q_band")]
    if "cell" in stages:
        tests += [F.col("cell_key") >= F.col("q_key"), *[F.col(f"cu{k}") >= F.col(f"q{k}") for k in p.dims]]
    if "label" in stages:
        tests.append(F.col("label") == F.col("q_label"))
    if "dominance" in stages:
        tests.append(dominates("q", "ub", p))
    out = index.synopsis.join(q, all_of(tests))
    if "box" in stages:
        boxes = index.boxes.select("v", F.col("delta").alias("q_deg"), *[f"{w}{k}" for k in p.dims for w in ("lo", "hi")])
        out = out.join(boxes, ["v", "q_deg"]).filter(in_box("q", p))
    return out.select("query_id", "qv", "v")


def label_only(star: DataFrame, patterns: Patterns) -> DataFrame:
    """Baseline: label equality."""
    q = patterns.hinted(patterns.q_vertex(star.sparkSession).select("query_id", "qv", "label"))
    return star.select("v", "label").join(q, "label").select("query_id", "qv", "v")


def full_star_dominance(star: DataFrame, patterns: Patterns, p: BuildParams, with_label: bool = False) -> DataFrame:
    """Dominance against the whole star, without bands or grid."""
    q = patterns.hinted(embed_patterns(star.sparkSession, patterns, p).withColumnRenamed("label", "q_label").drop("deg"))
    test = dominates("q", "e", p)
    if with_label:
        test = test & (F.col("label") == F.col("q_label"))
    return star.join(q, test).select("query_id", "qv", "v")


def label_frequency(hist: DataFrame, star: DataFrame, patterns: Patterns) -> DataFrame:
    """Exact containment of neighbour labels with counts: the best a one-hop filter can do."""
    spark = star.sparkSession
    need = [(q, i, pat.labels[i], pat.labels[j]) for q, pat in patterns for i in range(len(pat.labels)) for j in pat.neighbours(i)]
    q = spark.createDataFrame(need, "query_id int, qv int, label int, nlabel int").groupBy("query_id", "qv", "label", "nlabel").agg(F.count(F.lit(1)).alias("need"))
    kinds = q.groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("kinds"))
    rows = hist.join(star.select("v", "label"), "v").join(patterns.hinted(q), ["label", "nlabel"]).filter("cnt >= need")
    return rows.groupBy("query_id", "qv", "v").agg(F.count(F.lit(1)).alias("got")).join(patterns.hinted(kinds), ["query_id", "qv"]).filter("got = kinds").select("query_id", "qv", "v")


def update_candidates(cand: DataFrame, after: Index, patterns: Patterns, touched: DataFrame) -> DataFrame:
    """Candidates after updates: only the touched vertices' rows of the index as it is now are judged."""
    fresh = candidates(after.of_vertices(touched), patterns)
    return cand.join(touched, "v", "left_anti").select("query_id", "qv", "v").unionByName(fresh)
