"""Batch updates: grouped boxes of pattern edges and data edges, compared group by group first."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import all_of
from ..model import BuildParams
from ..plans.patterns import Patterns, embed_patterns

GROUP_CELLS = 4


def edge_group_pairs(ops: DataFrame, star: DataFrame, patterns: Patterns, p: BuildParams, cells: int = GROUP_CELLS) -> tuple[DataFrame, DataFrame]:
    """(surviving group pairs, surviving pairs of a pattern edge and an updated data edge).

    Data edges (both ways round) are grouped by labels-range cells of their ends and the
    magnitude of their embeddings; a group has a label box and a largest corner, a pattern group a label box and a
    smallest corner. Groups whose label boxes meet and whose corners dominate are opened.
    The number of groups is at most cells^2 times the magnitudes, so comparing groups is bounded.
    """
    s = star.select("v", "label", *[f"e{k}" for k in p.dims])
    both = ops.select("u", "v").unionAll(ops.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct()
    a = s.select(F.col("v").alias("u"), F.col("label").alias("la"), *[F.col(f"e{k}").alias(f"a{k}") for k in p.dims])
    b = s.select("v", F.col("label").alias("lb"), *[F.col(f"e{k}").alias(f"b{k}") for k in p.dims])
    data = both.join(a, "u").join(b, "v")
    spark = star.sparkSession
    q = embed_patterns(spark, patterns, p)
    qe = patterns.q_edge(spark).select("query_id", "qi", "qj")
    qa = q.select("query_id", F.col("qv").alias("qi"), F.col("label").alias("la"), *[F.col(f"q{k}").alias(f"a{k}") for k in p.dims])
    qb = q.select("query_id", F.col("qv").alias("qj"), F.col("label").alias("lb"), *[F.col(f"q{k}").alias(f"b{k}") for k in p.dims])
    query = qe.join(qa, ["query_id", "qi"]).join(qb, ["query_id", "qj"])
    group = [F.expr(f"la div {cells}").alias("ga"), F.expr(f"lb div {cells}").alias("gb"), F.floor(F.log2(F.col(f"a{p.d}") + 1)).cast("int").alias("gm")]
    corner = [f"{x}{k}" for x in "ab" for k in p.dims]
    data, query = data.withColumns({"ga": group[0], "gb": group[1], "gm": group[2]}), query.withColumns({"ga": group[0], "gb": group[1], "gm": group[2]})
    label_box = [f(c).alias(f"{w}_{c}") for c in ("la", "lb") for w, f in (("lo", F.min), ("hi", F.max))]
    dg = data.groupBy("ga", "gb", "gm").agg(*label_box, *[F.max(c).alias(f"top_{c}") for c in corner])
    qg = query.groupBy("ga", "gb", "gm").agg(*[x.alias(f"q_{n}") for x, n in zip([f(c) for c in ("la", "lb") for f in (F.min, F.max)], ("lo_la", "hi_la", "lo_lb", "hi_lb"), strict=True)], *[F.min(c).alias(f"low_{c}") for c in corner])
    qg = qg.withColumnsRenamed({"ga": "q_ga", "gb": "q_gb", "gm": "q_gm"})
    meet = all_of([F.col(f"lo_{c}") <= F.col(f"q_hi_{c}") for c in ("la", "lb")] + [F.col(f"q_lo_{c}") <= F.col(f"hi_{c}") for c in ("la", "lb")] + [F.col(f"low_{c}") <= F.col(f"top_{c}") for c in corner])
    pairs = dg.join(patterns.hinted(qg), meet).select("ga", "gb", "gm", "q_ga", "q_gb", "q_gm")
    opened = data.join(pairs, ["ga", "gb", "gm"])
    inner = query.withColumnsRenamed({"ga": "q_ga", "gb": "q_gb", "gm": "q_gm", **{c: f"q_{c}" for c in ("la", "lb", *corner)}})
    same = all_of([F.col("la") == F.col("q_la"), F.col("lb") == F.col("q_lb"), *[F.col(f"q_{c}") <= F.col(c) for c in corner]])
    hits = opened.join(patterns.hinted(inner), ["q_ga", "q_gb", "q_gm"]).filter(same).select("query_id", "qi", "qj", "u", "v").distinct()
    return pairs, hits
