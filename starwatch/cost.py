"""The cost model: expected candidates of a pattern vertex from means and variances per dimension."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.arithmetic import normal_cdf
from .model import BuildParams
from .plans.patterns import Patterns, embed_patterns


def moments(star: DataFrame, p: BuildParams, by_label: bool = False) -> DataFrame:
    """n, mu*, var* of the embedding, over all vertices or per centre label."""
    aggs = [F.count(F.lit(1)).alias("n"), *[F.avg(f"e{k}").alias(f"mu{k}") for k in p.dims], *[F.var_pop(F.col(f"e{k}").cast("double")).alias(f"var{k}") for k in p.dims]]
    return star.groupBy("label").agg(*aggs) if by_label else star.agg(*aggs)


def cost_estimate(star: DataFrame, patterns: Patterns, p: BuildParams, form: str = "standardised", unit: float = 65536.0, by_label: bool = False) -> DataFrame:
    """query_id, qv, estimate: the expected number of vertices that dominate the pattern vertex.

    ``printed`` divides the distance by the variance, so it depends on the unit in which vectors
    are counted; ``standardised`` divides by the standard deviation. ``by_label`` takes moments per
    centre label (an extension: base vectors make dimensions depend on the label).
    """
    q = patterns.hinted(embed_patterns(star.sparkSession, patterns, p))
    m = moments(star, p, by_label)
    rows = m.join(q, "label") if by_label else q.join(F.broadcast(m))
    product = "CAST(n AS DOUBLE)"
    for k in p.dims:
        if form == "printed":
            t = f"((mu{k} - q{k}) / {unit!r}D / (var{k} / {unit!r}D / {unit!r}D))"
        else:
            t = f"((mu{k} - q{k}) / sqrt(var{k}))"
        product += f" * CASE WHEN var{k} > 0 THEN {normal_cdf(t)} WHEN mu{k} >= q{k} THEN 1.0 ELSE 0.0 END"
    return rows.select("query_id", "qv", F.expr(product).alias("estimate"))


def calibration(estimate: DataFrame, actual: DataFrame) -> DataFrame:
    """query_id, qv, estimate, actual, log2_ratio: estimates beside counted candidates."""
    n = actual.groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("actual"))
    rows = estimate.join(n, ["query_id", "qv"], "left").fillna(0, ["actual"])
    return rows.withColumn("log2_ratio", F.log2((F.col("estimate") + 1) / (F.col("actual") + 1)))


def rank_variants(star_of, patterns: Patterns, variants: tuple[str, ...] = ("plain", "based", "skew_based")) -> list[tuple[str, float]]:
    """Embedding variants by total estimated candidates, best first; ``star_of(params)`` gives their stars."""
    out = []
    for v in variants:
        p = BuildParams(variant=v)
        out.append((v, cost_estimate(star_of(p), patterns, p).agg(F.sum("estimate")).first()[0] or 0.0))
    return sorted(out, key=lambda x: (x[1], x[0]))


def dominance_region(star: DataFrame, patterns: Patterns, query_id: int, qv: int, p: BuildParams) -> DataFrame:
    """v, x, y, dominates, label_ok: the points of two dimensions and whether they lie beyond the query point."""
    q = embed_patterns(star.sparkSession, patterns, p).filter((F.col("query_id") == query_id) & (F.col("qv") == qv)).withColumnRenamed("label", "q_label").drop("deg")
    test = F.lit(True)
    for k in p.dims:
        test = test & (F.col(f"q{k}") <= F.col(f"e{k}"))
    return star.join(F.broadcast(q)).select("v", F.col("e0").alias("x"), F.col(f"e{p.d}").alias("y"), test.alias("dominates"), (F.col("label") == F.col("q_label")).alias("label_ok"))
