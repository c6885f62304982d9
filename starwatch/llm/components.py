"""Connected components of a link table, by alternating stars; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import free, materialise


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """(node, component) for every node of ``edges`` (a, b long); component is the smallest node.

    Each round links every node's larger neighbours to the smallest node around it, then its
    smaller ones, until the table is a set of stars; the rounds grow with the logarithm of a
    component's length. Self-links name isolated nodes. Each round is a written table.
    """
    nodes = edges.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    links = materialise(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    state = None
    for _ in range(max_rounds):
        now = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == state or not now[0]:
            break
        state = now
        both = links.unionAll(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = materialise(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")), "least", 2 * now[0])
        large = both.filter("b > a").join(least.hint("merge"), "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        large = materialise(large, "large-star", 2 * now[0])
        low = materialise(large.groupBy("a").agg(F.min("b").alias("m")), "least", 2 * now[0])
        kept = large.join(low.hint("merge"), "a").filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        old, links = links, materialise(kept.unionAll(low.select("a", F.col("m").alias("b"))).distinct(), "links", 2 * now[0])
        free(old, least, large, low)
    else:
        raise RuntimeError("components: not settled")
    if state is None or not state[0]:
        return nodes.select("node", F.col("node").alias("component"))
    out = materialise(nodes.join(links.withColumnRenamed("a", "node"), "node", "left").select("node", F.coalesce("b", "node").alias("component")), "components", 2 * state[0])
    free(links)
    return out
