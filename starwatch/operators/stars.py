"""Stars: neighbour-label histograms, neighbour sums and embeddings, whole or updated."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import edge_label_dict, embedding_columns, label_dict
from ..model import BuildParams, Graph


def neighbour_histogram(g: Graph, t: int | None = None, with_elabel: bool = False) -> DataFrame:
    """v, nlabel, cnt (and elabel): runs of equal neighbour labels, at most one per label whatever the degree."""
    adj = g.adjacency_at(t)
    keys = ["nlabel", "elabel"] if with_elabel else ["nlabel"]
    return adj.select(F.col("src").alias("v"), F.col("dst_label").alias("nlabel"), "elabel").groupBy("v", *keys).agg(F.count(F.lit(1)).cast("int").alias("cnt"))


def neighbour_sums(hist: DataFrame, dictionary: DataFrame, p: BuildParams, edge_dictionary: DataFrame | None = None) -> DataFrame:
    """v, deg, ns0..ns{d-1}: sums of the neighbours' label vectors (and their edges' label vectors)."""
    lv = dictionary.select(F.col("label").alias("nlabel"), *[f"lv{k}" for k in range(p.d)])
    rows = hist.join(F.broadcast(lv), "nlabel")  # one row per label
    value = [F.col(f"lv{k}") for k in range(p.d)]
    if edge_dictionary is not None:
        rows = rows.join(F.broadcast(edge_dictionary), "elabel")
        value = [x + F.col(f"ev{k}") for k, x in enumerate(value)]
    return rows.groupBy("v").agg(F.sum("cnt").cast("int").alias("deg"), *[F.sum(F.col("cnt") * x).alias(f"ns{k}") for k, x in enumerate(value)])


def stars(g: Graph, p: BuildParams, t: int | None = None, hist: DataFrame | None = None) -> DataFrame:
    """v, label, deg, ns*, e*: every vertex's star at time ``t``, isolated vertices included."""
    now = g.snapshot(t)
    hist = neighbour_histogram(g, t, p.elabel_weight) if hist is None else hist
    d = label_dict(now.vertices, p)
    ed = edge_label_dict(now.edge_life, p) if p.elabel_weight else None
    sums = neighbour_sums(hist, d, p, ed)
    full = now.vertices.select("v", "label").join(sums, "v", "left").fillna(0, ["deg", *[f"ns{k}" for k in range(p.d)]])
    return full.join(F.broadcast(d), "label").select("v", "label", "deg", *[f"ns{k}" for k in range(p.d)], *embedding_columns(p))


def star_deltas(ops: DataFrame, vertices: DataFrame, p: BuildParams) -> DataFrame:
    """v, d_deg, d_ns*: what updates (op, u, v) change, two rows per operation, summed by vertex."""
    both = ops.select("op", F.col("u").alias("v"), F.col("v").alias("w")).unionAll(ops.select("op", "v", F.col("u").alias("w")))
    d = label_dict(vertices, p)
    rows = both.join(vertices.select(F.col("v").alias("w"), "label"), "w").join(F.broadcast(d), "label")
    sign = F.when(F.col("op") == "+", 1).otherwise(-1)
    return rows.groupBy("v").agg(F.sum(sign).cast("int").alias("d_deg"), *[F.sum(sign * F.col(f"lv{k}")).alias(f"d_ns{k}") for k in range(p.d)])


def update_stars(star: DataFrame, ops: DataFrame, vertices: DataFrame, p: BuildParams) -> DataFrame:
    """Stars after updates: touched ones get the signed sums added, new vertices start from nothing."""
    delta = star_deltas(ops, vertices, p)
    cols = ["deg", *[f"ns{k}" for k in range(p.d)]]
    merged = star.select("v", *cols).join(delta, "v", "full_outer")
    merged = merged.select("v", *[(F.coalesce(c, F.lit(0)) + F.coalesce(f"d_{c}", F.lit(0))).alias(c) for c in cols])
    d = label_dict(vertices, p)
    return merged.join(vertices.select("v", "label"), "v").join(F.broadcast(d), "label").select("v", "label", F.col("deg").cast("int").alias("deg"), *cols[1:], *embedding_columns(p))


def update_histogram(hist: DataFrame, ops: DataFrame, vertices: DataFrame) -> DataFrame:
    """The histogram after updates: a counter per (v, neighbour label)."""
    return add_counts(hist, signed_counts(ops, vertices))


def signed_counts(ops: DataFrame, vertices: DataFrame) -> DataFrame:
    """v, nlabel, cnt: what updates (op, u, v) add to or take from the counters, two rows per operation."""
    both = ops.select("op", F.col("u").alias("v"), F.col("v").alias("w")).unionAll(ops.select("op", "v", F.col("u").alias("w")))
    rows = both.join(vertices.select(F.col("v").alias("w"), F.col("label").alias("nlabel")), "w")
    return rows.select("v", "nlabel", F.when(F.col("op") == "+", 1).otherwise(-1).alias("cnt"))


def add_counts(hist: DataFrame, signed: DataFrame) -> DataFrame:
    return hist.select("v", "nlabel", "cnt").unionAll(signed).groupBy("v", "nlabel").agg(F.sum("cnt").cast("int").alias("cnt")).filter("cnt > 0")


def peak_histogram(g: Graph, t0: int, t1: int) -> DataFrame:
    """v, nlabel, cnt: the largest count of each neighbour label at any time in [t0, t1].

    A superset of every version of the star in an epoch, so bounds computed from it are
    sound for the whole epoch.
    """
    adj = g.adjacency().filter((F.col("born") <= t1) & (F.col("died") > t0))
    key = [F.col("src").alias("v"), F.col("dst_label").alias("nlabel")]
    up = adj.select(*key, F.greatest("born", F.lit(t0)).alias("at"), F.lit(1).alias("x"))
    down = adj.filter(F.col("died") <= t1).select(*key, F.col("died").alias("at"), F.lit(-1).alias("x"))
    w = Window.partitionBy("v", "nlabel").orderBy("at", "x").rowsBetween(Window.unboundedPreceding, 0)
    return up.unionAll(down).withColumn("now", F.sum("x").over(w)).groupBy("v", "nlabel").agg(F.max("now").cast("int").alias("cnt"))
