"""Degree bands, degree boxes and upper corners."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vectors import label_dict
from ..model import BuildParams
from ..storage import materialise

OPEN = (1 << 31) - 1  # the last band has no upper end: degrees may grow


def degree_histogram(star: DataFrame) -> DataFrame:
    return star.filter("deg > 0").groupBy("deg").agg(F.count(F.lit(1)).alias("n"))


def degree_bands(star: DataFrame, m: int, mode: str = "equal") -> DataFrame:
    """band, lo_excl, hi_incl from the survival mass P(degree >= delta).

    The j-th boundary is the smallest degree at which the running mass reaches j/m of the
    total. ``mode='single'``: one band per degree that occurs. The windows run over the histogram of
    degrees only.
    """
    h = degree_histogram(star)
    if mode == "single":
        w = Window.orderBy("deg")
        rows = h.select(F.row_number().over(w).cast("int").alias("band"), F.lag("deg", 1, 0).over(w).cast("int").alias("lo_excl"), F.col("deg").cast("int").alias("hi_incl"), F.lead("deg").over(w).alias("_next"))
        return rows.select("band", "lo_excl", F.when(F.col("_next").isNull(), F.lit(OPEN)).otherwise(F.col("hi_incl")).alias("hi_incl"))
    # vertices of degree >= x, for each x from 1 up: degrees between two that occur repeat the next one's
    tail = F.sum("n").over(Window.orderBy(F.desc("deg")).rowsBetween(Window.unboundedPreceding, 0))
    seen = h.withColumn("s", tail).withColumn("from", F.lag("deg", 1, 0).over(Window.orderBy("deg")))
    # running mass at the end of each gap (from, deg] is a straight line inside it
    mass = seen.withColumn("upto", F.sum(F.col("s") * (F.col("deg") - F.col("from"))).over(Window.orderBy("deg").rowsBetween(Window.unboundedPreceding, 0)))
    total = mass.agg(F.max("upto").alias("total"))
    parts = mass.crossJoin(F.broadcast(total)).select("*", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("j")) if m > 1 else None
    if parts is None:
        return star.sparkSession.createDataFrame([(1, 0, OPEN)], "band int, lo_excl int, hi_incl int")
    before = F.col("upto") - F.col("s") * (F.col("deg") - F.col("from"))
    need = F.ceil((F.col("j") * F.col("total") - before * m) / (F.lit(m) * F.col("s")))
    hit = parts.filter(F.col("upto") * m >= F.col("j") * F.col("total")).groupBy("j").agg(F.min(F.struct("deg", (F.col("from") + F.greatest(need, F.lit(1))).alias("at"))).getField("at").alias("at"))
    hit = hit.withColumn("hi", F.when(F.col("j") == m, F.lit(OPEN)).otherwise(F.col("at")).cast("int")).groupBy("hi").agg(F.min("j").alias("j"))
    w = Window.orderBy("hi")
    return hit.select(F.row_number().over(w).cast("int").alias("band"), F.lag("hi", 1, 0).over(w).cast("int").alias("lo_excl"), F.col("hi").alias("hi_incl"))


def wanted_boxes(star: DataFrame, deltas: DataFrame) -> DataFrame:
    """v, delta: every vertex with the given degrees that it reaches."""
    return star.select("v", "deg").join(F.broadcast(deltas), F.col("delta") <= F.col("deg")).select("v", F.col("delta").cast("int").alias("delta"))


def degree_boxes(hist: DataFrame, star: DataFrame, deltas: DataFrame, p: BuildParams) -> DataFrame:
    """v, label, deg, delta, lo*, hi*: bounds of the embeddings of all sub-stars with ``delta`` neighbours.

    ``deltas(delta)``: the degrees wanted (those of the registered patterns; a few). Sums of the delta smallest and
    largest neighbour values come from runs of equal labels: a run adds what of delta the
    runs before it have left, at most its count. Neither sub-stars nor sorted neighbour lists are built.
    """
    return degree_boxes_for(hist, star, wanted_boxes(star, deltas), p)


def boxes_by_enumeration(hist: DataFrame, star: DataFrame, deltas: DataFrame, p: BuildParams, limit: int = 10) -> DataFrame:
    """The same boxes by listing every sub-star, for degrees up to ``limit``; only to test with."""
    d = label_dict(star.select("label").unionAll(hist.select(F.col("nlabel").alias("label"))), p)
    lv = d.select(F.col("label").alias("nlabel"), *[f"lv{k}" for k in range(p.d)])
    each = hist.join(F.broadcast(lv), "nlabel").withColumn("_i", F.explode(F.sequence(F.lit(1), "cnt")))
    lists = each.groupBy("v").agg(F.collect_list(F.struct(*[f"lv{k}" for k in range(p.d)])).alias("n")).filter(F.size("n") <= limit)
    masks = lists.withColumn("mask", F.explode(F.sequence(F.lit(1), F.expr("CAST(shiftleft(1, size(n)) - 1 AS INT)"))))
    subs = masks.withColumn("sub", F.expr("filter(n, (x, i) -> (shiftright(mask, i) & 1) = 1)")).withColumn("delta", F.size("sub"))
    sums = subs.select("v", "delta", *[F.expr(f"aggregate(sub, 0L, (s, x) -> s + x.lv{k})").alias(f"s{k}") for k in range(p.d)])
    got = sums.groupBy("v", "delta").agg(*[f(f"s{k}").alias(f"s_{w}{k}") for k in range(p.d) for w, f in (("lo", F.min), ("hi", F.max))]).join(deltas, "delta", "left_semi")
    out = got.join(star.select("v", "label", "deg", *[f"e{k}" for k in range(p.d)]), "v").join(F.broadcast(d.select("label", *[f"bv{k}" for k in p.dims])), "label")
    cols = [F.col(f"e{k}").alias(f"{w}{k}") if k < p.d else (F.col(f"s_{w}{k - p.d}") + (0 if p.variant == "plain" else p.ratio * F.col(f"bv{k}"))).alias(f"{w}{k}") for k in p.dims for w in ("lo", "hi")]
    return out.select("v", "label", "deg", F.col("delta").cast("int").alias("delta"), *cols)


def in_bands(star: DataFrame, bands: DataFrame) -> DataFrame:
    """A vertex enters every band that begins below its degree: adds band and delta = min(deg, band end)."""
    b = F.broadcast(bands.select("band", "lo_excl", "hi_incl"))  # a row per band
    return star.join(b, F.col("deg") > F.col("lo_excl")).withColumn("delta", F.least("deg", "hi_incl").cast("int")).drop("lo_excl", "hi_incl")


def upper_corners(hist: DataFrame, star: DataFrame, bands: DataFrame, p: BuildParams) -> DataFrame:
    """v, label, deg, band, ub*: in each band, the box corner of the largest sub-stars the band allows."""
    member = in_bands(star.select("v", "label", "deg"), bands)
    return _corners(member, degree_boxes_for(hist, star, member.select("v", "delta").distinct(), p), p)


def corners_and_boxes(hist: DataFrame, star: DataFrame, bands: DataFrame, deltas: DataFrame, p: BuildParams, d: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``upper_corners`` and ``degree_boxes`` from one pass over the runs, which is written; ``d``: the label dictionary."""
    member = in_bands(star.select("v", "label", "deg"), bands)
    wanted = member.select("v", "delta").unionByName(wanted_boxes(star, deltas)).distinct()
    every = materialise(degree_boxes_for(hist, star, wanted, p, d), "all-boxes")
    return _corners(member, every, p), every.join(F.broadcast(deltas.select(F.col("delta").cast("int").alias("delta"))), "delta", "left_semi")


def _corners(member: DataFrame, boxes: DataFrame, p: BuildParams) -> DataFrame:
    return member.join(boxes.drop("label", "deg"), ["v", "delta"]).select("v", "label", "deg", "band", *[F.col(f"hi{k}").alias(f"ub{k}") for k in p.dims])


def degree_boxes_for(hist: DataFrame, star: DataFrame, wanted: DataFrame, p: BuildParams, d: DataFrame | None = None) -> DataFrame:
    """Boxes at given (v, delta) pairs, delta <= deg; ``d``: the label dictionary, if it is known."""
    if d is None:
        d = label_dict(star.select("label").unionAll(hist.select(F.col("nlabel").alias("label"))), p)
    lv = d.select(F.col("label").alias("nlabel"), *[f"lv{k}" for k in range(p.d)])
    runs = hist.join(F.broadcast(lv), "nlabel")
    for k in range(p.d):
        for way, order in (("lo", F.asc(f"lv{k}")), ("hi", F.desc(f"lv{k}"))):
            w = Window.partitionBy("v").orderBy(order, "nlabel").rowsBetween(Window.unboundedPreceding, -1)
            runs = runs.withColumn(f"_{way}{k}", F.coalesce(F.sum("cnt").over(w), F.lit(0)))
    rows = runs.join(wanted, "v")
    sums = []
    for k in range(p.d):
        for way in ("lo", "hi"):
            take = F.least(F.col("cnt"), F.greatest(F.lit(0), F.col("delta") - F.col(f"_{way}{k}")))
            sums.append(F.sum(take * F.col(f"lv{k}")).alias(f"s_{way}{k}"))
    got = rows.groupBy("v", "delta").agg(*sums)
    out = got.join(star.select("v", "label", "deg", *[f"e{k}" for k in range(p.d)]), "v").join(F.broadcast(d.select("label", *[f"bv{k}" for k in p.dims])), "label")
    cols = [F.col(f"e{k}").alias(f"{w}{k}") if k < p.d else (F.col(f"s_{w}{k - p.d}") + (0 if p.variant == "plain" else p.ratio * F.col(f"bv{k}"))).alias(f"{w}{k}") for k in p.dims for w in ("lo", "hi")]
    return out.select("v", "label", "deg", "delta", *cols)


def bands_from(spark: SparkSession, ends: list[int]) -> DataFrame:
    """Bands with given upper ends (the last one is open)."""
    rows = [(i + 1, ends[i - 1] if i else 0, e if i < len(ends) - 1 else OPEN) for i, e in enumerate(ends)]
    return spark.createDataFrame(rows, "band int, lo_excl int, hi_incl int")
