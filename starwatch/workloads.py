"""The experiment workloads: each returns a long table (graph, workload, method, phase, metric, value)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, measures
from .functions.vectors import label_dict
from .model import ALIVE, BuildParams, Graph, split_label
from .operators import monitor, prune, refine, synopsis
from .operators.stars import stars
from .plans.patterns import Patterns, trade_pattern
from .sources import synth, views

DEFAULT_PATTERNS = Patterns([trade_pattern(n) for n in ("triangle", "star3", "tri_tail", "two_tri")])
#: Ranges of the parameter studies.
RANGES = {"d": (1, 2, 3, 4), "ratio": (10, 100, 1_000, 10_000, 100_000), "k": (1, 2, 5, 8, 10), "m": (1, 2, 3, 4, 5), "variant": ("plain", "based", "skew_based")}
INSERT_PERCENTS = (10, 20, 30, 40, 50)
DELETE_PERCENTS = (10, 20, 30, 40, 50)
LABELS = (5, 10, 15, 20, 25)
PATTERN_DEGREES = (2.0, 2.5, 3.0, 3.5, 4.0)
PATTERN_SIZES = (5, 6, 8, 10, 12)
GRAPH_DEGREES = ((2, 0.5), (4, 0.0), (4, 0.25), (4, 0.5), (6, 0.17))  # (ring neighbours, chord share): about 3 to 7
GRAPH_SIZES = (10_000, 30_000, 50_000, 80_000, 100_000, 1_000_000, 10_000_000)


def parameter_study(spark: SparkSession, g: Graph, patterns: Patterns, parameter: str, values=None) -> DataFrame:
    """One parameter varied: candidates after each stage, cells, build and filter times."""
    timer = measures.Timer(g.name, f"vary_{parameter}")
    for x in values or RANGES[parameter]:
        p = BuildParams().but(**{parameter: x})
        method = f"{parameter}={x}"
        ix = synopsis.Index(g, p, patterns.deltas(spark), 0)
        timer.run(method, "index", lambda ix=ix: ix.synopsis)
        timer.run(method, "cells", lambda ix=ix: prune.cells_visited(ix, patterns))
        for stage in (("cell",), ("cell", "dominance"), prune.STAGES):
            timer.run(method, "+".join(stage), lambda ix=ix, stage=stage: prune.candidates(ix, patterns, stage))
    return timer.table(spark)


def filters(spark: SparkSession, g: Graph, patterns: Patterns) -> DataFrame:
    """Pruning by design and by baseline filters, per stage."""
    timer = measures.Timer(g.name, "pruning")
    for v in RANGES["variant"]:
        ix = synopsis.Index(g, BuildParams(variant=v), patterns.deltas(spark), 0)
        timer.run(v, "full_star", lambda ix=ix: prune.full_star_dominance(ix.star, patterns, ix.params))
        timer.run(v, "all", lambda ix=ix: prune.candidates(ix, patterns))
    timer.run("label_only", "all", lambda: prune.label_only(ix.star, patterns))
    timer.run("label_freq", "all", lambda: prune.label_frequency(ix.hist, ix.star, patterns))
    timer.run("all_vertices", "all", lambda: ix.star)
    return timer.table(spark)


def insertions(spark: SparkSession, sf_dir: str, percents=INSERT_PERCENTS, patterns: Patterns = DEFAULT_PATTERNS, full: bool = False) -> DataFrame:
    """Insertion rates: our delta with candidates against the plain delta join and recomputation."""
    v, e = views.trade_vertices(spark, sf_dir), views.trade_edges(spark, sf_dir, full)
    timer = measures.Timer("trade_full" if full else "trade", "insertions")
    for r in percents:
        g = views.insertion_stream(v, e, r, "trade").stored()
        timer.run(f"ours {r}%", "delta", lambda g=g: monitor.on_insert(g, patterns, 0, ALIVE - 1, monitor.peak_candidates(g, patterns, BuildParams(), 0, ALIVE - 1)))
        timer.run(f"delta_join {r}%", "delta", lambda g=g: baselines.delta_join(g, patterns, 0, ALIVE - 1))
        timer.run(f"lifetimes {r}%", "delta", lambda g=g: refine.lifetimes(g, patterns).filter("born > 0"))
        n = g.edge_life.filter("born > 0").count()
        seconds = timer.seconds(f"ours {r}%")
        timer.rows.append((timer.graph, "insertions", f"ours {r}%", "delta", "microseconds_per_edge", measures.per_edge_cost(seconds, n)))
        timer.rows.append((timer.graph, "insertions", f"ours {r}%", "delta", "log10_against_delta_join", measures.speedup_log10(seconds, timer.seconds(f"delta_join {r}%"))))
    return timer.table(spark)


def deletions(spark: SparkSession, sf_dir: str, percents=DELETE_PERCENTS, patterns: Patterns = DEFAULT_PATTERNS) -> DataFrame:
    v, e = views.trade_vertices(spark, sf_dir), views.trade_edges(spark, sf_dir)
    timer = measures.Timer("trade", "deletions")
    for r in percents:
        g = views.deletion_stream(v, e, r, "trade").stored()
        start = refine.lifetimes(g.snapshot(0), patterns)
        dead = g.edge_life.filter(F.col("died") != ALIVE).select("u", "v", F.col("died").alias("seq"))
        timer.run(f"ours {r}%", "delta", lambda start=start, dead=dead: monitor.on_delete(start, dead, patterns))
    return timer.table(spark)


def burst(spark: SparkSession, sf_dir: str, n: int = 300_000, patterns: Patterns = DEFAULT_PATTERNS) -> DataFrame:
    """The last ``n`` edges of the dense graph in one epoch."""
    v, e = views.trade_vertices(spark, sf_dir), views.trade_edges(spark, sf_dir, True)
    total = e.count()
    g = views.insertion_stream(v, e, min(100, max(1, 100 * n // total)), "trade_full").stored()
    timer = measures.Timer("trade_full", "burst")
    timer.run("ours", "delta", lambda: monitor.on_insert(g, patterns, 0, ALIVE - 1))
    return timer.table(spark)


def label_changes(spark: SparkSession, sf_dir: str, patterns: Patterns = DEFAULT_PATTERNS, every: int = 10_000) -> DataFrame:
    """One percent of the vertices change their label after every ``every`` updates (every tenth of short streams)."""
    g = views.trade(spark, sf_dir).stored()
    n = g.edge_life.agg(F.max("born")).first()[0]
    step = every if n >= 10 * every else max(1, n // 10)
    ticks = F.sequence(F.lit(step), F.lit(n), F.lit(step))
    changes = g.vertices.withColumn("t", F.explode(ticks)).filter((F.col("v") * 7919 + F.col("t")) % 100 == 0).select("v", ((F.col("label") + F.col("t")) % 16 + 1).cast("int").alias("newlabel"), F.col("t").cast("long").alias("t"))
    moved = Graph(g.vertices, g.edge_life, split_label(g.vertices, changes), "trade_labels").stored()
    timer = measures.Timer("trade", "label_changes")
    timer.run("ours", "lifetimes", lambda: refine.lifetimes(moved, patterns))
    return timer.table(spark)


def adversarial(spark: SparkSession, g: Graph, patterns: Patterns) -> DataFrame:
    timer = measures.Timer(g.name, "adversarial")
    for mode in ("absent", "heavy"):
        p = synth.adversarial(g, patterns, mode)
        ix = synopsis.Index(g, BuildParams(), p.deltas(spark), 0)
        timer.run(mode, "candidates", lambda ix=ix, p=p: prune.candidates(ix, p))
        timer.run(mode, "label_only", lambda ix=ix, p=p: prune.label_only(ix.star, p))
    return timer.table(spark)


def concurrency(spark: SparkSession, g: Graph, patterns: Patterns, counts=(50, 200)) -> DataFrame:
    """Many patterns at once: the level engine against a job chain per pattern."""
    timer = measures.Timer(g.name, "concurrency")
    for n in counts:
        some = Patterns((patterns.items * (n // max(1, len(patterns)) + 1))[:n])
        timer.run(f"levels {n}", "answers", lambda some=some: refine.match_levels(g.adjacency(), some))
    return timer.table(spark)


def graph_study(spark: SparkSession, sizes=(10_000,), dists=("uni", "gau", "zipf"), labels=(15,), degrees=((4, 0.25),), pattern_size: int = 8, pattern_degree: float = 3.0, n_patterns: int = 10) -> DataFrame:
    """Synthetic graphs over size, label law, number of labels and average degree: offline and filter cost."""
    rows = None
    for n in sizes:
        for dist in dists:
            for count in labels:
                for k, p in degrees:
                    g = synth.nws(spark, n, k, p, count, dist).stored()
                    patterns = synth.sample_patterns(g, n_patterns, pattern_size, pattern_degree)
                    timer = measures.Timer(g.name, f"labels={count} k={k} p={p} size={pattern_size} deg={pattern_degree}")
                    timer.run("ours", "embedding", lambda g=g: stars(g, BuildParams(), 0))
                    ix = synopsis.Index(g, BuildParams(), patterns.deltas(spark), 0)
                    timer.run("ours", "synopsis", lambda ix=ix: ix.synopsis)
                    timer.run("ours", "candidates", lambda ix=ix, patterns=patterns: prune.candidates(ix, patterns))
                    timer.run("label_only", "candidates", lambda ix=ix, patterns=patterns: prune.label_only(ix.star, patterns))
                    rows = timer.table(spark) if rows is None else rows.unionAll(timer.table(spark))
    return rows


def offline(spark: SparkSession, g: Graph, patterns: Patterns, p: BuildParams | None = None) -> DataFrame:
    """Embedding, synopsis and baseline index times, and space."""
    p = p or BuildParams()
    timer = measures.Timer(g.name, "offline")
    timer.run("ours", "dictionary", lambda: label_dict(g.vertices, p))
    timer.run("ours", "embedding", lambda: stars(g, p, 0))
    timer.run("ours", "synopsis", lambda: synopsis.Index(g, p, patterns.deltas(spark), 0).synopsis)
    adj = g.snapshot(0).adjacency()
    for q, pattern in patterns:
        timer.run(f"tree_index q{q}", "index", lambda pattern=pattern: baselines.tree_index(adj, pattern))
        timer.run(f"dag_index q{q}", "index", lambda pattern=pattern: baselines.dag_index(adj, pattern))
    return timer.table(spark)
