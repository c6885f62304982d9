"""Synthetic small-world graphs, update mixes and sampled patterns, from ranges and portable hashes."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.arithmetic import draw
from ..model import ALIVE, Graph
from ..plans.patterns import Pattern, Patterns
from ..storage import materialise
from .views import read



def mixed(c: Column | str, salt: int) -> Column:
    """A pseudo-random 0..65535 of a column, as in the vectors' arithmetic."""
    s = (48271 * (F.col(c) if isinstance(c, str) else c) % 2147483647 + 40692 * salt + 12345) % 2147483647
    for _ in range(3):
        s = (s * s + 16807 * s + 1013904223) % 2147483647
    return s % 65536


def label_of(v: Column, labels: int, dist: str, salt: int) -> Column:
    """A label 1..labels by a uniform, Gaussian (mean of four draws) or Zipf law."""
    if dist == "gau":
        total = mixed(v, salt) + mixed(v, salt + 1) + mixed(v, salt + 2) + mixed(v, salt + 3)
        return (F.floor(total * labels / (4 * 65536)) + 1).cast("int")
    if dist == "zipf":
        weights = [1 / (i + 1) for i in range(labels)]
        upto, total, out = 0.0, sum(weights), F.lit(labels)
        cuts = []
        for w in weights:
            upto += w
            cuts.append(round(65536 * upto / total))
        u = mixed(v, salt)
        for i in reversed(range(labels)):
            out = F.when(u < cuts[i], F.lit(i + 1)).otherwise(out)
        return out.cast("int")
    return (mixed(v, salt) % labels + 1).cast("int")


def nws(spark: SparkSession, n: int, k: int = 4, p: float = 0.25, labels: int = 15, dist: str = "uni", insert_percent: int = 10, seed: int = 1) -> Graph:
    """Small world: a ring where each vertex meets its k/2 next ones, plus random chords (no rewiring).

    Average degree is about k (1 + p). The last ``insert_percent`` of edges, in a hashed
    order, arrive as updates 1, 2, 3, ...
    """
    return small_world(spark.range(n).withColumnRenamed("id", "v"), n, k, p, labels, dist, insert_percent, seed)


def places(ids: DataFrame, per_bucket: int = 4096) -> DataFrame:
    """v: 0, 1, 2, ... in the order of the distinct ``id``, without a window over all rows: the number within a
    bucket of neighbouring ids plus the rows of the buckets before (one small row a bucket)."""
    e = ids.withColumn("_b", F.floor(F.col("id") / per_bucket))
    n = e.groupBy("_b").agg(F.count(F.lit(1)).alias("_n"))
    before = n.select("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_b").orderBy("id"))
    return e.withColumn("_r", rank).join(F.broadcast(before), "_b").select((F.col("_before") + F.col("_r") - 1).alias("v"))


def customers(spark: SparkSession, sf_dir: str, dist: str = "uni") -> Graph:
    """The small world over the customers: a vertex is a customer's place in the order of keys."""
    v = materialise(places(read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"))), "places")
    return small_world(v, v.count(), dist=dist)


def small_world(v: DataFrame, n: int, k: int = 4, p: float = 0.25, labels: int = 15, dist: str = "uni", insert_percent: int = 10, seed: int = 1) -> Graph:
    """The small world over vertices 0 to ``n`` - 1 given as rows (v)."""
    ring = v.select("v", F.explode(F.sequence(F.lit(1), F.lit(k // 2))).alias("j")).select("v", "j", ((F.col("v") + F.col("j")) % n).alias("w"))
    far = (mixed(F.col("v") * 8 + F.col("j"), seed + 20) * 65536 + mixed(F.col("v") * 8 + F.col("j"), seed + 21)) % n
    chords = ring.filter(mixed(F.col("v") * 8 + F.col("j"), seed + 22) < int(p * 65536)).select("v", far.alias("w"))
    edges = ring.select("v", "w").unionAll(chords).filter("v <> w").select(F.least("v", "w").alias("u"), F.greatest("v", "w").alias("v")).distinct()
    h = mixed(F.col("u") * 31 + F.col("v"), seed + 23)
    born = F.when(h < 65536 - insert_percent * 65536 // 100, F.lit(0)).otherwise(h * 65536 + mixed(F.col("u") + F.col("v") * 17, seed + 24) + 1)
    life = edges.select("u", "v", F.lit(1).alias("elabel"), born.cast("long").alias("born"), F.lit(ALIVE).alias("died"))
    return Graph(v.select("v", label_of(F.col("v"), labels, dist, seed).alias("label")), life, name=f"nws_{dist}_{n}")


def _walk(g: Graph, n: int, size: int, seed: int, pool: int) -> Iterator[tuple[dict[int, int], set[tuple[int, int]]]]:
    """Connected vertex sets grown from hashed start vertices, with their induced edges.

    ``pool`` start vertices and, per step, a bounded number of neighbours of the frontier are read.
    """
    adj = g.snapshot().adjacency()
    starts = [r[0] for r in g.vertices.join(adj.select(F.col("src").alias("v")).distinct(), "v").orderBy(mixed("v", seed + 40), "v").limit(pool).select("v").collect()]
    grown: list[list[int]] = [[s] for s in starts]
    for step in range(size - 1):
        spark = g.vertices.sparkSession
        rows = spark.createDataFrame([(i, x) for i, xs in enumerate(grown) for x in xs], "walk int, src long")
        taken = spark.createDataFrame([(i, x) for i, xs in enumerate(grown) for x in xs], "walk int, dst long")
        near = adj.select("src", "dst").join(F.broadcast(rows), "src").select("walk", "dst").distinct().join(F.broadcast(taken), ["walk", "dst"], "left_anti")
        best = near.groupBy("walk").agg(F.min_by("dst", F.struct(mixed(F.col("dst") + F.col("walk") * 7, seed + step), "dst")).alias("x")).collect()
        for r in best:
            grown[r.walk].append(r.x)
    done = [(i, xs) for i, xs in enumerate(grown) if len(xs) == size][:n]
    spark = g.vertices.sparkSession
    if not done:
        return
    members = F.broadcast(spark.createDataFrame([(i, x) for i, xs in done for x in xs], "walk int, v long"))
    labels = {r.v: r.label for r in g.vertices.join(members.select("v").distinct(), "v").collect()}
    inner = adj.select("src", "dst", "elabel").join(members.withColumnRenamed("v", "src"), "src").join(F.broadcast(members.select(F.col("walk").alias("w2"), F.col("v").alias("dst"))), "dst").filter("walk = w2 AND src < dst")
    edges: dict[int, set] = {}
    for r in inner.select("walk", "src", "dst").collect():
        edges.setdefault(r.walk, set()).add((r.src, r.dst))
    for i, xs in done:
        yield {x: labels[x] for x in xs}, edges.get(i, set())


def sample_patterns(g: Graph, n: int = 100, size: int = 8, avg_degree: float = 3.0, seed: int = 1) -> Patterns:
    """Random connected sub-graphs of the data as patterns: a spanning tree of each is kept, other
    induced edges are dropped (in a hashed order) down to the wanted average degree."""
    out = []
    for members, edges in _walk(g, n, size, seed, 2 * n):
        order = list(members)
        at = {x: i for i, x in enumerate(order)}
        tree: list[tuple[int, int]] = []
        for i, x in enumerate(order[1:], 1):
            tree.append(next((at[y], i) for y in order[:i] if (min(x, y), max(x, y)) in edges))
        kept = {frozenset(e) for e in tree}
        more = sorted(((at[a], at[b]) for a, b in edges if frozenset((at[a], at[b])) not in kept), key=lambda e: draw(e[0] * size + e[1], 0, seed))
        wanted = max(0, round(avg_degree * size / 2) - len(tree))
        out.append(Pattern(f"sampled{len(out)}", tuple(members[x] for x in order), tuple(tree + more[:wanted])))
    return Patterns(out)


def adversarial(g: Graph, patterns: Patterns, mode: str) -> Patterns:
    """``absent``: each pattern's labels are turned into the rarest ones, so matches become unlikely (the
    caller checks for none); ``heavy``: into the commonest label, so candidate sets are as large as can be."""
    counts = [r[0] for r in g.vertices.groupBy("label").count().orderBy(F.asc("count") if mode == "absent" else F.desc("count"), "label").limit(2).collect()]
    return Patterns([Pattern(f"{p.name}_{mode}", tuple(counts[i % len(counts)] if mode == "absent" else counts[0] for i in range(len(p.labels))), p.edges) for _, p in patterns])
