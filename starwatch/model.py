"""The graph model: vertices with labels, edges with lifetimes on a logical clock."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .storage import materialise, side_by_side

ALIVE = (1 << 63) - 1  # the end of an edge that was never deleted

VERTICES = "v BIGINT, label INT"
EDGE_LIFE = "u BIGINT, v BIGINT, elabel INT, born BIGINT, died BIGINT"
UPDATES = "seq BIGINT, ts TIMESTAMP, op STRING, u BIGINT, v BIGINT, elabel INT"


@dataclass(frozen=True)
class BuildParams:
    """Parameters of embedding and synopsis; the defaults are those of the experiments."""

    d: int = 2
    ratio: int = 1000  # weight of the base vector against the label vectors
    m: int = 3  # degree bands
    k: int = 5  # grid intervals per dimension
    variant: str = "skew_based"  # plain | based | skew_based
    base: str = "l1"  # l1 | l1_half | diag | l2
    salt: int = 1
    elabel_weight: bool = False  # edge labels take part in neighbour sums

    @property
    def dist(self) -> str:
        return "zipf" if self.variant == "skew_based" else "uniform"

    @property
    def dims(self) -> range:
        return range(2 * self.d)

    def but(self, **changes) -> BuildParams:
        return replace(self, **changes)


@dataclass
class Graph:
    """vertices(v, label) and edge_life(u < v, elabel, born, died); an edge lives on [born, died).

    ``vertex_life(v, label, born, died)`` replaces the fixed labels when labels change.
    """

    vertices: DataFrame
    edge_life: DataFrame
    vertex_life: DataFrame | None = None
    name: str = "graph"
    notes: dict = field(default_factory=dict)

    def adjacency(self) -> DataFrame:
        """Both directions of every edge with both labels: src, dst, src_label, dst_label, elabel, born, died.

        Written once per graph: every pattern edge of every join chain reads it.
        """
        if "adjacency" not in self.notes:
            self.notes["adjacency"] = materialise(self._adjacency(), "adjacency")
        return self.notes["adjacency"]

    def adjacency_at(self, t: int | None = None) -> DataFrame:
        """The rows of ``adjacency`` that live at ``t`` (the end of all updates if None), with their lives: nothing more is written."""
        if t is None:
            return self.adjacency().filter(F.col("died") == ALIVE)
        return self.adjacency().filter((F.col("born") <= t) & (F.col("died") > t))

    def _adjacency(self, pairs: DataFrame | None = None) -> DataFrame:
        """``pairs`` (src_label, dst_label, both ways round): only edges with these labels; their ends' labels are looked up, no others."""
        both = self.edge_life
        life = self.vertices if self.vertex_life is None else self.vertex_life
        if pairs is not None:
            life = life.join(pairs.select(F.col("src_label").alias("label")).distinct(), "label", "left_semi")
        for end in "uv":
            own = life.select(F.col("v").alias(end), F.col("label").alias(f"{end}_label"), *([] if self.vertex_life is None else [F.col("born").alias("_b"), F.col("died").alias("_d")]))
            both = both.join(own, end)
            if self.vertex_life is not None:  # a changed label ends all edges at the vertex and starts them anew: intersect the lifetimes
                both = both.withColumn("born", F.greatest("born", "_b")).withColumn("died", F.least("died", "_d")).filter("born < died").drop("_b", "_d")
        if pairs is not None:
            both = both.join(pairs.select(F.col("src_label").alias("u_label"), F.col("dst_label").alias("v_label")), ["u_label", "v_label"], "left_semi")

        def way(a: str, b: str) -> Column:
            return F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), F.lit(a == "u").alias("forward"), F.col(f"{a}_label").alias("src_label"), F.col(f"{b}_label").alias("dst_label"))

        ways = both.select(F.explode(F.array(way("u", "v"), way("v", "u"))).alias("_w"), "elabel", "born", "died")
        return ways.select("_w.src", "_w.dst", "_w.src_label", "_w.dst_label", "_w.forward", "elabel", "born", "died")

    def snapshot(self, t: int | None = None) -> Graph:
        """The graph at time ``t`` (the end of all updates if None); isolated vertices stay."""
        if t is None:
            alive = self.edge_life.filter(F.col("died") == ALIVE)
        else:
            alive = self.edge_life.filter((F.col("born") <= t) & (F.col("died") > t))
        vertices = self.vertices
        if self.vertex_life is not None:
            at = (F.col("died") == ALIVE) if t is None else (F.col("born") <= t) & (F.col("died") > t)
            vertices = self.vertex_life.filter(at).select("v", "label")
        now = alive.withColumn("born", F.lit(0).cast("long")).withColumn("died", F.lit(ALIVE))
        return Graph(vertices, now, None, self.name)

    def stored(self) -> Graph:
        """The same graph read from written tables, so later plans begin there."""
        vertices, edges, life = side_by_side(
            lambda: materialise(self.vertices, "vertices"),
            lambda: materialise(self.edge_life, "edge-life"),
            lambda: materialise(self.vertex_life, "vertex-life") if self.vertex_life is not None else None,
        )
        return Graph(vertices, edges, life, self.name)


def normalise_updates(raw: DataFrame, initial: DataFrame | None = None) -> DataFrame:
    """Canonical updates: u < v, no loops, and no operation that changes nothing.

    ``initial``: edges (u, v) present at the start. An insertion of a present edge or a
    deletion of an absent one is dropped: an operation counts iff it differs from the one before it.
    """
    ops = raw.filter("u <> v").select("seq", "ts", "op", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "elabel")
    if initial is not None:
        first = initial.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().withColumn("_there", F.lit("+"))
        ops = ops.join(first, ["u", "v"], "left")
    else:
        ops = ops.withColumn("_there", F.lit(None).cast("string"))
    before = F.coalesce(F.lag("op").over(Window.partitionBy("u", "v").orderBy("seq", "op")), "_there", F.lit("-"))
    return ops.withColumn("_before", before).filter("op <> _before").select("seq", "ts", "op", "u", "v", "elabel")


def edge_lifetimes(initial: DataFrame | None, updates: DataFrame) -> DataFrame:
    """edge_life from the edges at the start (u, v, elabel; born 0) and normalised updates."""
    ops = updates.select("u", "v", "elabel", "seq", "op")
    if initial is not None:
        ops = ops.unionAll(initial.select("u", "v", "elabel", F.lit(0).cast("long").alias("seq"), F.lit("+").alias("op")))
    w = Window.partitionBy("u", "v").orderBy("seq", "op")
    return ops.withColumn("died", F.coalesce(F.lead("seq").over(w), F.lit(ALIVE))).filter("op = '+'").select("u", "v", "elabel", F.col("seq").alias("born"), "died")


def split_label(vertices: DataFrame, changes: DataFrame) -> DataFrame:
    """vertex_life(v, label, born, died) from first labels and changes (v, newlabel, t)."""
    ops = vertices.select("v", "label", F.lit(0).cast("long").alias("born")).unionAll(changes.select("v", F.col("newlabel").alias("label"), F.col("t").alias("born")))
    w = Window.partitionBy("v").orderBy("born")
    return ops.withColumn("died", F.coalesce(F.lead("born").over(w), F.lit(ALIVE))).select("v", "label", "born", "died")


def effective_changes(vertices: DataFrame, changes: DataFrame) -> DataFrame:
    """Label changes (v, newlabel, t) of known vertices that give another label than the one before; of
    several at one time the largest label counts."""
    one = changes.groupBy("v", F.col("t").cast("long").alias("t")).agg(F.max("newlabel").cast("int").alias("newlabel"))
    w = Window.partitionBy("v").orderBy("t")
    known = one.join(vertices.select("v", "label"), "v").withColumn("_before", F.coalesce(F.lag("newlabel").over(w), F.col("label")))
    return known.filter("newlabel <> _before").select("v", "newlabel", "t")


def advance_labels(vertex_life: DataFrame, changes: DataFrame) -> DataFrame:
    """vertex_life after later effective changes: the last life of a changed vertex is cut, all others stay."""
    changed = changes.select("v").distinct()
    going = vertex_life.filter(F.col("died") == ALIVE)
    pieces = going.join(changed, "v", "left_semi").select("v", "label", "born").unionByName(changes.select("v", F.col("newlabel").alias("label"), F.col("t").alias("born")))
    fresh = pieces.withColumn("died", F.coalesce(F.lead("born").over(Window.partitionBy("v").orderBy("born")), F.lit(ALIVE)))
    rest = vertex_life.filter(F.col("died") != ALIVE).unionByName(going.join(changed, "v", "left_anti"))
    return rest.select("v", "label", "born", "died").unionByName(fresh)


def insertion_cases(g: Graph) -> DataFrame:
    """Each insertion's number of new ends (0, 1 or 2): seq, u, v, new_ends."""
    ends = g.edge_life.select("born", F.explode(F.array("u", "v")).alias("x"))
    first = ends.groupBy("x").agg(F.min("born").alias("first"))
    e = g.edge_life.filter("born > 0").select("born", "u", "v")
    e = e.join(first.select(F.col("x").alias("u"), F.col("first").alias("fu")), "u").join(first.select(F.col("x").alias("v"), F.col("first").alias("fv")), "v")
    return e.select(F.col("born").alias("seq"), "u", "v", ((F.col("fu") == F.col("born")).cast("int") + (F.col("fv") == F.col("born")).cast("int")).alias("new_ends"))


def graph_stats(g: Graph) -> DataFrame:
    """One row: n_vertices, n_connected, n_edges, n_labels, avg_degree, max_degree (final snapshot)."""
    now = g.snapshot()
    deg = now.edge_life.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))
    a = now.vertices.agg(F.count(F.lit(1)).alias("n_vertices"), F.count_distinct("label").alias("n_labels"))
    b = deg.agg(F.count(F.lit(1)).alias("n_connected"), (F.sum("deg") / 2).cast("long").alias("n_edges"), F.round(F.avg("deg"), 6).alias("avg_degree"), F.max("deg").alias("max_degree"))
    return a.join(F.broadcast(b))


def validate_graph(g: Graph) -> DataFrame:
    """Counts of rows that break the model: loops, wrong order, empty or overlapping lifetimes, ends without a label."""
    e = g.edge_life
    w = Window.partitionBy("u", "v").orderBy("born")
    life = e.withColumn("prev", F.lag("died").over(w))
    checks = life.agg(
        F.count_if(F.col("u") == F.col("v")).alias("loops"), F.count_if(F.col("u") > F.col("v")).alias("wrong_order"),
        F.count_if(F.col("born") >= F.col("died")).alias("empty_lives"), F.count_if(F.col("prev") > F.col("born")).alias("overlaps"),
    )
    ends = e.select(F.explode(F.array("u", "v")).alias("v")).distinct().join(g.vertices, "v", "left_anti").agg(F.count(F.lit(1)).alias("unlabelled"))
    return checks.join(F.broadcast(ends))
