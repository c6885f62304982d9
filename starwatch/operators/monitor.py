"""Monitoring: answer changes of an epoch of updates, insertions and deletions alike."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import all_of, embedding_columns, label_dict
from ..model import ALIVE, BuildParams, Graph, advance_labels, edge_lifetimes, effective_changes
from ..plans.joinorder import anchored_orders, candidate_counts, join_orders
from ..plans.patterns import Patterns, embed_patterns
from ..storage import grown, materialise, side_by_side, small
from .bands import degree_boxes_for
from .prune import candidates
from .refine import OUT, as_rows, fanouts, label_pairs, lifetimes, match_all_static, match_levels, match_plans, match_static, relevant, relevant_of, seeds
from .stars import neighbour_sums
from .synopsis import Index, Part


def peak_candidates(g: Graph, patterns: Patterns, p: BuildParams, t0: int, t1: int, adj: DataFrame | None = None) -> DataFrame:
    """cand(query_id, qv, v): a superset of the candidates at any time in [t0, t1] among the ends of edges that
    are born in it. Corners and boxes only widen with more neighbours, so they are taken from all
    edges a vertex has in that time; labels are exact. Other vertices are not judged and not read.

    ``adj``: the edges to judge by, if not all. A match uses edges of the patterns' labels only, so by these (see ``relevant``) no
    vertex of a match is lost, and fewer others pass."""
    adj = (g.adjacency() if adj is None else adj).filter((F.col("born") <= t1) & (F.col("died") > t0))
    ends = adj.filter(F.col("born") > t0).select("src").distinct()
    hist = adj.join(ends, "src", "left_semi").groupBy(F.col("src").alias("v"), F.col("dst_label").alias("nlabel")).agg(F.count(F.lit(1)).cast("int").alias("cnt"))
    vertices = g.vertices if g.vertex_life is None else g.vertex_life.select("v", "label").distinct()
    hist = materialise(hist, "peak-hist")
    d = label_dict(g.vertices if g.vertex_life is None else g.vertex_life, p)
    star = vertices.join(neighbour_sums(hist, d, p), "v").join(F.broadcast(d), "label").select("v", "label", "deg", *embedding_columns(p))
    q = patterns.hinted(embed_patterns(star.sparkSession, patterns, p).withColumnRenamed("label", "q_label").withColumnRenamed("deg", "q_deg"))
    test = (F.col("label") == F.col("q_label")) & (F.col("deg") >= F.col("q_deg")) & all_of([F.col(f"q{k}") <= F.col(f"e{k}") for k in p.dims])
    first = materialise(star.join(q, test), "peak-first")
    boxes = degree_boxes_for(hist, star, first.select("v", F.col("q_deg").alias("delta")).distinct(), p, d)
    top = boxes.select("v", F.col("delta").alias("q_deg"), *[f"hi{k}" for k in p.dims])
    return first.join(top, ["v", "q_deg"]).filter(all_of([F.col(f"q{k}") <= F.col(f"hi{k}") for k in p.dims])).select("query_id", "qv", "v")


def on_insert(g: Graph, patterns: Patterns, t0: int, t1: int, cand: DataFrame | None = None, live: set[int] | None = None, counts: dict[int, dict[int, int]] | None = None, adj: DataFrame | None = None) -> DataFrame:
    """Answers born in (t0, t1]: every new edge starts each pattern edge it fits, both ways round.

    A match belongs to its newest edge by (born, u, v): all its other edges are older than the anchor, which
    keeps the order of updates within an epoch without going through them one by one. ``cand`` holds the ends
    of new edges that may take part; pairs without both ends in it start nothing. All patterns and pattern edges
    advance in one plan, from ``counts`` (sizes of candidate sets) in order of the fewest candidates. ``live``: the query ids to answer.
    ``adj``: the rows of ``relevant``, if they are there already.
    """
    adj = relevant(g.adjacency(), patterns) if adj is None else adj
    fresh = adj.filter((F.col("born") > t0) & (F.col("born") <= t1))
    plans = []
    for q, p in patterns:
        if live is not None and q not in live:
            continue
        # adj holds both directions of a data edge, so one of each pattern edge serves
        plans += [(q, p, order) for i, j, order in anchored_orders(p, (counts or {}).get(q)) if any((i, j) == e[:2] for e in p.edges)]
    if not plans:
        return small(fresh.sparkSession, [], OUT)
    return match_plans(adj, patterns, plans, seed=seeds(fresh, patterns, plans, cand, anchored=True))


def answer_edges(answers: DataFrame, patterns: Patterns) -> DataFrame:
    """answers with one row per pattern edge: adds u < v."""
    edges = patterns.hinted(patterns.q_edge(answers.sparkSession).select("query_id", "qi", "qj"))
    a, b = F.expr("get(m, qi)"), F.expr("get(m, qj)")
    return answers.join(edges, "query_id").select("query_id", "m", "born", "died", F.least(a, b).alias("u"), F.greatest(a, b).alias("v"))


def on_delete(answers: DataFrame, deletes: DataFrame, patterns: Patterns) -> DataFrame:
    """Living answers that lose an edge: (query_id, m, born, died) with ``died`` the first deletion.

    ``deletes``: u, v, seq. Only deletions after an answer's birth end it.
    """
    living = answers.filter(F.col("died") == ALIVE)
    hit = answer_edges(living, patterns).join(deletes.select("u", "v", "seq"), ["u", "v"]).filter("seq > born")
    return hit.groupBy("query_id", "m", "born").agg(F.min("seq").alias("died"))


def lost(g: Graph, patterns: Patterns, t0: int, t1: int, engine: str = "static") -> DataFrame:
    """Answers that stand at ``t0`` and end in (t0, t1]: (query_id, m, born, died), ``died`` the first deletion.

    For many deletions and answers that are not stored: an answer's end comes out of the joins that find it, so it is
    not opened into its edges to meet the deletions (``on_delete`` does that for the stored answers of an epoch)."""
    at = Graph(g.vertices, g.edge_life.filter((F.col("born") <= t0) & (F.col("died") > t0)), g.vertex_life, g.name)
    return lifetimes(at, patterns, engine).filter((F.col("died") > t0) & (F.col("died") <= t1))


def on_relabel(answers: DataFrame, changes: DataFrame) -> DataFrame:
    """Living answers with a vertex that takes another label: (query_id, m, born, died), ``died`` the first change."""
    living = answers.filter(F.col("died") == ALIVE).select("query_id", "m", "born", F.explode("m").alias("v"))
    return living.join(changes.select("v", "t"), "v").filter("t > born").groupBy("query_id", "m", "born").agg(F.min("t").alias("died"))


@dataclass
class Delta:
    added: DataFrame
    removed: DataFrame


def epoch_lives(alive: DataFrame, ops: DataFrame) -> DataFrame:
    """u, v, elabel, born, died, old: the lives, after an epoch of raw updates, of all edges that these name; ``old``: it began before.

    ``alive``: the living edges. An operation counts iff it differs from the one before it (see ``normalise_updates``), so a life
    that is not ``old`` is an insertion that counts, and one that ends is a deletion that counts."""
    ops = ops.filter("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "elabel", F.col("seq").alias("born"), "op", F.lit(False).alias("old"))
    named = alive.join(ops.select("u", "v").distinct(), ["u", "v"], "left_semi").select("u", "v", "elabel", "born", F.lit("+").alias("op"), F.lit(True).alias("old"))
    edge = Window.partitionBy("u", "v")
    before = F.coalesce(F.lag("op").over(edge.orderBy(F.desc("old"), "born", "op")), F.lit("-"))
    counts = named.unionByName(ops).withColumn("_before", before).filter("old OR op <> _before")
    lives = counts.withColumn("died", F.coalesce(F.lead("born").over(edge.orderBy("born", "op")), F.lit(ALIVE)))
    return lives.filter("op = '+'").select("u", "v", "elabel", "born", "died", "old")


def lives_after(edge_life: DataFrame, lives: DataFrame) -> DataFrame:
    """``edge_life`` after an epoch (see ``epoch_lives``)."""
    rest = edge_life.join(lives.filter("old").select("u", "v", "born"), ["u", "v", "born"], "left_anti")
    return rest.select(edge_life.columns).unionByName(lives.select(edge_life.columns))


class Monitor:
    """Keeps the answers of registered patterns over epochs of updates.

    ``apply`` takes the raw updates of one epoch (any size); its number of stages grows with the largest
    pattern, not with the number of patterns or updates. State is written tables. An epoch without deletions and label
    changes writes rows of its own beside them; they are written anew when something in them ends.

    ``known``: ``initial`` is a written table's, and holds each edge once with u < v. Then nothing is made of it that is not asked for: the index
    is made of the graph before the first epoch that asks it, and the first answers may be found with their ends (see ``_apply_unasked``).
    """

    def __init__(self, initial: DataFrame | None, vertices: DataFrame, patterns: Patterns, params: BuildParams | None = None, prune: bool = True, known: bool = False):
        self.vertices, self.patterns, self.params, self.prune = vertices, patterns, params or BuildParams(), prune
        self.initial = initial
        self.now = 0
        self.live = {q for q, _ in patterns}
        self.vertex_life: DataFrame | None = None
        self.known = known = known and initial is not None
        if known:
            self.edge_life = initial.select("u", "v", "elabel", F.lit(0).cast("long").alias("born"), F.lit(ALIVE).alias("died"))
        else:
            self.edge_life = materialise(edge_lifetimes(initial, self._none()), "edge-life")
        self._graph: Graph | None = None
        g = self.graph
        self._near: tuple = (*self._now(), relevant(g.adjacency(), patterns) if initial is not None and not known else None)
        self._state: DataFrame | None = None  # the answers of the first graph are found when they are first asked for
        empty = not prune or initial is None or not self.edge_life.limit(1).count()
        self._index_due = known and not empty
        self.index = None if empty or known else Index(g, self.params, patterns.deltas(vertices.sparkSession), 0)
        self.history: list[dict] = []

    def _none(self) -> DataFrame:
        return small(self.vertices.sparkSession, [], "seq long, ts timestamp, op string, u long, v long, elabel int")

    def _now(self) -> tuple:
        return self.vertices, self.edge_life, self.vertex_life

    @property
    def graph(self) -> Graph:
        """The graph as it is now; its adjacency is written once for all that reads it."""
        g = self._graph
        if g is None or any(a is not b for a, b in zip(self._now(), (g.vertices, g.edge_life, g.vertex_life), strict=True)):
            self._graph = g = Graph(*self._now())
        return g

    @property
    def near(self) -> DataFrame:
        """The adjacency of the graph as it is now, of edges with the labels of some pattern edge (see ``relevant``)."""
        *then, adj = self._near
        if adj is None or any(a is not b for a, b in zip(self._now(), then, strict=True)):
            adj = materialise(relevant_of(self.graph, self.patterns), "relevant")
            self._set_near(adj)
        return adj

    def _set_near(self, adj: DataFrame, fans: DataFrame | None = None) -> None:
        adj._pairs = label_pairs(self.patterns)
        if hasattr(fans, "_fanouts"):  # they only choose among join orders
            adj._fanouts = fans._fanouts
        self._near = (*self._now(), adj)

    @property
    def state(self) -> DataFrame:
        """answers(query_id, m, born, died), those that ended too."""
        if self._state is None:
            self._state = materialise(match_all_static(self.near, self.patterns), "answers")
        return self._state

    @state.setter
    def state(self, answers: DataFrame) -> None:
        self._state = answers

    def _written_state(self) -> DataFrame:
        if not self.state.__dict__.get("_written", True):
            self.state = materialise(self.state, "answers")
        return self.state

    def _written_lives(self) -> DataFrame:
        if not self.edge_life.__dict__.get("_written", True):
            near, now = self._near, self._now()
            self.edge_life = materialise(self.edge_life, "edge-life")
            if all(a is b for a, b in zip(now, near[:-1], strict=True)):
                self._near = (*self._now(), near[-1])
        return self.edge_life

    def apply(self, ops: DataFrame, labels: DataFrame | None = None) -> Delta:
        """Answers added and removed by one epoch: edge updates ``ops``, and label changes ``labels`` (v, newlabel,
        t on the clock of seq). A changed vertex's edges end under its old label and begin anew under the new one.
        Changes of unknown vertices, and those that change nothing, are passed over."""
        last = ops.agg(F.max("seq")).first()[0]
        if labels is not None:
            labels = materialise(effective_changes(self.vertices, labels), "label-changes")
            newest = labels.agg(F.max("t")).first()[0]
            if newest is None:
                labels = None
            else:
                last = newest if last is None else max(last, newest)
        if last is None:
            return Delta(self.state.limit(0), self.state.limit(0))
        if self.known and self._state is None and labels is not None:
            return self._apply_unasked(ops, labels, last)
        alive = self._written_lives().filter(F.col("died") == ALIVE)
        if self._index_due and labels is None:
            self.index, self._index_due = Index(self.graph.snapshot(self.now), self.params, self.patterns.deltas(ops.sparkSession)), False
        near = self.near if labels is None or self._state is None else None
        state, lives, _ = side_by_side(
            self._written_state,
            lambda: materialise(epoch_lives(alive, ops), "updates"),
            lambda: self.index.prepare() if self.index is not None and labels is None else None,
        )
        fresh, ended = lives.filter("NOT old"), lives.filter(F.col("old") & (F.col("died") != ALIVE))
        n_ended, n_gone = lives.agg(F.count_if(F.col("old") & (F.col("died") != ALIVE)), F.count_if(F.col("died") != ALIVE)).first()
        columns = self.edge_life.columns
        if n_ended:
            rest = self.edge_life.join(ended.select("u", "v", "born"), ["u", "v", "born"], "left_anti")
            self.edge_life = materialise(rest.select(columns).unionByName(ended.unionByName(fresh).select(columns)), "edge-life")
        else:
            self.edge_life = grown(self.edge_life, fresh.select(columns), "edge-life")
        moved = self._relabel(alive, labels) if labels is not None else None
        t0, t1 = self.now, last
        adj, (part, cand) = side_by_side(
            lambda: self._moved_near(near, fresh if not n_ended and labels is None else None),
            lambda: self._candidates(lives, n_gone > 0, moved, labels),
        )
        g = self.graph
        if self.prune and cand is None:
            cand = materialise(peak_candidates(g, self.patterns, self.params, t0, t1, adj).distinct(), "peak")
        counts = candidate_counts(cand) if self.prune else None
        gone = on_delete(state, ended.select("u", "v", F.col("died").alias("seq")), self.patterns) if n_ended else None
        if labels is not None:
            changed = on_relabel(state, labels)
            gone = changed if gone is None else gone.unionByName(changed).groupBy("query_id", "m", "born").agg(F.min("died").alias("died"))
        added, removed = side_by_side(
            lambda: materialise(on_insert(g, self.patterns, t0, t1, cand, self.live, counts, adj), "added"),
            lambda: materialise(gone, "removed") if gone is not None else small(state.sparkSession, [], OUT),
        )
        if part is not None:
            self.index = self.index.merged(part)
        if gone is None:
            self.state = grown(state, added, "answers")
        else:  # written when the next epoch begins
            now = state.join(removed.select("query_id", "m", "born", F.col("died").alias("_d")), ["query_id", "m", "born"], "left")
            self.state = now.withColumn("died", F.coalesce("_d", "died")).drop("_d").select("query_id", "m", "born", "died").unionByName(added)
            self.state._written = False
        self.now = t1
        self.history.append({"t0": t0, "t1": t1})
        short = added.filter(F.col("died") <= t1).select("query_id", "m", "born", "died")
        return Delta(added, removed.select("query_id", "m", "born", "died").unionByName(short))

    def _apply_unasked(self, ops: DataFrame, labels: DataFrame, t1: int) -> Delta:
        """A first epoch with label changes, before which nothing was asked. Only edges whose ends have labels of the patterns at some time are
        worked on, and the first answers are found after it, with the ends that it gives them, as these come out of the same joins (see ``lost``);
        so no stored answer has to meet a change. What follows is unwritten: the answers, and the lives of all edges, are written if a next epoch begins."""
        t0, before = self.now, self.edge_life
        self._relabel(before, labels)
        wanted = small(ops.sparkSession, sorted({(a,) for a, _ in label_pairs(self.patterns)}), "label int")
        some = self.vertex_life.join(self.patterns.hinted(wanted), "label", "left_semi").select("v")

        def between(edges: DataFrame) -> DataFrame:
            return edges.join(some.withColumnRenamed("v", "u"), "u", "left_semi").join(some, "v", "left_semi").select(edges.columns)

        life, new = side_by_side(lambda: materialise(between(before), "near-life"), lambda: materialise(between(ops), "near-updates"))
        lives = materialise(epoch_lives(life.filter(F.col("died") == ALIVE), new), "updates")
        self.edge_life = lives_after(before, epoch_lives(before.filter(F.col("died") == ALIVE), ops))
        self.edge_life._written = False
        g = Graph(self.vertices, lives_after(life, lives), self.vertex_life)
        adj = materialise(relevant_of(g, self.patterns), "relevant")
        self._set_near(adj)
        cand, fan = side_by_side(
            lambda: materialise(peak_candidates(g, self.patterns, self.params, t0, t1, adj).distinct(), "peak") if self.prune else None,
            lambda: fanouts(adj, *self.patterns.items),
        )
        counts = candidate_counts(cand) if self.prune else None
        first = adj.filter(F.col("born") <= t0)
        first._pairs, first._fanouts = adj._pairs, fan
        first = match_all_static(first, self.patterns).filter(F.col("query_id").isin(sorted(self.live)))
        added = on_insert(g, self.patterns, t0, t1, cand, self.live, counts, adj).select("query_id", "m", "born", "died")
        self.state = first.unionByName(added)
        self.state._written = False
        self.now = t1
        self.history.append({"t0": t0, "t1": t1})
        return Delta(added, self.state.filter(F.col("died") <= t1))

    def _moved_near(self, before: DataFrame | None, fresh: DataFrame | None) -> DataFrame:
        """``near`` after an epoch: with rows of its ``fresh`` edges beside those of ``before``, if nothing else has changed."""
        if fresh is None:
            return self.near
        rows = materialise(relevant_of(Graph(self.vertices, fresh.drop("old"), self.vertex_life), self.patterns), "relevant")
        self._set_near(grown(before, rows.select(before.columns), "relevant"), before)
        return self.near

    def _relabel(self, alive: DataFrame, labels: DataFrame) -> DataFrame | None:
        """Vertex lives and current labels after label changes; returns all edges at changed vertices (u, v) for the index.
        ``alive``: the edges before the epoch."""
        life = self.vertex_life
        begun = self.vertices.select("v", "label", F.lit(0).cast("long").alias("born"), F.lit(ALIVE).alias("died"))
        life = begun if life is None else life.unionByName(begun.join(life.select("v"), "v", "left_anti"))
        self.vertex_life = materialise(advance_labels(life, labels), "vertex-life")
        self.vertices = materialise(self.vertex_life.filter(F.col("died") == ALIVE).select("v", "label"), "vertices")
        if self.index is None:
            return None
        moved = labels.select("v").distinct()
        at = alive.select("u", "v").join(moved.withColumnRenamed("v", "u"), "u", "left_semi").unionByName(alive.select("u", "v").join(moved, "v", "left_semi")).distinct()
        return materialise(at, "relabelled")

    def _candidates(self, lives: DataFrame, deletes: bool, moved: DataFrame | None, labels: DataFrame | None) -> tuple[Part | None, DataFrame | None]:
        """``lives``: see ``epoch_lives``; ``deletes``: some of them end. The index's rows that the epoch changes, and the ends of its new edges that pass the synopsis. It is asked as it would be without the epoch's
        deletions, when corners and boxes are widest, so nothing that matched within the epoch is missed; then it
        moves on by all updates, which is the same step if none of them is a deletion. (A graph that began empty has no bands, and an epoch of label changes gives vertices
        several stars: these are judged by all edges of the epoch, and no ends are given here.)"""
        if self.index is None:
            return None, None
        inserts = lives.filter("NOT old").select(F.lit("+").alias("op"), "u", "v")
        clean = inserts
        if deletes:
            clean = inserts.unionByName(lives.filter(F.col("died") != ALIVE).select(F.lit("-").alias("op"), "u", "v"))
        if labels is not None:
            return self.index.changed(clean, self.vertices, moved, labels), None
        part = self.index.changed(inserts, self.vertices)
        cand = materialise(candidates(part, self.patterns), "peak")
        if deletes:
            part = self.index.changed(clean, self.vertices)
        return part, cand

    def answers(self, t: int | None = None) -> DataFrame:
        t = self.now if t is None else t
        return self.state.filter((F.col("born") <= t) & (F.col("died") > t)).select("query_id", "m")

    def register(self, pattern) -> int:
        """A new pattern, answered as if it had always stood: with the times at which its matches
        came and went. Returns its query id."""
        q = len(self.patterns)
        state = self._written_state()
        self.patterns = Patterns([*self.patterns.items, pattern])
        self._near = (*self._now(), None)  # the new pattern may ask for other labels
        self.live.add(q)
        rows = as_rows(match_static(self.near, pattern), pattern, q)
        self.state = materialise(state.unionByName(rows), "answers")
        if self.index is not None:
            spark = self.vertices.sparkSession
            known, wanted = ({r.delta for r in x.collect()} for x in (self.index.deltas, self.patterns.deltas(spark)))
            if wanted - known:  # boxes for the new pattern's degrees
                now = self.graph.snapshot(self.now)
                self.index = Index(now, self.params, self.patterns.deltas(spark), None, self.index.bands, self.index.grid)
        return q

    def unregister(self, query_id: int) -> None:
        """The pattern's answers go, and none come any more; its query id is not used again."""
        self.live.discard(query_id)
        self.state = materialise(self.state.filter(F.col("query_id") != query_id), "answers")

    def stats(self) -> DataFrame:
        t = self.now
        return self.state.groupBy("query_id").agg(F.count_if((F.col("born") <= t) & (F.col("died") > t)).alias("living"), F.count(F.lit(1)).alias("ever"))


def initial_answers(index, patterns: Patterns, engine: str = "static") -> DataFrame:
    """Answers on an index's snapshot: candidates, join order from their counts, refinement."""
    cand = materialise(candidates(index, patterns), "candidates")
    orders = join_orders(patterns, candidate_counts(cand))
    adj = index.graph.adjacency_at(index.t)
    return (match_levels if engine == "levels" else match_all_static)(adj, patterns, orders, cand).select("query_id", "m")
