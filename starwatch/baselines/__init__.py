"""Methods to compare with, each re-expressed from its one-line idea."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph
from ..operators.refine import as_rows, fanouts, match_static, relevant, seeds
from ..plans.joinorder import anchored_orders, order_from
from ..plans.patterns import Pattern, Patterns
from ..storage import drop_shuffles, materialise, side_by_side


def recompute_diff(g: Graph, pattern: Pattern, times: list[int]) -> DataFrame:
    """t, m, change: full matching at each of a few times, and the differences of consecutive sets."""
    out = None
    before = None
    for t in times:
        now = as_rows(match_static(g.snapshot(t).adjacency(), pattern), pattern, 0).select("m")
        if before is not None:
            rows = now.exceptAll(before).select(F.lit(t).alias("t"), "m", F.lit(1).alias("change")).unionAll(before.exceptAll(now).select(F.lit(t).alias("t"), "m", F.lit(-1).alias("change")))
            out = rows if out is None else out.unionAll(rows)
        before = now
    return out


#: Patterns whose chains are planned and written at once: on little data the driver's planning is most of the time.
ABREAST = 3


def delta_join(g: Graph, patterns: Patterns, t0: int, t1: int, adj: DataFrame | None = None) -> DataFrame:
    """Direct enumeration from each new edge over the raw adjacency, a join chain for every pattern
    edge: no candidates, order by degree and mean numbers of neighbours only. The chains of a pattern are written as a plan of their own,
    ``ABREAST`` patterns at once, so the driver holds the plans of these and the shuffle files stay theirs. A step takes the edges of its two labels from the rows of
    ``relevant`` (``adj``, if they are there already)."""
    adj = relevant(g.adjacency(), patterns) if adj is None else adj
    fresh = adj.filter((F.col("born") > t0) & (F.col("born") <= t1))
    if not hasattr(adj, "_fanouts"):
        fanouts(adj, *patterns.items)  # counted before the patterns ask for it at once

    def chains(q: int, p: Pattern) -> DataFrame:
        out, parts = None, {}
        for i, j, order in anchored_orders(p):
            if not any((i, j) == e[:2] for e in p.edges):
                continue
            seed = seeds(fresh, patterns, [(q, p, order)], anchored=True).select(F.col("m")[0].alias(f"m{i}"), F.col("m")[1].alias(f"m{j}"), "born", "died", "anchor")
            rows = as_rows(match_static(adj, p, order, seed=seed, before_anchor=True, parts=parts), p, q)
            out = rows if out is None else out.unionAll(rows)
        return materialise(out, "delta-join") if len(patterns) > 1 else out

    done = None
    for n in range(0, len(patterns), ABREAST):
        for out in side_by_side(*[partial(chains, q, p) for q, p in list(patterns)[n : n + ABREAST]]):
            done = out if done is None else done.unionAll(out)
        if len(patterns) > 1:
            drop_shuffles(g.edge_life.sparkSession)
    return done


class PartialTree:
    """Stored matches of the pattern's prefixes, in a fixed order of its positions. New edges join the stored
    prefix before them, then what is new goes on to the next prefix. Insertions only."""

    def __init__(self, g: Graph, pattern: Pattern, t0: int = 0):
        self.pattern, self.now = pattern, t0
        self.order = order_from(pattern, {}, [0])
        adj = g.adjacency().filter(F.col("born") <= t0)
        self.stored: list[DataFrame] = []
        for n in range(1, len(self.order)):
            rows = self._edges(adj, n) if n == 1 else self._extend(self.stored[-1], adj, n)
            self.stored.append(materialise(rows, "prefix"))

    def _back(self, n: int) -> list[int]:
        return [y for y in self.order[:n] if y in self.pattern.neighbours(self.order[n])]

    def _between(self, adj: DataFrame, a: int, b: int) -> DataFrame:
        p = self.pattern
        e = adj.filter((F.col("src_label") == p.labels[a]) & (F.col("dst_label") == p.labels[b]))
        want = p.edge_label(a, b)
        e = e.filter(F.col("elabel") == want) if want is not None else e
        return e.select(F.col("src").alias(f"m{a}"), F.col("dst").alias(f"m{b}"), F.col("born").alias("_b"), F.col("died").alias("_d"))

    def _edges(self, adj: DataFrame, n: int) -> DataFrame:
        return self._between(adj, self.order[0], self.order[1]).withColumnsRenamed({"_b": "born", "_d": "died"})

    def _extend(self, prefix: DataFrame, adj: DataFrame, n: int, new: DataFrame | None = None, which: int = 0) -> DataFrame:
        """``prefix`` with position ``n``. With ``new``, its edge number ``which`` comes from the new edges, those
        before from the old ones and those after from all, so each match comes once."""
        x, out = self.order[n], prefix
        for k, y in enumerate(self._back(n)):
            source = adj if new is None or k > which else new if k == which else adj.filter(F.col("born") <= self.now)
            out = out.join(self._between(source, y, x), [f"m{y}"] if k == 0 else [f"m{y}", f"m{x}"])
            out = out.withColumn("born", F.greatest("born", "_b")).withColumn("died", F.least("died", "_d")).drop("_b", "_d").filter("born < died")
        for y in self.order[:n]:
            if self.pattern.labels[y] == self.pattern.labels[x]:
                out = out.filter(F.col(f"m{y}") != F.col(f"m{x}"))
        return out

    def advance(self, g: Graph, t1: int) -> DataFrame:
        """Answers born in (now, t1]; the stored prefixes move on to ``t1``."""
        if g.edge_life.filter((F.col("died") > self.now) & (F.col("died") <= t1)).limit(1).count():
            raise NotImplementedError("the partial-result tree has no deletions")
        adj = g.adjacency().filter(F.col("born") <= t1)
        new = adj.filter(F.col("born") > self.now)
        fresh: DataFrame | None = None
        for n in range(1, len(self.order)):
            if n == 1:
                more = self._edges(new, 1)
            else:
                more = self._extend(fresh, adj, n)
                for k in range(len(self._back(n))):
                    more = more.unionByName(self._extend(self.stored[n - 2], adj, n, new, k))
            before, fresh = fresh, materialise(more, "prefix-new")
            if before is not None:
                self.stored[n - 2] = materialise(self.stored[n - 2].unionByName(before), "prefix")
        self.stored[-1] = materialise(self.stored[-1].unionByName(fresh), "prefix")
        self.now = t1
        return as_rows(fresh, self.pattern, 0)

    def stored_rows(self) -> int:
        return sum(x.count() for x in self.stored)


def _semi_join_program(adj: DataFrame, pattern: Pattern, edges: list[tuple[int, int]], rounds: int) -> DataFrame:
    """cand(qv, v) after passes of semi-joins along the given pattern edges, both ways."""
    cand = {i: adj.filter(F.col("src_label") == label).select(F.col("src").alias("v")).distinct() for i, label in enumerate(pattern.labels)}

    def reduce(a: int, b: int) -> None:
        """Keep candidates of ``a`` with a neighbour among those of ``b``."""
        e = adj.filter((F.col("src_label") == pattern.labels[a]) & (F.col("dst_label") == pattern.labels[b])).select(F.col("src").alias("v"), F.col("dst").alias("w"))
        ok = e.join(cand[b].select(F.col("v").alias("w")), "w", "left_semi").select("v").distinct()
        cand[a] = materialise(cand[a].join(ok, "v", "left_semi"), "reduced")  # else each pass repeats all before it

    for _ in range(rounds):
        for a, b in reversed(edges):
            reduce(a, b)
        for a, b in edges:
            reduce(b, a)
    out = None
    for i, df in cand.items():
        rows = df.select(F.lit(i).alias("qv"), "v")
        out = rows if out is None else out.unionAll(rows)
    return out


def _bfs_edges(pattern: Pattern, root: int = 0) -> tuple[list[tuple[int, int]], list[tuple[int, int]]]:
    """(spanning tree edges, all edges oriented by breadth-first order), parents first."""
    order, tree = [root], []
    for x in order:
        for y in sorted(pattern.neighbours(x)):
            if y not in order:
                order.append(y)
                tree.append((x, y))
    rank = {x: i for i, x in enumerate(order)}
    every = sorted(((a, b) if rank[a] < rank[b] else (b, a) for a, b, *_ in pattern.edges), key=lambda e: (rank[e[0]], rank[e[1]]))
    return tree, every


def tree_index(adj: DataFrame, pattern: Pattern) -> DataFrame:
    """cand(qv, v) by one upward and one downward pass over a spanning tree."""
    return _semi_join_program(adj, pattern, _bfs_edges(pattern)[0], 1)


def dag_index(adj: DataFrame, pattern: Pattern, rounds: int = 2) -> DataFrame:
    """cand(qv, v) pruned along every pattern edge, for a number of rounds."""
    return _semi_join_program(adj, pattern, _bfs_edges(pattern)[1], rounds)


class KeptIndex:
    """The tree or DAG index under updates: for each position the data vertices that fit it, by counters.

    A vertex is *up* at a position if it has the label and, for each pattern edge to a child, a neighbour that is up there;
    it is *down* if it is up and, for each edge from a parent, has a neighbour that is down there. A counter a
    pattern edge and vertex holds the number of such neighbours. An epoch adds signed numbers of changed edges, and
    of neighbours that came or went, so a change goes as far as memberships turn and no further.
    ``down`` is what one upward and one downward pass of semi-joins leave.
    """

    def __init__(self, g: Graph, pattern: Pattern, kind: str = "tree", t0: int = 0):
        tree, every = _bfs_edges(pattern)
        self.pattern, self.now = pattern, t0
        self.order = [0, *[b for _, b in tree]]
        edges = tree if kind == "tree" else every
        self.children = {x: [b for a, b in edges if a == x] for x in self.order}
        self.parents = {x: [a for a, b in edges if b == x] for x in self.order}
        labelled = {x: g.vertices.filter(F.col("label") == pattern.labels[x]).select("v") for x in self.order}
        none = g.vertices.select("v").limit(0)
        self.up = {x: none if self.children[x] else labelled[x] for x in self.order}
        self.down = {x: none if self.parents[x] or self.children[x] else labelled[x] for x in self.order}
        self.up_counts, self.down_counts = ({x: none.select("v", *[F.lit(0).cast("long").alias(f"n{k}") for k in range(len(ys[x]))]) for x in self.order} for ys in (self.children, self.parents))
        adj = g.adjacency()
        start = adj.filter((F.col("born") <= t0) & (F.col("died") > t0))
        self._move(start.limit(0), start.withColumn("sign", F.lit(1)))

    def _fits(self, adj: DataFrame, x: int, y: int) -> DataFrame:
        """Edges from vertices that could be at ``x`` to those that could be at ``y``."""
        e = adj.filter((F.col("src_label") == self.pattern.labels[x]) & (F.col("dst_label") == self.pattern.labels[y]))
        want = self.pattern.edge_label(x, y)
        e = e.filter(F.col("elabel") == want) if want is not None else e
        return e.select(F.col("src").alias("v"), F.col("dst").alias("w"), "sign")

    def _counted(self, x: int, ys: list[int], old: DataFrame, diff: DataFrame, counts: DataFrame, member: dict, turned: dict) -> DataFrame:
        """v, n* before and a* after: the counters of ``x`` that change. ``member`` and ``turned`` (v, sign)
        are the positions' vertices after the epoch, and those that came or went."""
        parts = None
        for k, y in enumerate(ys):
            new = self._fits(diff, x, y).join(member[y].select(F.col("v").alias("w")), "w", "left_semi")
            moved = self._fits(old.withColumn("sign", F.lit(1)), x, y).drop("sign").join(turned[y].select(F.col("v").alias("w"), "sign"), "w")
            rows = new.select("v", "sign").unionByName(moved.select("v", "sign")).withColumn("k", F.lit(k))
            parts = rows if parts is None else parts.unionByName(rows)
        change = parts.groupBy("v").agg(*[F.coalesce(F.sum(F.when(F.col("k") == k, F.col("sign"))), F.lit(0)).cast("long").alias(f"d{k}") for k in range(len(ys))])
        both = change.join(counts, "v", "left").fillna(0, [f"n{k}" for k in range(len(ys))])
        return both.select("v", *[F.col(f"n{k}") for k in range(len(ys))], *[(F.col(f"n{k}") + F.col(f"d{k}")).alias(f"a{k}") for k in range(len(ys))])

    @staticmethod
    def _kept(counts: DataFrame, changed: DataFrame, n: int) -> DataFrame:
        fresh = changed.select("v", *[F.col(f"a{k}").alias(f"n{k}") for k in range(n)])
        return materialise(counts.join(changed, "v", "left_anti").unionByName(fresh.filter(" OR ".join(f"n{k} > 0" for k in range(n)))), "kept-counts")

    @staticmethod
    def _turned(member: DataFrame, touched: DataFrame) -> DataFrame:
        """(v, sign) of ``touched`` (v, now) whose membership differs from before."""
        was = touched.join(member.withColumn("_was", F.lit(True)), "v", "left").withColumn("_was", F.coalesce("_was", F.lit(False)))
        return materialise(was.filter("now <> _was").select("v", F.when(F.col("now"), 1).otherwise(-1).alias("sign")), "kept-turned")

    @staticmethod
    def _after(member: DataFrame, turned: DataFrame) -> DataFrame:
        return materialise(member.join(turned, "v", "left_anti").unionByName(turned.filter("sign > 0").select("v")), "kept-member")

    def _move(self, old: DataFrame, diff: DataFrame) -> None:
        diff = materialise(diff.select("src", "dst", "src_label", "dst_label", "elabel", "sign"), "kept-diff")
        nothing = diff.select(F.col("src").alias("v"), "sign").limit(0)
        turned: dict[int, DataFrame] = {}
        for x in reversed(self.order):
            ys = self.children[x]
            if not ys:
                turned[x] = nothing
                continue
            changed = materialise(self._counted(x, ys, old, diff, self.up_counts[x], self.up, turned), "kept-changed")
            turned[x] = self._turned(self.up[x], changed.select("v", F.expr(" AND ".join(f"a{k} > 0" for k in range(len(ys)))).alias("now")))
            self.up[x] = self._after(self.up[x], turned[x])
            self.up_counts[x] = self._kept(self.up_counts[x], changed, len(ys))
        fell: dict[int, DataFrame] = {}
        for x in self.order:
            ys = self.parents[x]
            if not ys:
                fell[x], self.down[x] = turned[x], self.up[x]
                continue
            changed = materialise(self._counted(x, ys, old, diff, self.down_counts[x], self.down, fell), "kept-changed")
            self.down_counts[x] = self._kept(self.down_counts[x], changed, len(ys))
            touched = changed.select("v").unionByName(turned[x].select("v")).distinct()
            enough = self.down_counts[x].filter(" AND ".join(f"n{k} > 0" for k in range(len(ys)))).select("v").join(self.up[x], "v", "left_semi")
            fell[x] = self._turned(self.down[x], touched.join(enough.withColumn("now", F.lit(True)), "v", "left").withColumn("now", F.coalesce("now", F.lit(False))))
            self.down[x] = self._after(self.down[x], fell[x])

    def candidates(self) -> DataFrame:
        """cand(qv, v)."""
        out = None
        for x in self.order:
            rows = self.down[x].select(F.lit(x).alias("qv"), "v")
            out = rows if out is None else out.unionByName(rows)
        return out

    def advance(self, g: Graph, t1: int) -> DataFrame:
        """Answers (query_id, m, born, died) that stand at ``t1`` and were born after the time before; the index moves
        on to ``t1``. Each new edge starts every pattern edge it fits, within the candidates."""
        t0, adj = self.now, g.adjacency()
        before, after = ((F.col("born") <= t) & (F.col("died") > t) for t in (t0, t1))
        came = adj.filter(after & (F.col("born") > t0)).withColumn("sign", F.lit(1))
        went = adj.filter(before & (F.col("died") <= t1)).withColumn("sign", F.lit(-1))
        self._move(adj.filter(before), came.unionByName(went))
        self.now = t1
        cand, p, now, out = materialise(self.candidates(), "kept-candidates"), self.pattern, adj.filter(after), None
        for i, j, order in anchored_orders(p):
            if not any((i, j) == e[:2] for e in p.edges):
                continue
            one = Patterns([p])
            seed = seeds(came, one, [(0, p, order)], cand.withColumn("query_id", F.lit(0)), anchored=True).select(F.col("m")[0].alias(f"m{i}"), F.col("m")[1].alias(f"m{j}"), "born", "died", "anchor")
            rows = as_rows(match_static(now, p, order, cand, seed=seed, before_anchor=True), p, 0)
            out = rows if out is None else out.unionAll(rows)
        return out


def indexed_answers(g: Graph, pattern: Pattern, t: int | None = None, kind: str = "tree") -> DataFrame:
    """query_id, m on a snapshot, refined within the candidates of the tree or the DAG index."""
    adj = g.snapshot(t).adjacency()
    cand = tree_index(adj, pattern) if kind == "tree" else dag_index(adj, pattern)
    return as_rows(match_static(adj, pattern, None, cand), pattern, 0).select("query_id", "m")


def acyclic_reduce(adj: DataFrame, pattern: Pattern) -> DataFrame:
    """Homomorphisms m0..mk of an acyclic pattern: full reduction first, then joins without dead ends."""
    if not pattern.acyclic:
        raise ValueError("the pattern has a cycle")
    cand = _semi_join_program(adj, pattern, _bfs_edges(pattern)[0], 1)
    return match_static(adj, pattern, None, cand, semantics="homo")
