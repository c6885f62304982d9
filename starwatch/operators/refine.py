"""Refinement: joining candidates into matches, with the lifetimes of their edges carried along.

A match lives on [largest born, smallest died) of its edges, so one pass over edges with
lifetimes gives the answers, and their changes, for every point in time.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import ALIVE, Graph
from ..storage import materialise, small
from ..plans.joinorder import Fanouts, block_steps, candidate_counts, join_orders, order_from, plan_steps, sub_pattern
from ..plans.patterns import Pattern, Patterns

OUT = "query_id INT, m ARRAY<BIGINT>, born BIGINT, died BIGINT"


def _edge(adj: DataFrame, pattern: Pattern, i: int, j: int) -> DataFrame:
    """Directed data edges that can play the pattern edge (i, j): the labels are compared here."""
    e = adj.filter((F.col("src_label") == pattern.labels[i]) & (F.col("dst_label") == pattern.labels[j]))
    el = pattern.edge_label(i, j)
    return e.filter(F.col("elabel") == el) if el is not None else e


def _distinct_from(pattern: Pattern, x: int, placed: list[int]) -> list[Column]:
    """Injectivity: only positions of equal label can coincide."""
    return [F.col(f"m{x}") != F.col(f"m{y}") for y in placed if pattern.labels[y] == pattern.labels[x]]


#: Edges are ordered by (born, u, v): edges that share a time of birth are told apart by their ends.
def _name(born: str, a: str, b: str) -> Column:
    return F.struct(F.col(born).alias("born"), F.least(a, b).alias("u"), F.greatest(a, b).alias("v"))


def edge_name(a: int, b: int) -> Column:
    """The name of the edge just joined between two positions."""
    return _name("_b", f"m{a}", f"m{b}")


#: An edge is older than the anchor, and alive when the anchor is born.
OLDER = "_n < anchor AND _d > anchor.born"


def fanouts(adj: DataFrame, *patterns: Pattern) -> Fanouts:
    """Mean numbers of neighbours by both labels, one small row per pair of labels; counted once per adjacency, and only
    for patterns with a cycle, as others leave little to choose."""
    if all(p.acyclic for p in patterns):
        return Fanouts()
    if not hasattr(adj, "_fanouts"):
        rows = adj.groupBy("src_label", "dst_label").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("src").alias("k")).collect()
        adj._fanouts = Fanouts({(r.src_label, r.dst_label): r.n / max(1, r.k) for r in rows})
    return adj._fanouts


def label_pairs(patterns: Patterns) -> frozenset[tuple[int, int]]:
    """The labels of the patterns' edges, both ways round."""
    return frozenset((p.labels[a], p.labels[b]) for _, p in patterns for i, j, *_ in p.edges for a, b in ((i, j), (j, i)))


def relevant(adj: DataFrame, patterns: Patterns) -> DataFrame:
    """The rows of ``adj`` with the labels of some pattern edge, as a written table: every step of every join reads them.
    Written once for the same adjacency and pairs of labels; a table made so serves patterns with fewer pairs too."""
    pairs = label_pairs(patterns)
    if not pairs or pairs <= adj.__dict__.get("_pairs", frozenset()):
        return adj
    made = adj.__dict__.setdefault("_relevant", {})
    if pairs not in made:
        wanted = patterns.hinted(small(adj.sparkSession, sorted(pairs), "src_label int, dst_label int"))
        made[pairs] = materialise(adj.join(wanted, ["src_label", "dst_label"], "left_semi"), "relevant")
        made[pairs]._pairs = pairs
    return made[pairs]


def relevant_of(g: Graph, patterns: Patterns) -> DataFrame:
    """The rows of ``relevant(g.adjacency(), patterns)``, but neither written nor taken from the whole adjacency."""
    wanted = patterns.hinted(small(g.vertices.sparkSession, sorted(label_pairs(patterns)), "src_label int, dst_label int"))
    return g._adjacency(wanted)


def known_relevant(adj: DataFrame, patterns: Patterns, counted: DataFrame | None = None) -> DataFrame:
    """``adj`` noted to be the rows of ``relevant``; ``counted``: the same edges with other lives, whose ``fanouts`` hold here too."""
    adj._pairs = label_pairs(patterns)
    if counted is not None and hasattr(counted, "_fanouts"):
        adj._fanouts = counted._fanouts
    return adj


#: So many pairs of labels stand in a filter, which a table written by them answers from its files; more are joined.
MAX_PAIRS = 64


def of_pairs(edges: DataFrame, pairs: set[tuple[int, int]], a: str = "src_label", b: str = "dst_label") -> DataFrame:
    """The rows with one of the pairs of labels."""
    if len(pairs) > MAX_PAIRS:
        return edges.join(small(edges.sparkSession, sorted(pairs), f"{a} int, {b} int"), [a, b], "left_semi")
    wanted = F.lit(False)
    for x, y in sorted(pairs):
        wanted = wanted | ((F.col(a) == x) & (F.col(b) == y))
    return edges.filter(wanted)


def match_static(adj: DataFrame, pattern: Pattern, order: list[int] | None = None, cand: DataFrame | None = None, semantics: str = "iso", seed: DataFrame | None = None, before_anchor: bool = False, parts: dict | None = None, newest: bool = False) -> DataFrame:
    """m0..mk, born, died of all matches of one pattern, by one chain of equi-joins.

    semantics: ``iso`` (injective), ``homo`` (positions may coincide) or ``induced`` (no further
    edges between matched vertices). ``cand(qv, v)`` restricts each position by a semi-join. ``seed``
    (m_a, m_b, born, died and more) starts from given pairs for the first two positions of
    ``order``; with ``before_anchor`` every other edge must be older than the seed's edge (column ``anchor``).
    Biconnected parts off the first one are matched on their own (see ``block_steps``), and kept in ``parts`` as written
    tables if it is given, for the other chains over the same ``adj``. ``newest`` adds each match's newest edge.
    """
    order = order or order_from(pattern, {}, [0])

    def allowed(df: DataFrame, x: int) -> DataFrame:
        if cand is None:
            return df
        return df.join(cand.filter(F.col("qv") == x).select(F.col("v").alias(f"m{x}")), f"m{x}", "left_semi")

    def part_of(at: int, rest: tuple[int, ...]) -> DataFrame:
        """Matches of a part with their own lifetime _b, _d (and newest edge _n)."""
        positions = [at, *rest]
        sub = sub_pattern(pattern, positions)
        key = (sub.labels, sub.edges)
        if parts is not None and key in parts and cand is None:
            rows = parts[key]
        else:
            mine = None
            if cand is not None:
                where = F.create_map(*[F.lit(y) for n, x in enumerate(positions) for y in (x, n)])
                mine = cand.filter(F.col("qv").isin(positions)).select(where[F.col("qv")].alias("qv"), "v")
            rows = match_static(adj, sub, None, mine, "homo" if semantics == "homo" else "iso", newest=before_anchor)
            if parts is not None and cand is None:
                rows = parts[key] = materialise(rows, "part")
        named = [F.col("newest").alias("_n")] if before_anchor else []
        return rows.select(*[F.col(f"m{n}").alias(f"m{x}") for n, x in enumerate(positions)], F.col("born").alias("_b"), F.col("died").alias("_d"), *named)

    state: DataFrame | None = seed
    placed = list(order[:2]) if seed is not None else []
    for kind, a, b in block_steps(pattern, order, 2 if seed is not None else 1, fanouts(adj, pattern)):
        name = edge_name(a, b)
        if kind == "part":
            state, fresh, name = state.join(part_of(a, b), f"m{a}"), list(b), F.col("_n")
        else:
            e = _edge(adj, pattern, a, b).select(F.col("src").alias(f"m{a}"), F.col("dst").alias(f"m{b}"), F.col("born").alias("_b"), F.col("died").alias("_d"))
            fresh = [b] if kind == "expand" else []
            e = allowed(e, b) if fresh else e
            if state is None:
                state, placed = allowed(e, a).select(f"m{a}", f"m{b}", F.col("_b").alias("born"), F.col("_d").alias("died"), *([name.alias("newest")] if newest else []), "_b", "_d"), [a]
            else:
                state = state.join(e, [f"m{a}"] if fresh else [f"m{a}", f"m{b}"])
                if newest:
                    state = state.withColumn("newest", F.greatest("newest", name))
        # one filter and one change of columns a step: the driver goes over the whole plan for each
        born, died = F.greatest("born", "_b"), F.least("died", "_d")
        keep = born < died
        if before_anchor:
            keep &= (name < F.col("anchor")) & (F.col("_d") > F.col("anchor.born"))
        for x in fresh:
            if semantics != "homo":
                for c in _distinct_from(pattern, x, placed):
                    keep &= c
        placed += fresh
        state = state.filter(keep).withColumns({"born": born, "died": died}).drop("_b", "_d", "_n")
    if semantics == "induced":
        for a, b in combinations(range(len(pattern.labels)), 2):
            if b not in pattern.neighbours(a):
                state = without_edge(state, adj, f"m{a}", f"m{b}", [f"m{i}" for i in range(len(pattern.labels))])
    return state


def without_edge(state: DataFrame, adj: DataFrame, a: str, b: str, key: list[str]) -> DataFrame:
    """``state`` (``key``, born, died) without the times at which an edge joins ``a`` and ``b``: a match is
    split into the parts of its life outside the lives of that edge."""
    e = adj.select(F.col("src").alias(a), F.col("dst").alias(b), F.col("born").alias("_b"), F.col("died").alias("_d"))
    met = state.join(e, [a, b], "left").withColumn("_cut", F.when((F.col("_b") < F.col("died")) & (F.col("_d") > F.col("born")), F.struct("_b", "_d")))
    lives = met.groupBy(*key, "born", "died").agg(F.sort_array(F.collect_list("_cut")).alias("_cuts"))  # lives of one edge do not overlap
    gaps = F.expr("transform(sequence(0, size(_cuts)), i -> struct(greatest(born, if(i = 0, born, get(_cuts, i - 1)._d)) AS b, least(died, if(i = size(_cuts), died, get(_cuts, i)._b)) AS d))")
    return lives.withColumn("_gap", F.explode(gaps)).filter("_gap.b < _gap.d").select(*key, F.col("_gap.b").alias("born"), F.col("_gap.d").alias("died"))


def as_rows(matches: DataFrame, pattern: Pattern, query_id: int) -> DataFrame:
    return matches.select(F.lit(query_id).alias("query_id"), F.array(*[F.col(f"m{i}") for i in range(len(pattern.labels))]).alias("m"), "born", "died")


def match_all_static(adj: DataFrame, patterns: Patterns, orders: dict[int, list[int]] | None = None, cand: DataFrame | None = None) -> DataFrame:
    """answers(query_id, m, born, died) of all patterns, a join chain each."""
    out = None
    adj = relevant(adj, patterns)
    for q, p in patterns:
        mine = cand.filter(F.col("query_id") == q).select("qv", "v") if cand is not None else None
        rows = as_rows(match_static(adj, p, (orders or {}).get(q), mine), p, q)
        out = rows if out is None else out.unionAll(rows)
    return out


def match_levels(adj: DataFrame, patterns: Patterns, orders: dict[int, list[int]] | None = None, cand: DataFrame | None = None) -> DataFrame:
    """The same for many patterns at once: all of them advance together, a join per level. Patterns that
    are alike are matched once, and their matches given to each of them (not with candidates, which are each pattern's own)."""
    orders = orders or join_orders(patterns, {})
    if cand is not None:
        return match_plans(adj, patterns, [(q, p, orders[q]) for q, p in patterns], cand)
    first: dict[tuple, int] = {}
    same = [(first.setdefault((p.labels, p.edges), q), q) for q, p in patterns]
    rows = match_plans(adj, patterns, [(q, patterns.items[q], orders[q]) for q in first.values()])
    if len(first) == len(same):
        return rows
    to = patterns.hinted(small(adj.sparkSession, same, "query_id int, to int"))
    return rows.join(to, "query_id").select(F.col("to").alias("query_id"), "m", "born", "died")


def seeds(fresh: DataFrame, patterns: Patterns, plans: list[tuple[int, Pattern, list[int]]], cand: DataFrame | None = None, anchored: bool = False, newest: bool = False) -> DataFrame:
    """(pid, query_id, m, born, died) of the directed edges that fit the first two positions of the
    plans, all at once; ``pid`` numbers the plans, and ``anchor`` names the edge."""
    rows = [(n, q, o[0], o[1], p.labels[o[0]], p.labels[o[1]], p.edge_label(o[0], o[1])) for n, (q, p, o) in enumerate(plans)]
    plan = patterns.hinted(small(fresh.sparkSession, rows, "pid int, query_id int, qi int, qj int, src_label int, dst_label int, want int"))
    hit = of_pairs(fresh, {x[4:6] for x in rows}).join(plan, ["src_label", "dst_label"]).filter("want IS NULL OR want = elabel")
    for pos, end in (("qi", "src"), ("qj", "dst")) if cand is not None else ():
        hit = hit.join(cand.select("query_id", F.col("qv").alias(pos), F.col("v").alias(end)), ["query_id", pos, end], "left_semi")
    extra = [_name("born", "src", "dst").alias(x) for x, wanted in (("anchor", anchored), ("newest", newest)) if wanted]
    return hit.select("pid", "query_id", F.array("src", "dst").alias("m"), "born", "died", *extra)


def match_plans(adj: DataFrame, patterns: Patterns, plans: list[tuple[int, Pattern, list[int]]], cand: DataFrame | None = None, seed: DataFrame | None = None, newest: bool = False) -> DataFrame:
    """answers(query_id, m, born, died) of plans (query id, pattern, order), all advancing together.

    The number of shuffles is the largest number of pattern edges, whatever the number of plans. ``seed`` gives
    the matches of each plan's first two positions (see ``seeds``); with a column ``anchor`` all other edges must be older.
    An expanding step joins on (vertex, wanted label), a closing one on both ends: the edges stand
    twice, once without and once with the far end as a key, so that hubs are not opened to close a cycle; only
    edges of label pairs that a level asks for are read. Biconnected parts off the first one are matched on their own, once for all
    plans, and joined at their one position (see ``block_steps``). Where plans end and others go on, the state before
    is written, and what is finished takes a join of its own: no level is worked out twice, and no answer is written.
    """
    spark = adj.sparkSession
    adj = relevant(adj, Patterns([p for _, p, _ in plans]))
    fan = fanouts(adj, *[p for _, p, _ in plans])
    place: list[dict[int, int]] = []
    steps: dict[int, list[tuple]] = {}
    hung: dict[int, list[tuple]] = {}
    last: dict[int, int] = {}
    subs: dict[tuple, int] = {}
    homes: list[tuple[int, list[int], Pattern]] = []
    for pid, (q, p, o) in enumerate(plans):
        at = {x: n for n, x in enumerate(o[:2])}
        todo = block_steps(p, o, 2, fan)
        last[pid] = len(todo)
        for n, (kind, a, b) in enumerate(todo, 1):
            if kind == "part":
                positions = [a, *b]
                sub = sub_pattern(p, positions)
                key = (sub.labels, sub.edges, *((q, *positions) if cand is not None else ()))
                if key not in subs:
                    subs[key] = len(homes)
                    homes.append((q, positions, sub))
                hung.setdefault(n, []).append((pid, subs[key], at[a]))
                at |= {x: len(at) + i for i, x in enumerate(b)}
                continue
            if kind == "expand":
                at[b] = len(at)
            steps.setdefault(n, []).append((pid, kind == "close", at[a], at[b], b, p.labels[a], p.labels[b], p.edge_label(a, b)))
        place.append(at)
    state = seed if seed is not None else seeds(adj, patterns, plans, cand, newest=newest)
    anchored = "anchor" in state.columns
    extra = (["anchor"] if anchored else []) + (["newest"] if newest else [])
    keys = adj.select(F.col("src").alias("_from"), F.col("dst").alias("_to"), F.col("src_label").alias("from_label"), F.col("dst_label").alias("to_label"), "elabel", F.col("born").alias("_b"), F.col("died").alias("_d"))
    born, died = F.greatest("born", "_b"), F.least("died", "_d")
    parts = _parts(adj, homes, cand, anchored) if homes else None

    def by_edges(state: DataFrame, rows: list[tuple]) -> DataFrame:
        plan = patterns.hinted(small(spark, rows, "pid int, close boolean, from_at int, to_at int, to_pos int, from_label int, to_label int, want int"))
        e = None
        for close in sorted({x[1] for x in rows}):
            some = of_pairs(keys, {(x[5], x[6]) for x in rows if x[1] == close}, "from_label", "to_label").withColumn("_far", F.col("_to") if close else F.lit(-1).cast("long"))
            e = some if e is None else e.unionByName(some)
        todo = state.join(plan, "pid").withColumn("_from", F.expr("get(m, from_at)")).withColumn("_far", F.when(F.col("close"), F.expr("get(m, to_at)")).otherwise(F.lit(-1)))
        hit = todo.join(e, ["_from", "from_label", "to_label", "_far"]).filter("want IS NULL OR want = elabel").filter(F.col("close") | ~F.array_contains("m", F.col("_to")))
        if anchored:
            hit = hit.withColumn("_n", _name("_b", "_from", "_to")).filter(OLDER)
        grown = [F.greatest("newest", _name("_b", "_from", "_to")).alias("newest")] if newest else []
        out = hit.filter(born < died).select("pid", "query_id", F.when(F.col("close"), F.col("m")).otherwise(F.array_append("m", F.col("_to"))).alias("m"), born.alias("born"), died.alias("died"), *(["anchor"] if anchored else []), *grown, F.when(~F.col("close"), F.col("_to")).alias("_v"), "to_pos")
        if cand is not None and not all(x[1] for x in rows):
            c = cand.select("query_id", F.col("qv").alias("to_pos"), F.col("v").alias("_v"), F.lit(True).alias("_in"))
            out = out.join(c, ["query_id", "to_pos", "_v"], "left").filter("_v IS NULL OR _in").drop("_in")
        return out.select("pid", "query_id", "m", "born", "died", *extra)

    def by_parts(state: DataFrame, rows: list[tuple]) -> DataFrame:
        plan = patterns.hinted(small(spark, rows, "pid int, part int, from_at int"))
        todo = state.join(plan, "pid").withColumn("_from", F.expr("get(m, from_at)"))
        hit = todo.join(parts, ["part", "_from"]).filter(~F.arrays_overlap("m", "_to"))
        if anchored:
            hit = hit.filter(OLDER)
        return hit.filter(born < died).select("pid", "query_id", F.concat("m", "_to").alias("m"), born.alias("born"), died.alias("died"), *extra)

    def step(state: DataFrame, n: int, which: set[int]) -> DataFrame:
        edge_rows, part_rows = ([x for x in rows.get(n, []) if x[0] in which] for rows in (steps, hung))
        made = [f(state, rows) for f, rows in ((by_edges, edge_rows), (by_parts, part_rows)) if rows]
        return made[0] if len(made) == 1 else made[0].unionByName(made[1])

    going = set(last)
    finished: list[DataFrame] = []
    for n in range(max(last.values()) + 1):
        ending = {pid for pid in going if last[pid] == n}
        if n == 0:
            if ending and ending != going:
                finished.append(state.filter(F.col("pid").isin(sorted(ending))))
                state = state.filter(~F.col("pid").isin(sorted(ending)))
            elif ending:
                finished.append(state)
        elif ending and ending != going or (n in steps and n in hung):
            if n > 1:
                state = materialise(state, f"level-{n}")
            if ending:
                finished.append(step(state.filter(F.col("pid").isin(sorted(ending))), n, ending))
            if going - ending:
                state = step(state.filter(~F.col("pid").isin(sorted(ending))) if ending else state, n, going - ending)
        else:
            state = step(state, n, going)
            if ending:
                finished.append(state)
        going -= ending
    back = patterns.hinted(small(spark, [(pid, [at[x] for x in range(len(at))]) for pid, at in enumerate(place)], "pid int, at array<int>"))
    done = [x.select("pid", "query_id", "m", "born", "died", *(["newest"] if newest else [])) for x in finished]
    out = done[0]
    for x in done[1:]:
        out = out.unionAll(x)
    return out.join(back, "pid").select("query_id", F.expr("transform(at, i -> get(m, i))").alias("m"), "born", "died", *(["newest"] if newest else []))


def _parts(adj: DataFrame, homes: list[tuple[int, list[int], Pattern]], cand: DataFrame | None, named: bool) -> DataFrame:
    """part, _from, _to, _b, _d (and newest edge _n): the matches of parts of patterns, each from its joining vertex."""
    subs = Patterns([sub for _, _, sub in homes])
    mine = None
    if cand is not None:
        rows = [(q, x, part, n) for part, (q, positions, _) in enumerate(homes) for n, x in enumerate(positions)]
        to = subs.hinted(small(adj.sparkSession, rows, "query_id int, qv int, part int, at int"))
        mine = cand.join(to, ["query_id", "qv"]).select(F.col("part").alias("query_id"), F.col("at").alias("qv"), "v")
    rows = match_plans(adj, subs, [(n, p, order_from(p, {}, [0])) for n, p in subs], mine, newest=named)
    cols = [F.col("query_id").alias("part"), F.col("m")[0].alias("_from"), F.expr("slice(m, 2, size(m) - 1)").alias("_to"), F.col("born").alias("_b"), F.col("died").alias("_d")]
    return materialise(rows.select(*cols, *([F.col("newest").alias("_n")] if named else [])), "parts")


def match_intersect(adj: DataFrame, pattern: Pattern, order: list[int] | None = None) -> DataFrame:
    """m0..mk of one pattern in a snapshot: neighbour lists of all earlier positions are intersected
    before anything is exploded, which helps cyclic patterns around hubs. The lists hold the
    neighbours of one label only."""
    order = order or order_from(pattern, {}, [0])
    state = adj.filter(F.col("src_label") == pattern.labels[order[0]]).select(F.col("src").alias(f"m{order[0]}")).distinct()
    for n, x in enumerate(order[1:], 1):
        back = [y for y in order[:n] if y in pattern.neighbours(x)]
        for y in back:
            lists = _edge(adj, pattern, y, x).groupBy(F.col("src").alias(f"m{y}")).agg(F.collect_set("dst").alias(f"_l{y}"))
            state = state.join(lists, f"m{y}")
        both = F.col(f"_l{back[0]}")
        for y in back[1:]:
            both = F.array_intersect(both, F.col(f"_l{y}"))
        state = state.withColumn(f"m{x}", F.explode(both)).drop(*[f"_l{y}" for y in back])
        for c in _distinct_from(pattern, x, order[:n]):
            state = state.filter(c)
    return state.withColumn("born", F.lit(0).cast("long")).withColumn("died", F.lit(ALIVE))


def subgraphs(matches: DataFrame, pattern: Pattern) -> DataFrame:
    """One row per subgraph instead of one per mapping: equal edge sets are merged."""
    edges = F.array_sort(F.array(*[F.struct(F.least(f"m{a}", f"m{b}").alias("u"), F.greatest(f"m{a}", f"m{b}").alias("v")) for a, b, *_ in pattern.edges]))
    first = F.min(F.struct(*[f"m{i}" for i in range(len(pattern.labels))])).alias("f")
    got = matches.withColumn("_e", edges).groupBy("_e").agg(first, F.min("born").alias("born"), F.max("died").alias("died"))
    return got.select(*[F.col(f"f.m{i}") for i in range(len(pattern.labels))], "born", "died")


def lifetimes(g: Graph, patterns: Patterns, engine: str = "static", cand: DataFrame | None = None, orders: dict[int, list[int]] | None = None) -> DataFrame:
    """answers(query_id, m, born, died) over all time."""
    adj = g.adjacency()
    return (match_levels if engine == "levels" else match_all_static)(adj, patterns, orders, cand)


def answers_at(answers: DataFrame, t: int) -> DataFrame:
    return answers.filter((F.col("born") <= t) & (F.col("died") > t)).select("query_id", "m")


def delta_at(answers: DataFrame, t0: int, t1: int) -> DataFrame:
    """Changes in (t0, t1]: query_id, m, t, change (+1 or -1)."""
    added = answers.filter((F.col("born") > t0) & (F.col("born") <= t1)).select("query_id", "m", F.col("born").alias("t"), F.lit(1).alias("change"))
    gone = answers.filter((F.col("died") > t0) & (F.col("died") <= t1)).select("query_id", "m", F.col("died").alias("t"), F.lit(-1).alias("change"))
    return added.unionAll(gone)


def directed_only(matches: DataFrame, pattern: Pattern, arcs: DataFrame) -> DataFrame:
    """Matches of which every pattern edge (i, j) runs along an arc (src, dst), one way only."""
    out = matches
    for a, b, *_ in pattern.edges:
        e = arcs.select(F.col("src").alias(f"m{a}"), F.col("dst").alias(f"m{b}")).distinct()
        out = out.join(e, [f"m{a}", f"m{b}"], "left_semi")
    return out


def with_loops(matches: DataFrame, position: int, loops: DataFrame) -> DataFrame:
    """Matches of which the vertex at ``position`` has a loop (loops: v); loops stay outside the graph."""
    return matches.join(loops.select(F.col("v").alias(f"m{position}")).distinct(), f"m{position}", "left_semi")


def plan_table(spark, patterns: Patterns, cand: DataFrame) -> DataFrame:
    return plan_steps(spark, patterns, join_orders(patterns, candidate_counts(cand)))
