"""Edges born at one time, patterns that come and go, stored prefixes, forbidden edges."""

import random

import pytest

from starwatch import baselines
from starwatch.model import ALIVE, Graph
from starwatch.operators import monitor, refine
from starwatch.plans.patterns import Patterns, parse

VEE = parse("vee", "a:1-b:1, b-c:1")
TRI = parse("tri", "a:1-b:1, b-c:1, a-c")
SQUARE = parse("square", "a:1-b:2, b-c:1, c-d:2, a-d")
ALL = Patterns([VEE, TRI, SQUARE, parse("edge", "a:1-b:2")])


def graph(spark, edges, labels):
    return Graph(spark.createDataFrame(list(labels.items()), "v long, label int"), spark.createDataFrame([(u, v, 1, b, d) for u, v, b, d in edges], "u long, v long, elabel int, born long, died long"))


def rows(df):
    return sorted((r.query_id, tuple(r.m), r.born, r.died) for r in df.collect())


@pytest.fixture(scope="module")
def stream(spark):
    r = random.Random(6)
    labels = {i: r.choice([1, 1, 2]) for i in range(12)}
    pairs = [(i, j) for i in range(12) for j in range(i)]
    # few distinct times, so many edges share one
    edges = [(min(p), max(p), b, r.choice([ALIVE, ALIVE, b + 3])) for p in r.sample(pairs, 40) for b in [r.choice([0, 0, 2, 4, 5])]]
    return graph(spark, edges, labels), labels, edges


def test_insertions_that_share_a_time(spark, stream):
    g, _, _ = stream
    want = [x for x in rows(refine.lifetimes(g, ALL)) if x[2] > 0]
    assert rows(monitor.on_insert(g, ALL, 0, ALIVE - 1)) == want and want
    assert rows(refine.lifetimes(g, ALL, "levels")) == rows(refine.lifetimes(g, ALL))
    assert rows(baselines.delta_join(g, ALL, 0, ALIVE - 1)) == want
    cand = monitor.peak_candidates(g, ALL, monitor.BuildParams(), 0, ALIVE - 1)
    assert rows(monitor.on_insert(g, ALL, 0, ALIVE - 1, cand)) == want
    assert rows(monitor.on_insert(g, ALL, 0, ALIVE - 1, cand, live={1})) == [x for x in want if x[0] == 1]


def ops(spark, some):
    return spark.createDataFrame([(s, None, o, u, v, 1) for s, o, u, v in some], "seq long, ts timestamp, op string, u long, v long, elabel int")


def test_patterns_come_and_go(spark):
    vertices = spark.createDataFrame([(i, 1) for i in range(6)], "v long, label int")
    m = monitor.Monitor(None, vertices, Patterns([VEE]))
    m.apply(ops(spark, [(1, "+", 0, 1), (7, "+", 1, 2)]))
    q = m.register(parse("vee2", "a:1-b:1, b-c:1"))
    assert m.answers(3).count() == 0 and m.answers(7).filter(f"query_id = {q}").count() == 2
    m.unregister(0)
    m.apply(ops(spark, [(9, "+", 2, 3)]))
    assert {r.query_id for r in m.answers().collect()} == {q} and m.answers().count() == 4


def test_stored_prefixes(spark):
    r = random.Random(1)
    labels = {i: r.choice([1, 1, 2]) for i in range(14)}
    pairs = [(j, i) for i in range(14) for j in range(i)]
    edges = [(u, v, r.choice([0, 1, 2, 3, 4]), ALIVE) for u, v in r.sample(pairs, 55)]
    g = graph(spark, edges, labels)
    for p in (TRI, SQUARE):
        tree = baselines.PartialTree(g, p)
        want = rows(refine.lifetimes(g, Patterns([p])))
        got = [x for t0, t1 in ((0, 2), (2, 4)) for x in rows(tree.advance(g, t1))]
        assert sorted(got) == [x for x in want if x[2] > 0] and want
        assert tree.stored_rows() >= len(want)


def test_forbidden_edges_end_a_match_when_they_come(spark, stream):
    g, labels, edges = stream
    got = refine.match_static(g.adjacency(), VEE, semantics="induced").collect()
    for t in range(9):
        now = {(u, v) for u, v, b, d in edges if b <= t < d}
        near = lambda x, y: (min(x, y), max(x, y)) in now
        ones = [i for i, x in labels.items() if x == 1]
        want = {(a, b, c) for a in ones for b in ones for c in ones if len({a, b, c}) == 3 and near(a, b) and near(b, c) and not near(a, c)}
        assert {(r.m0, r.m1, r.m2) for r in got if r.born <= t < r.died} == want


def test_monitor_asks_the_synopsis(spark, stream):
    g, _, edges = stream
    start = spark.createDataFrame([(u, v, 1) for u, v, b, _ in edges if b == 0], "u long, v long, elabel int")
    m = monitor.Monitor(start, g.vertices, ALL)
    updates = [(b, "+", u, v) for u, v, b, _ in edges if b] + [(d, "-", u, v) for u, v, _, d in edges if d != ALIVE]
    want = rows(refine.lifetimes(g, ALL))
    for low, high in ((0, 4), (4, 20)):
        some = [x for x in updates if low < x[0] <= high]
        m.apply(ops(spark, some))
    assert m.index is not None and m.index.n_touched < 12
    assert rows(m.state) == want
