"""The pattern engine against hand-made examples, brute force and itself."""

import random
from itertools import permutations

import pytest
from pyspark.sql import functions as F

from starwatch import baselines
from starwatch.functions.arithmetic import base_vector, label_vector
from starwatch.functions.vectors import dominates, label_dict, register_sql
from starwatch.model import ALIVE, BuildParams, Graph, edge_lifetimes, normalise_updates
from starwatch.operators import bands, monitor, prune, refine, stars, synopsis
from starwatch.plans.joinorder import anchored_orders, steps_of
from starwatch.plans.patterns import Pattern, Patterns, embed_patterns, parse

OPS = "seq long, ts timestamp, op string, u long, v long, elabel int"


def make(spark, n=8, n_ops=50, labels=2, seed=0):
    """A random micro graph with deletions, re-insertions and no-ops: (vertices, raw ops, snapshots)."""
    r = random.Random(seed)
    label = {v: r.randint(1, labels) for v in range(n)}
    live, ops, snaps = set(), [], {}
    for t in range(1, n_ops + 1):
        u, v = r.sample(range(n), 2)
        op = r.choice("++-")
        ops.append((t, None, op, u, v, 1))
        e = (min(u, v), max(u, v))
        live = live | {e} if op == "+" else live - {e}
        snaps[t] = set(live)
    return label, spark.createDataFrame(list(label.items()), "v long, label int"), spark.createDataFrame(ops, OPS), snaps


def brute(pattern, label, edges, injective=True):
    out = set()
    n = len(pattern.labels)
    for m in permutations(label, n):
        if all(label[m[i]] == pattern.labels[i] for i in range(n)) and all((min(m[a], m[b]), max(m[a], m[b])) in edges for a, b, *_ in pattern.edges):
            out.add(m)
    return out


PATTERNS = Patterns([parse("tri", "a:1-b:2, b-c:1, a-c"), parse("path", "a:1-b:2, b-c:1"), parse("square", "a:1-b:2, b-c:1, c-d:2, d-a")])


@pytest.fixture(scope="module")
def micro(spark):
    label, vertices, raw, snaps = make(spark)
    life = edge_lifetimes(None, normalise_updates(raw)).cache()
    return label, Graph(vertices, life), raw, snaps


def test_lifetimes_equal_replay(micro):
    label, g, _, snaps = micro
    rows = [(r.query_id, tuple(r.m), r.born, r.died) for r in refine.lifetimes(g, PATTERNS).collect()]
    level = [(r.query_id, tuple(r.m), r.born, r.died) for r in refine.lifetimes(g, PATTERNS, "levels").collect()]
    assert sorted(rows) == sorted(level)
    for t, edges in snaps.items():
        for q, p in PATTERNS:
            assert {m for k, m, b, d in rows if k == q and b <= t < d} == brute(p, label, edges)


def test_monitor_epochs_equal_replay(micro):
    label, g, raw, snaps = micro
    m = monitor.Monitor(None, g.vertices, PATTERNS)
    for low, high in ((0, 20), (20, 50)):
        m.apply(raw.filter((F.col("seq") > low) & (F.col("seq") <= high)))
        for q, p in PATTERNS:
            assert {tuple(r.m) for r in m.answers().filter(F.col("query_id") == q).collect()} == brute(p, label, snaps[high])


def test_intersect_and_baselines_agree(micro):
    label, g, _, snaps = micro
    last = snaps[50]
    adj = g.snapshot().adjacency().cache()
    for _, p in PATTERNS:
        want = brute(p, label, last)
        cols = [f"m{i}" for i in range(len(p.labels))]
        assert {tuple(r) for r in refine.match_intersect(adj, p).select(*cols).collect()} == want
        for kind in ("tree", "dag") if len(p.edges) < 4 else ():
            assert {tuple(r.m) for r in baselines.indexed_answers(g, p, None, kind).collect()} == want
    with pytest.raises(NotImplementedError):
        baselines.PartialTree(g, PATTERNS.items[0]).advance(g, 50)
    with pytest.raises(ValueError):
        baselines.acyclic_reduce(adj, PATTERNS.items[0])


def test_no_false_dismissals_and_boxes(spark, micro):
    label, g, _, snaps = micro
    p = BuildParams()
    ix = synopsis.Index(g, p, PATTERNS.deltas(spark))
    cand = {(r.query_id, r.qv, r.v) for r in prune.candidates(ix, PATTERNS).collect()}
    for q, pat in PATTERNS:
        for m in brute(pat, label, snaps[50]):
            assert all((q, i, v) in cand for i, v in enumerate(m))
    deltas = PATTERNS.deltas(spark)
    a = sorted(tuple(r) for r in bands.degree_boxes(ix.hist, ix.star, deltas, p).collect())
    b = sorted(tuple(r) for r in bands.boxes_by_enumeration(ix.hist, ix.star, deltas, p).collect())
    assert a == b and a


def test_driver_and_column_arithmetic_agree(spark):
    labels = spark.createDataFrame([(i,) for i in range(1, 40)], "label int")
    for p in (BuildParams(), BuildParams(variant="based", base="l1_half"), BuildParams(base="diag", d=3), BuildParams(base="l2")):
        for r in label_dict(labels, p).collect():
            assert [r[f"lv{k}"] for k in range(p.d)] == label_vector(r.label, p.d, p.salt, p.dist)
            assert [r[f"bv{k}"] for k in p.dims] == base_vector(r.label, p.d, p.base, p.salt)


def test_star_timeline(spark):
    """Two neighbours wanted; an extra one comes and goes, then one of the two leaves."""
    label = {1: 1, 2: 2, 3: 3, 4: 4}
    vertices = spark.createDataFrame(list(label.items()), "v long, label int")
    start = spark.createDataFrame([(1, 2, 1), (1, 3, 1)], "u long, v long, elabel int")
    ops = spark.createDataFrame([(1, None, "+", 1, 4, 1), (2, None, "-", 1, 4, 1), (3, None, "-", 1, 2, 1)], OPS)
    g = Graph(vertices, edge_lifetimes(start, ops))
    p = BuildParams(variant="plain")
    q = embed_patterns(spark, Patterns([Pattern("s", (1, 2, 3), ((0, 1), (0, 2)))]), p).filter("qv = 0").drop("label", "deg")
    hit = [stars.stars(g, p, t).filter("v = 1").join(q).filter(dominates("q", "e", p)).count() for t in range(4)]
    assert hit == [1, 1, 1, 0]
    last = stars.stars(g, p, 3).filter("v = 1").first()
    assert [last.ns0, last.ns1] == label_vector(3, 2, 1, "uniform")
    updated = stars.update_stars(stars.stars(g, p, 0), ops.select("op", "u", "v"), vertices, p)
    assert sorted(updated.collect()) == sorted(stars.stars(g, p, 3).select(*updated.columns).collect())


def test_bands_of_a_small_histogram(spark):
    star = spark.createDataFrame([(i, d) for i, d in enumerate([1, 1, 1, 2, 2, 3, 5, 9])], "v long, deg int")
    survive = [sum(d >= x for d in [1, 1, 1, 2, 2, 3, 5, 9]) for x in range(1, 10)]
    total, ends, run = sum(survive), [], 0
    for j in (1, 2):
        run, x = 0, 0
        while run * 3 < j * total:
            run += survive[x]
            x += 1
        ends.append(x)
    got = [(r.lo_excl, r.hi_incl) for r in bands.degree_bands(star, 3).orderBy("band").collect()]
    assert got == [(0, ends[0]), (ends[0], ends[1]), (ends[1], bands.OPEN)]


def test_normalise_drops_what_changes_nothing(spark):
    ops = spark.createDataFrame([(1, None, "-", 1, 2, 1), (2, None, "+", 2, 1, 1), (3, None, "+", 1, 2, 1), (4, None, "+", 3, 3, 1), (5, None, "-", 1, 2, 1)], OPS)
    assert [r.seq for r in normalise_updates(ops).orderBy("seq").collect()] == [2, 5]
    start = spark.createDataFrame([(1, 2)], "u long, v long")
    assert [r.seq for r in normalise_updates(ops, start).orderBy("seq").collect()] == [1, 2, 5]


def test_patterns_and_plans(spark):
    p = parse("x", "a:1-b:6[2], b-c:12, a-c")
    assert p.labels == (1, 6, 12) and p.edge_label(1, 0) == 2 and not p.acyclic
    assert Patterns.from_frames(Patterns([p]).q_vertex(spark), Patterns([p]).q_edge(spark)).items[0].labels == p.labels
    assert len(anchored_orders(p)) == 6
    assert [k for k, *_ in steps_of(p, [0, 1, 2])] == ["start", "expand", "expand", "close"]
    with pytest.raises(ValueError):
        parse("bad", "a:1 b:2")
    with pytest.raises(AssertionError):
        Pattern("apart", (1, 2, 3), ((0, 1),))


def test_symmetric_pattern_as_subgraphs(spark):
    vertices = spark.createDataFrame([(1, 1), (2, 2), (3, 1)], "v long, label int")
    life = spark.createDataFrame([(1, 2, 1, 0, ALIVE), (2, 3, 1, 0, ALIVE)], "u long, v long, elabel int, born long, died long")
    p = parse("vee", "a:1-b:2, b-c:1")
    m = refine.match_static(Graph(vertices, life).adjacency(), p)
    assert m.count() == 2 and refine.subgraphs(m, p).count() == 1
    assert refine.match_static(Graph(vertices, life).adjacency(), p, semantics="homo").count() == 4


def test_sql_functions(spark):
    register_sql(spark, BuildParams())
    r = spark.sql("SELECT dominates_vec(array(1L, 2L), array(1L, 3L)) AS a, in_box_vec(array(2L), array(1L), array(1L)) AS b, label_vec(3) AS c").first()
    assert r.a and not r.b and r.c == label_vector(3, 2, 1, "zipf")
