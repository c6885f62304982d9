"""What several steps read is written once, and the index moves on once an epoch."""

import random

import pytest

from starwatch.functions import vectors
from starwatch.model import ALIVE, BuildParams, Graph
from starwatch.operators import bands, monitor, refine, stars, synopsis
from starwatch.plans.patterns import Pattern, Patterns
from starwatch.sources import views
from starwatch.storage import materialise, side_by_side, small
from starwatch import model

PATTERNS = Patterns([Pattern("bow", (1, 1, 1, 2, 1), ((0, 1), (1, 2), (0, 2), (3, 4), (4, 2), (3, 2))), Pattern("vee", (1, 2, 1), ((0, 1), (1, 2)))])


@pytest.fixture
def written(monkeypatch):
    names = []

    def noted(df, name, rows=None):
        names.append(name)
        return materialise(df, name, rows)

    for m in (model, vectors, bands, monitor, refine, synopsis, views):
        monkeypatch.setattr(m, "materialise", noted)
    monkeypatch.setattr("starwatch.storage.materialise", noted)
    return names


def graph(spark):
    r = random.Random(4)
    labels = {i: 3 if i > 9 else r.choice([1, 1, 2]) for i in range(13)}
    pairs = [(j, i) for i in range(12) for j in range(i)]
    life = [(u, v, 1, 0 if n < 25 else n, ALIVE) for n, (u, v) in enumerate(r.sample(pairs, 40))]
    vertices = spark.createDataFrame(list(labels.items()), "v long, label int")
    return Graph(vertices, spark.createDataFrame(life, "u long, v long, elabel int, born long, died long"))


def rows(df):
    return sorted((r.query_id, tuple(r.m), r.born, r.died) for r in df.collect())


def fed(g):
    ops = g.edge_life.filter("born > 0").selectExpr("born AS seq", "CAST(NULL AS TIMESTAMP) AS ts", "'+' AS op", "u", "v", "elabel")
    return monitor.Monitor(g.edge_life.filter("born = 0").select("u", "v", "elabel"), g.vertices, PATTERNS), ops


def test_first_answers_by_levels(spark, written):
    """one adjacency and one label dictionary for index and answers, and joins that read the patterns' edges only."""
    g = graph(spark)
    index = synopsis.Index(g, BuildParams(), PATTERNS.deltas(spark), 0)
    got = sorted((r.query_id, tuple(r.m)) for r in monitor.initial_answers(index, PATTERNS, "levels").collect())
    assert got == [x[:2] for x in rows(refine.lifetimes(g.snapshot(0), PATTERNS))] and got
    mine = written[: written.index("parts")]
    assert mine.count("adjacency") == mine.count("labels") == mine.count("all-boxes") == mine.count("relevant") == 1
    some = refine.relevant(g.adjacency(), PATTERNS)
    assert {(r.src_label, r.dst_label) for r in some.collect()} == {(1, 1), (1, 2), (2, 1)}
    assert refine.relevant(some, Patterns(PATTERNS.items[1:])) is some


def test_corners_and_boxes_of_one_pass(spark):
    g, p = graph(spark), BuildParams()
    hist = stars.neighbour_histogram(g, 0)
    star, deltas = stars.stars(g, p, 0, hist), PATTERNS.deltas(spark)
    ends = bands.degree_bands(star, 3)
    got = bands.corners_and_boxes(hist, star, ends, deltas, p, vectors.label_dict(g.vertices, p))
    want = bands.upper_corners(hist, star, ends, p), bands.degree_boxes(hist, star, deltas, p)
    for a, b in zip(got, want, strict=True):
        assert sorted(map(tuple, a.select(*b.columns).collect())) == sorted(map(tuple, b.collect())) != []


def test_an_epoch_moves_the_index_once(spark, written):
    """without deletions the rows that answer an epoch are those of the next index."""
    g = graph(spark)
    m, ops = fed(g)
    assert written.count("adjacency") == 1
    m.apply(ops)
    assert written.count("touched") == 1 and rows(m.state) == rows(refine.lifetimes(g, PATTERNS))


def test_label_changes_move_the_index_once(spark, written):
    """old labels out, new labels in and the epoch's edges are one step; vertices without edges get their new label too."""
    g = graph(spark)
    m, ops = fed(g)
    changes = g.vertices.filter("v IN (2, 3, 12)").selectExpr("v", "label % 3 + 1 AS newlabel", "CAST(30 AS LONG) AS t")
    m.apply(ops, changes)
    assert written.count("touched") == 1
    now = Graph(m.vertices, g.edge_life)
    for mine, anew in ((m.index.star, stars.stars(now, BuildParams())), (m.index.hist, stars.neighbour_histogram(now))):
        assert sorted(map(tuple, mine.collect())) == sorted(map(tuple, anew.select(*mine.columns).collect()))
    moved = Graph(g.vertices, g.edge_life, model.split_label(g.vertices, changes))
    assert rows(m.state) == rows(refine.lifetimes(moved, PATTERNS)) != []


def test_small_tables(spark):
    got = small(spark, [(1, None, [1, 2]), (2, "x", [])], "a int, b string, c array<int>")
    assert [tuple(r) for r in got.collect()] == [(1, None, [1, 2]), (2, "x", [])] and small(spark, [], "a int").count() == 0
    assert side_by_side(lambda: 1, lambda: 2) == [1, 2]
