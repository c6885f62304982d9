"""An epoch writes what it changes: whole tables are written anew only when something in them ends."""

from test_written_once import PATTERNS, fed, graph, rows, written  # noqa: F401

from starwatch import model
from starwatch.model import ALIVE, Graph
from starwatch.operators import monitor, refine
from starwatch.storage import PIECES, grown, small


def test_insertions_stand_beside_the_old_rows(spark, written):  # noqa: F811
    """neither edges, adjacency, index nor answers are written as a whole in epochs of insertions."""
    g = graph(spark)
    m, ops = fed(g)
    for some in ("seq <= 32", "seq > 32"):
        m.apply(ops.filter(some))
    assert {n: written.count(n) for n in ("edge-life", "adjacency", "answers", "hist", "star", "synopsis", "removed", "touched")} == {
        "edge-life": 1, "adjacency": 1, "answers": 1, "hist": 1, "star": 1, "synopsis": 0, "removed": 0, "touched": 2,
    }
    assert rows(m.state) == rows(refine.lifetimes(g, PATTERNS)) != []
    assert m.near.exceptAll(refine.relevant(m.graph.adjacency(), PATTERNS).select(*m.near.columns)).count() == 0


def test_label_changes_ask_no_index(spark, written):  # noqa: F811
    """such an epoch is judged by edges of the patterns' labels: no whole adjacency is written for it, and no index table."""
    g = graph(spark)
    m, ops = fed(g)
    changes = g.vertices.filter("v IN (2, 3, 12)").selectExpr("v", "label % 3 + 1 AS newlabel", "CAST(30 AS LONG) AS t")
    m.apply(ops, changes)
    assert [written.count(n) for n in ("adjacency", "hist", "all-boxes", "answers")] == [1, 0, 0, 1]
    moved = Graph(g.vertices, g.edge_life, model.split_label(g.vertices, changes))
    assert rows(m.state) == rows(refine.lifetimes(moved, PATTERNS)) != []


def test_lives_of_one_epoch(spark):
    alive = small(spark, [(1, 2, 7, 0), (1, 3, 7, 0), (1, 4, 7, 0)], "u long, v long, elabel int, born long")
    ops = [(5, "-", 2, 1), (6, "+", 1, 2), (7, "+", 1, 2), (5, "+", 1, 3), (8, "+", 5, 4), (9, "-", 4, 5), (9, "+", 6, 6), (9, "-", 7, 8)]
    got = monitor.epoch_lives(alive, small(spark, [(s, o, u, v, 9) for s, o, u, v in ops], "seq long, op string, u long, v long, elabel int"))
    want = [(1, 2, 7, 0, 5, True), (1, 2, 9, 6, ALIVE, False), (1, 3, 7, 0, ALIVE, True), (4, 5, 9, 8, 9, False)]
    assert sorted(map(tuple, got.collect())) == want


def test_grown_tables_are_written_anew_at_times(spark):
    rows_of = [small(spark, [(n,)], "a int") for n in range(PIECES + 2)]
    table = rows_of[0]
    for n, new in enumerate(rows_of[1:], 2):
        table = grown(table, new, "grown")
        assert hasattr(table, "_stored_at") == (n == PIECES + 1)
    assert sorted(r.a for r in table.collect()) == list(range(PIECES + 2))
