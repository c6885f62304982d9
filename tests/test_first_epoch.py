"""a monitor's first epoch with label changes works on what can match, and only the days in which edges arrive are ranked."""

import random
from datetime import datetime, timedelta

import pytest
from test_written_once import PATTERNS, graph, rows, written  # noqa: F401

from starwatch import model
from starwatch.model import ALIVE, Graph, edge_lifetimes, normalise_updates
from starwatch.operators import monitor, refine
from starwatch.plans.patterns import parse
from starwatch.sources import views
from starwatch.storage import small

OPS = "seq long, ts timestamp, op string, u long, v long, elabel int"


def test_first_epoch_writes_what_can_match(spark, written):  # noqa: F811
    """Insertions, deletions and label changes in one epoch, then an epoch each of insertions, of labels, and a new pattern."""
    g = graph(spark)
    start = g.edge_life.filter("born = 0").select("u", "v", "elabel").cache()
    r = random.Random(5)
    ops = [(x.born, None, "+", x.v, x.u, 1) for x in g.edge_life.filter("born > 0").collect()]
    ops += [(20 + n, None, "-", x.u, x.v, 1) for n, x in enumerate(r.sample(start.collect(), 6))]
    ops = small(spark, sorted(ops), OPS)
    changes = small(spark, [(2, 3, 10), (3, 1, 11), (5, 2, 12), (2, 1, 30), (12, 1, 31), (7, 2, 50), (99, 1, 12)], "v long, newlabel int, t long")
    life = edge_lifetimes(start, normalise_updates(ops, start))

    def truth(patterns, upto):
        some = model.effective_changes(g.vertices, changes.filter(f"t <= {upto}"))
        part = edge_lifetimes(start, normalise_updates(ops.filter(f"seq <= {upto}"), start))
        return rows(refine.lifetimes(Graph(g.vertices, part, model.split_label(g.vertices, some)), patterns))

    m = monitor.Monitor(start, g.vertices, PATTERNS, known=True)
    written.clear()
    delta = m.apply(ops.filter("seq <= 32"), changes.filter("t <= 32"))
    assert not {"adjacency", "hist", "answers", "edge-life", "touched", "removed"} & set(written)
    assert rows(m.state) == truth(PATTERNS, 32) and any(x[3] != ALIVE for x in rows(m.state))
    first = {x[:2] for x in rows(refine.lifetimes(Graph(g.vertices, g.edge_life.filter("born = 0")), PATTERNS))}
    added, removed = ({x[:3] for x in rows(d)} for d in (delta.added, delta.removed))
    assert {x[:2] for x in ({(*x, 0) for x in first} | added) - removed} == {(x.query_id, tuple(x.m)) for x in m.answers().collect()}
    assert sorted(map(tuple, m.edge_life.collect())) == sorted(map(tuple, edge_lifetimes(start, normalise_updates(ops.filter("seq <= 32"), start)).collect()))
    m.apply(ops.filter("seq > 32 AND seq <= 36"))
    assert m.index is not None and rows(m.state) == truth(PATTERNS, 36)
    m.apply(ops.filter("seq > 36"), changes.filter("t > 36"))
    assert rows(m.state) == truth(PATTERNS, 99)
    assert sorted(map(tuple, m.edge_life.collect())) == sorted(map(tuple, life.collect()))
    tri = parse("tri", "a:1-b:1, b-c:1, a-c")
    q = m.register(tri)
    assert q == 2 and rows(m.state) == truth(m.patterns, 99)


@pytest.mark.parametrize("labels", [True, False])
def test_a_known_graph_is_followed(spark, labels):
    """The same answers as of a monitor that is told nothing, in whatever order it is asked."""
    g = graph(spark)
    ops = g.edge_life.filter("born > 0").selectExpr("born AS seq", "CAST(NULL AS TIMESTAMP) AS ts", "'+' AS op", "u", "v", "elabel")
    changes = small(spark, [(2, 3, 30), (5, 2, 31)], "v long, newlabel int, t long") if labels else None
    m = monitor.Monitor(g.edge_life.filter("born = 0").select("u", "v", "elabel"), g.vertices, PATTERNS, known=True)
    assert m.answers().count()  # asked before the epoch
    m.apply(ops, changes)
    life = None if changes is None else model.split_label(g.vertices, changes)
    assert rows(m.state) == rows(refine.lifetimes(Graph(g.vertices, g.edge_life, life), PATTERNS))


@pytest.mark.parametrize("percent", [0, 10, 35, 100])
def test_only_late_days_are_ranked(spark, percent):
    r = random.Random(percent)
    begin = datetime(1969, 12, 28)
    pairs = small(spark, [(a, b, begin + timedelta(hours=r.choice([0, 0, 5, 30, 60, 100, 200])), 1 + a % 2) for a in range(9) for b in range(10, 19)], "a long, b long, ts timestamp, elabel int")
    vertices = small(spark, [(v, 1) for v in range(19)], "v long, label int")
    days = views.day_starts(pairs.selectExpr("date_trunc('day', ts) AS _day", "1L AS _n"))
    got = views.insertions_by_day(vertices, pairs, days, percent, "g").edge_life
    want = views.insertion_stream(vertices, views.numbered(pairs, ["a", "b"]), percent, "g").edge_life
    assert got.schema == want.schema and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


@pytest.mark.parametrize("codes", [512, 1])
def test_first_lines(spark, codes, monkeypatch):
    """One number of time and flag, or the least structure where there are too many flags: the same rows."""
    monkeypatch.setattr(views, "MAX_CODES", codes)
    r = random.Random(3)
    at = [datetime(1969, 12, 31, 23, 59, 59, 999_999), datetime(1970, 1, 1), datetime(1998, 5, 2, 3, 4, 5, 6)]
    rows_ = [(r.randrange(4), 9, r.choice(at), r.choice("ANR")) for _ in range(9)]
    flags = ["A", "N", "R"]
    lines = small(spark, rows_, "a long, b long, ts timestamp, l_returnflag string")
    got = views.first_lines(lines.select("a", "b", views.line_code(flags).alias("_code")), flags)
    want = {a: min((t, f) for x, _, t, f in rows_ if x == a) for a in {x[0] for x in rows_}}
    assert {(x.a, x.b): (x.ts, x.l_returnflag) for x in got.collect()} == {(a, 9): x for a, x in want.items()}
