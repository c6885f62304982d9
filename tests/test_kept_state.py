"""Label changes through the monitor, and index baselines that are kept up, against answers made anew."""

import random

import pytest
from pyspark.sql import functions as F

from starwatch import baselines
from starwatch.model import ALIVE, Graph, edge_lifetimes, effective_changes, normalise_updates, split_label
from starwatch.operators import monitor, refine
from starwatch.plans.patterns import Patterns, parse

OPS = "seq long, ts timestamp, op string, u long, v long, elabel int"
TAIL = parse("tail", "a:1-b:2, b-c:1, a-c, c-d:2")
ALL = Patterns([parse("tri", "a:1-b:1, b-c:2, a-c"), parse("vee", "a:1-b:2, b-c:1"), TAIL])


def rows(df):
    return sorted((r.query_id, tuple(r.m), r.born, r.died) for r in df.collect())


@pytest.fixture(scope="module")
def story(spark):
    """Vertices, raw edge updates and label changes on one clock, no two at one time."""
    r = random.Random(11)
    vertices = spark.createDataFrame([(v, r.choice([1, 2])) for v in range(9)], "v long, label int").cache()
    ops, changes = [], []
    for t in range(1, 91):
        if t > 30 and r.random() < 0.2:
            changes.append((r.randrange(10), r.choice([1, 2]), t))  # 9 is unknown; some change nothing
        else:
            u, v = r.sample(range(9), 2)
            ops.append((t, None, r.choice("+++-"), u, v, 1))
    return vertices, spark.createDataFrame(ops, OPS).cache(), spark.createDataFrame(changes, "v long, newlabel int, t long").cache()


def test_label_changes_reach_the_monitor(spark, story):
    vertices, ops, changes = story
    first = normalise_updates(ops.filter("seq <= 25"))
    start = edge_lifetimes(None, first).filter(F.col("died") == ALIVE)
    rest = ops.filter("seq > 25")
    life = edge_lifetimes(start, normalise_updates(rest, start))
    truth = rows(refine.lifetimes(Graph(vertices, life, split_label(vertices, effective_changes(vertices, changes))), ALL))
    m = monitor.Monitor(start.select("u", "v", "elabel"), vertices, ALL)
    for low, high in ((25, 55), (55, 90)):
        before = {x[:3] for x in rows(m.state) if x[3] == ALIVE}
        delta = m.apply(rest.filter(f"seq > {low} AND seq <= {high}"), changes.filter(f"t > {low} AND t <= {high}"))
        after = {x[:3] for x in rows(m.state) if x[3] == ALIVE}
        added, removed = ({x[:3] for x in rows(d)} for d in (delta.added, delta.removed))
        assert (before | added) - removed == after
    assert rows(m.state) == truth and any(x[3] != ALIVE for x in truth)


def test_only_label_changes(spark, story):
    vertices, ops, _ = story
    life = edge_lifetimes(None, normalise_updates(ops)).filter(F.col("died") == ALIVE).withColumn("born", F.lit(0).cast("long"))
    m = monitor.Monitor(life.select("u", "v", "elabel"), vertices, ALL)
    none = ops.limit(0)
    same = vertices.limit(3).select("v", F.col("label").alias("newlabel"), F.lit(1).cast("long").alias("t"))
    assert m.apply(none, same).added.count() == 0 and m.now == 0
    changes = vertices.filter("v < 4").select("v", (3 - F.col("label")).alias("newlabel"), F.lit(5).cast("long").alias("t"))
    m.apply(none, changes)
    assert rows(m.state) == rows(refine.lifetimes(Graph(vertices, life, split_label(vertices, changes)), ALL))
    assert m.now == 5


@pytest.mark.parametrize("kind", ["tree", "dag"])
def test_kept_index_equals_one_made_anew(spark, story, kind):
    vertices, ops, _ = story
    g = Graph(vertices, edge_lifetimes(None, normalise_updates(ops)).cache())
    kept = baselines.KeptIndex(g, TAIL, kind, 20)
    every = refine.lifetimes(g, Patterns([TAIL]))
    for low, high in ((20, 60), (60, 90)):
        new = {x[1] for x in rows(kept.advance(g, high))}
        adj = g.snapshot(high).adjacency()
        anew = baselines.tree_index(adj, TAIL) if kind == "tree" else baselines.dag_index(adj, TAIL, 1)
        assert sorted(map(tuple, kept.candidates().collect())) == sorted(map(tuple, anew.collect()))
        assert new == {tuple(r.m) for r in every.filter(f"born > {low} AND born <= {high} AND died > {high}").collect()}
