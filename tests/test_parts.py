"""Patterns of several biconnected parts: parts are matched on their own and joined at one position."""

import random
from itertools import permutations

from starwatch import baselines
from starwatch.model import ALIVE, Graph
from starwatch.operators import monitor, refine
from starwatch.plans.joinorder import Fanouts, block_steps, blocks
from starwatch.plans.patterns import Pattern, Patterns, trade_pattern

BOW = Pattern("bow", (1, 1, 1, 2, 1), ((0, 1), (1, 2), (0, 2), (3, 4), (4, 2), (3, 2)))
TAIL = Pattern("tail", (1, 2, 1, 1), ((0, 1), (1, 2), (0, 2), (1, 3)))
MANY = Patterns([BOW, TAIL, BOW])


def random_graph(spark, seed=3, n=8, edges=17):
    rng = random.Random(seed)
    labels = {x: 2 if x % 4 == 0 else 1 for x in range(n)}
    pairs = rng.sample([(a, b) for a in range(n) for b in range(a + 1, n)], edges)
    life = [(a, b, 1, 0 if i < edges - 6 else i, rng.choice([ALIVE, ALIVE, 40 + i])) for i, (a, b) in enumerate(pairs)]
    g = Graph(spark.createDataFrame(list(labels.items()), "v long, label int"), spark.createDataFrame(life, "u long, v long, elabel int, born long, died long"))
    return g.stored(), labels, {frozenset(r[:2]): r[3:] for r in life}


def brute(p, labels, life):
    out = set()
    for m in permutations(labels, len(p.labels)):
        lives = [life.get(frozenset((m[a], m[b]))) for a, b in p.edges]
        if all(labels[x] == y for x, y in zip(m, p.labels, strict=True)) and None not in lives:
            out.add((m, max(x[0] for x in lives), min(x[1] for x in lives)))
    return out


def test_a_hub_is_opened_once_a_part():
    two = trade_pattern("two_tri")
    assert {frozenset({0, 1, 2}), frozenset({2, 3, 4})} == set(blocks(two))
    assert block_steps(two, [0, 1, 2, 3, 4], 1, Fanouts())[-1] == ("part", 2, (3, 4))
    assert len(blocks(trade_pattern("star3"))) == 3 and len(blocks(trade_pattern("square"))) == 1
    # the next position is reached from the end with fewer neighbours of its label
    dear = Fanouts({(12, 1): 117.0, (1, 6): 6.7, (6, 1): 6.0, (12, 6): 100.0, (1, 12): 7.8, (6, 12): 5.9})
    square = trade_pattern("square_sym")
    assert block_steps(square, [2, 3, 0, 1], 2, dear)[0] == ("expand", 2, 1)


def test_every_engine_finds_the_matches_of_the_parts(spark):
    g, labels, life = random_graph(spark)
    want = {q: brute(p, labels, life) for q, p in MANY}
    assert want[0] and want[1]
    for engine in ("static", "levels"):
        got = [(r.query_id, (tuple(r.m), r.born, r.died)) for r in refine.lifetimes(g, MANY, engine).collect()]
        assert len(got) == len(set(got)) and {q: {x for y, x in got if y == q} for q in want} == want
    vertices = [(q, i, v) for q, p in MANY for i, y in enumerate(p.labels) for v, label in labels.items() if label == y and v != 5]
    cand = spark.createDataFrame(vertices, "query_id int, qv int, v long")
    for engine in ("static", "levels"):
        some = {(r.query_id, tuple(r.m)) for r in refine.lifetimes(g, MANY, engine, cand).collect()}
        assert some == {(q, m) for q, rows in want.items() for m, _, _ in rows if 5 not in m}


def test_new_answers_of_the_parts(spark):
    g, labels, life = random_graph(spark, 5)
    want = sorted((q, m) for q, p in MANY for m, born, died in brute(p, labels, life) if 0 < born < died)
    assert want
    for rows in (monitor.on_insert(g, MANY, 0, ALIVE - 1), baselines.delta_join(g, MANY, 0, ALIVE - 1)):
        assert sorted((r.query_id, tuple(r.m)) for r in rows.collect()) == want


def test_lost_answers_come_with_their_end(spark):
    g, labels, life = random_graph(spark, 3)
    deletes = g.edge_life.filter(f"died <> {ALIVE}").selectExpr("u", "v", "died AS seq")
    slow = monitor.on_delete(refine.lifetimes(g.snapshot(0), MANY), deletes, MANY)
    want = sorted((r.query_id, tuple(r.m), r.died) for r in slow.collect())
    for engine in ("static", "levels"):
        assert sorted((r.query_id, tuple(r.m), r.died) for r in monitor.lost(g, MANY, 0, ALIVE - 1, engine).collect()) == want
    assert want
