"""Queries on all line items against a plain count over the whole table."""

from starwatch import queries
from starwatch.plans.patterns import trade_pattern

SF = "/root/testdata/sf0.001"


def lines(spark):
    d = lambda t: spark.read.parquet(f"{SF}/{t}.parquet")
    owner = {r.o_orderkey: r.o_custkey for r in d("orders").collect()}
    return [(owner[r.l_orderkey] * 4, r.l_partkey * 4 + 1, r.l_suppkey * 4 + 2) for r in d("lineitem").collect() if r.l_orderkey in owner]


def test_graph_and_triangles_of_all_lines(spark):
    rows = lines(spark)
    edges = {e for c, p, s in rows for e in ((c, p), (p, s), (c, s))}
    assert queries.QUERIES["full_trade_graph_stats"](spark, SF).first().n_edges == len(edges)
    label = {r.v: r.label for r in queries.QUERIES["trade_vertices"](spark, SF).collect()}
    want = trade_pattern("triangle").labels
    near = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    tri = {(x, y, z) for x in near if label[x] == want[0] for y in near[x] if label[y] == want[1] for z in near[x] & near[y] if label[z] == want[2]}
    assert {(r.m0, r.m1, r.m2) for r in queries.QUERIES["full_match_triangle"](spark, SF).collect()} == tri and tri
    first = {(r.m0, r.m1, r.m2) for r in queries.QUERIES["match_triangle"](spark, SF).collect()}
    assert first < tri  # the two graphs are kept apart


def test_every_line_query_has_a_whole_one():
    short = [n for n in queries.QUERIES if not n.startswith(("full_", *queries.NO_LINES))]
    assert len(short) > 80 and all(f"full_{n}" in queries.QUERIES for n in short)
    assert all("l_linenumber" not in s for n, s in queries.ORACLES.items() if n.startswith("full_"))
