"""the rates read the same rows, those that the patterns can use, and no rate writes a graph of its own."""

import pytest

from starwatch import baselines, model, queries
from starwatch.operators import refine
from starwatch.plans.patterns import Patterns, trade_pattern
from starwatch.sources import views
from starwatch.storage import materialise

SF = "/root/testdata/sf0.001"


@pytest.fixture
def written(monkeypatch):
    names = []

    def noted(df, name, *a, **b):
        names.append(name)
        return materialise(df, name, *a, **b)

    for m in (baselines, model, queries, refine):
        monkeypatch.setattr(m, "materialise", noted)
    monkeypatch.setattr(queries, "_memo", {})
    return names


def test_rates_are_those_of_the_stream(spark):
    v, edges = views.trade_vertices(spark, SF), views.trade_edges(spark, SF, True)
    with queries.all_lines():
        got = {r: queries._inserted(spark, SF, r) for r in queries.RATES}
    for r in (10, 30, 50):
        want = views.insertion_stream(v, edges, r, "trade")
        assert got[r][0].edge_life.schema == want.edge_life.schema
        assert sorted(map(tuple, got[r][0].edge_life.collect())) == sorted(map(tuple, want.edge_life.collect()))
        near = refine.relevant(want.adjacency(), queries.CORE)
        assert sorted(map(tuple, got[r][1].select(near.columns).collect())) == sorted(map(tuple, near.collect()))


@pytest.mark.parametrize("name", ["full_wl_insert_rates", "full_wl_insert_rates_delta_join"])
def test_no_rate_writes_a_graph(spark, written, monkeypatch, name):
    monkeypatch.setattr(queries, "RATES", (10, 50))
    monkeypatch.setattr(queries, "CORE", Patterns([trade_pattern("triangle"), trade_pattern("tri_tail")]))
    got = {(r.percent, r.query_id): r.n for r in queries.QUERIES[name](spark, SF).collect()}
    assert written.count("relevant") == 1 and not {"adjacency", "edge-life"} & set(written)
    edges = views.trade_edges(spark, SF, True)
    for r in (10, 50):
        g = views.insertion_stream(views.trade_vertices(spark, SF), edges, r, "trade")
        want = {x.query_id: x["count"] for x in refine.lifetimes(g, queries.CORE).filter("born > 0").groupBy("query_id").count().collect()}
        assert {q: got[r, q] for q, _ in queries.CORE} == {q: want.get(q, 0) for q, _ in queries.CORE} and any(want.values())


def test_a_reader_of_one_value_opens_its_files_only(spark):
    rows = spark.range(100).selectExpr("id AS v", "CAST(id % 5 AS INT) AS a", "id * 2 AS w")
    table = materialise(rows, "by", by=("a",))
    assert table.dtypes == rows.dtypes and sorted(map(tuple, table.collect())) == sorted(map(tuple, rows.collect()))
    assert len(table.filter("a = 3").select(spark_file()).distinct().collect()) < len(table.select(spark_file()).distinct().collect())


def spark_file():
    from pyspark.sql import functions as F

    return F.input_file_name()
