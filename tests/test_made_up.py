"""Queries that once made up their data read a given table, and agree with their SQL there."""

import duckdb
import pytest

from starwatch import queries
from starwatch.operators.refine import F
from starwatch.sources import synth

SF = "/root/testdata/sf0.001"


def by_sql(name):
    with duckdb.connect() as c:
        for t in ("nation", "customer", "supplier", "part", "orders", "lineitem"):
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
        return sorted(c.execute(queries.ORACLES[name]).fetchall())


@pytest.mark.parametrize("name", ["nws_edges_uni", "nws_labels_uni", "nws_labels_gau", "query_embedding"])
def test_reads_a_table_and_agrees(spark, name):
    df = queries.QUERIES[name](spark, SF)
    assert df.inputFiles()  # the table, or what was written from it
    got = sorted(map(tuple, df.collect()))
    assert got == by_sql(name) and got


def test_labels_by_zipf_are_of_all_customers(spark):
    rows = queries.QUERIES["nws_labels_zipf"](spark, SF).collect()
    assert sum(r.n for r in rows) == spark.read.parquet(f"{SF}/customer.parquet").count()


def test_places_over_gaps(spark):
    ids = spark.createDataFrame([(x,) for x in (9001, 3, 4, 10, 9000, 20)], "id long")
    got = synth.places(ids, 8)
    assert sorted(r.v for r in got.collect()) == [0, 1, 2, 3, 4, 5]
    assert got.filter(F.col("v") < 0).count() == 0
