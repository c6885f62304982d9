"""Rates are worked out one after another, so the driver holds one rate's plan."""

from starwatch import queries


def test_a_rate_leaves_no_plan_behind(spark):
    def make(r):
        rows = spark.range(r).selectExpr("CAST(id % 2 AS INT) AS query_id")
        return rows.join(rows.distinct(), "query_id")

    out = queries._over_rates(make)
    assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString()
    got = {(r.percent, r.query_id): r.n for r in out.collect()}
    assert len(got) == 5 * len(queries.CORE) and all(got[r, q] == (r // 2 if q < 2 else 0) for r in queries.RATES for q in range(5))
