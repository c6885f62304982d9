"""The nearest vectors of every fiftieth one, against the query's SQL."""

import duckdb
import numpy as np

from starwatch import queries
from starwatch.sources import views


def test_nearest_with_ties_and_several_blocks(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(1)
    vectors = rng.normal(size=(230, 64)).astype(np.float32)
    vectors[[3, 50, 51, 100, 140, 7, 229]] = vectors[0]  # equal vectors: ties go by id
    rows = [(i, [float(x) for x in v], i % 10) for i, v in enumerate(vectors)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3).write.parquet(str(tmp_path / "embeddings.parquet"))
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
        want = sorted(c.execute(queries.ORACLES["knn_edges"]).fetchall())
    monkeypatch.setattr(views, "SCORES", 60)  # a few rows at once
    assert sorted(map(tuple, queries.QUERIES["knn_edges"](spark, str(tmp_path)).collect())) == want
    monkeypatch.setattr(views, "QUERY_BLOCK", 2)
    assert sorted(map(tuple, queries.QUERIES["knn_edges"](spark, str(tmp_path)).collect())) == want
