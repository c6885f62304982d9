"""The URL filter on labels it has not seen, and its verdicts against the trees applied row by row."""

import numpy as np
from pyspark.sql import functions as F

from starwatch.llm import urlfilter

PAGES = "/root/testdata/sf0.01/pages.parquet"


def features(spark):
    rows = spark.read.parquet(PAGES).select("page_id", "url")
    rows = rows.withColumn("host", urlfilter.host_of(F.col("url"))).withColumn("path", urlfilter.path_of(F.col("url")))
    rule, verdict = urlfilter.rule_of(F.col("host"), F.col("path"))
    rows = rows.withColumn("rule", rule).withColumn("rule_verdict", verdict)
    return urlfilter.with_suffix_rates(urlfilter.lexical(rows.withColumn("label", urlfilter.rule_labels(rows))))


def test_verdicts_equal_the_trees_row_by_row(spark):
    rows = features(spark)
    x, y = urlfilter.training_rows(rows, urlfilter.TRAIN_ROWS)
    trees = urlfilter.BoostedTrees().fit(x, y)
    got = {r.page_id: r for r in urlfilter.judge_urls(spark.read.parquet(PAGES)).collect()}
    for r in rows.collect():
        margin = trees.margin(np.array([[r[c] for c in urlfilter.FEATURES]], float))[0]
        assert abs(got[r.page_id].score - 1 / (1 + np.exp(-margin))) < 1e-9
        assert got[r.page_id].verdict == (r.rule_verdict or ("block" if margin > 0 else "allow"))


def test_held_out_labels(spark):
    x, y = urlfilter.training_rows(features(spark), urlfilter.TRAIN_ROWS)
    held = np.arange(len(y)) % 3 == 1
    trees = urlfilter.BoostedTrees().fit(x[~held], y[~held])
    right = ((trees.margin(x[held]) > 0) == (y[held] > 0)).mean()
    print("held out", right, "of", held.sum(), "always block", y[held].mean())
    assert right > max(y[held].mean(), 1 - y[held].mean())
