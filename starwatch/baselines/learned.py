"""A stand-in for learned path embeddings: a monotone model whose dominance is checked and retrained."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arithmetic import label_vector
from ..plans.patterns import Patterns


class MonotoneModel:
    """Two layers with non-negative weights: a star's output cannot fall when a neighbour is added.

    Trained to spread the outputs of different stars while pairs (sub-star, star) keep their
    order; a violation (only possible by rounding or unseen labels) calls for another training.
    """

    def __init__(self, labels: list[int], d: int = 4, hidden: int = 8, seed: int = 7):
        self.labels = {x: np.array(label_vector(x, d, 9, "uniform"), float) / 65536 for x in labels}
        rng = np.random.default_rng(seed)
        self.w1, self.w2 = rng.random((hidden, 2 * d)), rng.random((d, hidden))
        self.d, self.retrained = d, 0

    def features(self, label: int, near: list[int]) -> np.ndarray:
        zero = np.zeros(self.d)
        return np.concatenate([self.labels.get(label, zero), sum((self.labels.get(x, zero) for x in near), zero)])

    def forward(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(0, x @ self.w1.T) @ self.w2.T

    def train(self, stars: list[tuple[int, list[int]]], rounds: int = 50, rate: float = 0.01) -> None:
        x = np.array([self.features(*s) for s in stars]).reshape(-1, 2 * self.d)
        for _ in range(rounds if len(x) > 1 else 0):
            h = np.maximum(0, x @ self.w1.T)
            out = h @ self.w2.T
            g = (out - out.mean(axis=0)) / len(x)  # a larger spread
            self.w2 = np.clip(self.w2 + rate * (g.T @ h), 1e-6, 4)
            self.w1 = np.clip(self.w1 + rate * (((g @ self.w2) * (h > 0)).T @ x), 1e-6, 4)
        self.retrained += 1

    def violations(self, pairs: list[tuple[tuple, tuple]]) -> int:
        return sum(bool((self.forward(self.features(*a)) > self.forward(self.features(*b)) + 1e-9).any()) for a, b in pairs)


def learned_dominance(hist: DataFrame, star: DataFrame, patterns: Patterns, sample: int = 500) -> DataFrame:
    """cand(query_id, qv, v): vertices whose model output is at least the pattern vertex's.

    Trained on a bounded sample of stars, and retrained until no sampled sub-star violates the order.
    """
    spark = star.sparkSession
    rows = hist.groupBy("v").agg(F.map_from_entries(F.collect_list(F.struct("nlabel", "cnt"))).alias("near")).join(star.select("v", "label"), "v")
    some = [(r.label, [x for x, n in r.near.items() for _ in range(n)]) for r in rows.orderBy("v").limit(sample).collect()]
    labels = sorted({r[0] for r in star.select("label").distinct().collect()} | {x for _, p in patterns for x in p.labels})
    model = MonotoneModel(labels)
    pairs = [((a, n[: len(n) // 2]), (a, n)) for a, n in some]
    while True:
        model.train(some)
        if not model.violations(pairs) or model.retrained >= 5:
            break
    q = [(i, j, p.labels[j], *model.forward(model.features(p.labels[j], [p.labels[x] for x in p.neighbours(j)])).tolist()) for i, p in patterns for j in range(len(p.labels))]
    qdf = spark.createDataFrame(q, "query_id int, qv int, q_label int, " + ", ".join(f"q{k} double" for k in range(model.d)))

    def run(batches):
        for pdf in batches:
            out = [model.forward(model.features(a, [x for x, n in near.items() for _ in range(int(n))])) for a, near in zip(pdf["label"], (dict(m) for m in pdf["near"]), strict=True)]
            for k in range(model.d):
                pdf[f"o{k}"] = [float(x[k]) for x in out]
            yield pdf[["v", "label", *[f"o{k}" for k in range(model.d)]]]

    scored = rows.select("v", "label", "near").mapInPandas(run, "v long, label int, " + ", ".join(f"o{k} double" for k in range(model.d)))
    test = F.col("label") == F.col("q_label")
    for k in range(model.d):
        test = test & (F.col(f"o{k}") >= F.col(f"q{k}") - 1e-9)
    return scored.join(patterns.hinted(qdf), test).select("query_id", "qv", "v")
