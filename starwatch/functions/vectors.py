"""Label dictionaries and vector tests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import BuildParams
from ..storage import materialise
from .arithmetic import BASE, EDGE, LABEL, UNIT, P, base_values, label_value, zipf_edges


def _draws(rows: DataFrame, label: str, wanted: dict[str, tuple[int, int]]) -> DataFrame:
    """Adds a pseudo-random 0..65535 per wanted column (name -> dimension, salt), a round per projection
    so that no expression repeats another."""
    out = rows.withColumns({c: (48271 * F.col(label).cast("long") + (69621 * k + 40692 * salt + 12345)) % P for c, (k, salt) in wanted.items()})
    for _ in range(3):
        out = out.withColumns({c: (F.col(c) * F.col(c) + 16807 * F.col(c) + 1013904223) % P for c in wanted})
    return out.withColumns({c: F.col(c) % UNIT for c in wanted})


def _spread(c: str, dist: str) -> Column:
    """A label value from its draw."""
    if dist == "uniform":
        return F.col(c) + 1
    q = zipf_edges()
    width = UNIT // (len(q) - 1)
    edges = F.expr(f"array({', '.join(f'{x}L' for x in q)})")
    i = F.expr(f"CAST({c} div {width} AS INT)")
    low, high = F.element_at(edges, i + 1), F.element_at(edges, i + 2)
    return F.greatest(F.lit(1).cast("long"), low + F.floor((high - low) * (F.col(c) % width) / width).cast("long"))


def label_dict(labels: DataFrame, p: BuildParams) -> DataFrame:
    """label, lv0..lv{d-1} (label vector) and bv0..bv{2d-1} (base vector), one row per label.

    Made once per frame of ``labels`` and parameters."""
    made = labels.__dict__.setdefault("_label_dicts", {})
    if p not in made:
        made[p] = _label_dict(labels, p)
    return made[p]


def _label_dict(labels: DataFrame, p: BuildParams) -> DataFrame:
    drawn = _draws(labels.select("label").distinct(), "label", {f"lv{k}": (k, 10 * p.salt + LABEL) for k in range(p.d)} | {f"bv{k}": (k, 10 * p.salt + BASE) for k in p.dims})
    drawn = drawn.withColumns({f"lv{k}": _spread(f"lv{k}", p.dist) for k in range(p.d)} | {f"bv{k}": F.col(f"bv{k}") + 1 for k in p.dims})
    raw = [f"bv{k}" for k in p.dims]
    over = {
        "l1": [" + ".join(raw)] * len(raw), "l1_half": [" + ".join(raw[: p.d])] * p.d + [" + ".join(raw[p.d :])] * p.d,
        "diag": [f"{p.d} * (bv0 + bv1)"] * len(raw), "l2": ["CAST(floor(sqrt(CAST(" + " + ".join(f"{r} * {r}" for r in raw) + " AS DOUBLE))) AS BIGINT)"] * len(raw),
    }[p.base]
    own = [f"bv{k // p.d}" for k in p.dims] if p.base == "diag" else raw
    out = drawn.select("label", *[f"lv{k}" for k in range(p.d)], *[F.expr(f"({x} * {UNIT}) div ({y})").alias(f"bv{k}") for k, (x, y) in enumerate(zip(own, over, strict=True))])
    return materialise(out, "labels")  # else filters on embeddings are pushed down into the long arithmetic


def edge_label_dict(labels: DataFrame, p: BuildParams) -> DataFrame:
    """elabel, ev0..ev{d-1}: the vectors of edge labels."""
    drawn = _draws(labels.select("elabel").distinct(), "elabel", {f"ev{k}": (k, 10 * p.salt + EDGE) for k in range(p.d)})
    return drawn.select("elabel", *[_spread(f"ev{k}", p.dist).alias(f"ev{k}") for k in range(p.d)])


def distinct_vectors(labels: DataFrame, p: BuildParams) -> BuildParams:
    """``p`` with the first salt under which no two labels share a label vector."""
    for salt in range(p.salt, p.salt + 20):
        q = p.but(salt=salt)
        got = label_dict(labels, q)
        a, b = got.agg(F.count(F.lit(1)), F.count_distinct(*[f"lv{k}" for k in range(p.d)])).first()
        if a == b:
            return q
    raise ValueError("no salt keeps the label vectors apart")


def embedding_columns(p: BuildParams, ns: str = "ns") -> list[Column]:
    """e0..e{2d-1}: own vector, then neighbour sum, plus the weighted base vector unless plain."""
    out = []
    for k in p.dims:
        own = F.col(f"lv{k}") if k < p.d else F.col(f"{ns}{k - p.d}")
        out.append((own if p.variant == "plain" else own + p.ratio * F.col(f"bv{k}")).alias(f"e{k}"))
    return out


def all_of(conditions: list[Column]) -> Column:
    out = conditions[0]
    for c in conditions[1:]:
        out = out & c
    return out


def dominates(q: str, v: str, p: BuildParams) -> Column:
    """Every q value is at most the v value (equality included); unrolled, so it is compiled."""
    return all_of([F.col(f"{q}{k}") <= F.col(f"{v}{k}") for k in p.dims])


def in_box(q: str, p: BuildParams) -> Column:
    """q lies between lo and hi in every dimension."""
    return all_of([F.col(f"{q}{k}").between(F.col(f"lo{k}"), F.col(f"hi{k}")) for k in p.dims])


def register_sql(spark: SparkSession, p: BuildParams | None = None) -> None:
    """SQL functions for the same tests on arrays: dominates_vec, in_box_vec, label_vec, base_vec."""
    p = p or BuildParams()
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dominates_vec(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BOOLEAN RETURN forall(zip_with(a, b, (x, y) -> x <= y), z -> z)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION in_box_vec(x ARRAY<BIGINT>, lo ARRAY<BIGINT>, hi ARRAY<BIGINT>) RETURNS BOOLEAN RETURN dominates_vec(lo, x) AND dominates_vec(x, hi)")
    lv = ", ".join(label_value("l", k, p.salt, p.dist) for k in range(p.d))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION label_vec(l INT) RETURNS ARRAY<BIGINT> RETURN array({lv})")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION base_vec(l INT) RETURNS ARRAY<BIGINT> RETURN array({', '.join(base_values('l', p.d, p.base, p.salt))})")
