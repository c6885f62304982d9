"""Registered patterns: small connected labelled graphs."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.arithmetic import EDGE, base_vector, label_vector
from ..functions.vectors import embedding_columns, label_dict
from ..model import BuildParams
from ..storage import small

MAX_VERTICES = 64  # of one pattern
MAX_BROADCAST = 200_000  # vertices of all patterns together that may be broadcast


@dataclass(frozen=True)
class Pattern:
    """labels[i] is the label of position i; edges are (i, j) or (i, j, edge label)."""

    name: str
    labels: tuple[int, ...]
    edges: tuple[tuple, ...]

    def __post_init__(self):
        n = len(self.labels)
        assert 1 <= n <= MAX_VERTICES and all(0 <= e[0] < n and 0 <= e[1] < n and e[0] != e[1] for e in self.edges)
        assert len({frozenset(e[:2]) for e in self.edges}) == len(self.edges), "an edge stands twice"
        seen, todo = {0}, [0]
        while todo:
            x = todo.pop()
            for y in self.neighbours(x) - seen:
                seen.add(y)
                todo.append(y)
        assert len(seen) == n, "a pattern must be connected"

    def neighbours(self, i: int) -> set[int]:
        return {e[1] if e[0] == i else e[0] for e in self.edges if i in e[:2]}

    def edge_label(self, i: int, j: int) -> int | None:
        return next((e[2] for e in self.edges if {i, j} == set(e[:2]) and len(e) > 2), None)

    @property
    def acyclic(self) -> bool:
        return len(self.edges) == len(self.labels) - 1


def parse(name: str, text: str) -> Pattern:
    """A pattern from text such as ``a:1-b:6, b-c:12``; a label is given once per vertex.
    An edge label follows the second vertex in brackets: ``a:1-b:6[2]``."""
    names: dict[str, int] = {}
    labels: list[int | None] = []
    edges = []
    for part in filter(None, (x.strip() for x in text.split(","))):
        m = re.fullmatch(r"(\w+)(?::(\d+))?\s*-\s*(\w+)(?::(\d+))?(?:\[(\d+)\])?", part)
        if not m:
            raise ValueError(f"cannot read {part!r}")
        ends = []
        for who, label in ((m[1], m[2]), (m[3], m[4])):
            i = names.setdefault(who, len(names))
            if i == len(labels):
                labels.append(None)
            if label is not None:
                if labels[i] not in (None, int(label)):
                    raise ValueError(f"two labels for {who}")
                labels[i] = int(label)
            ends.append(i)
        edges.append((*ends, int(m[5])) if m[5] else tuple(ends))
    if None in labels:
        raise ValueError("a vertex has no label")
    return Pattern(name, tuple(labels), tuple(edges))


class Patterns:
    """A set of patterns with query ids 0, 1, 2, ... in the given order."""

    def __init__(self, items: list[Pattern]):
        self.items = list(items)

    def __iter__(self):
        return iter(enumerate(self.items))

    def __len__(self) -> int:
        return len(self.items)

    @classmethod
    def from_text(cls, texts: dict[str, str]) -> Patterns:
        return cls([parse(k, v) for k, v in texts.items()])

    @classmethod
    def from_frames(cls, q_vertex: DataFrame, q_edge: DataFrame) -> Patterns:
        """From q_vertex(query_id, qv, label) and q_edge(query_id, qi, qj, elabel); patterns are small."""
        vs: dict[int, dict[int, int]] = {}
        es: dict[int, list] = {}
        for r in q_vertex.collect():
            vs.setdefault(r.query_id, {})[r.qv] = r.label
        for r in q_edge.collect():
            es.setdefault(r.query_id, []).append((r.qi, r.qj) if r.elabel is None else (r.qi, r.qj, r.elabel))
        return cls([Pattern(str(q), tuple(v[i] for i in range(len(v))), tuple(sorted(es.get(q, [])))) for q, v in sorted(vs.items())])

    def q_vertex(self, spark: SparkSession) -> DataFrame:
        rows = [(q, i, label, len(p.neighbours(i))) for q, p in self for i, label in enumerate(p.labels)]
        return small(spark, rows, "query_id int, qv int, label int, deg int")

    def q_edge(self, spark: SparkSession) -> DataFrame:
        rows = [(q, e[0], e[1], e[2] if len(e) > 2 else None) for q, p in self for e in p.edges]
        return small(spark, rows, "query_id int, qi int, qj int, elabel int")

    def deltas(self, spark: SparkSession) -> DataFrame:
        """The degrees that occur in the patterns: the only ones boxes are needed for."""
        return small(spark, sorted({(len(p.neighbours(i)),) for _, p in self for i in range(len(p.labels))}), "delta int")

    @property
    def broadcastable(self) -> bool:
        return sum(len(p.labels) for _, p in self) <= MAX_BROADCAST

    def hinted(self, df: DataFrame) -> DataFrame:
        """``df`` (a row per pattern vertex or edge) with a broadcast hint if the patterns are few enough."""
        return F.broadcast(df) if self.broadcastable else df


def embed_patterns(spark: SparkSession, patterns: Patterns, p: BuildParams) -> DataFrame:
    """query_id, qv, label, deg, q*: pattern vertices embedded with the integer arithmetic of data
    vertices (the tests hold both equal). Patterns are small and known to the driver."""
    rows = []
    for q, pat in patterns:
        for i, label in enumerate(pat.labels):
            near = pat.neighbours(i)
            ns = [0] * p.d
            for j in near:
                extra = label_vector(pat.edge_label(i, j), p.d, p.salt, p.dist, EDGE) if p.elabel_weight and pat.edge_label(i, j) is not None else [0] * p.d
                ns = [a + b + c for a, b, c in zip(ns, label_vector(pat.labels[j], p.d, p.salt, p.dist), extra, strict=True)]
            e = label_vector(label, p.d, p.salt, p.dist) + ns
            if p.variant != "plain":
                e = [a + p.ratio * z for a, z in zip(e, base_vector(label, p.d, p.base, p.salt), strict=True)]
            rows.append((q, i, label, len(near), *e))
    return small(spark, rows, "query_id int, qv int, label int, deg int, " + ", ".join(f"q{k} long" for k in p.dims))


def embed_by_data(vertices: DataFrame, patterns: Patterns, p: BuildParams) -> DataFrame:
    """The same with the label dictionary of a graph's ``vertices``: pattern vertices of which the own or a
    neighbour's label is on no data vertex, and which nothing can match, are left out. Edge labels are not weighed."""
    spark = vertices.sparkSession
    d = label_dict(vertices, p)
    near = [(q, i, pat.labels[i], len(pat.neighbours(i)), pat.labels[j]) for q, pat in patterns for i in range(len(pat.labels)) for j in pat.neighbours(i)]
    rows = patterns.hinted(small(spark, near, "query_id int, qv int, label int, deg int, nlabel int"))
    lv = d.select(F.col("label").alias("nlabel"), *[F.col(f"lv{k}").alias(f"_l{k}") for k in range(p.d)])
    sums = lv.join(rows, "nlabel").groupBy("query_id", "qv", "label", "deg").agg(F.count(F.lit(1)).alias("_n"), *[F.sum(f"_l{k}").alias(f"ns{k}") for k in range(p.d)])
    whole = sums.filter("_n = deg").join(d, "label")
    return whole.select("query_id", "qv", "label", "deg", *[c.alias(f"q{k}") for k, c in enumerate(embedding_columns(p))])


#: The patterns of the experiments on the trade graph.
TRADE_PATTERNS = {
    "triangle": "a:1-b:6, b-c:12, a-c",
    "star3": "a:1-b:6, a-c:7, a-d:12",
    "path4": "a:1-b:6, b-c:2, c-d:7",
    "tri_tail": "a:1-b:6, b-c:12, a-c, b-d:2",
    "two_tri": "a:1-b:6, b-c:12, a-c, d:2-e:7, e-c, d-c",
    "diamond": "a:1-b:6, b-c:12, a-c, a-d:7, d-c",
    "six": "a:1-b:6, b-c:12, a-c, d:2-b, d-e:13, b-e, d-f:8",
    "square": "a:1-b:6, b-c:1, c-d:6, d-a",
    "square_sym": "a:1-b:6, b-c:1, c-d:12, d-a",
    "vee_sym": "a:1-b:6, b-c:1",
}


def trade_pattern(name: str) -> Pattern:
    return parse(name, TRADE_PATTERNS[name])
