"""Join orders: smallest candidate set first, then the smallest connected one; and anchored orders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .patterns import Pattern, Patterns


def order_from(pattern: Pattern, counts: dict[int, int], start: list[int]) -> list[int]:
    """Positions in join order, beginning with ``start``; ties go to the lower position."""
    order = list(start)
    while len(order) < len(pattern.labels):
        reach = {j for i in order for j in pattern.neighbours(i)} - set(order)
        order.append(min(reach, key=lambda j: (counts.get(j, 0), j)))
    return order


def candidate_counts(cand: DataFrame) -> dict[int, dict[int, int]]:
    """Sizes of candidate sets: a number per pattern vertex comes to the driver."""
    out: dict[int, dict[int, int]] = {}
    for r in cand.groupBy("query_id", "qv").agg(F.count(F.lit(1)).alias("n")).collect():
        out.setdefault(r.query_id, {})[r.qv] = r.n
    return out


def join_orders(patterns: Patterns, counts: dict[int, dict[int, int]]) -> dict[int, list[int]]:
    out = {}
    for q, p in patterns:
        c = counts.get(q, {})
        out[q] = order_from(p, c, [min(range(len(p.labels)), key=lambda i: (c.get(i, 0), i))])
    return out


def anchored_orders(pattern: Pattern, counts: dict[int, int] | None = None) -> list[tuple[int, int, list[int]]]:
    """(qi, qj, order) for every pattern edge in both directions: 2 |E| plans, made once."""
    c = counts or {i: -len(pattern.neighbours(i)) for i in range(len(pattern.labels))}
    return [(i, j, order_from(pattern, c, [i, j])) for e in pattern.edges for i, j in ((e[0], e[1]), (e[1], e[0]))]


def steps_of(pattern: Pattern, order: list[int]) -> list[tuple[str, int, int]]:
    """('start', x, x), then for each position one ('expand', from, to) and ('close', a, to) for
    its other edges to positions already placed."""
    out = [("start", order[0], order[0])]
    for n, x in enumerate(order[1:], 1):
        back = [y for y in order[:n] if y in pattern.neighbours(x)]
        out.append(("expand", back[0], x))
        out += [("close", y, x) for y in back[1:]]
    return out


def blocks(pattern: Pattern) -> list[frozenset[int]]:
    """The pattern's biconnected parts as sets of positions: two parts share one position at most, and an
    edge on no cycle is a part of its own."""
    seen: dict[int, int] = {}
    low: dict[int, int] = {}
    open_edges: list[tuple[int, int]] = []
    out: list[frozenset[int]] = []

    def visit(x: int, parent: int) -> None:
        seen[x] = low[x] = len(seen)
        for y in sorted(pattern.neighbours(x)):
            if y not in seen:
                open_edges.append((x, y))
                visit(y, x)
                low[x] = min(low[x], low[y])
                if low[y] >= seen[x]:
                    at = open_edges.index((x, y))
                    out.append(frozenset(z for e in open_edges[at:] for z in e))
                    del open_edges[at:]
            elif y != parent and seen[y] < seen[x]:
                open_edges.append((x, y))
                low[x] = min(low[x], seen[y])

    visit(0, -1)
    return out


class Fanouts:
    """Neighbours of one label that a vertex of another has, on average over those that have any edge to it."""

    def __init__(self, rows: dict[tuple[int, int], float] | None = None):
        self.rows = rows or {}

    def __call__(self, pattern: Pattern, a: int, b: int) -> float:
        return self.rows.get((pattern.labels[a], pattern.labels[b]), 0.0)


def block_steps(pattern: Pattern, order: list[int], placed: int, fan: Fanouts) -> list[tuple]:
    """Steps after the first ``placed`` (1 or 2) positions of ``order``: ('expand', from, to) and ('close', a, to) as
    in ``steps_of``, and ('part', at, others) for a biconnected part that hangs on a placed position.

    A part is matched on its own and joined at that one position, so its inner edges are never opened once
    per match of the rest. Within a part the next position is the one reached with the fewest rows; ties go by ``order``.
    """
    rank = {x: n for n, x in enumerate(order)}
    have = list(order[:placed])
    left = blocks(pattern)
    out: list[tuple] = []

    def grow(among: set[int]) -> None:
        _, _, a, b = min((fan(pattern, y, x), rank[x], y, x) for x in among - set(have) for y in pattern.neighbours(x) & set(have))
        back = [y for y in have if y != a and y in pattern.neighbours(b)]
        out.append(("expand", a, b))
        out.extend(("close", y, b) for y in back)
        have.append(b)

    if placed == 1 and len(order) > 1:
        grow(set(order))
    while left:
        inside = [x for x in left if len(x & set(have)) > 1]
        if inside:  # begun: finished position by position
            while not inside[0] <= set(have):
                grow(set(inside[0]))
            left.remove(inside[0])
            continue
        ready = [x for x in left if x & set(have)]
        parts = [x for x in ready if len(x) > 2]
        if not parts:
            grow(set().union(*ready))
            continue
        part = min(parts, key=lambda x: sorted(rank[y] for y in x))
        at = next(iter(part & set(have)))
        rest = tuple(sorted(part - {at}, key=lambda x: rank[x]))
        out.append(("part", at, rest))
        have.extend(rest)
        left.remove(part)
    return out


def sub_pattern(pattern: Pattern, positions: list[int]) -> Pattern:
    """The pattern on the given positions, numbered in their order."""
    at = {x: n for n, x in enumerate(positions)}
    edges = tuple((at[e[0]], at[e[1]], *e[2:]) for e in pattern.edges if e[0] in at and e[1] in at)
    return Pattern(f"{pattern.name}[{','.join(map(str, positions))}]", tuple(pattern.labels[x] for x in positions), edges)


def plan_steps(spark, patterns: Patterns, orders: dict[int, list[int]]) -> DataFrame:
    """plan_step(query_id, step, kind, from_pos, to_pos, label)."""
    rows = [(q, n, kind, a, b, p.labels[b]) for q, p in patterns for n, (kind, a, b) in enumerate(steps_of(p, orders[q]))]
    return spark.createDataFrame(rows, "query_id int, step int, kind string, from_pos int, to_pos int, label int")
