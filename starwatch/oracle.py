"""DuckDB SQL for the registered queries, written independently of the DataFrame code."""

from __future__ import annotations

import re

from .functions.arithmetic import EDGE, base_values, label_value
from .model import ALIVE, BuildParams
from .plans.joinorder import order_from, steps_of
from .plans.patterns import Pattern, Patterns

D = BuildParams()

TRADE = """
tv AS (SELECT c_custkey * 4 AS v, dense_rank() OVER (ORDER BY c_mktsegment)::INT AS label, 0 AS kind FROM customer
  UNION ALL SELECT p_partkey * 4 + 1, (5 + dense_rank() OVER (ORDER BY p_type))::INT, 1 FROM part
  UNION ALL SELECT s_suppkey * 4 + 2, (12 + n_regionkey)::INT, 2 FROM supplier JOIN nation ON s_nationkey = n_nationkey),
raw AS (SELECT o_custkey * 4 AS c, l_partkey * 4 + 1 AS p, l_suppkey * 4 + 2 AS s, l_shipdate AS ts, l_returnflag AS f FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_linenumber = 1),
pairs AS (SELECT c AS a, p AS b, ts, f FROM raw UNION ALL SELECT p, s, ts, f FROM raw UNION ALL SELECT c, s, ts, f FROM raw),
te0 AS (SELECT a, b, min({'ts': ts, 'f': f}) AS x FROM pairs GROUP BY a, b),
te AS (SELECT rank() OVER (ORDER BY x.ts, a, b) AS seq, x.ts AS ts, a, b, dense_rank() OVER (ORDER BY x.f)::INT AS elabel FROM te0),
"""
LIFE = f"el AS (SELECT least(a, b) AS u, greatest(a, b) AS v, elabel, CASE WHEN seq * 100 <= (SELECT max(seq) FROM te) * 90 THEN 0 ELSE seq END AS born, {ALIVE} AS died, TRUE AS x FROM te),\n"
HASH = "((least(a, b) % 99991) * 7919 + (greatest(a, b) % 99991) * 104729 + 12345) % 1000003"
DELETED = f"el AS (SELECT least(a, b) AS u, greatest(a, b) AS v, elabel, 0 AS born, CASE WHEN {HASH} % 100 < 10 THEN seq ELSE {ALIVE} END AS died, TRUE AS x FROM te),\n"
MIXED = f"""ops AS (SELECT seq * 4 AS seq, '+' AS op, least(a, b) AS u, greatest(a, b) AS v, elabel FROM te
  UNION ALL SELECT seq * 4 + 4001, '-', least(a, b), greatest(a, b), elabel FROM te WHERE {HASH} % 20 < 2
  UNION ALL SELECT seq * 4 + 8002, '+', least(a, b), greatest(a, b), elabel FROM te WHERE {HASH} % 20 < 1
  UNION ALL SELECT seq * 4 + 4003, '+', least(a, b), greatest(a, b), elabel FROM te WHERE {HASH} % 20 IN (2, 3)),
clean AS (SELECT * FROM (SELECT *, lag(op, 1, '-') OVER (PARTITION BY u, v ORDER BY seq, op) AS b4 FROM ops) WHERE op <> b4),
el AS (SELECT u, v, elabel, seq AS born, died, TRUE AS x FROM (SELECT *, lead(seq, 1, {ALIVE}) OVER (PARTITION BY u, v ORDER BY seq, op) AS died FROM clean) WHERE op = '+'),
"""
ADJ = """adj AS (SELECT src, dst, fwd, elabel, born, died, p.label AS sl, q.label AS dl FROM
  (SELECT u AS src, v AS dst, TRUE AS fwd, elabel, born, died FROM el UNION ALL SELECT v, u, FALSE, elabel, born, died FROM el) z JOIN tv p ON p.v = src JOIN tv q ON q.v = dst),
"""


def labels_cte(p: BuildParams = D) -> str:
    lv = ", ".join(f"{label_value('label', k, p.salt, p.dist, spark=False)} AS lv{k}" for k in range(p.d))
    bv = ", ".join(f"{e} AS bv{k}" for k, e in enumerate(base_values("label", p.d, p.base, p.salt, spark=False)))
    return f"ld AS (SELECT label, {lv}, {bv} FROM (SELECT DISTINCT label FROM tv)),\n"


def snapshot_cte(t: str | None = "0") -> str:
    cond = f"died = {ALIVE}" if t is None else f"born <= {t} AND died > {t}"
    return f"now AS (SELECT * FROM adj WHERE {cond}),\nhist AS (SELECT src AS v, dl AS nlabel, count(*)::INT AS cnt FROM now GROUP BY 1, 2),\n"


def star_cte(p: BuildParams = D) -> str:
    ns = ", ".join(f"coalesce(sum(cnt * l.lv{k}), 0)::BIGINT AS ns{k}" for k in range(p.d))
    own = [f"d.lv{k}" for k in range(p.d)] + [f"ns{k}" for k in range(p.d)]
    e = ", ".join(f"{x}{'' if p.variant == 'plain' else f' + {p.ratio} * d.bv{k}'} AS e{k}" for k, x in enumerate(own))
    keep = ", ".join(f"ns{k}" for k in range(p.d))
    return f"""nsum AS (SELECT tv.v, tv.label, coalesce(sum(cnt), 0)::INT AS deg, {ns} FROM tv LEFT JOIN hist USING (v) LEFT JOIN ld l ON l.label = nlabel GROUP BY 1, 2),
star AS (SELECT n.v, n.label, deg, {keep}, {e} FROM nsum n JOIN ld d ON d.label = n.label),
"""


def bands_cte(m: int = 3) -> str:
    return f"""dh AS (SELECT deg, count(*) AS n FROM star WHERE deg > 0 GROUP BY deg),
sv AS (SELECT x, (SELECT sum(n) FROM dh WHERE deg >= x) AS s FROM (SELECT unnest(range(1, (SELECT max(deg) FROM dh) + 1)) AS x)),
cm AS (SELECT x, sum(s) OVER (ORDER BY x) AS c, sum(s) OVER () AS t FROM sv),
bh AS (SELECT DISTINCT CASE WHEN j = {m} THEN 2147483647 ELSE (SELECT min(x) FROM cm WHERE c * {m} >= j * t) END AS hi FROM (SELECT unnest(range(1, {m + 1})) AS j)),
bands AS (SELECT row_number() OVER (ORDER BY hi)::INT AS band, lag(hi, 1, 0) OVER (ORDER BY hi)::INT AS lo_excl, hi::INT AS hi_incl FROM bh),
"""


def boxes_cte(name: str, wanted: str, p: BuildParams = D) -> str:
    """``name``(v, label, deg, delta, lo*, hi*) for the rows (v, delta) of ``wanted``: neighbour values are listed one by one and sorted."""
    each = ", ".join(f"l.lv{k}" for k in range(p.d))
    ranks = ", ".join(f"row_number() OVER (PARTITION BY v ORDER BY lv{k} {o}) AS r{w}{k}" for k in range(p.d) for w, o in (("lo", "ASC"), ("hi", "DESC")))
    sums = ", ".join(f"sum(lv{k}) FILTER (r{w}{k} <= delta)::BIGINT AS s{w}{k}" for k in range(p.d) for w in ("lo", "hi"))
    cols = ", ".join((f"s.e{k} AS {w}{k}" if k < p.d else f"x.s{w}{k - p.d}{'' if p.variant == 'plain' else f' + {p.ratio} * d.bv{k}'} AS {w}{k}") for k in p.dims for w in ("lo", "hi"))
    return f"""{name}_n AS (SELECT h.v, {each} FROM hist h JOIN ld l ON l.label = h.nlabel, (SELECT unnest(range(1, 100000)) AS i) WHERE i <= h.cnt),
{name}_r AS (SELECT v, {', '.join(f'lv{k}' for k in range(p.d))}, {ranks} FROM {name}_n),
{name}_s AS (SELECT r.v, w.delta, {sums} FROM {name}_r r JOIN ({wanted}) w ON w.v = r.v GROUP BY 1, 2),
{name} AS (SELECT s.v, s.label, s.deg, x.delta::INT AS delta, {cols} FROM {name}_s x JOIN star s ON s.v = x.v JOIN ld d ON d.label = s.label),
"""


def corners_cte(p: BuildParams = D) -> str:
    member = "SELECT v, band, least(deg, hi_incl) AS delta FROM star JOIN bands ON deg > lo_excl"
    ub = ", ".join(f"b.hi{k} AS ub{k}" for k in p.dims)
    return boxes_cte("cb", f"SELECT DISTINCT v, delta FROM ({member})", p) + f"corners AS (SELECT m.v, b.label, b.deg, m.band, {ub} FROM ({member}) m JOIN cb b ON b.v = m.v AND b.delta = m.delta),\n"


def synopsis_cte(p: BuildParams = D) -> str:
    g = ", ".join(f"min(ub{k}) AS g{k}, (max(ub{k}) - min(ub{k})) // {p.k} + 1 AS w{k}" for k in p.dims)
    c = ", ".join(f"least({p.k - 1}, greatest(0, (ub{k} - g{k}) // w{k})) AS c{k}" for k in p.dims)
    cu = ", ".join(f"CASE WHEN c{k} = {p.k - 1} THEN {ALIVE} ELSE g{k} + (c{k} + 1) * w{k} - 1 END AS cu{k}" for k in p.dims)
    key = " + ".join(f"cu{k}::DOUBLE * cu{k}::DOUBLE" for k in p.dims)
    top = " OR ".join(f"c{k} = {p.k - 1}" for k in p.dims)
    cell = " || '-' || ".join(f"c{k}" for k in p.dims)
    return f"""gr AS (SELECT band, {g} FROM corners GROUP BY band),
pl AS (SELECT corners.*, {c}, {', '.join(f'g{k}, w{k}' for k in p.dims)} FROM corners JOIN gr USING (band)),
pc AS (SELECT *, {cu}, {cell} AS cell FROM pl),
syn AS (SELECT *, CASE WHEN {top} THEN 'Infinity'::DOUBLE ELSE {key} END AS cell_key FROM pc),
"""


def query_cte(patterns: Patterns, p: BuildParams = D) -> str:
    qv = [(q, i, x) for q, pat in patterns for i, x in enumerate(pat.labels)]
    qn = [(q, i, pat.labels[j]) for q, pat in patterns for i in range(len(pat.labels)) for j in pat.neighbours(i)]
    ns = ", ".join(f"sum(l.lv{k})::BIGINT AS ns{k}" for k in range(p.d))
    own = [f"d.lv{k}" for k in range(p.d)] + [f"ns{k}" for k in range(p.d)]
    e = ", ".join(f"{x}{'' if p.variant == 'plain' else f' + {p.ratio} * d.bv{k}'} AS q{k}" for k, x in enumerate(own))
    key = " + ".join(f"q{k}::DOUBLE * q{k}::DOUBLE" for k in p.dims)
    lv = ", ".join(f"{label_value('label', k, p.salt, p.dist, spark=False)} AS lv{k}" for k in range(p.d))
    bv = ", ".join(f"{x} AS bv{k}" for k, x in enumerate(base_values("label", p.d, p.base, p.salt, spark=False)))
    return f"""qv(query_id, qv, label) AS (VALUES {', '.join(map(str, qv))}), qn(query_id, qv, nlabel) AS (VALUES {', '.join(map(str, qn))}),
qld AS (SELECT label, {lv}, {bv} FROM (SELECT DISTINCT label FROM qv)),
qs AS (SELECT query_id, qv, count(*)::INT AS deg, {ns} FROM qn JOIN qld l ON l.label = nlabel GROUP BY 1, 2),
qe AS (SELECT qs.query_id, qs.qv, qv.label, deg, {e} FROM qs JOIN qv ON qv.query_id = qs.query_id AND qv.qv = qs.qv JOIN qld d ON d.label = qv.label),
qb AS (SELECT qe.*, band, {key} AS q_key FROM qe JOIN bands ON deg > lo_excl AND deg <= hi_incl),
"""


def candidate_sql(stages: tuple[str, ...], p: BuildParams = D) -> str:
    tests = ["s.band = q.band"]
    if "cell" in stages:
        tests += ["s.cell_key >= q.q_key", *[f"s.cu{k} >= q.q{k}" for k in p.dims]]
    if "label" in stages:
        tests.append("s.label = q.label")
    if "dominance" in stages:
        tests += [f"s.ub{k} >= q.q{k}" for k in p.dims]
    if "box" in stages:
        tests.append("EXISTS (SELECT 1 FROM bx WHERE bx.v = s.v AND bx.delta = q.deg AND " + " AND ".join(f"q.q{k} BETWEEN bx.lo{k} AND bx.hi{k}" for k in p.dims) + ")")
    return f"SELECT q.query_id, q.qv, s.v FROM syn s JOIN qb q ON {' AND '.join(tests)}"


def index_ctes(patterns: Patterns, p: BuildParams = D, t: str | None = "0") -> str:
    deltas = sorted({len(x.neighbours(i)) for _, x in patterns for i in range(len(x.labels))})
    wanted = f"SELECT v, delta FROM star, (SELECT unnest([{', '.join(map(str, deltas))}]) AS delta) WHERE delta <= deg"
    return labels_cte(p) + snapshot_cte(t) + star_cte(p) + bands_cte(p.m) + corners_cte(p) + synopsis_cte(p) + boxes_cte("bx", wanted, p) + query_cte(patterns, p)


def after_ctes(patterns: Patterns, p: BuildParams = D) -> str:
    """The index of the first graph, and as hist_z, star_z, syn_z, bx_z the final graph's with the first one's bands and grid."""
    deltas = sorted({len(x.neighbours(i)) for _, x in patterns for i in range(len(x.labels))})
    wanted = f"SELECT v, delta FROM star, (SELECT unnest([{', '.join(map(str, deltas))}]) AS delta) WHERE delta <= deg"
    grid = synopsis_cte(p)
    last = snapshot_cte(None) + star_cte(p) + corners_cte(p) + grid[grid.index("pl AS (") :] + boxes_cte("bx", wanted, p)
    names = re.findall(r"^(\w+)(?:\([^)]*\))? AS \(", last, re.M)
    return index_ctes(patterns, p) + re.sub(rf"\b({'|'.join(names)})\b", r"\1_z", last)


def with_(*parts: str, select: str) -> str:
    return "WITH " + "".join(parts).rstrip().rstrip(",") + "\n" + select


def match_select(p: Pattern, semantics: str = "iso", source: str = "adj") -> str:
    """The matches of a pattern as one self-join of the adjacency table."""
    order = order_from(p, {}, [0])
    edges, where, where_is = [], [], {}
    for n, (_, a, b) in enumerate(steps_of(p, order)[1:]):
        alias = f"e{n}"
        cond = [f"{alias}.sl = {p.labels[a]}", f"{alias}.dl = {p.labels[b]}"]
        el = p.edge_label(a, b)
        if el is not None:
            cond.append(f"{alias}.elabel = {el}")
        for x, col in ((a, "src"), (b, "dst")):
            if x in where_is:
                cond.append(f"{alias}.{col} = {where_is[x]}")
            else:
                where_is[x] = f"{alias}.{col}"
        edges.append((alias, cond))
    joins = f"{source} {edges[0][0]}" + "".join(f" JOIN {source} {a} ON {' AND '.join(c)}" for a, c in edges[1:])
    where += edges[0][1]
    if semantics != "homo":
        where += [f"{where_is[i]} <> {where_is[j]}" for i in range(len(p.labels)) for j in range(i) if p.labels[i] == p.labels[j]]
    born = f"greatest({', '.join(a + '.born' for a, _ in edges)})" if len(edges) > 1 else f"{edges[0][0]}.born"
    died = f"least({', '.join(a + '.died' for a, _ in edges)})" if len(edges) > 1 else f"{edges[0][0]}.died"
    if semantics == "induced":  # on a stream without deletions: a forbidden edge ends the match when it comes
        ends = [f"coalesce((SELECT min(z.born) FROM {source} z WHERE z.src = {where_is[i]} AND z.dst = {where_is[j]}), {ALIVE})" for i in range(len(p.labels)) for j in range(i) if j not in p.neighbours(i)]
        died = f"least({died}, {', '.join(ends)})" if ends else died
    cols = ", ".join(f"{where_is[i]} AS m{i}" for i in range(len(p.labels)))
    return f"SELECT {cols}, {born} AS born, {died} AS died FROM {joins} WHERE {' AND '.join(where)} AND {born} < {died}"


def edge_vectors(p: BuildParams = D) -> str:
    return ", ".join(f"{label_value('elabel', k, p.salt, p.dist, EDGE, spark=False)} AS ev{k}" for k in range(p.d))
