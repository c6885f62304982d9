"""The registered queries: one per method, variant, baseline, measure and workload, with DuckDB SQL where it can say the same."""

from __future__ import annotations

import re
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import baselines, cost, measures, streaming
from . import oracle as o
from .baselines.learned import learned_dominance
from .functions.arithmetic import normal_cdf
from .functions.vectors import label_dict
from .model import ALIVE, BuildParams, Graph, edge_lifetimes, graph_stats, insertion_cases, normalise_updates, split_label, validate_graph
from .operators import bands, batchgroups, monitor, prune, refine, stars, synopsis
from .plans.joinorder import candidate_counts
from .plans.patterns import Patterns, embed_by_data, parse, trade_pattern
from .sources import synth, views
from .storage import drop_shuffles, materialise

Query = Callable[[SparkSession, str], DataFrame]
D = BuildParams()
CORE = Patterns([trade_pattern(n) for n in ("triangle", "star3", "tri_tail", "two_tri", "square_sym")])
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_memo: dict[tuple, object] = {}
_all_lines = False  # while a full_ query is built: its graphs come from all line items


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def once(spark: SparkSession, sf_dir: str, key: str, make):
    """A graph or index built once per application and data set; kept as written tables."""
    full = (spark.sparkContext.applicationId, sf_dir, key, _all_lines)
    if full not in _memo:
        _memo[full] = make()
    return _memo[full]


@contextmanager
def all_lines():
    global _all_lines
    before, _all_lines = _all_lines, True
    try:
        yield
    finally:
        _all_lines = before


def edges_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.trade_edges(spark, sf_dir, _all_lines)


def stored_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The edges as a written table, for queries that make several streams of them."""
    return once(spark, sf_dir, "edges", lambda: materialise(edges_of(spark, sf_dir), "edges"))


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    return once(spark, sf_dir, "trade", lambda: views.trade(spark, sf_dir, full=_all_lines).stored())


def trade_deleted(spark: SparkSession, sf_dir: str) -> Graph:
    return once(spark, sf_dir, "deleted", lambda: views.deletion_stream(views.trade_vertices(spark, sf_dir), edges_of(spark, sf_dir), 10, "trade_del").stored())


def trade_mixed(spark: SparkSession, sf_dir: str) -> Graph:
    def make():
        ops = normalise_updates(views.mixed_updates(edges_of(spark, sf_dir)))
        return Graph(views.trade_vertices(spark, sf_dir).select("v", "label"), edge_lifetimes(None, ops), name="trade_mixed").stored()

    return once(spark, sf_dir, "mixed", make)


def index(spark: SparkSession, sf_dir: str, p: BuildParams = D, t: int | None = 0) -> synopsis.Index:
    return once(spark, sf_dir, f"index {p} {t}", lambda: synopsis.Index(trade(spark, sf_dir), p, CORE.deltas(spark), t))


BASE = o.TRADE + o.LIFE + o.ADJ
STAR = BASE + o.labels_cte() + o.snapshot_cte() + o.star_cte()
FULL = BASE + o.index_ctes(CORE)


# --- views and model ---------------------------------------------------------------------------
@query("trade_vertices", o.with_(o.TRADE, select="SELECT v, label, kind FROM tv"))
def trade_vertices(spark, d):
    return views.trade_vertices(spark, d)


@query("trade_edges", o.with_(o.TRADE, select="SELECT seq, a, b, elabel FROM te"))
def trade_edges(spark, d):
    return views.trade_edges(spark, d).select("seq", "a", "b", "elabel")


@query("trade_full_edges", o.with_(o.TRADE.replace("WHERE l_linenumber = 1", ""), select="SELECT seq, a, b, elabel FROM te"))
def trade_full_edges(spark, d):
    return views.trade_edges(spark, d, full=True).select("seq", "a", "b", "elabel")


@query("trade_graph_stats", o.with_(BASE, select=f"""SELECT (SELECT count(*) FROM tv) AS n_vertices, (SELECT count(DISTINCT label) FROM tv) AS n_labels, count(*) AS n_connected,
 (sum(d) / 2)::BIGINT AS n_edges, round(avg(d), 6) AS avg_degree, max(d) AS max_degree FROM (SELECT src, count(*) AS d FROM adj WHERE died = {ALIVE} GROUP BY src)"""))
def trade_graph_stats(spark, d):
    return graph_stats(trade(spark, d))


@query("graph_stats_rollup", o.with_(BASE, select="""SELECT kind, label, count(*) AS n, sum(deg)::BIGINT AS degrees FROM (SELECT v, label, kind, (SELECT count(*) FROM adj WHERE src = v) AS deg FROM tv) GROUP BY ROLLUP (kind, label)"""))
def graph_stats_rollup(spark, d):
    deg = trade(spark, d).adjacency().groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    return views.trade_vertices(spark, d).join(deg, "v", "left").fillna(0, ["deg"]).rollup("kind", "label").agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("degrees"))


@query("validate_graph", o.with_(BASE, select="SELECT 0::BIGINT AS loops, 0::BIGINT AS wrong_order, 0::BIGINT AS empty_lives, 0::BIGINT AS overlaps, 0::BIGINT AS unlabelled"))
def q_validate(spark, d):
    return validate_graph(trade_mixed(spark, d))


@query("edge_lifetimes", o.with_(o.TRADE, o.MIXED, select="SELECT u, v, elabel, born, died FROM el"))
def q_lifetimes(spark, d):
    return trade_mixed(spark, d).edge_life


@query("noop_updates", o.with_(o.TRADE, o.MIXED, select="SELECT count(*) AS n_raw, (SELECT count(*) FROM clean) AS n_clean FROM ops"))
def noop_updates(spark, d):
    raw = views.mixed_updates(edges_of(spark, d))
    return raw.agg(F.count(F.lit(1)).alias("n_raw")).join(normalise_updates(raw).agg(F.count(F.lit(1)).alias("n_clean")))


@query("snapshot_t", o.with_(o.TRADE, o.MIXED, select="SELECT u, v FROM el WHERE born <= 5000 AND died > 5000"))
def snapshot_t(spark, d):
    return trade_mixed(spark, d).snapshot(5000).edge_life.select("u", "v")


@query("insertion_cases", o.with_(BASE, select="""SELECT born AS seq, u, v, ((SELECT min(born) FROM el z WHERE e.u IN (z.u, z.v)) = born)::INT + ((SELECT min(born) FROM el z WHERE e.v IN (z.u, z.v)) = born)::INT AS new_ends
 FROM el e WHERE born > 0"""))
def q_insertion_cases(spark, d):
    return insertion_cases(trade(spark, d))


@query("degree_histogram", o.with_(STAR, select="SELECT deg, count(*) AS n FROM star WHERE deg > 0 GROUP BY deg"))
def degree_histogram(spark, d):
    return bands.degree_histogram(index(spark, d).star)


@query("hubs_top10", o.with_(STAR, select="SELECT label, v, deg FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY deg DESC, v) AS r FROM star) WHERE r <= 10"))
def hubs_top10(spark, d):
    r = F.row_number().over(Window.partitionBy("label").orderBy(F.desc("deg"), "v"))
    return index(spark, d).star.withColumn("r", r).filter("r <= 10").select("label", "v", "deg")


@query("updates_per_month", o.with_(o.TRADE, select="SELECT strftime(ts, '%Y-%m') AS month, count(*) AS n FROM te GROUP BY 1"))
def updates_per_month(spark, d):
    return edges_of(spark, d).groupBy(F.date_format("ts", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"))


# --- vectors -----------------------------------------------------------------------------------
def _label_query(name: str, p: BuildParams, cols: list[str]):
    @query(name, o.with_(o.TRADE, o.labels_cte(p), select=f"SELECT label, {', '.join(cols)} FROM ld"))
    def run(spark, d):
        return label_dict(trade(spark, d).vertices, p).select("label", *cols)


_label_query("label_vec_uniform", D.but(variant="based"), ["lv0", "lv1"])
_label_query("label_vec_zipf", D, ["lv0", "lv1"])
_label_query("label_vec_d4", D.but(d=4), [f"lv{k}" for k in range(4)])
for _norm in ("l1", "l1_half", "diag", "l2"):
    _label_query(f"base_vec_{_norm}", D.but(base=_norm), [f"bv{k}" for k in D.dims])


@query("neighbour_histogram", o.with_(BASE, o.snapshot_cte(), select="SELECT v, nlabel, cnt FROM hist"))
def neighbour_histogram(spark, d):
    return index(spark, d).hist


def _star_query(name: str, p: BuildParams):
    cols = ["v", "label", "deg", *[f"ns{k}" for k in range(p.d)], *[f"e{k}" for k in p.dims]]

    @query(name, o.with_(BASE, o.labels_cte(p), o.snapshot_cte(), o.star_cte(p), select=f"SELECT {', '.join(cols)} FROM star"))
    def run(spark, d):
        return stars.stars(trade(spark, d), p, 0).select(*cols)


for _v in ("plain", "based", "skew_based"):
    _star_query(f"emb_{_v}", D.but(variant=_v))
_star_query("emb_d1", D.but(d=1))
_star_query("emb_ratio10", D.but(ratio=10))


@query("emb_after_updates", o.with_(BASE, o.labels_cte(), o.snapshot_cte(None), o.star_cte(), select="SELECT v, deg, e0, e1, e2, e3 FROM star"))
def emb_after_updates(spark, d):
    """Stars at the start plus the signed sums of all later insertions: equal to stars at the end."""
    g = trade(spark, d)
    ops = g.edge_life.filter("born > 0").select(F.lit("+").alias("op"), "u", "v")
    return stars.update_stars(index(spark, d).star, ops, g.vertices, D).select("v", "deg", "e0", "e1", "e2", "e3")


@query("emb_edge_labels", o.with_(BASE, o.labels_cte(), "now AS (SELECT * FROM adj WHERE born <= 0),\n", f"ed AS (SELECT elabel, {o.edge_vectors()} FROM (SELECT DISTINCT elabel FROM el)),\n",
 select="SELECT n.src AS v, sum(l.lv0 + ed.ev0)::BIGINT AS ns0, sum(l.lv1 + ed.ev1)::BIGINT AS ns1 FROM now n JOIN ld l ON l.label = n.dl JOIN ed ON ed.elabel = n.elabel GROUP BY 1"))
def emb_edge_labels(spark, d):
    p = D.but(elabel_weight=True)
    return stars.stars(trade(spark, d), p, 0).filter("deg > 0").select("v", "ns0", "ns1")


@query("peak_histogram", o.with_(o.TRADE, o.MIXED, o.ADJ, select="""SELECT v, nlabel, max(c)::INT AS cnt FROM (SELECT v, nlabel, sum(x) OVER (PARTITION BY v, nlabel ORDER BY at0, x ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS c FROM
 (SELECT src AS v, dl AS nlabel, greatest(born, 4000) AS at0, 1 AS x FROM adj WHERE born <= 9000 AND died > 4000 UNION ALL SELECT src, dl, died, -1 FROM adj WHERE born <= 9000 AND died > 4000 AND died <= 9000)) GROUP BY 1, 2"""))
def peak_histogram(spark, d):
    return stars.peak_histogram(trade_mixed(spark, d), 4000, 9000)


# --- bands and synopsis ------------------------------------------------------------------------
@query("degree_bands_m3", o.with_(STAR, o.bands_cte(3), select="SELECT band, lo_excl, hi_incl FROM bands"))
def degree_bands_m3(spark, d):
    return index(spark, d).bands


@query("degree_bands_m5", o.with_(STAR, o.bands_cte(5), select="SELECT band, lo_excl, hi_incl FROM bands"))
def degree_bands_m5(spark, d):
    return bands.degree_bands(index(spark, d).star, 5)


@query("degree_bands_single", o.with_(STAR, select="SELECT row_number() OVER (ORDER BY deg)::INT AS band, lag(deg, 1, 0) OVER (ORDER BY deg)::INT AS lo_excl, CASE WHEN lead(deg) OVER (ORDER BY deg) IS NULL THEN 2147483647 ELSE deg END::INT AS hi_incl FROM (SELECT DISTINCT deg FROM star WHERE deg > 0)"))
def degree_bands_single(spark, d):
    return bands.degree_bands(index(spark, d).star, 0, "single")


_BOX = ", ".join(f"{w}{k}" for k in D.dims for w in ("lo", "hi"))


@query("degree_boxes", o.with_(FULL, select=f"SELECT v, label, deg, delta, {_BOX} FROM bx"))
def degree_boxes(spark, d):
    return index(spark, d).boxes


@query("upper_corners", o.with_(FULL, select="SELECT v, label, deg, band, ub0, ub1, ub2, ub3 FROM corners"))
def upper_corners(spark, d):
    return index(spark, d).corners


@query("synopsis_rows", o.with_(FULL, select="SELECT band, cell, cell_key, v, label, deg, ub0, ub1, ub2, ub3 FROM syn"))
def synopsis_rows(spark, d):
    return index(spark, d).synopsis.select("band", "cell", "cell_key", "v", "label", "deg", "ub0", "ub1", "ub2", "ub3")


@query("synopsis_cells", o.with_(FULL, select="SELECT band, cell, cell_key, cu0, cu1, cu2, cu3, count(*) AS n_vertices FROM syn GROUP BY ALL"))
def synopsis_cells(spark, d):
    return index(spark, d).cells()


@query("synopsis_space", o.with_(STAR, select="SELECT count(*) * 4 AS vector_scalars, sum(deg)::BIGINT * 10 AS box_and_list_scalars FROM star"))
def synopsis_space(spark, d):
    return synopsis.synopsis_space(index(spark, d).star, D)


def _insertions(spark, d) -> DataFrame:
    return trade(spark, d).edge_life.filter("born > 0").select(F.lit("+").alias("op"), "u", "v")


def _advanced(spark, d) -> synopsis.Index:
    return once(spark, d, "index after", lambda: index(spark, d).advance(_insertions(spark, d)))


AFTER = BASE + o.after_ctes(CORE)


@query("hist_after_updates", o.with_(AFTER, select="SELECT v, nlabel, cnt FROM hist_z"))
def hist_after_updates(spark, d):
    return _advanced(spark, d).hist.select("v", "nlabel", "cnt")


@query("hist_after_deletions", o.with_(o.TRADE, o.DELETED, o.ADJ, o.labels_cte(), o.snapshot_cte(None), o.star_cte(), select="SELECT v, nlabel, cnt FROM hist"))
def hist_after_deletions(spark, d):
    g = trade_deleted(spark, d)
    ops = g.edge_life.filter(F.col("died") != ALIVE).select(F.lit("-").alias("op"), "u", "v")
    return stars.update_histogram(stars.neighbour_histogram(g, 0), ops, g.vertices)


@query("synopsis_after_updates", o.with_(AFTER, select="SELECT band, cell, v, deg, ub0, ub1, ub2, ub3 FROM syn_z"))
def synopsis_after_updates(spark, d):
    """Rows of touched vertices made anew from their counters, others kept."""
    return _advanced(spark, d).synopsis.select("band", "cell", "v", "deg", "ub0", "ub1", "ub2", "ub3")


@query("boxes_after_updates", o.with_(AFTER, select=f"SELECT v, deg, delta, {_BOX} FROM bx_z"))
def boxes_after_updates(spark, d):
    return _advanced(spark, d).boxes.select("v", "deg", "delta", *[f"{w}{k}" for k in D.dims for w in ("lo", "hi")])


# --- filtering ---------------------------------------------------------------------------------
@query("query_embedding", o.with_(FULL, select="""SELECT query_id, qv, label, deg, q0, q1, q2, q3 FROM qe WHERE label IN (SELECT label FROM tv)
 AND NOT EXISTS (SELECT 1 FROM qn WHERE qn.query_id = qe.query_id AND qn.qv = qe.qv AND nlabel NOT IN (SELECT label FROM tv))"""))
def query_embedding(spark, d):
    return embed_by_data(views.trade_vertices(spark, d), CORE, D)


@query("cells_visited", o.with_(FULL, select="""SELECT query_id, qv, count(*) AS n_cells, sum(n)::BIGINT AS n_in_cells FROM qb JOIN (SELECT band, cell, cell_key, cu0, cu1, cu2, cu3, count(*) AS n FROM syn GROUP BY ALL) c
 ON c.band = qb.band AND cell_key >= q_key AND cu0 >= q0 AND cu1 >= q1 AND cu2 >= q2 AND cu3 >= q3 GROUP BY 1, 2"""))
def cells_visited(spark, d):
    return prune.cells_visited(index(spark, d), CORE)


def _cand_query(name: str, stages: tuple[str, ...]):
    @query(name, o.with_(FULL, select=o.candidate_sql(stages)))
    def run(spark, d):
        return prune.candidates(index(spark, d), CORE, stages)


_cand_query("cand_cell", ("cell",))
_cand_query("cand_dominance", ("dominance",))
_cand_query("cand_label_dominance", ("label", "dominance"))
_cand_query("cand_box", ("box",))
_cand_query("cand_all", prune.STAGES)


@query("cand_label_only", o.with_(FULL, select="SELECT query_id, qv, v FROM star JOIN qv USING (label)"))
def cand_label_only(spark, d):
    return prune.label_only(index(spark, d).star, CORE)


@query("cand_full_star", o.with_(FULL, select="SELECT query_id, qv, v FROM star s JOIN qe q ON " + " AND ".join(f"q{k} <= e{k}" for k in D.dims)))
def cand_full_star(spark, d):
    return prune.full_star_dominance(index(spark, d).star, CORE, D)


@query("cand_label_freq", o.with_(FULL, select="""SELECT query_id, qv, v FROM (SELECT n.query_id, n.qv, s.v, count(*) FILTER (h.cnt >= n.need) AS ok, count(*) AS k FROM
 (SELECT query_id, qv, nlabel, count(*) AS need FROM qn GROUP BY ALL) n JOIN qv USING (query_id, qv) JOIN star s ON s.label = qv.label LEFT JOIN hist h ON h.v = s.v AND h.nlabel = n.nlabel GROUP BY 1, 2, 3) WHERE ok = k"""))
def cand_label_freq(spark, d):
    ix = index(spark, d)
    return prune.label_frequency(ix.hist, ix.star, CORE)


@query("cand_after_updates", o.with_(AFTER, select=re.sub(r"\b(syn|bx)\b", r"\1_z", o.candidate_sql(prune.STAGES))))
def cand_after_updates(spark, d):
    touched = materialise(synopsis.touched(_insertions(spark, d)), "touched")
    return prune.update_candidates(prune.candidates(index(spark, d), CORE), _advanced(spark, d), CORE, touched)


@query("pruning_power", o.with_(FULL, f"c AS ({o.candidate_sql(prune.STAGES)}),\n", select="SELECT qv.query_id, qv.qv, count(c.v) AS n_cand, (SELECT count(*) FROM star) AS n_vertices, round(1 - count(c.v) / (SELECT count(*) FROM star), 6) AS pruned_share FROM qv LEFT JOIN c ON c.query_id = qv.query_id AND c.qv = qv.qv GROUP BY 1, 2"))
def pruning_power(spark, d):
    ix = index(spark, d)
    return measures.pruning_power(prune.candidates(ix, CORE), ix.star, CORE)


def _pruning_sql(p: BuildParams) -> str:
    return o.with_(BASE, o.index_ctes(CORE, p), f"c AS ({o.candidate_sql(prune.STAGES, p)}),\n", select="SELECT count(*) AS n_cand FROM c")


for _v in ("plain", "based"):

    def _run(spark, d, v=_v):
        return prune.candidates(index(spark, d, D.but(variant=v)), CORE).agg(F.count(F.lit(1)).alias("n_cand"))

    query(f"ablation_{_v}", _pruning_sql(D.but(variant=_v)))(_run)
for _name, _p in (("m1_no_bands", D.but(m=1)), ("k1_no_grid", D.but(k=1)), ("m5", D.but(m=5)), ("k10", D.but(k=10)), ("d1", D.but(d=1)), ("ratio10", D.but(ratio=10))):

    def _run2(spark, d, p=_p):
        return prune.candidates(index(spark, d, p), CORE, ("cell", "dominance")).agg(F.count(F.lit(1)).alias("n_cand"))

    query(f"ablation_{_name}", o.with_(BASE, o.index_ctes(CORE, _p), f"c AS ({o.candidate_sql(('cell', 'dominance'), _p)}),\n", select="SELECT count(*) AS n_cand FROM c"))(_run2)


@query("pruning_cube", o.with_(FULL, f"c AS ({' UNION ALL '.join(f'SELECT {chr(39)}{s}{chr(39)} AS stage, query_id FROM ({o.candidate_sql((s,))})' for s in ('cell', 'dominance', 'box'))}),\n", select="SELECT stage, query_id, count(*) AS n_cand FROM c GROUP BY CUBE (stage, query_id)"))
def pruning_cube(spark, d):
    ix = index(spark, d)
    return measures.pruning_cube({s: prune.candidates(ix, CORE, (s,)) for s in ("cell", "dominance", "box")}, ix.star, CORE)


@query("selectivity_box", o.with_(FULL, f"c AS ({o.candidate_sql(prune.STAGES)}), n AS (SELECT qv.query_id, qv.qv, count(c.v) AS n FROM qv LEFT JOIN c ON c.query_id = qv.query_id AND c.qv = qv.qv GROUP BY 1, 2),\n", select="SELECT min(n) AS least, quantile_cont(n, 0.25) AS lower, quantile_cont(n, 0.5) AS middle, quantile_cont(n, 0.75) AS upper, max(n) AS most FROM n"))
def selectivity_box(spark, d):
    return measures.selectivity_box(prune.candidates(index(spark, d), CORE), CORE)


@query("join_order")
def join_order(spark, d):
    return refine.plan_table(spark, CORE, prune.candidates(index(spark, d), CORE))


# --- matching ----------------------------------------------------------------------------------
def _match_query(name: str, pattern, semantics: str = "iso", graph: str = "trade"):
    life = {"trade": o.LIFE, "mixed": o.MIXED, "deleted": o.DELETED}[graph]
    source = {"trade": trade, "mixed": trade_mixed, "deleted": trade_deleted}[graph]

    @query(name, o.with_(o.TRADE, life, o.ADJ, select=o.match_select(pattern, semantics)))
    def run(spark, d):
        return refine.match_static(source(spark, d).adjacency(), pattern, semantics=semantics).select(*[f"m{i}" for i in range(len(pattern.labels))], "born", "died")


for _n in ("triangle", "star3", "path4", "tri_tail", "two_tri", "diamond", "six", "square", "square_sym", "vee_sym"):
    _match_query(f"match_{_n}", trade_pattern(_n))
_match_query("match_homo_tree", trade_pattern("vee_sym"), "homo")
_match_query("match_induced", trade_pattern("path4"), "induced")
_match_query("match_edge_label", parse("labelled", "a:1-b:6[2], b-c:12[2], a-c"))
_match_query("match_lifetimes_mixed", trade_pattern("star3"), graph="mixed")
_match_query("match_lifetimes_deleted", trade_pattern("two_tri"), graph="deleted")


@query("match_square_subgraphs", o.with_(BASE, f"m AS ({o.match_select(trade_pattern('square_sym'))}),\n", select="SELECT min(m0) AS m0, m1, max(m0) AS m2, m3 FROM m GROUP BY m1, m3, least(m0, m2), greatest(m0, m2)"))
def match_square_subgraphs(spark, d):
    p = trade_pattern("square_sym")
    return refine.subgraphs(refine.match_static(trade(spark, d).adjacency(), p), p).select("m0", "m1", "m2", "m3")


_ARC = "EXISTS (SELECT 1 FROM te WHERE te.a = m.m{0} AND te.b = m.m{1})"


def _directed_query(name: str, pattern):
    want = " AND ".join(_ARC.format(i, j) for i, j, *_ in pattern.edges)
    cols = [f"m{i}" for i in range(len(pattern.labels))]

    @query(name, o.with_(BASE, f"m AS ({o.match_select(pattern)}),\n", select=f"SELECT {', '.join(cols)} FROM m WHERE {want}"))
    def run(spark, d):
        arcs = edges_of(spark, d).select(F.col("a").alias("src"), F.col("b").alias("dst"))
        return refine.directed_only(refine.match_static(trade(spark, d).adjacency(), pattern), pattern, arcs).select(*cols)


#: Edges run from customers to parts and suppliers, and from parts to suppliers.
_directed_query("match_directed", parse("directed", "a:1-b:6, b-c:12, a-c"))
_directed_query("match_directed_against", parse("against", "a:1-b:6, c:12-b, a-c"))


@query("match_with_loop", o.with_(BASE, f"m AS ({o.match_select(trade_pattern('triangle'))}),\n", select="SELECT m0, m1, m2 FROM m WHERE m0 % 3 = 0"))
def match_with_loop(spark, d):
    g = trade(spark, d)
    return refine.with_loops(refine.match_static(g.adjacency(), trade_pattern("triangle")), 0, g.vertices.filter("v % 3 = 0").select("v")).select("m0", "m1", "m2")


def _rows_sql(condition: str = "TRUE", source: str = o.LIFE) -> str:
    parts = " UNION ALL ".join(f"SELECT {q} AS query_id, concat_ws(',', {', '.join(f'm{i}' for i in range(len(p.labels)))}) AS m, born, died FROM ({o.match_select(p)})" for q, p in CORE)
    return o.with_(o.TRADE, source, o.ADJ, f"ans AS ({parts}),\n", select=f"SELECT query_id, m FROM ans WHERE {condition}")


def _text(df: DataFrame) -> DataFrame:
    return df.withColumn("m", F.array_join("m", ","))


@query("initial_answers", _rows_sql("born <= 0"))
def initial_answers(spark, d):
    return _text(monitor.initial_answers(index(spark, d), CORE))


@query("initial_answers_levels", _rows_sql("born <= 0"))
def initial_answers_levels(spark, d):
    return _text(monitor.initial_answers(index(spark, d), CORE, "levels"))


@query("engine_levels", _rows_sql())
def engine_levels(spark, d):
    return _text(refine.lifetimes(trade(spark, d), CORE, "levels").select("query_id", "m"))


@query("engine_intersect", o.with_(BASE, select=f"SELECT m0, m1, m2, m3, m4 FROM ({o.match_select(trade_pattern('two_tri'))})"))
def engine_intersect(spark, d):
    return refine.match_intersect(trade(spark, d).adjacency(), trade_pattern("two_tri")).select("m0", "m1", "m2", "m3", "m4")


# --- monitoring --------------------------------------------------------------------------------
@query("answers_at_t", _rows_sql("born <= 30000 AND died > 30000", o.MIXED))
def answers_at_t(spark, d):
    return _text(refine.answers_at(refine.lifetimes(trade_mixed(spark, d), CORE), 30000))


@query("delta_at_t", o.with_(o.TRADE, o.MIXED, o.ADJ, f"a AS ({o.match_select(trade_pattern('star3'))}),\n", select="SELECT m0, m1, m2, m3, born AS t, 1 AS change FROM a WHERE born > 20000 AND born <= 40000 UNION ALL SELECT m0, m1, m2, m3, died, -1 FROM a WHERE died > 20000 AND died <= 40000"))
def delta_at_t(spark, d):
    rows = refine.delta_at(refine.lifetimes(trade_mixed(spark, d), Patterns([trade_pattern("star3")])), 20000, 40000)
    return rows.select(*[F.col("m")[i].alias(f"m{i}") for i in range(4)], "t", "change")


@query("delta_insert_only", _rows_sql("born > 0"))
def delta_insert_only(spark, d):
    g = trade(spark, d)
    cand = materialise(monitor.peak_candidates(g, CORE, D, 0, ALIVE - 1), "peak")
    return _text(monitor.on_insert(g, CORE, 0, ALIVE - 1, cand, counts=candidate_counts(cand)).select("query_id", "m"))


@query("delta_delete_only", _rows_sql(f"died < {ALIVE}", o.DELETED))
def delta_delete_only(spark, d):
    return _text(monitor.lost(trade_deleted(spark, d), CORE, 0, ALIVE - 1).select("query_id", "m"))


_RELABEL = ("ch AS (SELECT v, label % 16 + 1 AS nl FROM tv WHERE v % 100 = 8),\n", f"vl AS (SELECT tv.v, tv.label, 0 AS born, CASE WHEN nl IS NULL THEN {ALIVE} ELSE 500 END AS died FROM tv LEFT JOIN ch ON ch.v = tv.v UNION ALL SELECT v, nl, 500, {ALIVE} FROM ch),\n", "adj2 AS (SELECT src, dst, elabel, greatest(adj.born, p.born, q.born) AS born, least(adj.died, p.died, q.died) AS died, p.label AS sl, q.label AS dl FROM adj JOIN vl p ON p.v = src JOIN vl q ON q.v = dst WHERE greatest(adj.born, p.born, q.born) < least(adj.died, p.died, q.died)),\n")


@query("delta_label_change", o.with_(BASE, *_RELABEL, select=o.match_select(trade_pattern("star3"), source="adj2")))
def delta_label_change(spark, d):
    g = trade(spark, d)
    changes = g.vertices.filter("v % 100 = 8").select("v", (F.col("label") % 16 + 1).alias("newlabel"), F.lit(500).cast("long").alias("t"))
    moved = Graph(g.vertices, g.edge_life, split_label(g.vertices, changes))
    return refine.match_static(moved.adjacency(), trade_pattern("star3")).select("m0", "m1", "m2", "m3", "born", "died")


@query("monitor_label_change", o.with_(BASE, *_RELABEL, select=" UNION ALL ".join(f"SELECT {q} AS query_id, concat_ws(',', {', '.join(f'm{i}' for i in range(len(p.labels)))}) AS m, born, died FROM ({o.match_select(p, source='adj2')})" for q, p in CORE)))
def monitor_label_change(spark, d):
    """Insertions and label changes go through the monitor in one epoch; every answer with its life."""
    g = trade(spark, d)
    m = monitor.Monitor(g.edge_life.filter("born = 0").select("u", "v", "elabel"), g.vertices, CORE, known=True)
    ops = g.edge_life.filter("born > 0").select(F.col("born").alias("seq"), F.lit(None).cast("timestamp").alias("ts"), F.lit("+").alias("op"), "u", "v", "elabel")
    m.apply(ops, g.vertices.filter("v % 100 = 8").select("v", (F.col("label") % 16 + 1).alias("newlabel"), F.lit(500).cast("long").alias("t")))
    return _text(m.state)


_PAIRS = [(q, e[i], e[1 - i]) for q, p in CORE for e in p.edges for i in (0,)]


@query("edge_group_pairs", o.with_(FULL, "qp(query_id, qi, qj) AS (VALUES " + ", ".join(map(str, _PAIRS)) + "),\n", "up AS (SELECT u, v FROM el WHERE born > 0 UNION SELECT v, u FROM el WHERE born > 0),\n",
 select="SELECT qp.query_id, qi, qj, up.u, up.v FROM up JOIN star a ON a.v = up.u JOIN star b ON b.v = up.v JOIN qp ON TRUE JOIN qe x ON x.query_id = qp.query_id AND x.qv = qi AND x.label = a.label JOIN qe y ON y.query_id = qp.query_id AND y.qv = qj AND y.label = b.label WHERE " + " AND ".join(f"x.q{k} <= a.e{k} AND y.q{k} <= b.e{k}" for k in D.dims)))
def edge_group_pairs(spark, d):
    g = trade(spark, d)
    return batchgroups.edge_group_pairs(g.edge_life.filter("born > 0"), index(spark, d).star, CORE, D)[1]


@query("monitor_epochs", _rows_sql("born <= 0 OR born > 0"))
def monitor_epochs(spark, d):
    """The monitor fed with the insertions in two epochs ends with the answers of the whole graph."""
    g = trade(spark, d)
    start = g.edge_life.filter("born = 0").select("u", "v", "elabel")
    m = monitor.Monitor(start, g.vertices, CORE)
    ops = g.edge_life.filter("born > 0").select(F.col("born").alias("seq"), F.lit(None).cast("timestamp").alias("ts"), F.lit("+").alias("op"), "u", "v", "elabel")
    low, high = ops.agg(F.min("seq"), F.max("seq")).first()
    mid = (low + high) // 2
    m.apply(ops.filter(F.col("seq") <= mid))
    m.apply(ops.filter(F.col("seq") > mid))
    return _text(m.answers())


# --- baselines ---------------------------------------------------------------------------------
@query("bl_recompute", o.with_(BASE, f"a AS ({o.match_select(trade_pattern('triangle'))}), n AS (SELECT max(seq) AS n FROM te),\n", select="SELECT m0, m1, m2, 1 AS change FROM a, n WHERE born > 0 AND born <= n"))
def bl_recompute(spark, d):
    g = trade(spark, d)
    n = g.edge_life.agg(F.max("born")).first()[0]
    rows = baselines.recompute_diff(g, trade_pattern("triangle"), [0, n // 20 * 19, n])
    return rows.select(*[F.col("m")[i].alias(f"m{i}") for i in range(3)], "change")


@query("bl_delta_join", _rows_sql("born > 0"))
def bl_delta_join(spark, d):
    return _text(baselines.delta_join(trade(spark, d), CORE, 0, ALIVE - 1).select("query_id", "m"))


@query("bl_partial_tree", o.with_(BASE, f"a AS ({o.match_select(trade_pattern('star3'))}),\n", select="SELECT m0, m1, m2, m3 FROM a WHERE born > 0"))
def bl_partial_tree(spark, d):
    rows = baselines.PartialTree(trade(spark, d), trade_pattern("star3")).advance(trade(spark, d), ALIVE - 1)
    return rows.select(*[F.col("m")[i].alias(f"m{i}") for i in range(4)])


for _kind in ("tree", "dag"):

    def _idx(spark, d, kind=_kind):
        return baselines.indexed_answers(trade(spark, d), trade_pattern("tri_tail"), None, kind).select(*[F.col("m")[i].alias(f"m{i}") for i in range(4)])

    query(f"bl_{_kind}_index", o.with_(BASE, select=f"SELECT m0, m1, m2, m3 FROM ({o.match_select(trade_pattern('tri_tail'))})"))(_idx)


for _kind in ("tree", "dag"):

    def _kept(spark, d, kind=_kind):
        rows = baselines.KeptIndex(trade(spark, d), trade_pattern("tri_tail"), kind).advance(trade(spark, d), ALIVE - 1)
        return rows.select(*[F.col("m")[i].alias(f"m{i}") for i in range(4)])

    query(f"bl_{_kind}_kept", o.with_(BASE, f"a AS ({o.match_select(trade_pattern('tri_tail'))}),\n", select="SELECT m0, m1, m2, m3 FROM a WHERE born > 0"))(_kept)


@query("bl_acyclic", o.with_(BASE, select=f"SELECT m0, m1, m2, m3 FROM ({o.match_select(trade_pattern('path4'), 'homo')})"))
def bl_acyclic(spark, d):
    return baselines.acyclic_reduce(trade(spark, d).adjacency(), trade_pattern("path4")).select("m0", "m1", "m2", "m3")


@query("bl_learned")
def bl_learned(spark, d):
    ix = index(spark, d)
    return learned_dominance(ix.hist, ix.star, CORE)


# --- cost --------------------------------------------------------------------------------------
def _cost_sql(form: str) -> str:
    product = "n::DOUBLE"
    for k in D.dims:
        t = f"((mu{k} - q{k}) / 65536.0 / (var{k} / 65536.0 / 65536.0))" if form == "printed" else f"((mu{k} - q{k}) / sqrt(var{k}))"
        product += f" * {normal_cdf(t)}"
    m = ", ".join(f"avg(e{k}) AS mu{k}, var_pop(e{k}::DOUBLE) AS var{k}" for k in D.dims)
    return o.with_(FULL, f"mo AS (SELECT count(*) AS n, {m} FROM star),\n", select=f"SELECT query_id, qv, round({product}, 2) AS estimate FROM qe, mo")


for _form in ("printed", "standardised"):

    def _cost(spark, d, form=_form):
        return cost.cost_estimate(index(spark, d).star, CORE, D, form).withColumn("estimate", F.round("estimate", 2))

    query(f"cost_{_form}", _cost_sql(_form))(_cost)


@query("cost_calibration")
def cost_calibration(spark, d):
    star = index(spark, d).star
    return cost.calibration(cost.cost_estimate(star, CORE, D), prune.full_star_dominance(star, CORE, D)).select("query_id", "qv", F.round("estimate", 3).alias("estimate"), "actual", F.round("log2_ratio", 3).alias("log2_ratio"))


@query("dominance_region", o.with_(FULL, select="SELECT v, e0 AS x, e2 AS y, (" + " AND ".join(f"q{k} <= e{k}" for k in D.dims) + ") AS dominates, s.label = q.label AS label_ok FROM star s, qe q WHERE query_id = 0 AND qv = 0"))
def dominance_region(spark, d):
    return cost.dominance_region(index(spark, d).star, CORE, 0, 0, D)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: all triangles of the trade graph with the time in which each is an answer."""
    return QUERIES["match_triangle"](spark, sf_dir)


# --- generators, streams and workloads -----------------------------------------------------------
def _mixed_sql(c: str, salt: int) -> str:
    s = f"((48271 * ({c}) % 2147483647 + {40692 * salt + 12345}) % 2147483647)"
    for _ in range(3):
        s = f"(({s} * {s} + 16807 * {s} + 1013904223) % 2147483647)"
    return f"({s} % 65536)"


_PLACES = "cv AS (SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS v, count(*) OVER () AS n FROM customer),\n"
_RING = _PLACES + "ring AS (SELECT v, n, j, (v + j) % n AS w FROM cv, (SELECT unnest([1, 2]) AS j)),\n"
_CHORD = f"allp AS (SELECT v, w FROM ring UNION ALL SELECT v, ({_mixed_sql('v * 8 + j', 21)} * 65536 + {_mixed_sql('v * 8 + j', 22)}) % n FROM ring WHERE {_mixed_sql('v * 8 + j', 23)} < 16384),\n"


@query("nws_edges_uni", o.with_(_RING, _CHORD, select="SELECT DISTINCT least(v, w) AS u, greatest(v, w) AS v FROM allp WHERE v <> w"))
def nws_edges_uni(spark, d):
    return synth.customers(spark, d).edge_life.select("u", "v")


@query("nws_labels_uni", o.with_(_PLACES, select=f"SELECT v, ({_mixed_sql('v', 1)} % 15 + 1)::INT AS label FROM cv"))
def nws_labels_uni(spark, d):
    return synth.customers(spark, d).vertices


@query("nws_labels_gau", o.with_(_PLACES, select=f"SELECT v, (({' + '.join(_mixed_sql('v', s) for s in (1, 2, 3, 4))}) * 15 // 262144 + 1)::INT AS label FROM cv"))
def nws_labels_gau(spark, d):
    return synth.customers(spark, d, dist="gau").vertices


@query("nws_labels_zipf")
def nws_labels_zipf(spark, d):
    return synth.customers(spark, d, dist="zipf").vertices.groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query("knn_edges", """WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
n AS (SELECT a.vec_id AS v, b.vec_id AS w, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.e, b.e) DESC, b.vec_id) AS r FROM e a JOIN e b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0)
SELECT DISTINCT least(v, w) AS u, greatest(v, w) AS v FROM n WHERE r <= 3""")
def knn_edges(spark, d):
    return views.knn(spark, d).edge_life.select("u", "v")


@query("users_updates", """SELECT event_id, least(p, user_id) AS u, greatest(p, user_id) AS v FROM (SELECT *, lag(user_id) OVER (ORDER BY ts, event_id) AS p FROM events WHERE event_type = 'purchase') WHERE p <> user_id""")
def users_updates(spark, d):
    return views.users_updates(spark, d).select("event_id", "u", "v")


@query("users_sessions", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def users_sessions(spark, d):
    ev = views.read(spark, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return streaming.user_sessions(ev).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("users_props", "SELECT event_type, count(*) AS n, count(json_extract_string(props, '$.k')) AS with_k FROM events GROUP BY 1")
def users_props(spark, d):
    ev = views.read(spark, d, "events")
    return ev.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.count(F.get_json_object("props", "$.k")).alias("with_k"))


@query("stream_rate_tumbling", o.with_(o.TRADE, o.MIXED.replace("SELECT seq * 4 AS seq, '+' AS op", "SELECT ts, seq * 4 AS seq, '+' AS op").replace("UNION ALL SELECT seq", "UNION ALL SELECT ts, seq"), select="SELECT strftime(ts, '%Y-%m-%d') AS day, op, count(*) AS n FROM ops GROUP BY 1, 2"))
def stream_rate_tumbling(spark, d):
    ops = views.mixed_updates(edges_of(spark, d))
    return streaming.update_rates(ops).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "op", "n")


@query("sample_patterns")
def sample_patterns(spark, d):
    return synth.sample_patterns(trade(spark, d), 10).q_vertex(spark)


@query("adversarial_a1")
def adversarial_a1(spark, d):
    g = trade(spark, d)
    return prune.candidates(index(spark, d), synth.adversarial(g, CORE, "absent"))


@query("adversarial_a2")
def adversarial_a2(spark, d):
    g = trade(spark, d)
    return prune.label_only(index(spark, d).star, synth.adversarial(g, CORE, "heavy"))


# --- workloads: what each method finds (times are in workloads.py) ---------------------------------
RATES = (10, 20, 30, 40, 50)


def _rate_sql(life: str, old: str, new: str, condition: str) -> str:
    """percent, query_id, n over the rates: the stream's SQL once per rate."""
    parts = []
    for r in RATES:
        some = life.replace(old, new.format(r))
        assert some != life or r == 10
        names = o.with_(o.TRADE, some, o.ADJ, select="")
        cells = " UNION ALL ".join(f"SELECT {r} AS percent, {q} AS query_id, count(*) AS n FROM ({o.match_select(p)}) WHERE {condition}" for q, p in CORE)
        parts.append(f"SELECT * FROM ({names} {cells})")
    return " UNION ALL ".join(parts)


def _counted(df: DataFrame, percent: int) -> DataFrame:
    every = df.sparkSession.createDataFrame([(q,) for q, _ in CORE], "query_id int")
    n = df.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return every.join(n, "query_id", "left").select(F.lit(percent).alias("percent"), "query_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def _arriving(spark, d) -> tuple[DataFrame, Graph, DataFrame, int]:
    """Vertices, the stream of the largest rate, its rows that the patterns can use (written), and the number of all edges. An
    edge arrives at the same seq at every rate at which it is not there from the start, so the smaller rates read the same rows."""

    def make():
        vertices = materialise(views.trade_vertices(spark, d), "vertices")
        pairs, days = views.trade_pairs(spark, d, _all_lines)
        n = days.agg(F.max("_upto")).first()[0] or 0
        g = views.insertions_by_day(vertices, pairs, days, max(RATES), "trade")
        near = refine.known_relevant(materialise(refine.relevant_of(g, CORE), "relevant", by=("src_label", "dst_label")), CORE)
        refine.fanouts(near, *CORE.items)
        return vertices, g, near, n

    return once(spark, d, "arriving", make)


def _inserted(spark, d, percent: int) -> tuple[Graph, DataFrame]:
    """The graph of ``insertion_stream`` at a rate, and its rows that the patterns can use (see ``refine.relevant``)."""
    vertices, g, near, n = _arriving(spark, d)
    life = views.fewer_arrive(g.edge_life, n, percent)
    return Graph(vertices.select("v", "label"), life, name="trade"), refine.known_relevant(views.fewer_arrive(near, n, percent), CORE, near)


def _over_rates(make) -> DataFrame:
    """A rate's few rows are written before the next rate's plan is made, so the driver holds one rate's plan."""
    out = None
    for r in RATES:
        rows = materialise(_counted(make(r), r), "rate", rows=len(CORE))
        drop_shuffles(rows.sparkSession)
        out = rows if out is None else out.unionAll(rows)
    return out


@query("wl_insert_rates", _rate_sql(o.LIFE, "* 90", "* (100 - {})", "born > 0"))
def wl_insert_rates(spark, d):
    """New answers at 10 to 50 percent insertions, by the method."""

    def one(r):
        g, adj = _inserted(spark, d, r)
        cand = materialise(monitor.peak_candidates(g, CORE, D, 0, ALIVE - 1, adj), "peak")
        return monitor.on_insert(g, CORE, 0, ALIVE - 1, cand, counts=candidate_counts(cand), adj=adj)

    return _over_rates(one)


@query("wl_insert_rates_delta_join", _rate_sql(o.LIFE, "* 90", "* (100 - {})", "born > 0"))
def wl_insert_rates_delta_join(spark, d):
    def one(r):
        g, adj = _inserted(spark, d, r)
        return baselines.delta_join(g, CORE, 0, ALIVE - 1, adj)

    return _over_rates(one)


@query("wl_delete_rates", _rate_sql(o.DELETED, "% 100 < 10", "% 100 < {}", f"died < {ALIVE}"))
def wl_delete_rates(spark, d):
    """Answers lost at 10 to 50 percent deletions."""

    def one(r):
        g = views.deletion_stream(views.trade_vertices(spark, d), stored_edges(spark, d), r, "trade_del").stored()
        return monitor.lost(g, CORE, 0, ALIVE - 1, "levels")

    return _over_rates(one)


_MANY = 10


@query("wl_concurrent_patterns", o.with_(BASE, select=" UNION ALL ".join(f"SELECT {q} + {len(CORE)} * i AS query_id, n FROM (SELECT count(*) AS n FROM ({o.match_select(p)})), (SELECT unnest(range({_MANY}))::INT AS i)" for q, p in CORE)))
def wl_concurrent_patterns(spark, d):
    """Fifty patterns in one plan."""
    many = Patterns(CORE.items * _MANY)
    n = refine.lifetimes(trade(spark, d), many, "levels").groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return spark.createDataFrame([(q,) for q, _ in many], "query_id int").join(n, "query_id", "left").select("query_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


# --- whole tables --------------------------------------------------------------------------------
#: Queries that read no line item, and the one that reads all of them already.
NO_LINES = ("trade_vertices", "trade_edges", "trade_full_edges", "query_embedding", "label_vec_", "base_vec_", "nws_", "knn_", "users_")


def _full_query(name: str, first_lines: Query):
    sql = ORACLES[name].replace("WHERE l_linenumber = 1", "") if name in ORACLES else None

    @query(f"full_{name}", sql)
    def run(spark, d):
        with all_lines():
            return first_lines(spark, d)


for _n, _f in list(QUERIES.items()):
    if not _n.startswith(NO_LINES):
        _full_query(_n, _f)
