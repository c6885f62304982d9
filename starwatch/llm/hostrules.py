"""Host-level quality rules.

Per-document rules give failures; failures are summed by host, each host's rate is shrunk
with an empirical beta prior fitted to all hosts, and the hosts' verdicts are joined back.
Native: DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .heavy import join_back
from .storage import materialise

BLANK = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
MAX_HOST_RATE = 0.5
_INDEX_BITS = 20


def _length(c: Column) -> Column:
    return F.length(c).cast("long")


def document_rules(docs: DataFrame, id_col: str, text_col: str, host_col: str) -> DataFrame:
    """doc_id, host, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed.

    Repeated three-word windows are found inside the row: 64-bit hashes of the windows,
    with the place in the low bits, are sorted as plain longs; equal neighbours are
    repeats. Where a shortened hash meets one of other words (or the text is too long for
    the place bits), the row takes the slower path that sorts the words themselves.
    """
    raw = F.coalesce(F.col(text_col), F.lit(""))
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(host_col).cast("string").alias("host"), raw.alias("text"))
    trimmed = F.btrim(F.col("text"), F.lit(BLANK))
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(F.btrim(x, F.lit(BLANK))) > 0)
    counted = base.select(
        "doc_id", "host",
        _length(F.translate("text", BLANK, "")).alias("word_chars"),
        (_length(F.col("text")) - _length(F.translate("text", SYMBOLS, ""))).alias("n_symbols"),
        lines.alias("lines"),
        F.when(F.length(trimmed) > 0, F.split(trimmed, r"[\x20\x09-\x0D]+")).otherwise(F.array().cast("array<string>")).alias("w"),
    )
    counted = counted.select("doc_id", "host", "word_chars", "n_symbols", (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"), F.size("w").alias("n"), "w")
    place = (1 << _INDEX_BITS) - 1
    keys = F.expr(f"CASE WHEN n >= 3 AND n <= {place} THEN sort_array(transform(sequence(1, n - 2), i -> (shiftleft(xxhash64(get(w, i - 1), get(w, i), get(w, i + 1)), {_INDEX_BITS}) | i))) END")
    hashed = counted.withColumn("keys", keys)
    prefix = f"shiftright({{}}, {_INDEX_BITS})"
    twins = F.expr(
        f"filter(keys, (k, p) -> {prefix.format('k')} = {prefix.format('get(keys, p - 1)')} OR {prefix.format('k')} = {prefix.format('get(keys, p + 1)')})"
    )
    found = hashed.withColumn("twins", twins).drop("keys")

    def word(shift: int, at: str) -> str:
        return f"get(w, CAST(({at} & {place}) + {shift} AS INT))"

    differ = " OR ".join(f"{word(s, 't')} <> {word(s, 'get(twins, p - 1)')}" for s in (-1, 0, 1))
    clash = F.expr(f"exists(transform(twins, (t, p) -> p > 0 AND {prefix.format('t')} = {prefix.format('get(twins, p - 1)')} AND ({differ})), x -> x)")
    marked = found.withColumn("clash", F.coalesce(clash, F.col("n") >= 3))
    # the slow path: (words, place) sorted as structs
    whole = marked.withColumn("sorted", F.expr("CASE WHEN clash THEN array_sort(transform(sequence(1, n - 2), i -> struct(get(w, i - 1) AS a, get(w, i) AS b, get(w, i + 1) AS c, i AS i))) END"))
    same = "(x.a <=> {0}.a AND x.b <=> {0}.b AND x.c <=> {0}.c)"
    slow = F.expr(f"transform(filter(sorted, (x, p) -> {same.format('get(sorted, p - 1)')} OR {same.format('get(sorted, p + 1)')}), x -> x.i)")
    fast = F.expr(f"transform(twins, t -> CAST(t & {place} AS INT))")
    placed = whole.withColumn("at", F.sort_array(F.when(F.col("clash"), slow).otherwise(fast))).drop("w", "sorted", "twins")
    covered = F.expr("aggregate(transform(at, (a, p) -> CAST(least(3, coalesce(get(at, p + 1) - a, 3)) AS BIGINT)), 0L, (s, x) -> s + x)")
    out = placed.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0).cast("long"))).withColumn("n_words", F.col("n").cast("long"))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return out.select("doc_id", "host", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"))


def host_rates(rules: DataFrame) -> DataFrame:
    """host, n_docs, n_failed, shrunk_rate. The prior's two numbers come from the moments of the
    raw rates over all hosts; with one host, or rates that do not vary, it weighs two documents."""
    hosts = rules.filter(F.col("host").isNotNull()).groupBy("host").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(F.col("base_failed").cast("long")).alias("n_failed"))
    rate = F.col("n_failed") / F.col("n_docs")
    moments = hosts.agg(F.avg(rate).alias("mean"), F.var_pop(rate).alias("variance"))
    strength = F.when((F.col("variance") > 0) & (F.col("mean") * (1 - F.col("mean")) > F.col("variance")), F.col("mean") * (1 - F.col("mean")) / F.col("variance") - 1).otherwise(F.lit(2.0))
    prior = moments.select((F.col("mean") * strength).alias("alpha"), ((1 - F.col("mean")) * strength).alias("beta")).first()
    alpha, beta = (prior.alpha or 0.0, prior.beta or 2.0)
    return hosts.withColumn("shrunk_rate", (F.col("n_failed") + alpha) / (F.col("n_docs") + alpha + beta))


def judge_hosts(docs: DataFrame, max_rate: float = MAX_HOST_RATE, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """Rules per row, base_failed, host_rate, host_rejected and kept.

    A document is kept if it passes the base rules and its host's shrunk failure rate is at most
    ``max_rate``. A null text has no words (and fails); a null host has no verdict, its documents
    are judged alone. Repeated rows and null ids are rows of their own; an empty table gives an
    empty result; other columns are not read. Hosts that hold many of all documents are salted when joined back.
    """
    rules = materialise(document_rules(docs, id_col, text_col, host_col), "host-rules")
    verdicts = materialise(host_rates(rules).select("host", "n_docs", F.col("shrunk_rate").alias("host_rate")), "host-rates")
    joined = join_back(rules, verdicts, "host", "n_docs", F.xxhash64("doc_id", "word_chars"))
    rejected = F.coalesce(F.col("host_rate") > max_rate, F.lit(False))
    return joined.withColumn("host_rejected", rejected).withColumn("kept", ~F.col("base_failed") & ~F.col("host_rejected"))


def op6_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = judge_hosts(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS t, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
  list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM documents),
tri AS (SELECT r, s, [w[s], w[s + 1], w[s + 2]] AS g FROM (SELECT r, w, unnest(range(1, greatest(1, len(w) - 1))) AS s FROM d)),
rep AS (SELECT r, s FROM (SELECT *, count(*) OVER (PARTITION BY r, g) AS c FROM tri) WHERE c > 1),
cov AS (SELECT r, count(DISTINCT s + o) AS n FROM rep, (SELECT unnest(range(3)) AS o) GROUP BY r),
f AS (SELECT d.r, doc_id, source, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
  length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN cov USING (r)),
b AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM f),
h AS (SELECT source, count(*) AS n, count(*) FILTER (base_failed) AS k FROM b WHERE source IS NOT NULL GROUP BY source),
m AS (SELECT avg(k / n) AS m, var_pop(k / n) AS v FROM h),
p AS (SELECT m, CASE WHEN v > 0 AND m * (1 - m) > v THEN m * (1 - m) / v - 1 ELSE 2 END AS s FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT coalesce((k + m * s) / (n + s) > 0.5, false) AS kept
FROM b LEFT JOIN h USING (source), p
"""

QUERIES = {"op6_host_rules": op6_host_rules}
ORACLES = {"op6_host_rules": ORACLE}
