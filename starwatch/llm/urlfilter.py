"""URL filter: host and path rules first, then gradient-boosted trees on lexical features.

The labels are the rules' verdicts, or a caller's own. The trees are learned on the driver from a bounded sample
of labelled URLs, and applied as plain column expressions. Suffix statistics are counted over all labelled rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .heavy import join_back
from .storage import free, materialise

#: The rules of the result contract, (verdict, rule).
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
TRAIN_ROWS = 20_000
FOLDS = 5
FEATURES = ("url_length", "host_length", "path_length", "depth", "digit_ratio", "entropy", "n_params", "host_hyphens", "host_labels", "has_fragment", "suffix_rate", "suffix_weight")
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict (both null without one)."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, text in sorted(rules, key=lambda r: len(r[1])):
        h, _, p = text.partition("/")
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit("/" + p))
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def lexical(rows: DataFrame) -> DataFrame:
    """``rows`` (url, host, path, ...) with the lexical features that need no statistics."""
    url = F.coalesce(F.col("url"), F.lit(""))
    n = F.length(url)
    query = F.regexp_extract(url, r"\?([^#]*)", 1)
    share = "((length(u) - length(replace(u, c, ''))) / length(u))"
    entropy = F.expr(f"aggregate(array_distinct(split(u, '')), 0D, (s, c) -> CASE WHEN c = '' THEN s ELSE s - {share} * log2({share}) END)")
    return rows.withColumn("u", url).withColumns({
        "url_length": n.cast("double"),
        "host_length": F.length("host").cast("double"),
        "path_length": F.length("path").cast("double"),
        "depth": F.size(F.filter(F.split("path", "/"), lambda x: x != "")).cast("double"),
        "digit_ratio": F.when(n > 0, (n - F.length(F.translate(url, "0123456789", ""))) / n).otherwise(0.0),
        "entropy": F.when(n > 0, entropy).otherwise(0.0),
        "n_params": F.when(query == "", 0).otherwise(F.size(F.split(query, "&"))).cast("double"),
        "host_hyphens": (F.length("host") - F.length(F.replace("host", F.lit("-"), F.lit("")))).cast("double"),
        "host_labels": F.size(F.split("host", r"\.")).cast("double"),
        "has_fragment": F.contains(url, F.lit("#")).cast("double"),
        "suffix": F.element_at(F.split("host", r"\."), -1),
    }).drop("u")


def with_suffix_rates(rows: DataFrame) -> DataFrame:
    """Adds the block rate of the host's suffix over labelled rows, smoothed by two rows of an even
    rate, and the logarithm of their count. A labelled row's own fold (by its URL) is left out of both, so
    that no row's rate holds its own label. A written table."""
    rows = rows.withColumn("_fold", F.when(F.col("label").isNotNull(), F.pmod(F.xxhash64("url", F.lit("fold")), F.lit(FOLDS)).cast("int")))
    parts = [x for f in range(FOLDS) for x in (F.count_if(F.col("_fold") == f).alias(f"_n{f}"), F.coalesce(F.sum(F.when(F.col("_fold") == f, F.col("label"))), F.lit(0)).alias(f"_k{f}"))]
    table = materialise(rows.groupBy("suffix").agg(F.count(F.lit(1)).alias("_rows"), *parts), "url-suffixes")
    out = join_back(rows, table, "suffix", "_rows", F.xxhash64("page_id", "url"))
    n, k = (sum((F.when(F.col("_fold").eqNullSafe(F.lit(f)), 0).otherwise(F.col(f"_{x}{f}")) for f in range(FOLDS)), F.lit(0)) for x in "nk")
    out = out.withColumn("suffix_rate", F.coalesce((k + 1) / (n + 2), F.lit(0.5))).withColumn("suffix_weight", F.coalesce(F.log2(n + 1), F.lit(0.0)))
    out = materialise(out.drop("_fold", *[f"_{x}{f}" for f in range(FOLDS) for x in "nk"]), "url-features")
    free(table)
    return out


class BoostedTrees:
    """Logistic gradient boosting of shallow trees over binned features."""

    def __init__(self, trees: int = 40, depth: int = 3, rate: float = 0.2, bins: int = 32, ridge: float = 1.0, least: int = 5):
        self.n_trees, self.depth, self.rate, self.bins, self.ridge, self.least = trees, depth, rate, bins, ridge, least
        self.base = 0.0
        self.trees: list[dict] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        share = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
        self.base = float(np.log(share / (1 - share)))
        cuts = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) if len(c) else np.zeros(0) for c in x.T]
        binned = np.stack([np.searchsorted(cut, c, side="right") for cut, c in zip(cuts, x.T, strict=True)], axis=1)
        total = np.full(len(y), self.base)
        for _ in range(self.n_trees if len(y) else 0):
            p = 1 / (1 + np.exp(-total))
            tree = self._grow(binned, cuts, p - y, p * (1 - p), np.arange(len(y)), self.depth)
            self.trees.append(tree)
            total += self._apply(tree, x)
        return self

    def _grow(self, binned, cuts, g, h, rows, depth) -> dict:
        gs, hs = g[rows].sum(), h[rows].sum()
        leaf = {"value": float(-self.rate * gs / (hs + self.ridge))}
        if depth == 0 or len(rows) < 2 * self.least:
            return leaf
        best = (1e-6, -1, 0)
        for f, cut in enumerate(cuts):
            if not len(cut):
                continue
            b = binned[rows, f]
            gl = np.cumsum(np.bincount(b, g[rows], len(cut) + 1))[:-1]
            hl = np.cumsum(np.bincount(b, h[rows], len(cut) + 1))[:-1]
            nl = np.cumsum(np.bincount(b, minlength=len(cut) + 1))[:-1]
            gain = gl**2 / (hl + self.ridge) + (gs - gl) ** 2 / (hs - hl + self.ridge) - gs**2 / (hs + self.ridge)
            gain[(nl < self.least) | (len(rows) - nl < self.least)] = -1
            i = int(gain.argmax())
            if gain[i] > best[0]:
                best = (float(gain[i]), f, i)
        if best[1] < 0:
            return leaf
        _, f, i = best
        left = binned[rows, f] <= i
        return {"feature": f, "cut": float(cuts[f][i]), "low": self._grow(binned, cuts, g, h, rows[left], depth - 1), "high": self._grow(binned, cuts, g, h, rows[~left], depth - 1)}

    def _apply(self, tree: dict, x: np.ndarray) -> np.ndarray:
        if "value" in tree:
            return np.full(len(x), tree["value"])
        return np.where(x[:, tree["feature"]] < tree["cut"], self._apply(tree["low"], x), self._apply(tree["high"], x))

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.base + sum((self._apply(t, x) for t in self.trees), np.zeros(len(x)))

    def expression(self, names=FEATURES) -> str:
        """The margin as SQL over the feature columns."""

        def walk(t: dict) -> str:
            if "value" in t:
                return f"{t['value']!r}D"
            return f"CASE WHEN {names[t['feature']]} < {t['cut']!r}D THEN {walk(t['low'])} ELSE {walk(t['high'])} END"

        return " + ".join([f"{self.base!r}D", *(f"({walk(t)})" for t in self.trees)])


def rule_labels(rows: DataFrame) -> Column:
    """1 (block) or 0 (allow) by the rule's verdict; URLs without a rule are unlabelled."""
    return (rows.rule_verdict == "block").cast("int")


def training_rows(rows: DataFrame, train_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of about ``train_rows`` labelled rows, chosen by a hash of the URL and in a fixed order."""
    n = rows.filter("label IS NOT NULL").count()
    dice = F.pmod(F.xxhash64("url", F.lit("train")), F.lit(1 << 30)) / float(1 << 30)
    got = rows.filter(F.col("label").isNotNull() & (dice < min(1.0, train_rows / max(1, n)))).select("url", "label", *FEATURES).collect()
    got.sort()
    return np.array([r[2:] for r in got], float).reshape(-1, len(FEATURES)), np.array([r[1] for r in got], float)


def learn(rows: DataFrame, train_rows: int = TRAIN_ROWS) -> BoostedTrees | None:
    x, y = training_rows(rows, train_rows)
    return BoostedTrees().fit(x, y) if len(y) else None


def judge_urls(pages: DataFrame, rules=RULES, labels=rule_labels, train_rows: int = TRAIN_ROWS, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, score and verdict of every row.

    ``labels`` gives the label column (1 block, 0 allow, null unlabelled) from url, host, path and rule_verdict;
    about ``train_rows`` labelled rows, chosen by a hash of the URL, train the trees. A null URL, or
    one without ``://``, has an empty host and path and no rule. With no labelled row all
    URLs without a rule are allowed. Repeated rows and null ids are kept as they are; an
    empty table gives an empty result; other columns are not read.
    """
    rows = pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].alias("url"))
    rows = rows.withColumn("host", host_of(F.col("url"))).withColumn("path", path_of(F.col("url")))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("rule_verdict", verdict)
    rows = with_suffix_rates(lexical(rows.withColumn("label", labels(rows))))
    trees = learn(rows, train_rows)
    out = rows.withColumn("margin", F.expr(trees.expression() if trees else "-1D"))
    method = F.when(F.col("margin") > 0, "block").otherwise("allow")
    return out.select("page_id", "host", "path", "rule", (1 / (1 + F.exp(-F.col("margin")))).alias("score"), F.coalesce("rule_verdict", method).alias("verdict"))


def op3_boosted_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "host", "path", "rule", "verdict", F.round("score", 6).alias("score"))


QUERIES = {"op3_boosted_urls": op3_boosted_urls}
ORACLES: dict[str, str] = {}
