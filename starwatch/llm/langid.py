"""Language identification in two steps: the family first, then linear support vector
machines, one for each pair of languages of that family.

Features are relative frequencies of hashed three-byte strings of the lower-cased text, with
everything but letters taken as a blank. A linear model's score of a text is
then the mean of its weights over the text's places, whatever its length.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import small_batches
from .wordhash import groups

LOG_BUCKETS = 12
MAX_LANGUAGES = 200  # the most frequent ones are learned
FAMILY_ROWS = 10_000  # rows a family's model is learned from, at most
PER_LANGUAGE = 600  # labelled documents a language is learned from, about
SNIPPET_BYTES = 160
SCALE = 50.0
#: Families of common languages; any other language is a family of its own.
FAMILIES = {
    "germanic": ("en", "de", "nl", "sv", "da", "no", "nb", "nn", "is", "af"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca", "gl"),
    "slavic": ("ru", "uk", "be", "pl", "cs", "sk", "bg", "sr", "hr", "sl", "mk"),
    "indic": ("hi", "mr", "ne", "bn", "gu", "pa"),
}
_FAMILY_OF = {lang: family for family, langs in FAMILIES.items() for lang in langs}
_FOLD = np.full(256, 0x20, np.uint8)
_FOLD[0x80:] = np.arange(0x80, 0x100)
for _c in range(0x61, 0x7B):
    _FOLD[_c] = _FOLD[_c - 32] = _c


def family_of(lang: str) -> str:
    return _FAMILY_OF.get(lang, lang)


def places(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of every three-byte string of the texts, end to end, and where each text's begin.

    Strings of blanks only are left out, and a blank stands at either end of a text."""
    raw = _FOLD[np.frombuffer(b"  " + b"  ".join(texts) + b"  ", np.uint8)].astype(np.uint32)
    code = raw[:-2] | (raw[1:-1] << np.uint32(8)) | (raw[2:] << np.uint32(16))
    begin = np.concatenate(([0], np.cumsum([len(t) + 2 for t in texts]))).astype(np.int64)
    keep = (code != 0x202020) & ((code >> np.uint32(8)) != 0x2020)
    before = np.concatenate(([0], np.cumsum(keep)))
    at = code[keep] * np.uint32(0x9E3779B1)
    return (at >> np.uint32(32 - LOG_BUCKETS)).astype(np.int32), before[np.minimum(begin, len(keep))]


def train_svm(x: np.ndarray, y: np.ndarray, decay: float = 1e-4, rounds: int = 120) -> tuple[np.ndarray, float]:
    """Linear support vector machine, squared hinge, by accelerated gradient steps (y is +1 or -1)."""
    n = len(y)
    weight = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum())).astype(np.float32)
    v = np.full(x.shape[1], 1 / np.sqrt(x.shape[1]), np.float32)
    for _ in range(8):  # the largest curvature, by power iteration
        v = x.T @ (weight * (x @ v)) + np.float32(1e-12)
        top = float(np.linalg.norm(v))
        v /= top
    step = 1 / (2 * (top + 1) + decay)
    w, b = np.zeros(x.shape[1], np.float32), 0.0
    pw, pb = w.copy(), b
    for t in range(1, rounds + 1 if n else 1):
        m = t / (t + 3)
        zw, zb = w + m * (w - pw), b + m * (b - pb)
        pw, pb = w, b
        slack = np.maximum(0, 1 - y * (x @ zw + zb)) * y * weight
        w = (zw - step * (decay * zw - 2 * (x.T @ slack))).astype(np.float32)
        b = float(zb + step * 2 * slack.sum())
    return w, b


class Model:
    """Weights of all linear models side by side: families one against the rest, languages by pair."""

    def __init__(self, langs: list[str], rows: list[tuple[str, bytes, bytes]]):
        self.langs = langs
        self.families = sorted({family_of(x) for x in langs})
        lang = np.array([r[0] for r in rows])
        fam = np.array([family_of(r[0]) for r in rows])
        weights, bias = [], []

        def fit(some: np.ndarray, positive: np.ndarray) -> None:
            x = np.zeros((len(some), 1 << LOG_BUCKETS), np.float32)  # of a bounded number of rows
            for i, j in enumerate(some):
                x[i, np.frombuffer(rows[j][1], "<u2")] = np.frombuffer(rows[j][2], "<f4") * SCALE
            w, b = train_svm(x, np.where(positive[some], 1.0, -1.0).astype(np.float32))
            weights.append(w * SCALE)
            bias.append(b)

        # a family against all others: evenly spaced rows of each side, half of FAMILY_ROWS at most
        def spread(some: np.ndarray) -> np.ndarray:
            return some[np.linspace(0, len(some) - 1, min(len(some), FAMILY_ROWS // 2)).astype(int)]

        self.family_models = self.families if len(self.families) > 2 else self.families[:1] if len(self.families) == 2 else []
        for f in self.family_models:
            fit(np.concatenate((spread(np.flatnonzero(fam == f)), spread(np.flatnonzero(fam != f)))), fam == f)
        self.pairs = [(a, b) for f in self.families for a, b in combinations([x for x in langs if family_of(x) == f], 2)]
        for a, b in self.pairs:
            fit(np.flatnonzero((lang == a) | (lang == b)), lang == a)
        self.weights = np.array(weights, np.float32).reshape(-1, 1 << LOG_BUCKETS)
        self.bias = np.array(bias, np.float32)

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Language and score (0 to 1) of each text."""
        raw = [(t or "").lower().encode() for t in texts]
        at, begin = places(raw)
        n = np.diff(begin)
        margin = np.zeros((len(self.bias), len(texts)), np.float64)
        for i, w in enumerate(self.weights):
            total = np.concatenate(([0.0], np.cumsum(w[at], dtype=np.float64)))
            margin[i] = (total[begin[1:]] - total[begin[:-1]]) / np.maximum(n, 1) + self.bias[i]
        sure = 1 / (1 + np.exp(-4 * np.clip(margin, -50, 50)))
        k = len(self.family_models)
        if k == 1:
            family = np.where(margin[0] >= 0, 0, 1)
            score = np.maximum(sure[0], 1 - sure[0])
        elif k:
            family = margin[:k].argmax(axis=0)
            score = sure[:k].max(axis=0)
        else:
            family, score = np.zeros(len(texts), int), np.ones(len(texts))
        lang = np.array([""] * len(texts), object)
        for f, name in enumerate(self.families):
            mine = np.flatnonzero(family == f)
            own = [x for x in self.langs if family_of(x) == name]
            votes, sums, pairs = ({x: np.zeros(len(mine)) for x in own} for _ in range(3))
            for i, (a, b) in enumerate(self.pairs, k):
                if a in votes:
                    win, p = margin[i, mine] >= 0, sure[i, mine]
                    votes[a] += win
                    votes[b] += ~win
                    for x, q in ((a, p), (b, 1 - p)):
                        sums[x] += q
                        pairs[x] += 1
            rank = np.array([votes[x] + sums[x] / (len(own) + 1) for x in own])
            best = rank.argmax(axis=0)
            part = np.array([sums[x] / np.maximum(1, pairs[x]) if len(own) > 1 else np.ones(len(mine)) for x in own])
            lang[mine] = np.array(own, object)[best]
            score[mine] *= part[best, np.arange(len(mine))]
        for i, t in enumerate(texts):
            if t is None or not any(map(str.isalpha, t)):
                lang[i], score[i] = "und", 0.0
        return lang.tolist(), np.clip(score, 0, 1)


def held_out(id_col: Column) -> Column:
    """Whether a document is kept from learning: crc32 of its id as text, modulo 3, is 1."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def learn(docs: DataFrame, per_language: int = PER_LANGUAGE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model | None:
    """Learn from a sample of about ``per_language`` labelled documents of each language.

    The sample is bounded by that parameter whatever the table's size; a document is in it by a
    hash of its id, against its language's share. Of more than MAX_LANGUAGES values the most frequent are learned. Each gives its whole text and a short piece.
    """
    small_batches(docs.sparkSession)
    usable = docs.filter(docs[id_col].isNotNull() & ~held_out(docs[id_col]) & docs[lang_col].isNotNull() & docs[text_col].isNotNull())
    common = usable.groupBy(lang_col).count().orderBy(F.desc("count"), lang_col).limit(MAX_LANGUAGES)
    counts = {r[0]: r[1] for r in common.collect()}
    if not counts:
        return None
    share = F.create_map(*[F.lit(v) for lang, n in sorted(counts.items()) for v in (lang, min(1.0, per_language / n))])
    dice = F.pmod(F.xxhash64(usable[id_col].cast("string"), F.lit("sample")), F.lit(1 << 30)) / float(1 << 30)
    sample = usable.filter(usable[lang_col].isin(sorted(counts))).filter(dice < share[usable[lang_col]]).select(usable[lang_col].alias("lang"), usable[text_col].alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if not any(map(str.isalpha, text)):
                    continue
                raw = text.lower().encode()
                cut = len(raw) // 3 if len(raw) > 3 * SNIPPET_BYTES else 0
                for part in (raw, raw[cut : cut + SNIPPET_BYTES]):
                    at, _ = places([part])
                    if len(at):
                        n = np.bincount(at, minlength=1 << LOG_BUCKETS) / len(at)
                        some = np.flatnonzero(n)
                        out.append((lang, some.astype("<u2").tobytes(), n[some].astype("<f4").tobytes()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), (pa.string(), pa.binary(), pa.binary()), strict=True)], names=["lang", "at", "n"])

    rows = [(r[0], bytes(r[1]), bytes(r[2])) for r in sample.mapInArrow(run, "lang string, at binary, n binary").collect()]
    rows.sort()
    return Model(sorted({r[0] for r in rows}), rows) if rows else None


def identify(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred and score of every row.

    ``und`` (score 0) for a null text, one without a letter, or when nothing was learned.
    Repeated rows and null ids are kept as they are (a null id is not held out); an empty table gives an
    empty result; other columns are not read.
    """
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), held_out(docs[id_col]).alias("held_out"), docs[text_col].alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lang, score = _judge(sent.value, batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def _judge(model: Model | None, texts: list[str | None]) -> tuple[list[str], list[float]]:
    langs: list[str] = []
    scores: list[float] = []
    if model is None:
        return ["und"] * len(texts), [0.0] * len(texts)
    for some in groups([len(t or "") for t in texts]):
        a, b = model.predict(texts[some])
        langs += a
        scores += b.tolist()
    return langs, scores


def keep_identified(docs: DataFrame, model: Model | None, text_col: str = "text") -> DataFrame:
    """``docs`` without the rows whose language is undetermined; all columns pass through."""
    at = docs.columns.index(text_col)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lang, _ = _judge(sent.value, batch.column(at).to_pylist())
            yield batch.filter(pa.array([x != "und" for x in lang], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, learn(docs))


QUERIES = {"op4_language_id": op4_language_id}
ORACLES: dict[str, str] = {}
