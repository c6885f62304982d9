"""Substring dedup: word windows that occur earlier are removed, with a count-min prefilter.

First pass: every window of ``width`` words is represented by its anchor, the smallest
hash among the shorter runs inside it. Equal windows have equal anchors, so a sketch
that counts the places of anchors (about a sixth of all places) overestimates the count of
every window. Second pass: only windows whose estimate is 2 or more are grouped, exactly, by a
128-bit hash of their words; a window that is not the first of its group is removed. No
repeated window can be lost; a full sketch only lets more windows through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .countmin import BLOCKS, Partial, SketchShape, at_least_twice, merge
from .storage import drop_shuffles, small_batches
from .wordhash import Words, byte_groups, mix, sliding, words_of

WIDTH = 20
FLUSH = 1_000_000
CELLS_PER_ANCHOR = 4  # rounded up to a power of two; at most about one unrepeated window in twenty passes
BYTES_PER_ANCHOR = 24  # anchors are a sixth of the words or so
LOG_WIDTHS = (20, 30)  # the smallest sketch, and the largest (256 MB as bits; each executor keeps a copy on disk)
NO_ID = -(1 << 63)


def _windows(words: Words, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each window of ``width`` words in one text: index of its first word, its anchor;
    and the run values with which of them are an anchor of some window."""
    run = max(1, width // 2)
    value, _ = words.runs(run)
    n = len(words.value) - width + 1
    if n <= 0:
        none = np.zeros(0, np.uint64)
        return np.zeros(0, np.int64), none, none, np.zeros(0, bool), none
    span = width - run + 1
    low = sliding(value, span, np.minimum)
    ok = words.doc[width - 1 :] == words.doc[:n]
    # a run is an anchor if some window over it, within its text, has it as the minimum
    seen = np.concatenate([np.zeros(span - 1, np.uint64), np.where(ok, low, np.uint64(0)), np.zeros(span - 1, np.uint64)])
    anchor = sliding(seen, span, np.maximum) >= value
    # (a maximum from a window of another text could only add an anchor, never hide one)
    return np.flatnonzero(ok), low, value, anchor, words.runs(width)[0]


def shape_for(docs: DataFrame, text_col: str = "text") -> SketchShape:
    """A sketch for the bytes of text there are, between the two ends of LOG_WIDTHS."""
    size = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    need = max(1, size // BYTES_PER_ANCHOR * CELLS_PER_ANCHOR)
    width = min(LOG_WIDTHS[1], max(LOG_WIDTHS[0], (need - 1).bit_length()))
    return SketchShape(2, width, min(22, width - 4))


def _sketch(docs: DataFrame, width: int, shape: SketchShape) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        partial = Partial(shape)

        def rows(block):
            return pa.RecordBatch.from_arrays([pa.array([b[0] for b in block], pa.int32()), pa.array([part] * len(block), pa.int64()), pa.array([b[1] for b in block], pa.binary()), pa.array([b[2] for b in block], pa.binary())], names=["tile", "part", "once", "twice"])

        for batch in batches:
            for _, texts in byte_groups(batch.column(1)):
                _, _, value, anchor, _ = _windows(words_of(texts), width)
                for block in partial.add(value[anchor]):
                    yield rows(block)
        block = partial.flush()
        if block:
            yield rows(block)

    return docs.mapInArrow(run, BLOCKS)


def _candidates(docs: DataFrame, width: int, shape: SketchShape, sent) -> DataFrame:
    """Rows (h1, h2, doc_id, start, stop): the first window of each hash in the task, with
    ``stop`` null; and as runs of words with ``stop``, the windows that came after such a first."""
    schema = "h1 long, h2 long, doc_id long, start int, stop int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.frombuffer(sent.value, np.uint8)
        held: list[tuple] = []
        n = 0
        for batch in batches:
            ids = batch.column(0).fill_null(NO_ID).to_numpy()
            for some, texts in byte_groups(batch.column(1)):
                words = words_of(texts)
                at, low, _, _, value = _windows(words, width)
                at = at[at_least_twice(bits, shape, low[at])]
                if len(at):
                    doc = words.doc[at]
                    # the second half of the hash comes from the window's two halves
                    half = words.runs(width - width // 2)[0]
                    second = mix(half[at] * np.uint64(3) + mix(half[at + width // 2] + np.uint64(7)))
                    held.append((value[at], second, ids[some][doc], (at - words.first[doc]).astype(np.int32)))
                    n += len(at)
                if n >= FLUSH:
                    yield _local(held, width)
                    held, n = [], 0
        if held:
            yield _local(held, width)

    return docs.mapInArrow(run, schema)


def _local(held: list[tuple], width: int) -> pa.RecordBatch:
    h1, h2, doc, start = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.lexsort((start, doc, h2, h1))
    h1, h2, doc, start = h1[order], h2[order], doc[order], start[order]
    same = np.zeros(len(h1), bool)
    same[1:] = (h1[1:] == h1[:-1]) & (h2[1:] == h2[:-1])
    lead = np.maximum.accumulate(np.where(same, 0, np.arange(len(h1))))
    later = (doc != doc[lead]) | (start != start[lead])
    first = ~later & ~np.concatenate(([False], same[1:] & ~later[1:]))
    d, s = doc[later], start[later]
    order = np.lexsort((s, d))
    d, s = d[order], s[order]
    new = np.ones(len(d), bool)
    new[1:] = (d[1:] != d[:-1]) | (s[1:] > s[:-1] + width)
    at = np.flatnonzero(new)
    last = np.concatenate((at[1:], [len(d)])) - 1 if len(at) else at
    stop = np.concatenate((np.zeros(first.sum(), np.int32), s[last] + np.int32(width))) if len(at) else np.zeros(first.sum(), np.int32)
    runs_h = mix(np.arange(len(at), dtype=np.uint64) + d[at].view(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    a1 = np.concatenate((h1[first], runs_h)).view(np.int64)
    a2 = np.concatenate((h2[first], np.zeros(len(at), np.uint64))).view(np.int64)
    none = np.zeros(len(a1), bool)
    none[: first.sum()] = True
    return pa.RecordBatch.from_arrays([pa.array(a1), pa.array(a2), pa.array(np.concatenate((doc[first], d[at]))), pa.array(np.concatenate((start[first], s[at])), pa.int32()), pa.array(stop, pa.int32(), mask=none)], names=["h1", "h2", "doc_id", "start", "stop"])


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n_words, n_removed, kept, spans = [], [], [], []
        for text, found in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
            words = text.encode().split() if text else []
            gone = np.zeros(len(words) + 1, np.int32)
            runs = found.values
            if runs is not None and len(runs):
                np.add.at(gone, runs.field(0).to_numpy(), 1)
                np.add.at(gone, np.minimum(runs.field(1).to_numpy(), len(words)), -1)
            out = np.cumsum(gone[:-1]) > 0
            edge = np.flatnonzero(np.diff(out.view(np.int8), prepend=np.int8(0), append=np.int8(0)))
            parts, at = [], 0
            for a, b in zip(edge[0::2].tolist(), edge[1::2].tolist(), strict=True):
                parts += words[at:a]
                at = b
            n_words.append(len(words))
            n_removed.append(int(out.sum()))
            kept.append(b" ".join(parts + words[at:]).decode())
            spans.append([{"start": a, "stop": b} for a, b in zip(edge[0::2].tolist(), edge[1::2].tolist(), strict=True)])
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.string()), pa.array(spans, pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())])))],
            names=["doc_id", "n_words", "n_removed", "kept_text", "removed"],
        )


def drop_repeats(docs: DataFrame, width: int = WIDTH, shape: SketchShape | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Remove every word covered by a window of ``width`` words that also starts earlier.

    Earlier: a smaller id, or the same id and an earlier start; windows are judged on the
    input. Returns doc_id, n_words, n_removed, kept_text (kept words joined by a space) and
    ``removed`` (word spans). Null or empty texts and texts shorter than a window lose nothing.
    Rows that share an id count as copies of one document: a window of one is not earlier
    than the same place of another, and all lose the same word positions. A null id comes
    before all others. An empty table gives an empty result; other columns are not read.
    ``shape``: of the sketch, by default from the size of the texts.
    """
    spark = docs.sparkSession
    small_batches(spark)
    docs = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    shape = shape or shape_for(docs)
    sent = spark.sparkContext.broadcast(merge(_sketch(docs, width, shape), shape))
    drop_shuffles(spark)
    found = _candidates(docs, width, shape, sent)
    # each task sent one row per hash, so a window that is everywhere has a row per task
    place = F.rank().over(Window.partitionBy("h1", "h2").orderBy("doc_id", "start"))
    again = found.withColumn("place", place).filter((F.col("place") > 1) | F.col("stop").isNotNull())
    spans = again.groupBy("doc_id").agg(F.collect_list(F.struct("start", F.coalesce("stop", F.col("start") + width).alias("stop"))).alias("found"))
    key = F.coalesce(docs.doc_id, F.lit(NO_ID))
    joined = docs.withColumn("_key", key).join(spans.withColumnRenamed("doc_id", "_key"), "_key", "left").select("doc_id", "text", "found")
    return joined.mapInArrow(_remove, "doc_id long, n_words long, n_removed long, kept_text string, removed array<struct<start:int,stop:int>>")


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = drop_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
win AS (SELECT doc_id, s, md5(array_to_string(w[s + 1 : s + 20], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(greatest(0, len(w) - 19))) AS s FROM d)),
later AS (SELECT doc_id, s FROM (SELECT *, rank() OVER (PARTITION BY h ORDER BY doc_id, s) AS r FROM win) WHERE r > 1),
hit AS (SELECT DISTINCT doc_id, s + o AS p FROM later, (SELECT unnest(range(20)) AS o)),
word AS (SELECT doc_id, unnest(w) AS x, unnest(range(len(w))) AS p FROM d),
j AS (SELECT word.*, hit.p IS NOT NULL AS gone FROM word LEFT JOIN hit USING (doc_id, p)),
a AS (SELECT doc_id, count(*) AS n, count(*) FILTER (gone) AS g, string_agg(x, ' ' ORDER BY p) FILTER (NOT gone) AS kept FROM j GROUP BY doc_id)
SELECT d.doc_id, coalesce(n, 0) AS n_words, coalesce(g, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN a USING (doc_id)
"""

QUERIES = {"op5_substring_dedup": op5_substring_dedup}
ORACLES = {"op5_substring_dedup": ORACLE}
