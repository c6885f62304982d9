"""Line dedup with a sharded minimal perfect hash over the distinct frequent line hashes.

A first pass counts, per line key, the documents that have it. The keys that reach the
limit (others have no use as their lines stay, and a probe that finds nothing says so) go into shards; each shard gets a minimal perfect hash (levels of bit arrays), and
at a key's place stand a 64-bit fingerprint and its count. Documents then probe these
arrays line by line; no line is joined or shuffled in the second pass.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import free, materialise, small_batches
from .wordhash import groups, mix

MIN_DOCS = 10
MIN_CHARS = 1
SHARD_KEYS = 50_000
PROBE_BYTES = 64 << 20  # of arrays held by a worker at a time; more shards are probed in rounds
BLANK = " \t\n\x0b\x0c\r"
UPPER = {i: i + 32 for i in range(0x41, 0x5B)}
GAMMA = 2.0


def line_key(line: str) -> str:
    """A line without ASCII white space at its ends, A-Z lower-cased (only those)."""
    line = line.strip(BLANK)
    return line.lower() if line.isascii() else line.translate(UPPER)


def key_hash(key: str) -> tuple[int, int]:
    """Two independent halves of a 128-bit hash: the place hash and the fingerprint."""
    h = xxhash.xxh3_128_intdigest(key.encode())
    return h & 0xFFFFFFFFFFFFFFFF, h >> 64


class PerfectHash:
    """Minimal perfect hash: a key stands in the first level where nobody shares its cell."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels  # packed bits, with their cell counts
        sizes = [int(x[:8].view(np.uint64)[0]) for x in levels]
        self.bits = [np.unpackbits(x[8:], count=n, bitorder="little").astype(bool) for x, n in zip(levels, sizes, strict=True)]
        self.rank = []
        before = 0
        for b in self.bits:
            self.rank.append(before + np.cumsum(b, dtype=np.int64) - b)
            before += int(b.sum())
        self.size = before

    @staticmethod
    def cell(keys: np.ndarray, level: int, cells: int) -> np.ndarray:
        return (mix(keys + np.uint64(level * 0x9E3779B97F4A7C15 % (1 << 64))) % np.uint64(cells)).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        """``keys``: distinct uint64."""
        levels, left = [], keys
        while len(left):
            cells = max(8, int(GAMMA * len(left)))
            at = cls.cell(left, len(levels), cells)
            alone = np.bincount(at, minlength=cells) == 1
            packed = np.concatenate([np.array([cells], np.uint64).view(np.uint8), np.packbits(alone, bitorder="little")])
            levels.append(packed)
            left = left[~alone[at]]
        return cls(levels)

    def places(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key; of a key not built in, any place or -1."""
        out = np.full(len(keys), -1, np.int64)
        left = np.arange(len(keys))
        for level, (bits, rank) in enumerate(zip(self.bits, self.rank, strict=True)):
            if not len(left):
                break
            at = self.cell(keys[left], level, len(bits))
            hit = bits[at]
            out[left[hit]] = rank[at[hit]]
            left = left[~hit]
        return out


class Shard:
    """One shard's perfect hash with the fingerprint and count at each key's place."""

    def __init__(self, levels: list[bytes], prints: bytes, counts: bytes):
        self.hash = PerfectHash([np.frombuffer(x, np.uint8) for x in levels])
        self.prints = np.frombuffer(prints, np.uint64)
        self.counts = np.frombuffer(counts, np.int64)

    def lookup(self, keys: np.ndarray, prints: np.ndarray) -> np.ndarray:
        """The count of each key, 0 if it is not in the shard."""
        out = np.zeros(len(keys), np.int64)
        at = self.hash.places(keys)
        ok = np.flatnonzero(at >= 0)
        ok = ok[self.prints[at[ok]] == prints[ok]]
        out[ok] = self.counts[at[ok]]
        return out


def count_keys(docs: DataFrame, text_col: str, min_chars: int) -> DataFrame:
    """(place hash, fingerprint, documents that have the key), summed per task before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[int, int] = {}
            for text in batch.column(0).to_pylist():
                keys = {line_key(x) for x in text.split("\n")} if text else {""}
                for k in keys:
                    if len(k) >= min_chars:
                        h = xxhash.xxh3_128_intdigest(k.encode())
                        seen[h] = seen.get(h, 0) + 1
            h = [(x & 0xFFFFFFFFFFFFFFFF, x >> 64) for x in seen]
            both = np.array(h, np.uint64).reshape(-1, 2).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy()), pa.array(list(seen.values()), pa.int64())], names=["h", "f", "n"])

    each = docs.select(F.col(text_col)).mapInArrow(run, "h long, f long, n long")
    return each.groupBy("h", "f").agg(F.sum("n").alias("n"))


def build_shards(keys: DataFrame, n_keys: int, shard_keys: int) -> DataFrame:
    """Rows (shard, levels, prints, counts), built by one task per shard of bounded size."""
    n_shards = max(1, -(-n_keys // shard_keys))

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        h, f, n = (pdf[c].to_numpy() for c in ("h", "f", "n"))
        order = np.lexsort((f, h))
        h, f, n = h[order].view(np.uint64), f[order].view(np.uint64), n[order]
        # two keys with one place hash (never seen, but possible): the second is found by its fingerprint
        h = np.where(np.concatenate(([False], h[1:] == h[:-1])), mix(h ^ f), h)
        mph = PerfectHash.build(h)
        at = mph.places(h)
        prints, counts = np.zeros(mph.size, np.uint64), np.zeros(mph.size, np.int64)
        prints[at], counts[at] = f, n
        return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0])], "levels": [[x.tobytes() for x in mph.levels]], "prints": [prints.tobytes()], "counts": [counts.tobytes()]})

    parts = keys.withColumn("shard", F.pmod(F.col("h"), F.lit(n_shards)).cast("int"))
    return parts.groupBy("shard").applyInPandas(build, "shard int, levels array<binary>, prints binary, counts binary")


def drop_lines(docs: DataFrame, min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS, text_col: str = "text", shard_keys: int = SHARD_KEYS, probe_bytes: int = PROBE_BYTES) -> DataFrame:
    """``docs`` with the frequent lines taken out of ``text_col``, and two more columns.

    ``line_count`` is the number of lines before, ``lines_dropped`` of lines taken out; all other
    columns, whatever their names, pass through (an input column of these two names is replaced).
    A null text is one empty line and stays null. A key counts once per row, so repeated rows
    count as documents of their own. An empty table gives an empty result. A text that loses all
    its lines becomes empty.

    The arrays of frequent lines are broadcast in rounds of at most ``probe_bytes``. All rounds but the last
    are written before the next begins, and their arrays given back, so driver and workers hold one
    round's arrays however many frequent lines there are; lines judged in one round cannot
    change the verdict on others, as counts are those of the input.
    """
    spark = docs.sparkSession
    small_batches(spark)
    clash = [c for c in docs.columns if c in ("line_count", "lines_dropped")]
    docs = docs.drop(*clash)
    frequent = materialise(count_keys(docs, text_col, min_chars).filter(F.col("n") >= min_docs), "frequent-lines")
    n_keys = frequent.count()
    schema = docs.schema.add("line_count", "long").add("lines_dropped", "long")
    at = docs.columns.index(text_col)
    if not n_keys:
        lines = F.size(F.split(F.coalesce(text_col, F.lit("")), "\n")).cast("long")
        return docs.withColumns({"line_count": lines, "lines_dropped": F.lit(0).cast("long")})
    shards = materialise(build_shards(frequent, n_keys, shard_keys), "line-shards")
    n_shards = max(1, -(-n_keys // shard_keys))
    per_round = max(1, probe_bytes // max(1, shard_keys * 24))
    out = docs.withColumns({"line_count": F.lit(-1).cast("long"), "lines_dropped": F.lit(0).cast("long")})
    sent = None
    for low in range(0, n_shards, per_round):
        if sent is not None:
            before, out = out, materialise(out, "line-round")
            free(before)
            sent.unpersist()
        rows = shards.filter((F.col("shard") >= low) & (F.col("shard") < low + per_round)).collect()
        sent = spark.sparkContext.broadcast([(r.shard, [bytes(x) for x in r.levels], bytes(r.prints), bytes(r.counts)) for r in rows])
        out = out.mapInArrow(_probe(sent, n_shards, at, min_docs, min_chars), schema)
    free(frequent, shards)
    return out


def _probe(sent, n_shards: int, at: int, min_docs: int, min_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shards = {s: Shard(levels, prints, counts) for s, levels, prints, counts in sent.value}
        for batch in batches:
            texts = batch.column(at).to_pylist()  # (batches are small, see small_batches)
            before = batch.column(batch.num_columns - 2).to_numpy().copy()
            gone = batch.column(batch.num_columns - 1).to_numpy().copy()
            for some in groups([len(t or "") for t in texts]):
                split = [(t or "").split("\n") for t in texts[some]]
                keys = [line_key(x) for lines in split for x in lines]
                dig = np.array([key_hash(k) for k in keys], np.uint64).reshape(-1, 2)
                long_enough = np.array([len(k) >= min_chars for k in keys], bool)
                shard = dig[:, 0].view(np.int64) % n_shards
                hot = np.zeros(len(keys), bool)
                for s, arrays in shards.items():
                    mine = np.flatnonzero((shard == s) & long_enough)
                    if len(mine):
                        h, f = dig[mine, 0], dig[mine, 1]
                        hot[mine] = (arrays.lookup(h, f) >= min_docs) | (arrays.lookup(mix(h ^ f), f) >= min_docs)
                i = 0
                for j, lines in enumerate(split, some.start):
                    if before[j] < 0:
                        before[j] = len(lines)
                    here = hot[i : i + len(lines)]
                    i += len(lines)
                    if here.any():
                        kept = [x for x, h in zip(lines, here, strict=True) if not h]
                        gone[j] += len(lines) - len(kept)
                        texts[j] = "\n".join(kept)
            cols = [*batch.columns[:-2], pa.array(before, pa.int64()), pa.array(gone, pa.int64())]
            cols[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(cols, names=batch.schema.names)

    return run


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    kept = F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256)
    return drop_lines(docs).select("doc_id", F.col("line_count").alias("n_lines"), F.col("lines_dropped").alias("n_dropped"), kept.alias("kept_sha256"))


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
l AS (SELECT r, doc_id, unnest(lines) AS line, unnest(range(len(lines))) AS i FROM d),
k AS (SELECT *, translate(trim(line, concat(' ', chr(9), chr(10), chr(11), chr(12), chr(13))), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
hot AS (SELECT key FROM k WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT r) >= 10),
j AS (SELECT k.*, hot.key IS NOT NULL AS gone FROM k LEFT JOIN hot ON k.key = hot.key)
SELECT any_value(doc_id) AS doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM j GROUP BY r
"""

QUERIES = {"op7_line_dedup": op7_line_dedup}
ORACLES = {"op7_line_dedup": ORACLE}
