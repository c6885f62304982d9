"""Best-fit-decreasing packing of token sequences into windows of a fixed length.

Overlong documents are first cut into full windows and a rest. Lengths are small
integers, so the whole packing is decided on the histogram of lengths: a segment tree
indexed by remaining capacity finds the tightest open window for each length, and
windows with one history are handled as one range of ids. The plan's size depends on
the window length only, not on the number of documents; every piece then finds its
window from its rank among the pieces of its length.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import tokens
from .storage import materialise, small_batches
from .wordhash import groups

WINDOW = 1024
GROUP_BYTES = 1 << 19  # of text encoded at a time
PIECES = "doc_id long, doc_tokens long, start long, length long, ids binary, part long, local_rank long"


class CapacityTree:
    """Segment tree over remaining capacities 0..size; a leaf holds how many open windows have it."""

    def __init__(self, size: int):
        self.width = 1 << size.bit_length()
        self.count = [0] * (2 * self.width)

    def add(self, capacity: int, n: int) -> None:
        i = capacity + self.width
        while i:
            self.count[i] += n
            i >>= 1

    def tightest(self, need: int) -> int | None:
        """The smallest capacity >= ``need`` that an open window has."""
        i = need + self.width
        if self.count[i]:
            return need
        while i > 1:
            if i % 2 == 0 and self.count[i + 1]:
                i += 1
                while i < self.width:
                    i = 2 * i if self.count[2 * i] else 2 * i + 1
                return i - self.width
            i >>= 1
        return None


def plan_windows(counts: dict[int, int], window: int = WINDOW) -> list[tuple[int, int, int, int, int, int]]:
    """The best-fit-decreasing packing of ``counts`` (pieces by length).

    Rows (length, rank_from, rank_to, first_window, per_window, offset): the pieces of that
    length with these ranks fill the windows from ``first_window`` on, ``per_window`` each
    (the last may get fewer), the first of a window at ``offset``. As one window takes pieces
    of a length until the rest is below it, and the rest stays the tightest meanwhile, this is
    what placing them one by one gives.
    """
    tree = CapacityTree(window)
    open_ranges: dict[int, list[tuple[int, int]]] = {}  # capacity -> (first window, windows)
    plan, made = [], 0

    def free(capacity: int, first: int, n: int) -> None:
        if capacity > 0 and n > 0:
            open_ranges.setdefault(capacity, []).append((first, n))
            tree.add(capacity, n)

    for length in sorted((x for x, n in counts.items() if n), reverse=True):
        left, rank = counts[length], 0
        while left:
            room = tree.tightest(length)
            if room is None:
                room, per = window, window // length
                first, n = made, -(-left // per)
                made += n
            else:
                per = room // length
                first, have = open_ranges[room].pop()
                n = min(have, -(-left // per))
                tree.add(room, -have)
                free(room, first + n, have - n)
            full = min(n, left // per)
            placed = min(left, n * per)
            plan.append((length, rank, rank + placed, first, per, window - room))
            free(room - per * length, first, full)
            if full < n:
                free(room - (placed - full * per) * length, first + full, 1)
            rank, left = rank + placed, left - placed
    return plan


def cut_pieces(docs: DataFrame, id_col: str, text_col: str, window: int, json_path: str, ranks_path: str) -> DataFrame:
    """Tokenise, append the end id 0 and cut: full windows and one rest per document.

    ``part`` and ``local_rank`` number the pieces of one length within a task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = tokens.rank_encoder(json_path, ranks_path)
        part = TaskContext.get().partitionId()
        seen = np.zeros(window + 1, np.int64)
        end = np.zeros(1, "<u4").tobytes()
        for batch in batches:
            ids_of, text_of = batch.column(0), batch.column(1)
            for some in groups(pc.binary_length(text_of).fill_null(0).to_pylist(), GROUP_BYTES):
                n_rows = some.stop - some.start
                texts = [t or "" for t in text_of.slice(some.start, n_rows).to_pylist()]
                out: list[tuple] = []
                for doc_id, ids in zip(ids_of.slice(some.start, n_rows).to_pylist(), enc.encode(texts), strict=True):
                    ids += end
                    n = len(ids) // 4
                    for start in range(0, n, window):
                        length = min(window, n - start)
                        out.append((doc_id, n, start, length, ids[4 * start : 4 * (start + length)], part, int(seen[length])))
                        seen[length] += 1
                yield _batch(out)

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, PIECES)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    names = ["doc_id", "doc_tokens", "start", "length", "ids", "part", "local_rank"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def pack_documents(
    docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", json_path: str | None = None, ranks_path: str | None = None
) -> DataFrame:
    """Pieces with their token ids (little-endian unsigned 32-bit), sequence and offset in it.

    The ids are those of the library at ``json_path``; they are made from the same vocabulary at ``ranks_path``, which
    costs less than half as much, and compared with the library's on a part of the texts.

    A null text counts as empty: the document is then its end id alone. Repeated rows and
    null ids are packed as rows of their own; an empty table gives an empty result; other
    columns are not read. What reaches the driver is the histogram of lengths (at most
    ``window`` numbers); what rides in the plan is bounded by the window length too.
    """
    spark = docs.sparkSession
    small_batches(spark)
    names = json_path or tokens.vocabulary_path(), ranks_path or tokens.vocabulary_path("byte_bpe_50k.tiktoken")
    cut = cut_pieces(docs, id_col, text_col, window, *names)
    pieces = materialise(cut.withColumn("ids_crc32", F.crc32("ids")), "pack-pieces")
    per_task = pieces.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    counts = {r.length: r.n for r in per_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    w = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = per_task.select("length", "part", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("base"))
    plan = spark.createDataFrame(plan_windows(counts, window), "length long, rank_from long, rank_to long, first_window long, per_window long, at long")
    # ``base`` has a row per task and length, ``plan`` a few rows per length; a caller that
    # does not ask for ``ids`` moves only the small columns.
    placed = pieces.join(base.hint("shuffle_hash"), ["length", "part"]).withColumn("rank", F.col("base") + F.col("local_rank"))
    k = F.col("rank") - F.col("rank_from")
    return placed.join(F.broadcast(plan), "length").filter((F.col("rank") >= F.col("rank_from")) & (F.col("rank") < F.col("rank_to"))).select(
        "doc_id", "start", "length", "ids", "ids_crc32", "doc_tokens",
        F.expr("first_window + (rank - rank_from) div per_window").alias("sequence_id"),
        (F.col("at") + k % F.col("per_window") * F.col("length")).alias("offset"),
    )


def digest(packed: DataFrame) -> DataFrame:
    """The result contract's columns, from the packed pieces."""
    return packed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet")))


QUERIES = {"op2_best_fit_packing": op2_best_fit_packing}
ORACLES: dict[str, str] = {}
