"""Benchmark decontamination by greedy string tiling.

The seeds of all test items (runs of ``min_tile`` words) are probed by the running hashes of
each document. Where seeds are shared, the longest common run of words is marked, then the
longest among the words not yet marked, and so on; a test is leaked if the marked tiles
cover enough of it, in whatever order its passages come.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .storage import small_batches
from .wordhash import groups, words_of

MIN_TILE = 4
COVERAGE = 0.5
BLOCK_WORDS = 2_000_000  # of test items held by a worker at a time
FILTER_BITS = 22
SEEDS = 1_000_000  # listed at a time


def tiles(pairs_item: np.ndarray, pairs_doc: np.ndarray, n_item: int, min_tile: int) -> list[tuple[int, int, int]]:
    """Greedy tiling from equal seeds at (item place, document place): (item, document, length) tiles.

    Seeds on one diagonal and without a gap form a maximal match. The longest match with
    no marked word is marked; one that meets marked words is cut to its free parts.
    """
    return tiles_of_runs(*diagonal_runs(pairs_item, pairs_doc), n_item, min_tile)


def diagonal_runs(p: np.ndarray, q: np.ndarray, length: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(item place, document place, seeds) of the runs along diagonals that seeds, or shorter runs, make up."""
    length = np.ones(len(p), np.int64) if length is None else length
    order = np.lexsort((p, q - p))
    p, q, length = p[order], q[order], length[order]
    new = np.ones(len(p), bool)
    new[1:] = (q[1:] - p[1:] != q[:-1] - p[:-1]) | (p[1:] != p[:-1] + length[:-1])
    begin = np.flatnonzero(new)
    return p[begin], q[begin], np.add.reduceat(length, begin) if len(p) else length


def tiles_of_runs(p: np.ndarray, q: np.ndarray, seeds: np.ndarray, n_item: int, min_tile: int) -> list[tuple[int, int, int]]:
    heap = [(-n, a, b) for a, b, n in zip(p.tolist(), q.tolist(), (seeds + min_tile - 1).tolist(), strict=True)]
    heapq.heapify(heap)
    item_marked = np.zeros(n_item, bool)
    low = int(q.min(initial=0))
    doc_marked = np.zeros(int((q + seeds).max(initial=0)) + min_tile - low, bool)
    out = []
    while heap and _free_runs(~item_marked, min_tile):
        n, a, b = heapq.heappop(heap)
        free = ~(item_marked[a : a - n] | doc_marked[b - low : b - low - n])
        if free.all():
            item_marked[a : a - n] = True
            doc_marked[b - low : b - low - n] = True
            out.append((a, b, -n))
            continue
        for i, j in _free_runs(free, min_tile):
            heapq.heappush(heap, (i - j, a + i, b + i))
    return out


def _free_runs(free: np.ndarray, least: int) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(free.view(np.int8), prepend=np.int8(0), append=np.int8(0)))
    return [(i, j) for i, j in zip(edge[0::2].tolist(), edge[1::2].tolist(), strict=True) if j - i >= least]


class TestItems:
    """Seeds of a block of test items, sorted by hash, with a bit filter before them."""

    def __init__(self, rows: list[tuple[int, str]], min_tile: int):
        self.ids = [r[0] for r in rows]
        words = words_of([(r[1] or "").lower().encode() for r in rows], bare=True)
        self.sizes = np.diff(words.first)
        value, ok = words.runs(min_tile)
        at = np.flatnonzero(ok)
        order = np.argsort(value[at], kind="stable")
        at = at[order]
        self.seed, self.item = value[at], words.doc[at]
        self.place = at - words.first[self.item]
        self.bits = np.zeros(1 << FILTER_BITS, bool)
        self.bits[(self.seed >> np.uint64(64 - FILTER_BITS)).astype(np.int64)] = True
        # items shorter than a seed are matched as wholes
        self.short: dict[int, dict[int, list[int]]] = {}
        for n in range(1, min_tile):
            v, _ = words.runs(n)
            for i in np.flatnonzero(self.sizes == n):
                self.short.setdefault(n, {}).setdefault(int(v[words.first[i]]), []).append(int(i))
        self.min_tile = min_tile

    def _runs(self, words, at, low, n) -> tuple[np.ndarray, ...]:
        """(text and item, item place, text place, seeds) of diagonal runs of the seeds at the words ``at``, of
        which ``n`` lie from ``low`` on. Seeds are listed a bounded number at a time, as words that repeat in both give their product."""
        parts = []
        total = np.cumsum(n)
        a = 0
        while a < len(at):
            b = max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + SEEDS)))
            k = n[a:b]
            seed = np.repeat(low[a:b], k) + np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)
            where = np.repeat(at[a:b], k)
            doc = words.doc[where]
            pair, p, q = doc * len(self.ids) + self.item[seed], self.place[seed], where - words.first[doc]
            order = np.lexsort((p, q - p, pair))
            pair, p, q = pair[order], p[order], q[order]
            new = np.ones(len(p), bool)
            new[1:] = (pair[1:] != pair[:-1]) | (q[1:] - p[1:] != q[:-1] - p[:-1]) | (p[1:] != p[:-1] + 1)
            begin = np.flatnonzero(new)
            parts.append((pair[begin], p[begin], q[begin], np.diff(np.append(begin, len(p)))))
            a = b
        return tuple(np.concatenate(x) for x in zip(*parts, strict=True))

    def leaks(self, texts: list[str | None], coverage: float):
        """(text number, item, tiles, covered words) of every leaked item."""
        words = words_of([(t or "").lower().encode() for t in texts], bare=True)
        value, ok = words.runs(self.min_tile)
        at = np.flatnonzero(ok)
        at = at[self.bits[(value[at] >> np.uint64(64 - FILTER_BITS)).astype(np.int64)]]
        low, high = (np.searchsorted(self.seed, value[at], side=s) for s in ("left", "right"))
        n = high - low
        at, low, n = at[n > 0], low[n > 0], n[n > 0]
        if len(at):
            pair, p, q, seeds = self._runs(words, at, low, n)
            order = np.argsort(pair, kind="stable")
            begin = np.flatnonzero(np.diff(pair[order], prepend=-1))
            for i, j in zip(begin, np.append(begin[1:], len(order)), strict=True):
                mine = order[i:j]
                t, x = divmod(int(pair[mine[0]]), len(self.ids))
                size = int(self.sizes[x])
                reach = np.zeros(size + 1, np.int32)  # at most what the seeds touch can be covered
                np.add.at(reach, p[mine], 1)
                np.add.at(reach, p[mine] + seeds[mine] + self.min_tile - 1, -1)
                if np.count_nonzero(np.cumsum(reach[:-1])) < coverage * size:
                    continue
                found = tiles_of_runs(*diagonal_runs(p[mine], q[mine], seeds[mine]), size, self.min_tile)
                covered = sum(z for _, _, z in found)
                if covered >= coverage * size:
                    yield t, x, found, covered
        for n, table in self.short.items():
            v, ok = words.runs(n)
            seen = set()
            for i in np.flatnonzero(ok & np.isin(v, np.array(list(table), np.uint64))):
                for x in table[int(v[i])]:
                    t = int(words.doc[i])
                    if (t, x) not in seen:
                        seen.add((t, x))
                        yield t, x, [(0, int(i - words.first[t]), n)], n


def item_blocks(benchmark: DataFrame, id_col: str, text_col: str, block_words: int) -> Iterator[list[tuple[int, str]]]:
    """Test items, streamed to the driver and given on in blocks of bounded size."""
    block, n = [], 0
    for r in benchmark.select(id_col, text_col).toLocalIterator():
        block.append((r[0], r[1]))
        n += len(r[1] or "") // 4 + 1
        if n >= block_words:
            yield block
            block, n = [], 0
    if block:
        yield block


FOUND = "doc_id long, item_id long, item_words long, covered_words long, coverage double, tiles array<struct<item_at:int,doc_at:int,length:int>>"


def find_leaks(
    docs: DataFrame, benchmark: DataFrame, min_tile: int = MIN_TILE, coverage: float = COVERAGE, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", block_words: int = BLOCK_WORDS
) -> DataFrame:
    """One row per document and test item whose words are covered to ``coverage`` by tiles.

    Words are runs of letters and digits, lower-cased (all other ASCII characters separate).
    Items shorter than ``min_tile`` words must occur as a whole; items without words and null texts
    match nothing. Repeated rows give repeated results. Empty tables give an empty result. The
    benchmark is broadcast in blocks of ``block_words`` words; each block reads the documents once.
    """
    small_batches(docs.sparkSession)
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    out = None
    for block in item_blocks(benchmark, item_col, item_text, block_words):
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches, sent=sent):
            items = TestItems(sent.value, min_tile)
            for batch in batches:
                texts = batch.column(1).to_pylist()
                found = []
                for some in groups([len(t or "") for t in texts]):
                    for t, x, marked, covered in items.leaks(texts[some], coverage):
                        size = int(items.sizes[x])
                        found.append((batch.column(0)[some.start + t].as_py(), items.ids[x], size, covered, covered / size, [{"item_at": a, "doc_at": b, "length": n} for a, b, n in marked]))
                if found:
                    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.list_(pa.struct([("item_at", pa.int32()), ("doc_at", pa.int32()), ("length", pa.int32())]))]
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*found, strict=True), kinds, strict=True)], names=["doc_id", "item_id", "item_words", "covered_words", "coverage", "tiles"])

        part = rows.mapInArrow(run, FOUND)
        out = part if out is None else out.unionAll(part)
    return out if out is not None else docs.sparkSession.createDataFrame([], FOUND)


def drop_leaks(docs: DataFrame, benchmark: DataFrame, min_tile: int = MIN_TILE, coverage: float = COVERAGE, text_col: str = "text", block_words: int = BLOCK_WORDS) -> DataFrame:
    """``docs`` without the rows that leak a test item; all columns pass through."""
    small_batches(docs.sparkSession)
    at = docs.columns.index(text_col)
    out = docs
    for block in item_blocks(benchmark, "item_id", "text", block_words):
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches, sent=sent):
            items = TestItems(sent.value, min_tile)
            for batch in batches:
                texts = batch.column(at).to_pylist()
                keep = np.ones(len(texts), bool)
                for some in groups([len(t or "") for t in texts]):
                    for t, *_ in items.leaks(texts[some], coverage):
                        keep[some.start + t] = False
                yield batch.filter(pa.array(keep))

        out = out.mapInArrow(run, docs.schema)
    return out


def op9_string_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leaked (document, test item) pairs, whole tables."""
    found = find_leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.selectExpr("doc_id", "item_id", "item_words", "covered_words", "round(coverage, 6) AS coverage", "size(tiles) AS n_tiles")


QUERIES = {"op9_string_tiling": op9_string_tiling}
ORACLES: dict[str, str] = {}
