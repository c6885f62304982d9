"""Token counts of whole texts, huge ones by overlap resynchronisation.

A long text is encoded in overlapping chunks with offsets. Two neighbouring encodings
are spliced where both begin a pre-token at the same character: the splitting pattern
runs left to right and depends only on what follows a pre-token's begin, so from a true
begin on, both chunks cut alike. A begin close to the end of a chunk is not trusted (what
follows the chunk may change it). Without a common begin, the overlap is doubled, and in
the end the chunk itself grows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from . import tokens
from .storage import small_batches
from .wordhash import groups

CHUNK_CHARS = 32_768
OVERLAP_CHARS = 256
GROUP_BYTES = 1 << 19  # of texts encoded at a time
GUARD_CHARS = 16  # longer than any special string and than any look-ahead of the pattern
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, n_chunks int"


def _begins(encoding) -> tuple[np.ndarray, np.ndarray]:
    """Character offset of each token, and whether the token begins a pre-token."""
    at = np.array([a for a, _ in encoding.offsets], np.int64)
    word = np.array([-1 if w is None else w for w in encoding.word_ids], np.int64)
    new = np.ones(len(at), bool)
    new[1:] = (word[1:] != word[:-1]) | (word[1:] < 0) | (word[:-1] < 0)
    return at, new


def count_by_chunks(text: str, encode, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS, guard: int = GUARD_CHARS) -> tuple[int, int]:
    """(tokens, chunks encoded) of ``text``; ``encode(part)`` gives offsets and word_ids."""
    n, total, encoded = len(text), 0, 1
    size, a = chunk, 0
    b = min(n, size)
    at, new = _begins(encode(text[a:b]))
    sync = 0  # a true begin; everything before it is counted
    while b < n:
        trusted = at[new] + a
        trusted = trusted[(trusted > sync) & (trusted <= b - guard)]
        width, spliced = overlap, None
        while len(trusted):
            c = max(sync + 1, b - width)
            d = min(n, max(c + size, b + guard))
            at2, new2 = _begins(encode(text[c:d]))
            encoded += 1
            common = np.intersect1d(trusted, at2[new2] + c)
            common = common[common > c]
            if len(common):
                spliced = int(common[-1])
                break
            if c == sync + 1:
                break
            width *= 2
        if spliced is None:  # nothing to splice at: encode on from the last true begin, further
            size *= 2
            b = min(n, sync + size)
            a = sync
            at, new = _begins(encode(text[a:b]))
            encoded += 1
            continue
        total += int(np.count_nonzero((at + a >= sync) & (at + a < spliced)))
        sync, a, b, at, new, size = spliced, c, d, at2, new2, chunk
    return total + int(np.count_nonzero(at + a >= sync)), encoded


def count_tokens(
    docs: DataFrame, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, chunk: int = CHUNK_CHARS
) -> DataFrame:
    """n_bytes, n_tokens, over_limit and chunks encoded, for every row.

    A null text counts as empty: no bytes, no tokens, and no chunk. Repeated rows and
    null ids are kept as they are; an empty table gives an empty result; other columns
    are not read. Memory is bounded by a chunk (and the row itself), whatever a text's length.
    """
    path = path or tokens.vocabulary_path()
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = tokens.encoder(path)
        lib = tokens.library(path)
        for batch in batches:
            text_of, n = batch.column(1), batch.num_rows
            size = pc.binary_length(text_of).fill_null(0)
            counts, chunks = np.zeros(n, np.int64), np.zeros(n, np.int32)
            for some in groups(size.to_pylist(), GROUP_BYTES):
                texts = [t or "" for t in text_of.slice(some.start, some.stop - some.start).to_pylist()]
                short = [i for i, t in enumerate(texts) if 0 < len(t) <= chunk]
                for i, ids in zip(short, whole.encode([texts[i] for i in short]), strict=True):
                    counts[some.start + i], chunks[some.start + i] = len(ids) // 4, 1
                for i, t in enumerate(texts, some.start):
                    if len(t) > chunk:
                        counts[i], chunks[i] = count_by_chunks(t, lambda part: lib.encode(part, add_special_tokens=False), chunk)
            yield pa.RecordBatch.from_arrays([batch.column(0), size.cast(pa.int64()), pa.array(counts), pa.array(counts > limit), pa.array(chunks)], names=["doc_id", "n_bytes", "n_tokens", "over_limit", "n_chunks"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, SCHEMA)


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"))


QUERIES = {"op1_token_counts": op1_token_counts}
ORACLES: dict[str, str] = {}
