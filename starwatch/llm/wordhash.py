"""Vectorised 64-bit hashes of words and word runs, over many texts at once.

Words are ``[^\\x20\\x09-\\x0D]+`` on UTF-8 bytes. All arithmetic is modulo 2^64.
A word's value is a positional sum of per-byte random values, a run's value is the
same sum over mixed word values; prefix sums give any run's value in O(1).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_NOT_WORD = np.array([i < 0x80 and not chr(i).isalnum() for i in range(256)])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 32
_BYTE_BASE = np.uint64(0x9E3779B97F4A7C15)
_RUN_BASE = np.uint64(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), a bijection."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE_VALUE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019))
CHUNK_BYTES = 1 << 20  # hashed at a time, so a very long text needs no wide arrays of its own size
CHUNK_WORDS = 1 << 18
LONG_WORD = 1 << 12  # longer words get their value from another hash, which needs no table


@lru_cache(maxsize=8)
def _power_table(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i for i <= n; base is odd, so it has an inverse. Asked for with a few fixed n only."""
    up, down = np.full(n + 1, np.uint64(base)), np.full(n + 1, np.uint64(pow(base, -1, 1 << 64)))
    up[0] = down[0] = 1
    return np.cumprod(up), np.cumprod(down)


@dataclass
class Words:
    """The words of a group of texts laid end to end. ``doc`` says whose word each is."""

    doc: np.ndarray
    value: np.ndarray
    first: np.ndarray  # n_docs + 1: where each text's words begin

    def runs(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Values of the k-word runs that begin at each word, and which lie within one text."""
        n = len(self.value) - k + 1
        if n <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, bool)
        up, down = _power_table(int(_RUN_BASE), CHUNK_WORDS + k)
        value = np.empty(n, np.uint64)
        for at in range(0, n, CHUNK_WORDS):
            m = min(CHUNK_WORDS, n - at)
            total = np.zeros(m + k, np.uint64)
            np.cumsum(self.value[at : at + m + k - 1] * up[: m + k - 1], out=total[1:])
            value[at : at + m] = mix((total[k:] - total[:m]) * down[:m] + np.uint64(k))
        return value, self.doc[k - 1 :] == self.doc[:n]


def _word_values(raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """The value of each word raw[start:end]."""
    value = np.empty(len(start), np.uint64)
    up, down = _power_table(int(_BYTE_BASE), CHUNK_BYTES + LONG_WORD)
    i = 0
    while i < len(start):
        low = start[i]
        j = int(np.searchsorted(start, low + CHUNK_BYTES))
        part = raw[low : min(end[j - 1], low + CHUNK_BYTES + LONG_WORD)]
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(_BYTE_VALUE[part] * up[: len(part)], out=total[1:])
        a, b = start[i:j] - low, np.minimum(end[i:j] - low, len(part))
        value[i:j] = mix((total[b] - total[a]) * down[a])
        i = j
    for i in np.flatnonzero(end - start > LONG_WORD):
        value[i] = xxhash.xxh3_64_intdigest(raw[start[i] : end[i]].tobytes())
    return value


def words_of(texts: list[bytes], lower: bool = False, bare: bool = False) -> Words:
    """Find and hash the words of ``texts`` (None counts as empty).

    ``bare``: every ASCII character but letters and digits separates words."""
    texts = [t or b"" for t in texts]
    raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
    if lower:
        raw = _LOWER[raw]
    begin = np.concatenate(([0], np.cumsum([len(t) + 1 for t in texts]))).astype(np.int64)
    inside = ~(_NOT_WORD if bare else _SPACE)[raw]
    edge = np.flatnonzero(np.diff(inside.view(np.int8), prepend=np.int8(0)))
    start, end = edge[0::2], edge[1::2]
    first = np.searchsorted(start, begin)
    return Words(np.repeat(np.arange(len(texts)), np.diff(first)), _word_values(raw, start, end), first)


def groups(sizes: list[int], limit: int = CHUNK_BYTES) -> Iterator[slice]:
    """Slices of consecutive texts of about ``limit`` bytes; a longer text stands alone."""
    at, total = 0, 0
    for i, n in enumerate(sizes):
        if i > at and total + n > limit:
            yield slice(at, i)
            at, total = i, 0
        total += n
    if at < len(sizes):
        yield slice(at, len(sizes))


def byte_groups(column: pa.Array) -> Iterator[tuple[slice, list[bytes | None]]]:
    """The texts of an Arrow column as UTF-8, a group at a time; the others stay in the column's buffer."""
    raw = column.cast(pa.binary() if pa.types.is_string(column.type) else pa.large_binary())
    for some in groups(pc.binary_length(column).fill_null(0).to_pylist()):
        yield some, raw.slice(some.start, some.stop - some.start).to_pylist()


def sliding(values: np.ndarray, width: int, op) -> np.ndarray:
    """``op`` (np.minimum or np.maximum) over each ``width`` consecutive values, in log steps."""
    have, out = 1, values
    while have * 2 <= width:
        out = op(out[:-have], out[have:]) if len(out) > have else out[:0]
        have *= 2
    rest = width - have
    if rest:
        out = op(out[:-rest], out[rest:]) if len(out) > rest else out[:0]
    return out
