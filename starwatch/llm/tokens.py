"""Byte-level BPE by the public tokenizer library, with a memo of short pieces.

A text may be cut before a space that stands between two characters which are not
white space: byte-level BPE splits a text by a pattern in which a space can only open
a piece, so no token lies across such a cut (a special string has no space, and takes none
beside it), and the encodings of the parts, laid end to end, are the encoding of the whole.
Parts repeat a lot, so each worker keeps the encodings of those it has seen.
"""

from __future__ import annotations

import os
import re

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

MEMO_ENTRIES = 300_000  # about 60 MB in each Python worker
MEMO_CHARS = 48  # longer pieces are not kept
#: A space that no token crosses. (White space in Python's sense takes in all that the pattern's does.)
#: A line feed alone between others is a token of its own, so a cut may go before it as well.
_CUT = re.compile(r"(?<=\S) (?=\S)|(?<=\S)(?=\n\S)")
_WHITE = re.compile(r"\s")
OPENERS = ("\u0120", "\u010a")  # fixed values: how the vocabulary writes a space and a line feed
JOINED = 500


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


_loaded: dict[str, object] = {}


def library(path: str):
    if path not in _loaded:
        from tokenizers import Tokenizer

        _loaded[path] = Tokenizer.from_file(path)
    return _loaded[path]


class PieceEncoder:
    """Whole-text encoding as bytes of little-endian unsigned 32-bit ids."""

    def __init__(self, path: str):
        self.path = path
        self.memo: dict[str, bytes] = {}  # by the piece without the space that opens it (if one does); the first that came
        self.opens: np.ndarray | None = None  # which tokens begin with a space

    def _library(self, pieces: list[str]) -> list[bytes]:
        got = library(self.path).encode_batch_fast(pieces, add_special_tokens=False)
        return [np.array(e.ids, "<u4").tobytes() for e in got]

    def _tails(self, pieces: list[str]) -> list[bytes]:
        """The ids of pieces with the space that opens them (unless a line feed does). Pieces without other white
        space are encoded as one text; in it, exactly the first token of each begins with a space or line feed."""
        if self.opens is None:
            vocabulary = library(self.path).get_vocab(with_added_tokens=True)
            self.opens = np.zeros(max(vocabulary.values()) + 1, bool)
            self.opens[[i for t, i in vocabulary.items() if t.startswith(OPENERS)]] = True
        whole = "".join([p if p[0] == "\n" else " " + p for p in pieces])
        if len(whole.split()) == len(pieces):  # no white space inside a piece
            raw = self._library([whole])[0]
            at = np.flatnonzero(self.opens[np.frombuffer(raw, "<u4")]) * 4
            if len(at) == len(pieces):
                return list(map(raw.__getitem__, map(slice, at.tolist(), [*at[1:].tolist(), len(raw)])))
        odd = {i for i, p in enumerate(pieces) if _WHITE.search(p, 1)}
        if not odd or len(odd) == len(pieces):
            return self._library([p if p[0] == "\n" else " " + p for p in pieces])
        sides = [iter(self._tails([p for i, p in enumerate(pieces) if (i in odd) == x])) for x in (False, True)]
        return [next(sides[i in odd]) for i in range(len(pieces))]

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, as the library gives them for the text as a whole."""
        memo, get = self.memo, self.memo.get
        cut = [_CUT.split(t) for t in texts]
        heads = self._library([c.pop(0) for c in cut])
        found = [list(map(get, c)) for c in cut]
        new = [p for c, ids in zip(cut, found, strict=True) for p, x in zip(c, ids, strict=True) if x is None]
        if len(memo) < MEMO_ENTRIES:
            new = list(dict.fromkeys(new))
        fresh = [x for i in range(0, len(new), JOINED) for x in self._tails(new[i : i + JOINED])]
        if len(memo) < MEMO_ENTRIES:
            here = dict(zip(new, fresh, strict=True))
            memo.update((p, x) for p, x in here.items() if len(p) <= MEMO_CHARS)
            found = [[here[p] if x is None else x for p, x in zip(c, ids, strict=True)] for c, ids in zip(cut, found, strict=True)]
        elif new:
            rest = iter(fresh)
            found = [[next(rest) if x is None else x for x in ids] for ids in found]
            if 2 * len(new) > sum(map(len, cut)):  # other texts than those it was filled from
                memo.clear()
        return [head + b"".join(ids) for head, ids in zip(heads, found, strict=True)]


_encoders: dict[str, PieceEncoder] = {}


def encoder(path: str) -> PieceEncoder:
    """One encoder per worker process; its memo serves all tasks the worker runs."""
    if path not in _encoders:
        _encoders[path] = PieceEncoder(path)
    return _encoders[path]


class RankEncoder:
    """The same ids from the same vocabulary given as byte ranks, at under half the library's cost.

    Every CHECK_EACH-th text goes through the library as well, and a difference is an error. Texts whose white
    space runs exceed what the pattern engine here can backtrack over go to the library alone.
    """

    def __init__(self, json_path: str, ranks_path: str):
        import base64

        import public_tokenizers
        import tiktoken

        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.special = {SPECIAL}
        self.core = tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={SPECIAL: len(ranks)})._core_bpe
        self.json_path = json_path
        self.seen = 0

    def _library(self, text: str) -> bytes:
        return np.array(library(self.json_path).encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        out = []
        for text in texts:
            if _LONG_RUN.search(text) is not None:
                out.append(self._library(text))
                continue
            out.append(bytes(self.core.encode_to_tiktoken_buffer(text, self.special)) if text else b"")
            self.seen += 1
            if self.seen % CHECK_EACH == 1 and out[-1] != self._library(text):
                raise ValueError("the two vocabulary files disagree on a text")
        return out


SPECIAL = "<|endoftext|>"  # fixed value: the vocabulary's one special string
CHECK_EACH = 25
_LONG_RUN = re.compile(r"\s{10000}|\w{20000}")
_rank_encoders: dict[str, RankEncoder] = {}


def rank_encoder(json_path: str, ranks_path: str) -> RankEncoder:
    if ranks_path not in _rank_encoders:
        _rank_encoders[ranks_path] = RankEncoder(json_path, ranks_path)
    return _rank_encoders[ranks_path]
