"""Links within large groups of near copies, against brute force."""

import random

import numpy as np
import pytest

from starwatch.llm import paritysketch


def near_copies():
    r = random.Random(11)
    voc = [f"w{i}" for i in range(400)]
    base = [r.choice(voc) for _ in range(150)]
    out = []
    for i in range(60):
        copy = list(base)
        for _ in range(r.randint(0, 4)):
            copy[r.randrange(150)] = r.choice(voc)
        out.append((i, " ".join(copy)))
    out += [(60 + i, " ".join(r.choice(voc) for _ in range(80))) for i in range(10)]
    return out + [(70, out[3][1]), (71, None), (72, "")]


@pytest.mark.parametrize("tile", [8, 256])
def test_every_link_of_a_large_group(spark, monkeypatch, tile):
    monkeypatch.setattr(paritysketch, "TILE", tile)
    monkeypatch.setattr(paritysketch, "GROUP_TILE", tile)
    sets = {}
    for i, t in near_copies():
        w = (t or "").split()
        sets[i] = frozenset(tuple(w[s : s + 4]) for s in range(max(1, len(w) - 3))) if w else frozenset()
    distinct = set(sets.values()) - {frozenset()}
    want = {i: sum(x != s and 100 * len(s & x) >= 85 * len(s | x) for x in distinct) if s else 0 for i, s in sets.items()}
    docs = spark.createDataFrame(near_copies(), "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.n_verified_links for r in paritysketch.shingle_components(docs, 4, 85).collect()}
    assert got == want and max(want.values()) > paritysketch.PAIR_GROUP


def test_classes_that_share_half_a_fingerprint(spark, monkeypatch):
    whole = paritysketch._prints

    def half(values, begin):
        f1, f2 = whole(values, begin)
        return f1 & np.uint64(7), f2

    docs = spark.createDataFrame(near_copies(), "doc_id long, text string").repartition(3)
    want = {r.doc_id: r[1:] for r in paritysketch.shingle_components(docs, 4, 85).collect()}
    monkeypatch.setattr(paritysketch, "_prints", half)
    assert {r.doc_id: r[1:] for r in paritysketch.shingle_components(docs, 4, 85).collect()} == want


def test_sketches_fold_and_bound_the_difference():
    r = np.random.default_rng(3)
    x = np.unique(r.integers(0, 1 << 62, 5000).astype(np.uint64))
    for y in (x[100:], x[::2], np.unique(r.integers(0, 1 << 62, 400).astype(np.uint64))):
        a, b = paritysketch.short_sketch(x), paritysketch.short_sketch(y)
        assert paritysketch.apart(a, b) <= len(np.setxor1d(x, y))
    assert paritysketch.apart(a, a) == 0
