"""String tiling against a plain version, with words that repeat in item and text."""

import random
import time

import pytest

from starwatch.llm import decontaminate


def plain_words(text):
    return "".join(c.lower() if c.isalnum() else c if ord(c) > 127 else " " for c in text or "").split()


def plain_cover(item, text, least):
    """Words of the item covered by greedy tiles: the longest unmarked match, again and again."""
    mi, mt, covered = [False] * len(item), [False] * len(text), 0
    while True:
        best = 0
        for i in range(len(item)):
            for j in range(len(text)):
                n = 0
                while i + n < len(item) and j + n < len(text) and item[i + n] == text[j + n] and not mi[i + n] and not mt[j + n]:
                    n += 1
                if n > best:
                    best, at = n, (i, j)
        if best < least:
            return covered
        for k in range(best):
            mi[at[0] + k] = mt[at[1] + k] = True
        covered += best


@pytest.mark.parametrize("seeds", [7, 1_000_000])
def test_leaks_equal_plain_tiling(spark, monkeypatch, seeds):
    monkeypatch.setattr(decontaminate, "SEEDS", seeds)
    r = random.Random(2)
    items = [" ".join(r.choice("abcde") + r.choice("xyz") for _ in range(r.randint(4, 24))) for _ in range(12)] + ["one two", "one-two", None, " ", "ha ha ha ha ha ha ha ha"]
    docs = []
    for i in range(60):
        words = [r.choice("abcde") + r.choice("xyz") for _ in range(r.randint(0, 30))]
        if i % 3 == 0:  # passages of an item in another order
            w = items[i % 12].split()
            words += w[len(w) // 2 :] + ["q"] + w[: len(w) // 2]
        docs.append((i, " ".join(words)))
    docs += [(60, None), (61, ""), (62, "One, TWO!"), (None, items[0]), (62, "ha " * 40), (63, items[1].upper()), (63, items[1].upper())]
    want = []
    for d, t in docs:
        text = plain_words(t)
        for x, item in enumerate(map(plain_words, items)):
            if not item:
                continue
            if len(item) < 4:
                n = len(item) if any(text[s : s + len(item)] == item for s in range(len(text))) else 0
            else:
                n = plain_cover(item, text, 4)
            if n and n >= 0.5 * len(item):
                want.append((d, x, len(item)))
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    table = spark.createDataFrame([(a, b, "x", 1) for a, b in docs], "doc_id long, text string, tiles string, coverage int").repartition(3)
    got = [(x.doc_id, x.item_id, x.item_words) for x in decontaminate.find_leaks(table, bench).collect()]
    key = lambda x: (x[0] is None, x)
    assert sorted(got, key=key) == sorted(want, key=key) and len(want) > 20
    gone = {x[0] for x in want}
    kept = decontaminate.drop_leaks(table, bench).collect()
    assert [x.doc_id for x in kept if x.doc_id in gone - {62}] == [] and {x.doc_id for x in kept} >= {a for a, _ in docs} - gone


def test_repeated_words_do_not_multiply(spark):
    item = decontaminate.TestItems([(0, "la " * 200)], 4)
    began = time.time()
    found = list(item.leaks(["la " * 100_000], 0.5))
    assert [(t, x, c) for t, x, _, c in found] == [(0, 0, 200)] and time.time() - began < 20
