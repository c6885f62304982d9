"""Parts of the operators that need no Spark, against brute force."""

import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np

from starwatch.llm import decontaminate, linededup, packing, paritysketch, sharding, substringdedup, tokencount, tokens, urlfilter, wordhash
from starwatch.llm.countmin import Partial, SketchShape, _unpack

PIECES = ["a", "b", " ", "  ", "\n", "\t", "'s", "'", "<|endoftext|>", "<|", "ü", "1", ".", " hello", "\u3000", "\r\n", "'re", "日本", "\x1c", "\x85", "\x00", "aaaaaaaaaaaaaaaaaaa", "      "]


def texts(n, top=40, seed=0):
    r = random.Random(seed)
    return ["".join(r.choice(PIECES) for _ in range(r.randint(0, top))) for _ in range(n)]


def test_encoder_equals_the_library(monkeypatch):
    lib = tokens.library(tokens.vocabulary_path())
    some = texts(1500)
    want = [np.array(e.ids, "<u4").tobytes() for e in lib.encode_batch(some, add_special_tokens=False)]
    for entries in (0, 30, tokens.MEMO_ENTRIES):  # no memo, a full one, one that learns
        monkeypatch.setattr(tokens, "MEMO_ENTRIES", entries)
        whole = tokens.PieceEncoder(tokens.vocabulary_path())
        assert [x for i in range(0, len(some), 50) for x in whole.encode(some[i : i + 50])] == want
    rank = tokens.rank_encoder(tokens.vocabulary_path(), tokens.vocabulary_path("byte_bpe_50k.tiktoken"))
    assert rank.encode(some) == want
    long = [" " * 20_000 + "x", "a b\nc " * 3000]
    assert rank.encode(long) == whole.encode(long)
    assert whole.encode(long) == [np.array(lib.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in long]


def test_chunked_counts_equal_whole_ones():
    lib = tokens.library(tokens.vocabulary_path())
    encode = lambda p: lib.encode(p, add_special_tokens=False)
    for t in texts(800, 60, 3):
        assert tokencount.count_by_chunks(t, encode, 40, 20)[0] == len(encode(t).ids)
    t = "a" * 5000  # no boundary at all: the chunk must grow
    assert tokencount.count_by_chunks(t, encode, 64, 20)[0] == len(encode(t).ids)


def one_by_one(lengths, window):
    """Best-fit decreasing, item by item."""
    rooms = []
    for n in sorted(lengths, reverse=True):
        fits = [r for r in rooms if r >= n]
        if fits:
            rooms.remove(min(fits))
            rooms.append(min(fits) - n)
        else:
            rooms.append(window - n)
    return Counter(rooms)


def test_packing_plan_equals_item_by_item():
    r = random.Random(1)
    for _ in range(60):
        window = r.choice([7, 16, 31])
        lengths = [r.randint(1, window) for _ in range(r.randint(0, 60))]
        used = {}
        for n, a, b, first, per, at in packing.plan_windows(Counter(lengths), window):
            for rank in range(a, b):
                w, k = first + (rank - a) // per, (rank - a) % per
                used.setdefault(w, []).append((at + k * n, n))
        assert sorted(used) == list(range(len(used)))
        rooms = Counter()
        for pieces in used.values():
            end = 0
            for at, n in sorted(pieces):
                assert at == end
                end += n
            assert end <= window
            rooms[window - end] += 1
        assert rooms == one_by_one(lengths, window)


def test_capacity_tree():
    t = packing.CapacityTree(20)
    assert t.tightest(1) is None
    for c in (5, 9, 20):
        t.add(c, 1)
    assert [t.tightest(x) for x in (1, 5, 6, 10, 20)] == [5, 5, 9, 20, 20]
    t.add(9, -1)
    assert t.tightest(6) == 20


def test_words_and_runs_match_python():
    some = [b"", b" \t", b"a b  a b\nc", "x ü\u00a0y z".encode(), b"one"]
    w = wordhash.words_of(some)
    flat = [x for t in some for x in t.split()]
    assert len(w.value) == len(flat)
    assert all((w.value[i] == w.value[j]) == (flat[i] == flat[j]) for i in range(len(flat)) for j in range(len(flat)))
    v, ok = w.runs(2)
    pairs = [tuple(flat[i : i + 2]) for i in range(len(flat) - 1)]
    assert all((v[i] == v[j]) == (pairs[i] == pairs[j]) for i in range(len(v)) for j in range(len(v)))
    assert ok.sum() == sum(max(0, len(t.split()) - 1) for t in some)


def test_sliding():
    x = np.array([5, 3, 8, 1, 9, 2, 7], np.uint64)
    for k in range(1, 8):
        assert wordhash.sliding(x, k, np.minimum).tolist() == [min(x[i : i + k]) for i in range(len(x) - k + 1)]


def test_sketch_never_underestimates():
    shape = SketchShape(2, 10, 6)
    rng = np.random.default_rng(0)
    values = rng.integers(0, 1 << 63, 900).astype(np.uint64)
    p = Partial(shape)
    list(p.add(np.concatenate([values, values[:50]])))
    twice = set()
    for tile, _, two in p.flush():
        twice |= {(tile, int(c)) for c in _unpack(two)}
    for v in values[:50]:
        for row in range(2):
            cell = int(shape.cells(np.array([v]), row)[0])
            assert (row * 16 + (cell >> 6), cell & 63) in twice


def test_every_repeated_window_has_a_counted_anchor():
    r = random.Random(5)
    docs = [" ".join(r.choice("abcd") for _ in range(r.randint(0, 60))).encode() for _ in range(30)]
    words = wordhash.words_of(docs)
    at, low, value, anchor, _ = substringdedup._windows(words, 20)
    counted = Counter(value[anchor].tolist())
    seen = {}
    flat = [x for t in docs for x in t.split()]
    for i in at:
        seen.setdefault(tuple(flat[i : i + 20]), []).append(int(low[i]))
    for lows in seen.values():
        assert len(set(lows)) == 1
        if len(lows) > 1:
            assert counted[lows[0]] >= 2


def test_perfect_hash_is_minimal_and_perfect():
    keys = np.unique(np.random.default_rng(2).integers(0, 1 << 63, 5000).astype(np.uint64))
    h = linededup.PerfectHash.build(keys)
    assert sorted(h.places(keys).tolist()) == list(range(len(keys)))
    again = linededup.PerfectHash([x for x in h.levels])
    assert (again.places(keys) == h.places(keys)).all()
    assert linededup.PerfectHash.build(keys[:0]).size == 0


def brute_components(sets, percent):
    n = len(sets)
    comp = list(range(n))
    for i in range(n):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = comp[i], comp[j]
                comp = [min(a, b) if c in (a, b) else c for c in comp]
    return comp


def test_linked_sets_share_a_block():
    r = random.Random(7)
    bands = paritysketch.Bands(80)
    for _ in range(200):
        n = r.choice([5, 9, 20, 60, 200])
        a = {r.getrandbits(64) for _ in range(n)}
        drop = r.randint(0, max(0, n // 8))
        b = set(sorted(a)[drop:]) | {r.getrandbits(64) for _ in range(r.randint(0, n // 10))}
        if a != b and 100 * len(a & b) >= 80 * len(a | b):
            ka, kb = (set(paritysketch.block_keys(np.array(sorted(x), np.uint64), bands).tolist()) for x in (a, b))
            assert ka & kb
            sa, sb = (np.frombuffer(paritysketch.short_sketch(np.array(sorted(x), np.uint64)), np.uint64) for x in (a, b))
            assert int(np.bitwise_count(sa ^ sb).sum()) <= len(a ^ b) <= bands.largest_difference(len(a), len(b))


def brute_tiles(item, doc, least):
    """Longest common unmarked run first, by trying every pair of places."""
    mi, md, total = [False] * len(item), [False] * len(doc), 0
    while True:
        best = (0, 0, 0)
        for i in range(len(item)):
            for j in range(len(doc)):
                k = 0
                while i + k < len(item) and j + k < len(doc) and item[i + k] == doc[j + k] and not mi[i + k] and not md[j + k]:
                    k += 1
                if k > best[0]:
                    best = (k, i, j)
        if best[0] < least:
            return total
        k, i, j = best
        for x in range(k):
            mi[i + x] = md[j + x] = True
        total += k


def test_tiling_matches_brute_force():
    r = random.Random(11)
    for _ in range(80):
        item = [r.choice("abcdefghijklmnop") for _ in range(r.randint(6, 25))]
        cut = r.randint(1, len(item) - 1)
        doc = [r.choice("uvwxyz") for _ in range(5)] + item[cut:] + ["q"] + item[:cut]
        items = decontaminate.TestItems([(1, " ".join(item))], 4)
        got = list(items.leaks([" ".join(doc)], 0.0001))
        assert sum(x[3] for x in got) == brute_tiles(item, doc, 4)


def test_reordered_passage_is_caught_and_clean_text_is_not():
    item = "the quick brown fox jumps over the lazy dog while seven wizards quietly judge my vow of silence"
    a, b = item.split()[:9], item.split()[9:]
    items = decontaminate.TestItems([(3, item), (4, ""), (5, "two words")], 4)
    leaks = {(t, items.ids[x]) for t, x, _, _ in items.leaks(["unrelated words only here", " ".join(b + ["and"] + a).upper(), None, "", "there are Two, Words in this"], 0.5)}
    assert leaks == {(1, 3), (4, 5)}


def test_slots_balance_and_growth_moves_only_into_the_new_shard():
    r = random.Random(3)
    loads = [(r.choice([0, 0, 100, 1000, 5000]) + r.randint(0, 50), 1) for _ in range(512)]
    owner = sharding.assign_slots(loads, 8)
    total = [sum(b for (b, _), o in zip(loads, owner, strict=True) if o == s) for s in range(8)]
    assert max(total) - min(total) <= 60
    grown = sharding.grow(owner, loads, 8)
    assert all(a == b or b == 8 for a, b in zip(owner, grown, strict=True))
    after = [sum(b for (b, _), o in zip(loads, grown, strict=True) if o == s) for s in range(9)]
    assert max(after) < 1.1 * sum(after) / 9


def test_boosted_trees_learn_and_equal_their_expression():
    rng = np.random.default_rng(0)
    x = rng.random((600, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 2] > 0.7)).astype(float)
    model = urlfilter.BoostedTrees(trees=30).fit(x, y)
    assert ((model.margin(x) > 0) == (y > 0)).mean() > 0.97
    text = re.sub(r"([0-9])D\b", r"\1", model.expression(("f0", "f1", "f2")))
    f0, f1, f2 = x[0].tolist()
    got = duckdb.execute(f"SELECT {text} FROM (SELECT {f0!r}::DOUBLE AS f0, {f1!r}::DOUBLE AS f1, {f2!r}::DOUBLE AS f2)").fetchone()[0]
    assert abs(float(got) - model.margin(x[:1])[0]) < 1e-9


def test_line_key():
    assert linededup.line_key(" \t ÄBc\u00a0 \r") == "Äbc\u00a0"
    assert zlib.crc32(b"") == 0
