"""Jaccard self-join of word shingles with parity sketches.

A set's sketch has a bit per hashed position, flipped once per shingle; two sketches differ
in at most as many bits as the sets' symmetric difference has members. For a pair that
links, that difference is at most a known share of the two sizes, D in a size band. In each
band the (very wide) sketch is cut into D + 1 + slack blocks, so a linked pair agrees on at
least slack + 1 blocks: sets are joined on equal blocks, pairs filtered by a short sketch,
and verified on the shingles themselves.

The slack serves blocks without a shingle: they say nothing and are shared by many. A
set with at most ``slack`` of them leaves them out; whatever it links with still meets it in
another block. Sets with more give them all.

Equal sets are one class throughout, so copies are never paired. A class is named by 64 bits of
its fingerprint; where two classes share them, the other 64 bits tell them apart and all but one get another name.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache, reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .storage import free, materialise, small_batches
from .wordhash import Words, byte_groups, groups, mix, words_of

SKETCH_BITS = 1024  # of the short sketch, at least; two a shingle for larger sets
MOST_BITS = 1 << 17
PAIRS_PER_TASK = 2000
PAIR_GROUP = 16  # up to so many classes on one block, all pairs are tried; more go by leaders first
SENT_PAIRS = 200_000  # pairs a task remembers, so that copies with many common blocks do not come again and again
GROUP_TILE = 4096  # classes of a larger group whose sketches are held with as many others in one task
TILE = 256  # classes of a component that are counted together with as many others in one task


class Bands:
    """Size bands for links of 100 * intersection >= percent * union."""

    def __init__(self, percent: int):
        self.percent = percent
        self.ratio = 100 / percent

    def largest_difference(self, a, b):
        """The largest symmetric difference of linked sets of sizes a and b."""
        return (100 - self.percent) * (a + b) // (100 + self.percent)

    @lru_cache(maxsize=None)
    def low(self, band: int) -> int:
        """Smallest size of a band; bands widen by the ratio of sizes that can link."""
        if band <= 0:
            return 1
        return max(self.low(band - 1) + 1, math.ceil(self.low(band - 1) * self.ratio))

    @lru_cache(maxsize=None)
    def blocks(self, band: int) -> tuple[int, int]:
        """(blocks, slack) of a band; no block where linked sets are equal sets."""
        top = self.low(band + 1) - 1
        d = self.largest_difference(top, top)
        if not d:
            return 0, 0
        slack = 1
        for _ in range(8):
            m = d + 1 + slack
            load = self.percent / 100 * self.low(band) / m
            empty = m * math.exp(-load)
            slack = max(1, min(d + 1, math.ceil(empty + 2 * math.sqrt(empty))))
        return d + 1 + slack, slack

    @lru_cache(maxsize=1 << 16)
    def of_size(self, n: int) -> tuple[int, ...]:
        """Bands in which a set of n members takes part: its own, and those of larger partners."""
        band = 0
        while self.low(band + 1) <= n:
            band += 1
        out = [band]
        while 100 * n >= self.percent * self.low(out[-1] + 1):
            out.append(out[-1] + 1)
        return tuple(b for b in out if self.blocks(b)[0])


def shingle_sets(words: Words, n_docs: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct shingle hashes of each text, end to end, and where each text's begin."""
    value, _ = words.runs(k)
    count = np.diff(words.first)
    # fewer words than a shingle: the whole sequence is one
    short = {n: words.runs(n)[0] for n in np.unique(count[(count > 0) & (count < k)]).tolist()}
    sets = []
    for at, n in zip(words.first[:n_docs].tolist(), count.tolist(), strict=True):
        if n >= k:
            v = np.sort(value[at : at + n - k + 1])
            sets.append(v[np.concatenate(([True], v[1:] != v[:-1]))])
        else:
            sets.append(short[n][at : at + 1] if n else value[:0])
    begin = np.cumsum([0, *map(len, sets)])
    return (np.concatenate(sets) if sets else value[:0]), begin


def sets_of(texts: list[str], k: int) -> tuple[np.ndarray, np.ndarray]:
    """The same of any list of texts, hashed a bounded group at a time."""
    values, begin = [np.zeros(0, np.uint64)], [np.zeros(1, np.int64)]
    for some, raw in byte_groups(pa.array(texts, pa.large_string())):
        v, b = shingle_sets(words_of(raw, lower=True), some.stop - some.start, k)
        values.append(v)
        begin.append(begin[-1][-1] + b[1:])
    return np.concatenate(values), np.concatenate(begin)


def short_sketch(values: np.ndarray) -> bytes:
    """Parities of the set at 2**i bits. Positions are low bits of the hash, so a wide sketch folds into a narrow one."""
    width = min(MOST_BITS, max(SKETCH_BITS, 1 << (2 * len(values) - 1).bit_length()))
    bits = np.bincount((values >> np.uint64(7)).astype(np.int64) & (width - 1), minlength=width) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little").tobytes()


def folded(sketches: list[bytes], width: int = SKETCH_BITS) -> np.ndarray:
    """The sketches folded to ``width`` bits, a row of 64-bit words each."""
    if all(8 * len(x) == width for x in sketches):
        return np.frombuffer(b"".join(sketches), np.uint64).reshape(len(sketches), -1)
    return np.array([np.bitwise_xor.reduce(np.frombuffer(x, np.uint64).reshape(-1, width // 64), axis=0) for x in sketches]).reshape(len(sketches), -1)


def apart(x: bytes, y: bytes) -> int:
    """Bits in which two sketches differ, at the narrower one's width."""
    width = 8 * min(len(x), len(y))
    return int(np.bitwise_count(folded([x], width) ^ folded([y], width)).sum())


def block_keys(values: np.ndarray, bands: Bands) -> np.ndarray:
    """Keys (64-bit hashes of band, block and the block's odd bits) under which a set is joined."""
    out = []
    for band in bands.of_size(len(values)):
        m, slack = bands.blocks(band)
        spread = mix(values + np.uint64(band + 1))
        block = (spread >> np.uint64(33)).astype(np.int64) % m
        order = np.argsort(block, kind="stable")
        block, bits = block[order], mix(spread[order] ^ np.uint64(0x5851F42D4C957F2D))
        begin = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1])))
        odd = np.bitwise_xor.reduceat(bits, begin)
        out.append(mix(odd ^ mix(block[begin].astype(np.uint64) + np.uint64(band << 40))))
        if m - len(begin) > slack:
            empty = np.setdiff1d(np.arange(m), block[begin])
            out.append(mix(mix(empty.astype(np.uint64) + np.uint64(band << 40))))
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def _sets(batches: Iterator[pa.RecordBatch], k: int):
    """(batch columns before the text, row numbers, set members, begins) of groups of texts."""
    for batch in batches:
        for some, texts in byte_groups(batch.column(batch.num_columns - 1)):
            values, begin = shingle_sets(words_of(texts, lower=True), len(texts), k)
            yield batch.slice(some.start, some.stop - some.start), values, begin


def _prints(values: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit fingerprints of each set (0 for empty ones)."""
    out = []
    for salt in (0x2545F4914F6CDD1D, 0x9FB21C651E98DF25):
        total = np.concatenate(([np.uint64(0)], np.cumsum(mix(values ^ np.uint64(salt)))))
        out.append(total[begin[1:]] - total[begin[:-1]])
    return out[0], out[1]


def _features(docs: DataFrame, k: int) -> DataFrame:
    def run(batches):
        for rows, values, begin in _sets(batches, k):
            f1, f2 = _prints(values, begin)
            n = np.diff(begin)
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(n, pa.int64()), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), pa.array([short_sketch(values[a:b]) if b > a else None for a, b in zip(begin[:-1], begin[1:], strict=True)], pa.binary())], names=["doc_id", "mark", "n", "f1", "f2", "sketch"])

    return docs.mapInArrow(run, "doc_id long, mark long, n long, f1 long, f2 long, sketch binary")


def shared_names(classes: DataFrame) -> dict[tuple[int, int], int]:
    """New names of classes whose first 64 bits another class has too, by both halves of the fingerprint.

    Of n classes about n^2 / 2^65 pairs are expected: a few hundred at 10^11."""
    twice = classes.groupBy("cls").agg(F.sort_array(F.collect_list("f2")).alias("f2")).filter(F.size("f2") > 1)
    out = {}
    for r in twice.collect():
        for f2 in r.f2[1:]:
            out[r.cls, f2] = int(mix(np.array([r.cls ^ f2], np.int64).view(np.uint64) * _OTHER).view(np.int64)[0])
    return out


_OTHER = np.uint64(0xA24BAED4963EE407)


def _keyed(docs: DataFrame, k: int, bands: Bands, other: dict[tuple[int, int], int]) -> DataFrame:
    """(key, cls) of every set's blocks; each task gives a class once."""

    def run(batches):
        seen: set[int] = set()
        for _, values, begin in _sets(batches, k):
            f1, f2 = _prints(values, begin)
            if other:
                f1 = np.array([other.get(x, x[0]) for x in zip(f1.view(np.int64).tolist(), f2.view(np.int64).tolist(), strict=True)], np.int64).view(np.uint64)
            keys, owners = [], []
            for i, (a, b) in enumerate(zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True)):
                c = int(f1[i])
                if b > a and c not in seen:
                    seen.add(c)
                    some = block_keys(values[a:b], bands)
                    keys.append(some)
                    owners.append(np.full(len(some), f1[i]))
            if keys:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.concatenate(owners).view(np.int64))], names=["key", "cls"])

    return docs.mapInArrow(run, "key long, cls long")


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by (key, cls): pairs (a, b) to try, and for larger groups the pairs with
    the group's first class only (and its own), marked as such. A group may span batches; only its
    first class and size so far, or its few first members, are held. Pairs that went out before go out once."""
    key, lead, members, size, last = None, 0, [], 0, None
    sent: set[tuple[int, int, bool]] = set()
    for batch in batches:
        keys, classes = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        if not len(keys):
            continue
        new = np.ones(len(keys), bool)
        new[1:] = keys[1:] != keys[:-1]
        begin = np.flatnonzero(new)
        alone = np.diff(np.append(begin, len(keys))) == 1
        alone[[0, -1]] = False  # may go on in another batch
        out: list[tuple[int, int, bool]] = []
        begins, ends = begin[~alone].tolist(), np.append(begin[1:], len(keys))[~alone].tolist()
        for i, j in zip(begins, ends, strict=True):
            if keys[i] != key:
                key, members, size, last = keys[i], [], 0, None
                lead = int(classes[i])
            for c in classes[i:j].tolist():
                if c == last:
                    continue
                last = c
                size += 1
                if size <= PAIR_GROUP:
                    out += [(m, c, False) for m in members]
                    members.append(c)
                else:
                    if size == PAIR_GROUP + 1:
                        out += [(lead, m, True) for m in members]
                    out.append((lead, c, True))
        if len(sent) > SENT_PAIRS:
            sent = set()
        fresh = set(out) - sent
        sent |= fresh
        a, b, large = zip(*fresh, strict=True) if fresh else ((), (), ())
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(large, pa.bool_())], names=["a", "b", "large"])


def _near(bands: Bands):
    """Pairs whose sizes and short sketches allow a link."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            n1, n2 = batch.column("n1").to_numpy(), batch.column("n2").to_numpy()
            s1, s2 = batch.column("s1").to_pylist(), batch.column("s2").to_pylist()
            most = bands.largest_difference(n1, n2)
            ok = (100 * np.minimum(n1, n2) >= bands.percent * np.maximum(n1, n2)) & (np.bitwise_count(folded(s1) ^ folded(s2)).sum(axis=1, dtype=np.int64) <= most)
            for i in np.flatnonzero(ok):
                if 8 * len(s1[i]) > SKETCH_BITS and apart(s1[i], s2[i]) > most[i]:
                    ok[i] = False
            yield batch.select(["a", "b"]).filter(pa.array(ok))

    return run


def _verify(k: int, percent: int):
    def run(batches):
        for batch in batches:
            ok = []
            t1, t2 = batch.column("t1"), batch.column("t2")
            for some in groups((pc.binary_length(t1).to_numpy() + pc.binary_length(t2).to_numpy()).tolist()):
                (v1, b1), (v2, b2) = (sets_of(t.slice(some.start, some.stop - some.start).to_pylist(), k) for t in (t1, t2))
                for j in range(len(b1) - 1):
                    x, y = v1[b1[j] : b1[j + 1]], v2[b2[j] : b2[j + 1]]
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    ok.append(100 * common >= percent * (len(x) + len(y) - common))
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return run


def _leftover(bands: Bands, nearest: bool):
    """From rows sorted by (key, p, q): pairs of the tiles p and q of a larger group that are in
    different components so far, if their sketches allow a link. With ``nearest`` a member outside
    the tiles' main component gives only its nearest in it and its nearest in any other; else all.
    Sketches, not texts, are held, for two tiles at a time."""

    def emit(p, q, rows):
        cls, n, comp, tile = (np.array([r[i] for r in rows]) for i in range(4))
        whole = [r[4] for r in rows]
        sketch = folded(whole)
        names, sizes = np.unique(comp, return_counts=True)
        main = names[np.argmax(sizes)]
        for i in np.flatnonzero(comp != main):
            ok = (comp != comp[i]) & (100 * np.minimum(n, n[i]) >= bands.percent * np.maximum(n, n[i]))
            if p != q:
                ok &= tile != tile[i]
            j = np.flatnonzero(ok)
            most = bands.largest_difference(n[j], n[i])
            far = np.bitwise_count(sketch[j] ^ sketch[i]).sum(axis=1, dtype=np.int64)
            j, far, most = j[far <= most], far[far <= most], most[far <= most]
            if len(j) and 8 * len(whole[i]) > SKETCH_BITS:
                far = np.array([apart(whole[x], whole[i]) for x in j])
                j, far = j[far <= most], far[far <= most]
            if nearest and len(j):
                inside = comp[j] == main
                j = np.array([x[a.argmin()] for x, a in ((j[inside], far[inside]), (j[~inside], far[~inside])) if len(x)])
            yield {(min(cls[i], c), max(cls[i], c)) for c in cls[j]}

    def run(batches):
        def out(pairs):
            a, b = zip(*pairs, strict=True) if pairs else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        key, rows, waiting = None, [], set()
        for batch in batches:
            for r in zip(*(batch.column(c).to_pylist() for c in ("key", "p", "q", "cls", "n", "component", "tile", "sketch")), strict=True):
                if r[:3] != key:
                    if rows:
                        for pairs in emit(*key[1:], rows):  # a pair that meets on several keys of the task goes out once
                            waiting |= pairs
                            if len(waiting) > 200_000:
                                yield out(waiting)
                                waiting = set()
                    key, rows = r[:3], []
                rows.append(r[3:])
        if rows:
            for pairs in emit(*key[1:], rows):
                waiting |= pairs
        yield out(waiting)

    return run


def in_tiles(rows: DataFrame, sizes: DataFrame, group: str, member: str, tile: int) -> DataFrame:
    """``rows`` once for each pair of tiles (p <= q) of its group that its own tile is in. ``sizes``: group, size;
    a group is dealt by hash into tiles of about ``tile`` members, so a task never holds a large group."""
    tiles = F.ceil(F.col("size") / tile).cast("int")
    dealt = rows.join(sizes.withColumn("tiles", tiles).drop("size"), group).withColumn("tile", F.pmod(F.xxhash64(member), F.col("tiles")).cast("int"))
    each = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    return each.withColumn("p", F.least("tile", "other")).withColumn("q", F.greatest("tile", "other")).drop("tiles", "other")


def _common(x: np.ndarray, bx: np.ndarray, y: np.ndarray, by: np.ndarray, width: int = 8192) -> np.ndarray:
    """Sizes of the intersections of the sets x[bx[i]:bx[i + 1]] with the sets of y, as a matrix:
    products of 0/1 matrices over ``width`` shared members at a time."""
    shared = np.intersect1d(x, y)
    out = np.zeros((len(bx) - 1, len(by) - 1), np.int64)
    sides = []
    for v, b in ((x, bx), (y, by)):
        at = np.minimum(np.searchsorted(shared, v), max(0, len(shared) - 1))
        hit = np.flatnonzero(shared[at] == v) if len(shared) else np.zeros(0, np.int64)
        row = np.repeat(np.arange(len(b) - 1), np.diff(b))[hit]
        order = np.argsort(at[hit], kind="stable")
        sides.append((row[order], at[hit][order], len(b) - 1))
    for begin in range(0, len(shared), width):
        parts = []
        for row, at, n in sides:
            i, j = np.searchsorted(at, (begin, begin + width))
            m = np.zeros((n, min(width, len(shared) - begin)), np.float32)
            m[row[i:j], at[i:j] - begin] = 1
            parts.append(m)
        out += (parts[0] @ parts[1].T).astype(np.int64)
    return out


def _tile_links(k: int, percent: int):
    """From rows sorted by (component, p, q): each class's number of links between the tiles p and q."""

    def count(p, q, rows):
        sides = []
        for tile in (p, q):
            mine = [(c, t) for at, c, t in rows if at == tile]
            values, begin = sets_of([t for _, t in mine], k)
            sides.append(([c for c, _ in mine], values, begin))
        (c1, x, bx), (c2, y, by) = sides
        common = _common(x, bx, y, by)
        linked = 100 * common >= percent * (np.diff(bx)[:, None] + np.diff(by)[None, :] - common)
        if p == q:
            np.fill_diagonal(linked, False)
            return c1, linked.sum(axis=1).tolist()
        return c1 + c2, linked.sum(axis=1).tolist() + linked.sum(axis=0).tolist()

    def run(batches):
        key, rows = None, []
        for batch in batches:
            for c, p, q, *row in zip(*(batch.column(x).to_pylist() for x in ("component", "p", "q", "tile", "cls", "text")), strict=True):
                if (c, p, q) != key:
                    if rows:
                        yield out(*count(*key[1:], rows))
                    key, rows = (c, p, q), []
                rows.append(row)
        if rows:
            yield out(*count(*key[1:], rows))

    def out(classes, n):
        return pa.RecordBatch.from_arrays([pa.array(classes, pa.int64()), pa.array(n, pa.int64())], names=["node", "n"])

    return run


def all_degrees(docs: DataFrame, classes: DataFrame, links: DataFrame, comp: DataFrame, large: DataFrame, k: int, percent: int) -> DataFrame:
    """(node, n_verified_links): every class's number of links to other classes, none left out.

    Classes that meet in small groups only had all their pairs tried. Of the classes in larger
    groups, all pairs within a component (no link leaves it) are counted: the component is dealt
    into tiles by hash, and a task gets two tiles at a time. Counts go out, not pairs.
    """
    members = materialise(large.select(F.col("cls").alias("node")).distinct().join(comp, "node"), "tile-members")
    named = members.join(classes.select(F.col("cls").alias("node"), "first.doc_id", "first.mark"), "node")
    texts = materialise(texts_of(docs, named.select(F.col("node").alias("cls"), "component", "doc_id", "mark"), members.count(), "component"), "tile-texts")
    pairs = in_tiles(texts, members.groupBy("component").agg(F.count(F.lit(1)).alias("size")), "component", "cls", TILE)
    inner = pairs.repartition("component", "p", "q").sortWithinPartitions("component", "p", "q").mapInArrow(_tile_links(k, percent), "node long, n long")
    a, b = (members.select(F.col("node").alias(x), F.lit(True).alias(f"_{x}")) for x in "ab")
    outer = links.join(a, "a", "left").join(b, "b", "left").filter("_a IS NULL OR _b IS NULL").select(F.explode(F.array("a", "b")).alias("node"), F.lit(1).cast("long").alias("n"))
    out = materialise(inner.unionByName(outer).groupBy("node").agg(F.sum("n").alias("n_verified_links")), "tile-degrees")
    free(members, texts)
    return out


def texts_of(docs: DataFrame, named: DataFrame, most: int, *more: str) -> DataFrame:
    """(cls, text, ``more``) of classes named by (doc_id, mark), at most ``most`` of them. Names and documents are
    shuffled at any size, so that the cost grows with the documents alone."""
    named = materialise(named, "text-names", most)
    found = docs.join(named.hint("shuffle_hash"), docs.doc_id.eqNullSafe(named.doc_id) & (docs.mark == named.mark))
    return found.select("cls", "text", *more).dropDuplicates(["cls"])


def joined_by(comp: DataFrame, links: DataFrame) -> DataFrame:
    """Components (node, component) after more links: only the components that these join are worked on."""
    ends = links.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    comp = comp.unionByName(ends.join(comp, "node", "left_anti").withColumn("component", F.col("node")))
    a, b = (comp.select(F.col("node").alias(x), F.col("component").alias(f"c{x}")) for x in "ab")
    between = links.join(a, "a").join(b, "b").filter("ca <> cb").select(F.col("ca").alias("a"), F.col("cb").alias("b")).distinct()
    merged = components(between).select(F.col("node").alias("component"), F.col("component").alias("_to"))
    return comp.join(merged, "component", "left").select("node", F.coalesce("_to", "component").alias("component"))


@dataclass
class Linked:
    """What the join leaves: features of every row, links between classes (each a written table),
    components of linked classes, classes, members of larger groups. The links join all that belongs
    together but lack some within larger groups: see all_degrees."""

    features: DataFrame
    links: list[DataFrame]
    comp: DataFrame
    classes: DataFrame
    large: DataFrame

    def all_links(self) -> DataFrame:
        return reduce(DataFrame.unionAll, self.links)

    def free(self) -> None:
        """All but the features."""
        free(*self.links, self.comp, self.classes, self.large)


def linked_classes(docs: DataFrame, k: int, percent: int) -> Linked:
    """``docs``: doc_id, mark, text."""
    bands = Bands(percent)
    small_batches(docs.sparkSession)
    features = materialise(_features(docs, k), "sketch-features")
    # of each class: its first document (the smallest id), size and short sketch
    first = features.filter("n > 0").groupBy(F.col("f1").alias("cls"), "f2").agg(F.min(F.struct("doc_id", "mark")).alias("first"), F.max("n").alias("n"), F.max("sketch").alias("sketch"))
    classes = materialise(first, "sketch-classes", features.count())
    other = shared_names(classes)
    if other:

        def renamed(name: str):
            out = F.col(name)
            for (f1, f2), new in other.items():
                out = F.when((F.col(name) == f1) & (F.col("f2") == f2), F.lit(new)).otherwise(out)
            return out

        old = features, classes
        classes = materialise(classes.withColumn("cls", renamed("cls")), "sketch-classes")
        features = materialise(features.withColumn("f1", renamed("f1")), "sketch-features")
        free(*old)
    met = materialise(_keyed(docs.select("text"), k, bands, other).repartition("key").sortWithinPartitions("key", "cls").mapInArrow(_meet, "a long, b long, large boolean"), "sketch-meet")

    n_met = met.count()

    def verified(pairs: DataFrame, most: int | None = None) -> DataFrame:
        """The links among ``pairs``, of which there are ``most`` at most."""
        first = pairs.distinct().join(classes.select(F.col("cls").alias("a"), F.col("n").alias("n1"), F.col("sketch").alias("s1")), "a")
        near = first.join(classes.select(F.col("cls").alias("b"), F.col("n").alias("n2"), F.col("sketch").alias("s2")), "b").mapInArrow(_near(bands), "a long, b long")
        near = materialise(near, "sketch-near", most)
        need = near.select(F.explode(F.array("a", "b")).alias("cls")).distinct()
        texts = materialise(texts_of(docs, classes.join(need, "cls").select("cls", "first.doc_id", "first.mark"), 2 * near.count()), "sketch-texts")
        both = near.join(texts.select(F.col("cls").alias("a"), F.col("text").alias("t1")), "a").join(texts.select(F.col("cls").alias("b"), F.col("text").alias("t2")), "b")
        tasks = 1 + near.count() // PAIRS_PER_TASK  # texts pass here, but a few pairs make no task
        out = materialise(both.select("a", "b", "t1", "t2").coalesce(tasks).mapInArrow(_verify(k, percent), "a long, b long"), "sketch-links")
        free(near, texts)
        return out

    links = [verified(met.filter("a <> b").select("a", "b"), n_met)]
    # Larger groups with one leader are one group: near copies share many blocks, and so many groups.
    large = materialise(met.filter("large").select(F.col("a").alias("key"), F.col("b").alias("cls")).distinct(), "sketch-large", n_met)
    free(met)
    # Leaders may not link all that their group does: what is still apart is tried with its
    # nearest and then in full. Joined components need no more pairs, so little is left.
    comp = components(links[0])
    for nearest in (True, False):
        members = large.join(comp.withColumnRenamed("node", "cls"), "cls", "left").withColumn("component", F.coalesce("component", "cls"))
        members = materialise(members, "sketch-members", n_met)
        split = members.groupBy("key").agg(F.min("component").alias("x"), F.max("component").alias("y"), F.count(F.lit(1)).alias("size")).filter("x <> y").select("key", "size")
        split = materialise(split, "sketch-split", n_met)
        if not split.limit(1).count():
            free(members, split)
            break
        rows = in_tiles(members, split, "key", "cls", GROUP_TILE).join(classes.select("cls", "n", "sketch"), "cls").select("key", "p", "q", "cls", "n", "component", "tile", "sketch")
        more = rows.repartition("key", "p", "q").sortWithinPartitions("key", "p", "q", "cls").mapInArrow(_leftover(bands, nearest), "a long, b long")
        fresh = verified(more)
        if fresh.limit(1).count():
            links.append(fresh)
            old, comp = comp, materialise(joined_by(comp, fresh), "sketch-components")
            free(old)
        free(members, split)
    return Linked(features, links, comp, classes, large)


def shingle_components(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", every_link: bool = True) -> DataFrame:
    """doc_id, mark, n_shingles, n_verified_links and component_id of every row.

    Sets are the distinct ``k``-word shingles of the text with A-Z lower-cased; a text of fewer
    words is one shingle, and one without words (or null) has none and links with nothing. Two
    rows link when 100 * intersection >= ``percent`` * union. component_id is the smallest id
    reachable by links, the own id included; a null id counts as smaller than all others only
    if every member's id is null (then component_id is null). n_verified_links counts the links to
    other classes of equal sets, all of them; without ``every_link`` members of groups of more than PAIR_GROUP
    classes on one block are not compared further once joined (components are exact either way). Repeated rows are copies of each other; ``mark`` hashes the text.
    An empty table gives an empty result; other columns are not read.
    """
    return _rows(docs, k, percent, id_col, text_col, every_link).drop("component")


def _rows(docs: DataFrame, k: int, percent: int, id_col: str, text_col: str, every_link: bool) -> DataFrame:
    """The rows of shingle_components with ``component``: the fingerprint of a class, null where a text has no words."""
    docs = docs.select(docs[id_col].cast("long").alias("doc_id"), F.xxhash64(docs[text_col]).alias("mark"), docs[text_col].alias("text"))
    found = linked_classes(docs, k, percent)
    if every_link:
        degree = all_degrees(docs, found.classes, found.all_links(), found.comp, found.large, k, percent)
    else:
        degree = found.all_links().select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n_verified_links"))
    slim = found.features.select("doc_id", "mark", F.col("n").alias("n_shingles"), "f1")
    sizes = slim.filter("n_shingles > 0").groupBy("f1").agg(F.min("doc_id").alias("low"))
    named = sizes.join(found.comp.withColumnRenamed("node", "f1"), "f1", "left").withColumn("component", F.coalesce("component", "f1")).join(degree.withColumnRenamed("node", "f1"), "f1", "left")
    n_classes = found.classes.count()
    named = materialise(named, "sketch-named", n_classes)
    found.free()
    low = named.groupBy("component").agg(F.min("low").alias("component_id"))
    by_class = materialise(named.join(low, "component").select("f1", "component", "component_id", "n_verified_links"), "sketch-groups", n_classes)
    free(named)
    out = slim.join(by_class.hint("merge"), "f1", "left")
    empty = F.col("n_shingles") == 0
    return out.select("doc_id", "mark", "n_shingles", F.coalesce(F.when(empty, F.lit(0)).otherwise(F.col("n_verified_links")), F.lit(0)).cast("long").alias("n_verified_links"), F.when(empty, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "component")


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one row of each component: the one with the smallest (id, mark), null ids last (of repeated rows, one).
    Texts without words link with nothing and all stay. Components go by fingerprint, as ids may be null or shared."""
    rows = _rows(docs, k, percent, "doc_id", "text", False).groupBy("component", "doc_id", "mark").agg(F.count(F.lit(1)).alias("n"))
    n = docs.count()
    rows = materialise(rows, "keep-one-rows", n)
    first = rows.filter("component IS NOT NULL").groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "mark", "n")).alias("f"))
    found = first.select("f.doc_id", "f.mark", "f.n").unionAll(rows.filter("component IS NULL").select("doc_id", "mark", "n"))
    found = materialise(found.select(F.col("doc_id").alias("_id"), F.col("mark").alias("_mark"), "n"), "keep-one", n)
    free(rows)
    kept = docs.withColumn("_own_mark", F.xxhash64("text"))
    kept = kept.join(found.drop("n").hint("shuffle_hash"), kept.doc_id.eqNullSafe(found._id) & (kept._own_mark == found._mark), "left_semi")
    return (kept.dropDuplicates(["doc_id", "_own_mark"]) if found.filter("n > 1").limit(1).count() else kept).drop("_own_mark")


def op8_parity_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shingle_components(spark.read.parquet(f"{sf_dir}/documents.parquet"), 4, 85, every_link=False)
    return out.select("doc_id", "n_shingles", "component_id")


def op8_parity_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The join with each document's number of links to different texts."""
    out = shingle_components(spark.read.parquet(f"{sf_dir}/documents.parquet"), 4, 85)
    return out.select("doc_id", "n_shingles", "component_id", F.col("n_verified_links").alias("n_links"))


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, md5(array_to_string(w[s + 1 : s + 4], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(greatest(1, len(w) - 3))) AS s FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS i FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * i >= 85 * (a.n + b.n - i)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id AS v, doc_id AS c FROM d UNION SELECT e.y, r.c FROM r JOIN e ON r.v = e.x WHERE r.c < e.y)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, (SELECT min(c) FROM r WHERE r.v = d.doc_id) AS component_id
FROM d LEFT JOIN n USING (doc_id)
"""

QUERIES = {"op8_parity_join": op8_parity_join, "op8_parity_links": op8_parity_links}
ORACLES = {"op8_parity_join": ORACLE}
