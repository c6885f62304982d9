"""Sharding by fixed virtual slots.

A record's slot is a hash of its id modulo a fixed number of slots (thousands). Bytes
are summed per slot, and a small versioned map says which shard owns each slot; to
rebalance or to grow, the map is edited and only the slots named in the edit move.
Native: DataFrame functions only.
"""

from __future__ import annotations

import hashlib
import heapq

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .storage import materialise, shared_root

SLOTS = 4096
MAP_SCHEMA = "version int, virtual_slot int, shard int, slot_bytes long, slot_rows long"


def virtual_slot(id_col: Column, slots: int = SLOTS) -> Column:
    """The slot of an id; a null id has the slot of the empty key."""
    return F.pmod(F.xxhash64(id_col.cast("string")), F.lit(slots)).cast("int")


def slot_loads(rows: DataFrame, slots: int = SLOTS) -> list[tuple[int, int]]:
    """(bytes, rows) of every slot. At most ``slots`` rows reach the driver, whatever the input."""
    got = rows.groupBy("virtual_slot").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n")).collect()
    loads = [(0, 0)] * slots
    for r in got:
        loads[r.virtual_slot] = (r.b, r.n)
    return loads


def assign_slots(loads: list[tuple[int, int]], n_shards: int) -> list[int]:
    """First map: heaviest slot first, each to the shard with the fewest bytes so far."""
    heap = [(0, 0, s) for s in range(n_shards)]
    owner = [0] * len(loads)
    for slot in sorted(range(len(loads)), key=lambda i: (-loads[i][0], i)):
        total, n, shard = heapq.heappop(heap)
        owner[slot] = shard
        heapq.heappush(heap, (total + loads[slot][0], n + 1, shard))
    return rebalance(owner, loads, n_shards)


def rebalance(owner: list[int], loads: list[tuple[int, int]], n_shards: int, rounds: int = 10_000) -> list[int]:
    """Edit a map until no single move or swap of slots narrows the gap of the extreme shards.

    Also serves growth: a new, empty shard is then the lightest and only takes slots.
    Works on the slots alone, never on the records.
    """
    owner = list(owner)
    members: list[set[int]] = [set() for _ in range(n_shards)]
    total = [0] * n_shards
    for slot, shard in enumerate(owner):
        members[shard].add(slot)
        total[shard] += loads[slot][0]
    for _ in range(rounds):
        high = max(range(n_shards), key=lambda s: (total[s], -s))
        low = min(range(n_shards), key=lambda s: (total[s], s))
        gap = total[high] - total[low]
        move = max((loads[s][0] for s in members[high] if 0 < loads[s][0] < gap), default=0, key=lambda b: min(b, gap - b))
        best, give, take = min(move, gap - move), move, None
        mine = sorted(members[low], key=lambda s: loads[s][0])
        theirs = sorted(members[high], key=lambda s: loads[s][0])
        j = 0
        for s in theirs:  # the swap whose difference comes closest to half of the gap
            while j < len(mine) and loads[s][0] - loads[mine[j]][0] >= gap / 2:
                j += 1
            for k in (j - 1, j):
                if 0 <= k < len(mine):
                    d = loads[s][0] - loads[mine[k]][0]
                    if 0 < d < gap and min(d, gap - d) > best:
                        best, give, take = min(d, gap - d), s, mine[k]
        if best <= 0:
            break
        if take is None:
            give = min(s for s in members[high] if loads[s][0] == move)
        moves = [(give, high, low)] + ([(take, low, high)] if take is not None else [])
        for slot, a, b in moves:
            members[a].discard(slot)
            members[b].add(slot)
            owner[slot] = b
            total[a] -= loads[slot][0]
            total[b] += loads[slot][0]
    return owner


def grow(owner: list[int], loads: list[tuple[int, int]], n_shards: int) -> list[int]:
    """The map with shard ``n_shards`` added: slots move into the new shard only."""
    owner, new = list(owner), n_shards
    total = [0] * (n_shards + 1)
    members: dict[int, list[int]] = {s: [] for s in range(n_shards)}
    for slot, shard in enumerate(owner):
        total[shard] += loads[slot][0]
        members[shard].append(slot)
    for s in members:
        members[s].sort(key=lambda slot: (loads[slot][0], -slot))
    fair = sum(total) / (n_shards + 1)
    while True:
        high = max(range(n_shards), key=lambda s: (total[s], -s))
        if not members[high]:
            break
        slot = members[high].pop()
        b = loads[slot][0]
        if not b or total[new] + b > fair + b / 2:
            break
        total[high] -= b
        total[new] += b
        owner[slot] = new
    return owner


def edited(owner: list[int], loads: list[tuple[int, int]], n_shards: int) -> list[int]:
    """The next map after ``owner``: shards that are gone give their slots to the lightest, new ones
    are grown one by one, and the rest is rebalanced; slots that no edit names stay."""
    if len(owner) != len(loads):
        raise ValueError(f"the stored map has {len(owner)} slots, not {len(loads)}")
    owner, have = list(owner), max(owner) + 1
    total = [0] * n_shards
    for slot, shard in enumerate(owner):
        if shard < n_shards:
            total[shard] += loads[slot][0]
    for slot in sorted((i for i, s in enumerate(owner) if s >= n_shards), key=lambda i: (-loads[i][0], i)):
        owner[slot] = min(range(n_shards), key=lambda s: (total[s], s))
        total[owner[slot]] += loads[slot][0]
    for new in range(have, n_shards):
        owner = grow(owner, loads, new)
    return rebalance(owner, loads, n_shards)


def map_rows(owner: list[int], loads: list[tuple[int, int]], version: int) -> list[tuple]:
    return [(version, slot, shard, *loads[slot]) for slot, shard in enumerate(owner)]


def save_map(spark: SparkSession, path: str, owner: list[int], loads: list[tuple[int, int]], version: int) -> None:
    """Append one version of the map to the table at ``path``; older versions stay readable."""
    spark.createDataFrame(map_rows(owner, loads, version), MAP_SCHEMA).coalesce(1).write.mode("append").partitionBy("version").parquet(path)


def load_map(spark: SparkSession, path: str, version: int | None = None) -> list[int]:
    """The owners by slot in ``version`` (the newest if None)."""
    table = spark.read.schema(MAP_SCHEMA).parquet(path)
    if version is None:
        version = table.agg(F.max("version")).first()[0]
    rows = table.filter(F.col("version") == version).select("virtual_slot", "shard").collect()
    owner = [0] * len(rows)
    for r in rows:
        owner[r.virtual_slot] = r.shard
    return owner


def shard_rows(
    docs: DataFrame, n_shards: int = 8, slots: int = SLOTS, id_col: str = "doc_id", text_col: str = "text", map_path: str | None = None
) -> DataFrame:
    """Give every row a shard 0..n_shards-1 of near equal bytes and a place in it.

    Returns id, size (UTF-8 bytes of the text plus 1), text_crc32, virtual_slot, shard and
    ``slot``: the row's place in its shard, gapless from 0. Places come from a row number
    within the virtual slot plus the rows of the shard's earlier slots, so no task ever
    holds a whole shard. Null text: size 1 and the CRC of no bytes; null ids and repeated
    rows are rows like any other (order within a slot: id, CRC, size); an empty table
    gives an empty result. Other columns are not looked at, whatever their names.
    ``map_path``: the newest map there is edited (or a first one made) and appended as the next version.
    """
    spark = docs.sparkSession
    raw = F.coalesce(F.col(text_col), F.lit(""))
    rows = materialise(
        docs.select(
            F.col(id_col).alias("doc_id"),
            (F.octet_length(raw) + 1).cast("long").alias("size"),
            F.crc32(raw.cast("binary")).alias("text_crc32"),
            virtual_slot(F.col(id_col), slots).alias("virtual_slot"),
        ),
        "shard-rows",
    )
    loads = slot_loads(rows, slots)
    owner, version = None, 1
    if map_path is not None:
        have = spark._jvm.org.apache.hadoop.fs.Path(map_path)
        if have.getFileSystem(spark._jsc.hadoopConfiguration()).exists(have):
            version = spark.read.schema(MAP_SCHEMA).parquet(map_path).agg(F.max("version")).first()[0]
            owner, version = edited(load_map(spark, map_path, version), loads, n_shards), version + 1
    if owner is None:
        owner = assign_slots(loads, n_shards)
    if map_path is not None:
        save_map(spark, map_path, owner, loads, version)
    before, upto = [], [0] * n_shards
    for slot, shard in enumerate(owner):
        before.append(upto[shard])
        upto[shard] += loads[slot][1]
    # The map has exactly ``slots`` entries, so it rides in the plan as two constant arrays.
    at = F.col("virtual_slot") + 1

    def constant(values: list[int]) -> Column:
        return F.split(F.lit(",".join(map(str, values))), ",").cast("array<long>")

    w = Window.partitionBy("virtual_slot").orderBy("doc_id", "text_crc32", "size")
    return rows.withColumn("_rank", F.row_number().over(w)).select(
        "doc_id", "size", "text_crc32", "virtual_slot",
        F.element_at(constant(owner), at).cast("int").alias("shard"),
        (F.element_at(constant(before), at) + F.col("_rank") - 1).cast("long").alias("slot"),
    )


def op10_virtual_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shards 0..7 of ``documents`` under the law ``bytes``; each data set's map is kept in the shared folder."""
    name = hashlib.md5(sf_dir.rstrip("/").encode()).hexdigest()
    placed = shard_rows(spark.read.parquet(f"{sf_dir}/documents.parquet"), 8, map_path=f"{shared_root(spark)}/op10-slots-{name}")
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "virtual_slot")


QUERIES = {"op10_virtual_slots": op10_virtual_slots}
ORACLES: dict[str, str] = {}
