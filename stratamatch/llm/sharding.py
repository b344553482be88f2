"""Shards by fixed virtual slots.

Records hash into a fixed number of slots; bytes and rows are added up per slot; a
map from slot to shard is kept as a table of versions in the shared folder. A new
version is the last one edited: slots that have no shard yet get one, and slots move
only as far as the law asks. A call with the path of an earlier map goes on from it.
One of two laws is chosen:

* ``bytes``: slots of the text. Version 1 deals slots out evenly; each call then moves
  slots from the fullest shard to the least filled one while that brings them closer.
  A slot of more than an eighth of a shard goes by its sub-slots (by id) instead.
* ``key``: slots of the id. Each new shard takes its even part of the slots from those
  that have most, so a row's shard depends on its id and the number of shards only,
  and one more shard takes rows only into itself.

Hashing by text keeps copies together; a slot with more than its fair part, such as
that of a text that a third of all rows share, has sub-slots, in which places are
counted. Only tables of slots (at most two times the number of slots, whatever the
input) are ordered on the driver. DataFrame functions only.

Defined results: null text is 0 bytes, so size 1 and crc32 0; a null id is a key
as any other; repeated rows get places of their own; an empty table gives none.
"""

from __future__ import annotations

import heapq
import re
from itertools import count

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .durable import new_folder, stored

SLOTS = 4096


def slot_map(shards: int, slots: int = SLOTS) -> list[int]:
    """Version ``shards`` of the map by key: from version 1, where shard 0 has all slots,
    each new shard takes its even part, slot by slot, from the shards that have most."""
    if not 1 <= shards <= slots:
        raise ValueError("shards must lie between 1 and the number of slots")
    where = [0] * slots
    for new in range(1, shards):
        held = [[] for _ in range(new)]
        for slot, shard in enumerate(where):
            held[shard].append(slot)
        heap = [(-len(h), shard) for shard, h in enumerate(held)]
        heapq.heapify(heap)
        for _ in range(slots // (new + 1)):
            n, shard = heapq.heappop(heap)
            where[held[shard].pop()] = new
            heapq.heappush(heap, (n + 1, shard))
    return where


def edited_map(old: dict, weights: list[tuple], shards: int) -> dict:
    """Next version after growth: units without a shard go to the least filled one, largest first;
    then units leave the fullest shard for the least filled one, the one that brings them closest
    first, until no such move helps. Units that are gone keep their place."""
    size, now, held = dict(weights), dict(old), [0] * shards
    for key in size:
        if key in now:
            held[now[key]] += size[key]
    for key in sorted((k for k in size if k not in now), key=lambda k: (-size[k], k)):
        now[key] = min(range(shards), key=held.__getitem__)
        held[now[key]] += size[key]
    for _ in count():
        full, low = max(range(shards), key=held.__getitem__), min(range(shards), key=held.__getitem__)
        gap = held[full] - held[low]
        best = min((k for k in size if now[k] == full and 0 < size[k] < gap), key=lambda k: (abs(gap - 2 * size[k]), k), default=None)
        if best is None:
            return now
        now[best] = low
        held[full] -= size[best]
        held[low] += size[best]


def save_map(spark: SparkSession, path: str, version: int, shards: int, units: dict) -> None:
    """Add a version of the map (slot, sub-slot or -1) -> shard under ``path``."""
    rows = [(slot, sub, shard, shards) for (slot, sub), shard in sorted(units.items())]
    spark.createDataFrame(rows, "slot int, sub int, shard int, shards int").coalesce(1).write.parquet(f"{path}/version={version}")


def load_map(spark: SparkSession, path: str) -> tuple[int, int, dict]:
    """(version, shards, units) of the last version under ``path``; (0, 0, {}) if there is none."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [f.getPath().getName() for f in files.listStatus(folder)] if files.exists(folder) else []
    # A version counts once its write has committed.
    done = [int(n[8:]) for n in names if re.fullmatch(r"version=\d+", n) and files.exists(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/{n}/_SUCCESS"))]
    if not done:
        return 0, 0, {}
    rows = spark.read.parquet(f"{path}/version={max(done)}").collect()
    return max(done), max((r["shards"] for r in rows), default=0), {(r["slot"], r["sub"]): r["shard"] for r in rows}


def next_map(law: str, old: dict, cells: list[tuple], shards: int, slots: int) -> dict:
    """Units (slot, sub-slot or -1) to shards: the map ``old`` edited for cells (slot, sub, rows, bytes)."""
    if law == "key":
        return {(slot, -1): shard for slot, shard in enumerate(slot_map(shards, slots))}
    by_slot, units = {}, {}
    for slot, _, _, size in cells:
        by_slot[slot] = by_slot.get(slot, 0) + size
    whole = sum(by_slot.values())
    for slot, sub, _, size in cells:
        # A slot moves as one, so copies stay together, unless it is an eighth of a shard.
        unit = (slot, sub if 8 * shards * by_slot[slot] > whole else -1)
        units[unit] = units.get(unit, 0) + size
    old = old or {(slot, -1): slot % shards for slot in range(slots)}
    # A sub-slot without a place of its own starts in the place of its slot.
    start = {k: s for k, s in old.items() if s < shards} | {u: old[u[0], -1] for u in units if u not in old and old.get((u[0], -1), shards) < shards}
    return edited_map(start, list(units.items()), shards)


def sizes(docs: DataFrame, law: str, id_col: str = "doc_id", text_col: str = "text", slots: int = SLOTS) -> DataFrame:
    """id, size, text_crc32, slot_no and a hash that cuts slots into sub-slots."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    of, within = (text, key) if law == "bytes" else (key, text)
    return docs.select(
        F.col(id_col).alias("id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
        F.pmod(F.xxhash64(F.lit(law), of), F.lit(slots)).cast("int").alias("slot_no"), F.xxhash64(F.lit("sub"), within).alias("sub_hash"),
    )


def shard(docs: DataFrame, shards: int = 8, law: str = "bytes", id_col: str = "doc_id", text_col: str = "text", slots: int = SLOTS, map_path: str | None = None) -> DataFrame:
    """id, size, text_crc32, law, shard, slot (place in the shard, gapless from 0) and grown_shard (law
    ``key``: its shard with one more) for every row. The map of an earlier call under ``map_path`` is
    edited and a version added, unless nothing changes; without a path the map has a folder of its own."""
    if law not in ("bytes", "key"):
        raise ValueError(law)
    spark = docs.sparkSession
    map_path = map_path or new_folder(spark, "slot-map")
    rows = stored(sizes(docs, law, id_col, text_col, slots), "sized")
    by_slot = rows.groupBy("slot_no").agg(F.count("*").alias("n"), F.sum("size").alias("b")).collect()  # at most ``slots`` rows
    fair_n, fair_b = max(1, -(-sum(r["n"] for r in by_slot) // slots)), max(1, -(-sum(r["b"] for r in by_slot) // slots))
    split = {r["slot_no"]: min(slots, max(-(-r["n"] // fair_n), -(-r["b"] // fair_b))) for r in by_slot}
    parts = F.broadcast(spark.createDataFrame(list(split.items()) or [(0, 1)], "slot_no int, parts int"))
    rows = rows.join(parts, "slot_no").withColumn("sub", F.pmod(F.col("sub_hash"), F.col("parts")).cast("int"))
    rows = stored(rows.drop("parts", "sub_hash"), "slotted")
    cells = sorted(tuple(r) for r in rows.groupBy("slot_no", "sub").agg(F.count("*"), F.sum("size")).collect())  # at most 3 x slots rows
    version, before, old = load_map(spark, map_path)
    units = next_map(law, old, cells, shards, slots)
    if units != old or before != shards:
        save_map(spark, map_path, version + 1, shards, units)
        _, _, units = load_map(spark, map_path)
    grown = slot_map(shards + 1, slots) if law == "key" else None
    filled, placed = [0] * shards, []
    for slot, sub, n, _ in cells:
        at = units[slot, sub] if (slot, sub) in units else units[slot, -1]
        placed.append((slot, sub, filled[at], at, grown[slot] if grown else None))
        filled[at] += n
    table = F.broadcast(spark.createDataFrame(placed or [(0, 0, 0, 0, None)], "slot_no int, sub int, start long, shard int, grown_shard int"))
    inside = F.row_number().over(Window.partitionBy("slot_no", "sub").orderBy("text_crc32", "id", "size")) - 1
    out = rows.withColumn("inside", inside).join(table, ["slot_no", "sub"])
    return out.select(F.col("id").alias(id_col), "size", "text_crc32", F.lit(law).alias("law"), "shard", (F.col("start") + F.col("inside")).cast("long").alias("slot"), "grown_shard")
