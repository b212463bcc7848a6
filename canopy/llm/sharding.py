"""Sharding by fixed virtual slots.

A record's slot is a hash of its id and never changes. What changes is the map from slots to shards: a
small table, stored under a version, built from the bytes of each slot and edited when shards are added or loads
drift. Records are placed by what is read back from storage. The law that holds is ``bytes``: shard sizes near equal. Other laws have no meaning here.
"""

from __future__ import annotations

import heapq
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy.llm.common import cut, scratch_root

SLOTS = 16_384
HEAD_BYTES = 16


def with_slots(docs: DataFrame, slots: int = SLOTS) -> DataFrame:
    """doc_id, size, text_crc32 and virtual slot of each row. The text's crc is in the hash, so rows that share an id spread."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select("doc_id", (F.octet_length(raw) + HEAD_BYTES).cast("long").alias("size"), F.crc32(raw).alias("text_crc32")).withColumn(
        "vslot", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(slots)).cast("int")
    )


def slot_loads(rows: DataFrame) -> DataFrame:
    """Bytes and rows of each used slot: at most SLOTS rows."""
    return rows.groupBy("vslot").agg(F.sum("size").alias("bytes"), F.count("*").alias("n"))


def first_map(loads: pd.DataFrame, shards: int) -> pd.DataFrame:
    """Version 1: slots by falling bytes, each to the lightest shard."""
    heap = [(0, s) for s in range(shards)]
    out = []
    for slot, size in loads.sort_values(["bytes", "vslot"], ascending=[False, True])[["vslot", "bytes"]].itertuples(index=False):
        total, shard = heapq.heappop(heap)
        out.append((1, int(slot), shard))
        heapq.heappush(heap, (total + int(size), shard))
    return pd.DataFrame(out, columns=["version", "vslot", "shard"])


def edited_map(old: pd.DataFrame, loads: pd.DataFrame, shards: int, slack: float = 0.02) -> pd.DataFrame:
    """The next version: slots leave shards above (1 + slack) of the mean, largest that fits first, for the lightest shard.

    Slots that need not move stay. Slots unknown to the old map go to the lightest shard.
    """
    size = dict(zip(loads.vslot, loads.bytes))
    at = {int(v): int(s) for v, s in zip(old.vslot, old.shard) if v in size}
    held: dict[int, list[int]] = {s: [] for s in range(shards)}
    for v, s in at.items():
        held[s].append(v)
    total = {s: sum(int(size[v]) for v in held[s]) for s in held}
    mean = sum(int(b) for b in size.values()) / shards
    loose = sorted((v for v in size if v not in at), key=lambda v: (-size[v], v))
    for s in held:
        for v in sorted(held[s], key=lambda v: (-size[v], v)):
            if total[s] > (1 + slack) * mean and total[s] - size[v] >= (1 - slack) * mean:
                total[s] -= int(size[v])
                loose.append(v)
    heap = [(t, s) for s, t in total.items()]
    heapq.heapify(heap)
    for v in sorted(loose, key=lambda v: (-size[v], v)):
        t, s = heapq.heappop(heap)
        at[v] = s
        heapq.heappush(heap, (t + int(size[v]), s))
    version = int(old.version.max()) + 1 if len(old) else 1
    return pd.DataFrame([(version, int(v), s) for v, s in sorted(at.items())], columns=["version", "vslot", "shard"])


def store_map(spark: SparkSession, root: str, table: pd.DataFrame) -> int:
    """Write a map (version, vslot, shard) under its version; an existing version is never written again."""
    version = int(table.version.max()) if len(table) else 1
    rows = [(int(v), int(s)) for v, s in zip(table.vslot, table.shard)]
    spark.createDataFrame(rows, "vslot int, shard int").coalesce(1).write.mode("error").parquet(f"{root}/version={version}")
    return version


def stored_versions(spark: SparkSession, root: str) -> list[int]:
    folder = spark._jvm.org.apache.hadoop.fs.Path(root)
    fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    return sorted(int(x.getPath().getName().split("=")[1]) for x in fs.listStatus(folder) if x.getPath().getName().startswith("version=")) if fs.exists(folder) else []


def read_map(spark: SparkSession, root: str, version: int | None = None) -> pd.DataFrame | None:
    """A stored version, the latest if none is named; None where nothing is stored. At most SLOTS rows."""
    known = stored_versions(spark, root)
    if not known:
        return None
    version = known[-1] if version is None else version
    got = spark.read.schema("vslot int, shard int").parquet(f"{root}/version={version}").collect()
    return pd.DataFrame([(version, r.vslot, r.shard) for r in got], columns=["version", "vslot", "shard"])


def place_slots(spark: SparkSession, root: str, loads: pd.DataFrame, shards: int) -> pd.DataFrame:
    """The map for these loads, read from storage: the first version, or the latest one edited and stored as the next."""
    old = read_map(spark, root)
    store_map(spark, root, first_map(loads, shards) if old is None else edited_map(old, loads, shards))
    return read_map(spark, root)


def shard_documents(docs: DataFrame, shards: int = 40, slots: int = SLOTS, maps: str | None = None) -> DataFrame:
    """Every row with its shard and its gapless place in it, by the versioned map stored in the folder ``maps`` (a new one if none is named).

    The place is the slot's first place in its shard plus the rank inside the slot, so no window spans a
    shard. Null texts have size 16; an empty table gives no rows; equal rows take neighbouring places.
    The slot table holds at most ``slots`` rows and is the only thing that reaches the driver.
    """
    spark = docs.sparkSession
    rows = cut(with_slots(docs, slots), "shard-rows")
    loads = slot_loads(rows).toPandas()
    root = maps or f"{scratch_root(spark)}/canopy/slot-map-{uuid.uuid4().hex}"
    table = place_slots(spark, root, loads, shards)
    table = table.merge(loads, on="vslot").sort_values(["shard", "vslot"])
    table["first"] = table.groupby("shard")["n"].cumsum() - table["n"]
    entries = spark.createDataFrame(
        [tuple(map(int, x)) for x in table[["vslot", "version", "shard", "first"]].itertuples(index=False)], "vslot int, version int, shard int, first long"
    )
    place = F.row_number().over(Window.partitionBy("vslot").orderBy("doc_id", "text_crc32")) - 1
    return (
        rows.withColumn("place", place)
        .join(F.broadcast(entries), "vslot")
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("first") + F.col("place")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), F.col("vslot").alias("virtual_slot"), F.col("version").alias("map_version"))
    )
