"""Sharding by longest processing time first: whole groups, largest first, go to the least-loaded shard.

Groups of one size are interchangeable, so the schedule needs only how many groups have each size. The driver
holds that histogram: its distinct sizes add up to at most all bytes, hence there are at most sqrt(2 * bytes) of
them (1.4e7 at 100 TB in the worst case), whatever the number of documents. A heap deals each size class; the
groups of a class then take the class's places by their rank, which is counted over salted cells, so no group and
no size class is ever gathered in one task.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import SALTS, bytes_of, salt_of, settle

#: Size classes up to this many are sent with the plan; more are joined as a table.
BROADCAST_CLASSES = 1 << 20


def deal(classes: Iterable[tuple[int, int]], shards: int) -> list[tuple[int, list[int]]]:
    """For (size, number of groups), largest first: how many groups of the class each shard takes. The result is
    that of taking the groups one by one, ties going to the shard with the lower number."""
    load = [0] * shards
    out = []
    for size, count in classes:
        taken = [0] * shards
        if count > 4 * shards and size > 0:
            _bulk(load, taken, size, count)
        heap = [(load[k], k) for k in range(shards)]
        heapq.heapify(heap)
        for _ in range(count - sum(taken)):
            least, k = heap[0]
            taken[k] += 1
            load[k] = least + size
            heapq.heapreplace(heap, (load[k], k))
        out.append((size, taken))
    return out


def _bulk(load: list[int], taken: list[int], size: int, count: int) -> None:
    """Give the rounds that the heap would surely give: fill the lower shards to one group below the common level."""
    low = sorted(range(len(load)), key=lambda k: load[k])
    total, used = count * size, 0
    for n, k in enumerate(low, 1):
        used += load[k]
        level = (total + used) / n
        if n == len(low) or level <= load[low[n]]:
            break
    for k in low:
        more = int((level - load[k]) // size) - 1
        if more > 0:
            taken[k] += more
            load[k] += more * size


def shard(docs: DataFrame, shards: int = 8, *, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """Rows (doc_id, size, text_crc32, law, shard, slot, grown_shard): a place for every row of docs.

    Equal texts form a group and stay together; a null text is grouped with the empty one (size 1, crc 0). Rows
    may repeat and ids may be null: every row gets a slot of its own. An empty table gives an empty result. Other
    columns of docs are ignored.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = settle(
        docs.select(
            F.col(id_col).alias("doc_id"),
            (bytes_of(text) + 1).alias("size"),
            F.crc32(text).alias("text_crc32"),
            F.unhex(F.sha2(text, 256)).alias("grp"),
        ).withColumn("part", salt_of(F.col("doc_id"), salts=salts))
    )
    cells = rows.groupBy("grp", "part").agg(F.count("*").alias("n"), F.first("size").alias("size"))
    groups = cells.groupBy("grp").agg(F.sum("n").alias("n"), (F.sum("n") * F.first("size")).alias("total"))
    groups = groups.withColumn("salt", salt_of(F.col("grp"), salts=salts))
    cell_counts = groups.groupBy("total", "salt").agg(F.count("*").alias("c"))
    histogram = cell_counts.groupBy("total").agg(F.sum("c").alias("c")).toArrow()
    classes = sorted(zip(histogram["total"].to_pylist(), histogram["c"].to_pylist(), strict=True), reverse=True)
    places = [(size, _running(taken)) for size, taken in deal(classes, shards)]
    places = docs.sparkSession.createDataFrame(places, "total long, upto array<long>")
    if len(classes) <= BROADCAST_CLASSES:
        places = F.broadcast(places)

    before = Window.partitionBy("total").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = cell_counts.withColumn("start", F.coalesce(F.sum("c").over(before), F.lit(0))).drop("c")
    ranked = (
        groups.withColumn("r", F.row_number().over(Window.partitionBy("total", "salt").orderBy("grp")) - 1)
        .join(offsets, ["total", "salt"])
        .join(places, "total")
        .select("grp", F.size(F.filter("upto", lambda x: x <= F.col("r") + F.col("start"))).alias("shard"))
    )
    placed = settle(cells.join(ranked, "grp").select("grp", "part", "n", "shard", salt_of(F.col("grp"), F.col("part"), salts=4 * salts).alias("lane")))
    lanes = placed.groupBy("shard", "lane").agg(F.sum("n").alias("n"))
    ahead = Window.partitionBy("shard").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)
    lanes = lanes.select("shard", "lane", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("lane_start"))
    within = Window.partitionBy("shard", "lane").orderBy("grp", "part").rowsBetween(Window.unboundedPreceding, -1)
    starts = placed.join(F.broadcast(lanes), ["shard", "lane"]).select(
        "grp", "part", "shard", (F.col("lane_start") + F.coalesce(F.sum("n").over(within), F.lit(0))).alias("start")
    )
    own = F.row_number().over(Window.partitionBy("grp", "part").orderBy("doc_id")) - 1
    return (
        rows.withColumn("own", own)
        .join(starts, ["grp", "part"])
        .select(
            "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
            (F.col("start") + F.col("own")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
        )
    )


def _running(taken: list[int]) -> list[int]:
    total, out = 0, []
    for n in taken:
        total += n
        out.append(total)
    return out
