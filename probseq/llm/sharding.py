"""Sharding by longest-processing-time scheduling.

Groups of equal texts stay together. They are placed by falling size on the least loaded shard, which a heap yields.
Groups above a share of the total are few by arithmetic (at most `shards * resolution`) and are scheduled one by one;
smaller ones are scheduled in classes of nearly equal size, where a class of c groups takes the c earliest places of
the same greedy rule at once. So the driver holds a bounded plan, whatever the number of groups, and groups find
their shard by their rank within their class.

Law kept: `bytes` (sum of sizes near equal). Defined results: a null text counts as the empty one; null ids are
placed like others; repeated rows are rows of their own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import by_sort, numbered, partitions

RESOLUTION = 1024  # a group above 1 / (shards * RESOLUTION) of all bytes is scheduled by itself
MANTISSA = 8  # classes keep so many leading bits of a size


def earliest_places(loads: list[float], size: float, count: int) -> list[int]:
    """How many of `count` equal items each shard gets when each goes to the least loaded shard (ties: lower number)."""
    given = [0] * len(loads)
    if count > 2 * len(loads) and size > 0:
        low, high = min(loads), max(loads) + size * count
        for _ in range(80):
            mid = (low + high) / 2
            if sum(max(0, int((mid - x) // size) + 1) for x in loads if x <= mid) > count - len(loads):
                high = mid
            else:
                low = mid
        given = [max(0, int((low - x) // size) + 1) if x <= low else 0 for x in loads]
    heap = [(x + g * size, s) for s, (x, g) in enumerate(zip(loads, given, strict=True))]
    heapq.heapify(heap)
    for _ in range(count - sum(given)):
        load, s = heap[0]
        given[s] += 1
        heapq.heapreplace(heap, (load + size, s))
    return given


def schedule(classes: list[tuple], shards: int) -> list[tuple]:
    """classes: (class, mean size, count) -> (class, shard, first rank, end rank), by falling size."""
    loads, plan = [0.0] * shards, []
    for key, size, count in sorted(classes, key=lambda c: (-c[1], str(c[0]))):
        at = 0
        for s, n in enumerate(earliest_places(loads, size, count)):
            if n:
                plan.append((key, s, at, at + n))
                loads[s] += n * size
                at += n
    return plan


def shard(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, size, text_crc32, group, shard, slot) of every row; groups are equal texts, slots are gapless per shard."""
    spark = docs.sparkSession
    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(
        F.col(id_col),
        (F.octet_length(body) + 8).cast("long").alias("size"),
        F.crc32(body.cast("binary")).alias("text_crc32"),
        F.sha2(body.cast("binary"), 256).alias("group"),
    )
    groups = rows.groupBy("group").agg(F.sum("size").alias("bytes"))
    total = rows.agg(F.sum("size")).first()[0] or 0
    large = max(1, -(-total // (shards * RESOLUTION)))
    # a class: the exponent and leading bits of the size; a large group is a class by itself
    shift = F.greatest(F.floor(F.log2(F.col("bytes"))).cast("int") - MANTISSA, F.lit(0))
    rough = F.concat_ws(":", shift, F.expr(f"shiftright(bytes, greatest(cast(floor(log2(bytes)) as int) - {MANTISSA}, 0))"))
    classed = groups.withColumn("class", F.when(F.col("bytes") >= large, F.col("group")).otherwise(rough))
    counted = classed.groupBy("class").agg(F.avg("bytes").alias("size"), F.count(F.lit(1)).alias("n"))
    plan = schedule([(r["class"], r["size"], r["n"]) for r in counted.collect()], shards)
    placed = spark.createDataFrame(plan or [("", 0, 0, 0)], "class string, shard int, low long, high long")
    ranked = numbered(classed, ["class"], F.col("group"), [F.col("group")], "rank")
    homes = ranked.join(F.broadcast(placed), (ranked["class"] == placed["class"]) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high"))).select("group", "shard")
    dealt = by_sort(rows, homes, "group")
    parts = max(1, partitions(spark) // shards + 1)
    return numbered(dealt, ["shard"], F.struct("group", id_col), [F.col(id_col), F.col("group")], "slot", parts).select(id_col, "size", "text_crc32", "group", "shard", "slot")
