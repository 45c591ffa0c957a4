"""Longest-processing-time sharding: groups of equal texts, largest first, each to the least-loaded shard.

Groups of one size are interchangeable, so the driver's heap schedules sizes, not groups: (size, number of groups) by falling size.
Sizes are told apart to STEPS steps an octave (exactly below STEPS bytes), so their number is bounded by STEPS times the octaves of
a long, whatever the input's size; groups in one step count with the mean of their sizes. What each step gives to each shard is a range
of ranks, and a group's rank in its step, which the executors find, names its shard. The rule is the same for all groups and tables.

Null text: no bytes, grouped with the empty text. Rows with the same doc_id are separate rows of their texts' groups,
and so are rows without one. An empty table gives no rows. Texts are read once and whole, as digest, length and checksum, however long; other
columns are ignored. A group larger than a fair share gets a shard to itself, as equal texts must stay together.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Steps of sizes in an octave: sizes in one step differ by less than 0.1 %.
STEPS = 1024
ROW_BYTES = 16


def size_step(size: Column) -> Column:
    """The size without its bits below the STEPS greatest steps of its octave."""
    spare = F.greatest(F.floor(F.log2(size.cast("double"))).cast("int") - F.lit(STEPS.bit_length() - 1), F.lit(0))
    return F.call_function("shiftleft", F.call_function("shiftright", size, spare), spare)


def least_loaded(sizes: list[tuple[float, int]], shards: int) -> list[list[int]]:
    """For each (size, groups), by falling size, how many of the groups each shard gets: each group goes to the least-loaded shard (ties: the lowest number).

    Equal groups are dealt in rounds: while at least one group for each shard is left, whole layers that the heap would give are found at once.
    """
    loads, out = [0.0] * shards, []
    for size, n in sizes:
        got = [0] * shards
        if n > 2 * shards:
            # each shard is filled up to a level that takes at most n - shards groups; the heap deals the rest
            lo, hi = min(loads), max(loads) + size * (n // shards + 1)
            for _ in range(64):
                mid = (lo + hi) / 2
                lo, hi = (mid, hi) if sum(max(0, int((mid - x) // size)) for x in loads) <= n - shards else (lo, mid)
            got = [max(0, int((lo - x) // size)) for x in loads]
        heap = [(x + size * g, s) for s, (x, g) in enumerate(zip(loads, got, strict=True))]
        heapq.heapify(heap)
        for _ in range(n - sum(got)):
            load, s = heap[0]
            got[s] += 1
            heapq.heapreplace(heap, (load + size, s))
        loads = [x + size * g for x, g in zip(loads, got, strict=True)]
        out.append(got)
    return out


def shard(docs: DataFrame, shards: int = 40) -> DataFrame:
    """doc_id, size, text_crc32, shard and slot (gapless from 0 in each shard) of every row."""
    spark, text = docs.sparkSession, F.coalesce(F.col("text"), F.lit(""))
    rows = common.written(docs.select(F.col("doc_id"), (F.octet_length(text) + ROW_BYTES).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("group")), "shard-rows")
    groups = rows.groupBy("group").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n"))
    groups = common.written(groups.withColumn("step", size_step(F.col("bytes"))), "shard-groups")
    steps = groups.groupBy("step").agg(F.avg("bytes").alias("size"), F.count(F.lit(1)).alias("groups")).orderBy(F.desc("step")).collect()  # bounded, see above
    dealt = least_loaded([(r["size"], r["groups"]) for r in steps], shards)
    plan = spark.createDataFrame([(r["step"], [sum(got[: s + 1]) for s in range(shards)]) for r, got in zip(steps, dealt, strict=True)], "step long, ends array<long>")
    placed = common.ranked(groups, ["step"], ["group"]).join(F.broadcast(plan), "step")
    placed = common.written(placed.select("group", "n", F.size(F.filter("ends", lambda end: end <= F.col("rank"))).alias("shard")), "shard-places")
    out = common.looked_up(rows, placed, "group", "n").select("doc_id", "size", "text_crc32", "shard")
    return common.ranked(out, ["shard"], ["doc_id", "text_crc32", "size"], "slot")


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shard(common.table(spark, sf_dir, "documents"), 40)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
