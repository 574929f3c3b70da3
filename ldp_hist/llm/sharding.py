"""Sharding by longest-processing-time scheduling."""

from __future__ import annotations

import heapq
import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ldp_hist.llm.shared import digest16, materialise, run_of

#: Groups of one size, and rows of one shard, are numbered in lots of about this many.
LOT = 100_000


def lpt_plan(sizes: list[tuple[int, int]], shards: int) -> dict[int, list[tuple[int, int]]]:
    """For each size the shards of its groups, as (end, shard): the groups numbered up to ``end`` go there.

    ``sizes`` tells how many groups there are of each size; groups of a size are interchangeable. Longest first, each
    to the shard with the least load, ties by shard number, through a heap. Many groups of one size are dealt at
    once: the loads that the heap would pop are the least of load + i*size over all shards and i, so a search for the last
    load popped says how many groups each shard gets.
    """
    loads, plan = [(0, s) for s in range(shards)], {}
    heapq.heapify(loads)
    for size, count in sorted(sizes, reverse=True):
        ends: list[tuple[int, int]] = []
        if count <= 4 * shards or size <= 0:
            for i in range(count):
                load, shard = loads[0]
                heapq.heapreplace(loads, (load + size, shard))
                ends.append((i + 1, shard))
        else:
            load = dict((s, v) for v, s in loads)
            low, high = min(load.values()), max(load.values()) + size * count + 1
            while high - low > 1:  # the last level with at most ``count`` pops below it
                level = (low + high) // 2
                if sum(max(0, -((v - level) // size)) for v in load.values()) <= count:
                    low = level
                else:
                    high = level
            number = {s: max(0, -((v - low) // size)) for s, v in load.items()}
            spare = count - sum(number.values())
            for s in sorted(load):
                if spare and load[s] + number[s] * size == low:
                    number[s] += 1
                    spare -= 1
            end = 0
            for s in sorted(load):
                if number[s]:
                    end += number[s]
                    ends.append((end, s))
            loads = [(load[s] + number[s] * size, s) for s in load]
            heapq.heapify(loads)
        plan[size] = ends
    return plan


def lpt_shards(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text", lot: int = LOT) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of ``docs``.

    Equal texts form a group that stays together; null counts as the empty text. Sizes are UTF-8 bytes
    plus 8, a group's size is the sum over its rows. The driver schedules from the number of groups of each size: different sizes
    are at most the square root of twice all bytes (14 million at 100 TB, far fewer in practice), whatever the number of groups.
    A group's place among those of its size decides where it goes: groups of a size are numbered in lots by hash, of about ``lot`` groups, and
    the lots' starts are added. Slots count from 0 in each shard in the same way, by (doc_id, digest) within a lot.

    Null ids sort first; repeated rows get a slot each; an empty table gives an empty result; other columns are ignored.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = materialise(docs.select(
        F.col(id_col).cast("long").alias("doc_id"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
        F.hex(digest16(text)).alias("digest"), run_of().alias("run"), F.xxhash64(F.monotonically_increasing_id()).alias("any"),
    ))
    per_run = rows.groupBy("run", "digest").agg(F.sum("size").alias("bytes"))
    groups = materialise(per_run.groupBy("digest").agg(F.sum("bytes").alias("bytes")))
    sizes = [(r[0], r[1]) for r in groups.groupBy("bytes").count().collect()]
    plan = spark.createDataFrame(list(lpt_plan(sizes, shards).items()), "bytes long, ends array<struct<end:long,shard:int>>")
    lots = 1 + max((n for _, n in sizes), default=0) // lot
    dealt = groups.withColumn("lot", F.pmod(F.xxhash64("digest"), F.lit(lots)).cast("int"))
    earlier = Window.partitionBy("bytes").orderBy("lot").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("bytes", "lot").agg(F.count("*").alias("n")).select("bytes", "lot", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("start"))
    nth = F.row_number().over(Window.partitionBy("bytes", "lot").orderBy("digest"))
    placed = dealt.withColumn("nth", nth).join(starts.join(plan, "bytes"), ["bytes", "lot"])
    placed = placed.select("digest", F.filter("ends", lambda x: x["end"] >= F.col("start") + F.col("nth"))[0]["shard"].alias("shard"))
    shard_of = per_run.select("run", "digest").join(placed, "digest")
    blocks = 1 + math.ceil(sum(n for _, n in sizes) / (shards * lot))
    held = rows.join(shard_of, ["run", "digest"]).withColumn("block", F.pmod("any", F.lit(blocks)).cast("int"))
    before = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    first = held.groupBy("shard", "block").agg(F.count("*").alias("n")).select("shard", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    inside = F.row_number().over(Window.partitionBy("shard", "block").orderBy("doc_id", "digest"))
    return held.withColumn("nth", inside).join(first, ["shard", "block"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("first") + F.col("nth") - 1).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"), F.col("digest").alias("group_digest"),
    )
