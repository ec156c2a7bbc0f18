"""Longest-processing-time scheduling of groups that must stay together.

The plan is made on sizes alone. Sizes are classed by their 12 leading bits, so sizes under 4096 are exact, larger
ones are off by less than 2^-11 of themselves, and there are fewer than 80,000 classes at any scale, whatever the groups. The driver
gets only (class, number of groups), runs a heap over them from the largest class down, and hands out each class's
groups as ranges of ranks, one row a class: group by group this is the classic heap schedule, since groups of one class are alike.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polymetric.llm.common import Scratch, heavy_join, numbered

BITS = 12


def _alike(loads: list[int], size: int, count: int) -> list[int]:
    """How many of ``count`` groups of one size each shard gets when each goes to the least-loaded shard.

    The j-th group a shard could take starts at load + j * size; the heap takes the ``count`` least of these starts,
    so a level is searched for and the last few are taken one by one.
    """
    below = lambda level: sum(max(0, (level - x) // size + 1) for x in loads)
    low, high = min(loads) - 1, min(loads) + size * count
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if below(mid) <= count else (low, mid - 1)
    took = [max(0, (low - x) // size + 1) for x in loads]
    heap = [(x + n * size, s) for s, (x, n) in enumerate(zip(loads, took, strict=True))]
    heapq.heapify(heap)
    for _ in range(count - sum(took)):
        start, s = heap[0]
        heapq.heapreplace(heap, (start + size, s))
        took[s] += 1
    return took


def schedule(classes: Iterable[tuple[int, int]], shards: int) -> list[tuple[int, int, int, int]]:
    """(size, count) pairs, in any order, to (size, shard, first rank, end rank).

    From the largest size down each group goes to the least-loaded shard, ties to the lowest number. A few groups of a
    size go through the heap one by one; more of them are placed at once, with the same result.
    """
    loads, out = [0] * shards, []
    for size, count in sorted(classes, reverse=True):
        if count > 2 * shards:
            took = _alike(loads, size, count)
        else:
            took, heap = [0] * shards, [(x, s) for s, x in enumerate(loads)]
            heapq.heapify(heap)
            for _ in range(count):
                load, s = heap[0]
                heapq.heapreplace(heap, (load + size, s))
                took[s] += 1
        rank = 0
        for s, n in enumerate(took):
            loads[s] += n * size
            if n:
                out.append((size, s, rank, rank + n))
                rank += n
    return out


def shard_by_size(docs: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text", overhead: int = 16, scratch: Scratch | None = None) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard): equal texts share a shard, and bytes are near equal.

    Texts are equal by their SHA-256. size is the text's UTF-8 bytes plus ``overhead``; null counts as an empty text. A group weighs the sum of its
    rows. slot numbers a shard's rows from 0 without gaps. Repeated rows each get a slot, null ids sort first, other
    columns are ignored, and an empty table gives no rows. The law is ``bytes``; grown_shard is null under it.
    """
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark)
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + F.lit(overhead)).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("key"))
    base = scratch.table(base, "base")
    n = base.count()
    groups = base.groupBy("key").agg(F.sum("size").alias("weight"), F.count("*").alias("copies"))
    unit = F.expr(f"shiftleft(1L, greatest(0, length(bin(weight)) - {BITS}))")
    groups = scratch.table(groups.withColumn("class", ((F.col("weight") / unit).cast("long") * unit).cast("long")), "groups")
    plan = schedule(((r["class"], r["n"]) for r in groups.groupBy("class").agg(F.count("*").alias("n")).collect()), shards)
    ends: dict[int, list[int]] = {}
    for size, shard, _, end in plan:  # ends[size][s]: the first rank that is not in shards 0 to s
        row = ends.setdefault(size, [0] * shards)
        row[shard:] = [end] * (shards - shard)
    made = spark.createDataFrame(pa.table([pa.array(list(ends), pa.int64()), pa.array(list(ends.values()), pa.list_(pa.int64()))], ["class", "ends"]))
    parts = 1 + n // 2_000_000
    ranked = numbered(groups, ["class"], F.xxhash64("key"), ["key"], "rank", parts)
    shard = F.size(F.filter("ends", lambda e: e <= F.col("rank")))
    placed = ranked.join(F.broadcast(made), "class").select("key", "copies", shard.alias("shard"))  # fewer than 80,000 rows
    placed = scratch.table(placed, "placed")
    rows = scratch.table(heavy_join(base, placed, ["key"], "copies", n).drop("key", "copies"), "rows")
    out = numbered(rows, ["shard"], F.xxhash64("doc_id"), ["doc_id", "text_crc32"], "slot", 16 + n // (shards * 100_000))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
