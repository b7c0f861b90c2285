"""Shards of nearly equal bytes by longest-processing-time scheduling.

Documents of equal text stay together. Groups go, largest first, to the least-loaded shard. Groups of
one size are interchangeable, so the schedule is made over the histogram of sizes instead of
over groups: ``d`` different sizes need at least ``d * d / 2`` bytes of text, so even 100 TB has
fewer than 15 million of them, and the driver holds them packed, in 150 bytes each. Within one size the greedy rounds are filled at once and only the last,
incomplete one goes through the heap; the loads are those of the group-by-group schedule.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupflow.storage import materialize

_SPREAD = 64
_HOT = 1000


def schedule(weights: np.ndarray, counts: np.ndarray, shards: int) -> np.ndarray:
    """For each weight, largest first, how many groups the shards up to each one get in all (``weights x shards``).

    ``weights`` descend. Ties between equally loaded shards go to the lower number.
    """
    loads = [0] * shards
    ends = np.empty((len(weights), shards), np.int64)
    for row, (size, left) in enumerate(zip(weights.tolist(), counts.tolist())):
        given = [0] * shards
        if left > 2 * shards:
            # the highest level such that filling each shard up to it takes no more than the groups there are
            lo, hi = min(loads), min(loads) + size * (left + 1)
            while lo < hi:
                mid = (lo + hi + 1) // 2
                if sum(max(0, -((x - mid) // size)) for x in loads) <= left:
                    lo = mid
                else:
                    hi = mid - 1
            given = [max(0, -((x - lo) // size)) for x in loads]
            left -= sum(given)
        heap = [(x + size * g, i) for i, (x, g) in enumerate(zip(loads, given))]
        heapq.heapify(heap)
        while left:
            load, i = heap[0]
            heapq.heapreplace(heap, (load + size, i))
            given[i] += 1
            left -= 1
        loads = [x + size * g for x, g in zip(loads, given)]
        ends[row] = np.cumsum(given)
    return ends


def assign(docs: DataFrame, shards: int = 16) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` for each row of ``docs``.

    A null text has size 1, crc32 0 and a group of its own kind with other null texts. Repeated rows
    are separate documents of one group, rows with a null doc_id documents like others. Equally loaded shards: the lower
    number. ``slot`` numbers the rows of a shard from 0 without a gap, by doc_id inside hash parts.
    An empty table gives an empty result; other columns are not read.
    """
    spark = docs.sparkSession
    base = materialize(
        docs.select(
            F.col("doc_id").cast("long"),
            (F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1).alias("size"),
            F.coalesce(F.crc32("text"), F.lit(0).cast("long")).alias("text_crc32"),
            F.coalesce(F.unhex(F.sha2("text", 256)), F.unhex(F.lit("00"))).alias("group"),
        ),
        "sized",
    )
    groups = materialize(base.groupBy("group").agg(F.sum("size").alias("weight"), F.count("*").alias("n")), "groups")
    # packed: 16 bytes for each weight on the way here, 8 * (shards + 1) for the plan
    histogram = groups.groupBy("weight").agg(F.count("*").alias("c")).toArrow()
    weights, counts = (histogram.column(c).to_numpy() for c in ("weight", "c"))
    order = np.argsort(-weights)
    weights, counts = weights[order], counts[order]
    ends = schedule(weights, counts, shards)
    offsets = np.arange(0, ends.size + 1, shards, dtype=np.int32)
    table = pa.table({"weight": pa.array(weights, pa.int64()), "ends": pa.ListArray.from_arrays(offsets, ends.ravel())})
    plan = spark.createDataFrame(table, "weight long, ends array<long>")
    # rank of a group among those of its weight: an offset for each hash part, and a number inside it
    parted = groups.withColumn("part", F.pmod(F.xxhash64("group"), F.lit(_SPREAD)))
    before = Window.partitionBy("weight").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parted.groupBy("weight", "part").count().select(
        "weight", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("offset")
    )
    number = F.row_number().over(Window.partitionBy("weight", "part").orderBy("group")) - 1
    placed = materialize(
        parted.withColumn("number", number)
        .join(offsets, ["weight", "part"])
        .join(plan, "weight")
        .select(
            "group",
            "n",
            F.expr("cast(size(filter(ends, e -> e <= number + offset)) as int)").alias("shard"),
        ),
        "plan",
    )
    # texts with over a thousandth of all rows, so a thousand at most, do not gather their rows in a task
    many = F.broadcast(placed.join(F.broadcast(groups.agg((F.sum("n") / _HOT).alias("least"))), F.col("n") > F.col("least")).select("group", F.col("shard").alias("known")))
    first = base.join(many, "group", "left")
    rows = first.filter("known is not null").withColumnRenamed("known", "shard").unionByName(
        first.filter("known is null").drop("known").join(placed.drop("n"), "group")
    )
    rows = materialize(rows.withColumn("part", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(_SPREAD))), "placed")
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy("shard", "part").count().select(
        "shard", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("offset")
    )
    number = F.row_number().over(Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size")) - 1
    return (
        rows.withColumn("number", number)
        .join(F.broadcast(offsets), ["shard", "part"])  # shards x parts rows, whatever the data
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("bytes").alias("law"),
            "shard",
            (F.col("offset") + F.col("number")).cast("long").alias("slot"),
            F.lit(None).cast("int").alias("grown_shard"),
        )
    )
