"""Connected components by alternating star contraction (DataFrame joins only)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.storage import materialize, release


def _hook_larger(edges: DataFrame) -> DataFrame:
    """Every neighbour larger than a node is re-attached to the node's smallest neighbour."""
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    low = both.groupBy("src").agg(F.least(F.col("src"), F.min("dst")).alias("low"))
    return (
        both.filter("dst > src")
        .join(low, "src")
        .select(F.col("dst").alias("src"), F.col("low").alias("dst"))
        .filter("src <> dst")
        .distinct()
    )


def _hook_smaller(edges: DataFrame) -> DataFrame:
    """Every node and its smaller neighbours are attached to the smallest of them."""
    down = edges.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst"))
    low = down.groupBy("src").agg(F.min("dst").alias("low"))
    kept = down.join(low, "src")
    return (
        kept.select(F.col("dst").alias("src"), F.col("low").alias("dst"))
        .unionByName(low.select("src", F.col("low").alias("dst")))
        .filter("src <> dst")
        .distinct()
    )


def _settled(edges: DataFrame) -> bool:
    """Whether every node is attached to one other that is attached to none."""
    each = edges.groupBy("src").agg(F.count("*").alias("n"))
    ends = edges.select(F.col("dst").alias("src"), F.lit(True).alias("also")).distinct()
    return each.join(ends, "src", "left").filter("n > 1 or also").isEmpty()


def components(edges: DataFrame, max_iter: int = 40) -> DataFrame:
    """``(node, component)`` for every node of ``edges(src, dst)``; component = smallest node.

    Null ends and self loops are ignored as links; a node met only in self loops is not returned.
    Rounds grow with the logarithm of the component size; each round is two aggregations and two
    joins, written to shared storage. No part of the graph is brought to the driver: only whether a row is left.
    """
    now = materialize(
        edges.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst"))
        .filter("src <> dst")
        .distinct(),
        "star",
    )
    for _ in range(max_iter):
        if _settled(now):
            break
        new = materialize(_hook_smaller(_hook_larger(now)), "star")
        release(now)
        now = new
    else:
        raise RuntimeError(f"components: no fixpoint after {max_iter} rounds")
    return now.select(F.col("src").alias("node"), F.col("dst").alias("component")).unionByName(
        now.select(F.col("dst").alias("node"), F.col("dst").alias("component")).distinct()
    )
