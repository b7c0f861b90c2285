"""Snapshots: one position for each object and timestamp."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def bucket(fix: DataFrame, step: int, origin: int = 0) -> DataFrame:
    """``fix`` with ``t``, the number of its ``step`` microseconds long interval since ``origin``."""
    return fix.withColumn("t", F.floor((F.unix_micros("ts") - F.lit(origin)) / F.lit(step)).cast("long"))


def synchronize(fix: DataFrame, how: str = "last") -> DataFrame:
    """``snap(t, obj_id, x, y)`` from bucketed fixes: the last position of an interval, or their mean.

    ``event_id`` breaks ties of time. One hash aggregation, combined on the map side.
    """
    if how == "mean":
        return fix.groupBy("t", "obj_id").agg(F.avg("x").alias("x"), F.avg("y").alias("y"))
    if how != "last":
        raise ValueError("how is 'last' or 'mean'")
    last = F.max_by(F.struct("x", "y"), F.struct("ts", "event_id"))
    return fix.groupBy("t", "obj_id").agg(last.alias("p")).select("t", "obj_id", "p.x", "p.y")


def interpolate(fix: DataFrame, step: int, origin: int = 0, max_gap: float | None = None) -> DataFrame:
    """``snap`` at every whole timestamp between an object's first and last fix, linear in between.

    ``max_gap``: no position inside gaps of more timestamps. Each pair of neighbouring fixes yields
    the timestamps from the first one on and before the second, so none comes twice.
    """
    e = (F.unix_micros("ts") - F.lit(origin)).cast("double") / F.lit(float(step))
    order = Window.partitionBy("obj_id").orderBy("ts", "event_id")
    nxt = lambda c: F.lead(c).over(order).alias(f"{c}2")
    rows = fix.select("obj_id", "ts", "event_id", "x", "y", e.alias("e")).select(
        "obj_id", "x", "y", "e", nxt("x"), nxt("y"), nxt("e")
    )
    first = F.ceil("e").cast("long")
    last = F.when(F.col("e2").isNull(), F.floor("e")).otherwise(F.ceil("e2") - 1).cast("long")
    if max_gap is not None:
        last = F.when(F.col("e2") - F.col("e") > max_gap, F.floor("e").cast("long")).otherwise(last)
    some = rows.withColumn("t", F.explode(F.when(first <= last, F.sequence(first, last))))
    part = (F.col("t") - F.col("e")) / (F.col("e2") - F.col("e"))
    mix = lambda c: F.when(F.col("t") == F.col("e"), F.col(c)).otherwise(F.col(c) + (F.col(f"{c}2") - F.col(c)) * part)
    return some.select("t", "obj_id", mix("x").alias("x"), mix("y").alias("y"))
