"""Summaries of clusters: what pruning and linking read instead of points."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def summarize(member: DataFrame) -> DataFrame:
    """``shape(cluster_id, t, n, mx, my, r, var, minx, maxx, miny, maxy, objs, pts)``, one row for each cluster.

    Sums run over sorted points, so that equal clusters have equal summaries on any partitioning.
    ``r`` is the largest distance to the mean, ``var`` the mean squared one.
    """
    rows = (
        member.groupBy("cluster_id", "t")
        .agg(F.sort_array(F.collect_list(F.struct("obj_id", "x", "y"))).alias("p"))
        .withColumns(
            {
                "n": F.size("p"),
                "objs": F.col("p.obj_id"),
                "pts": F.transform("p", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y"))),
            }
        )
    )
    total = lambda c: F.aggregate(F.col(f"p.{c}"), F.lit(0.0), lambda s, v: s + v)
    rows = rows.withColumns({"mx": total("x") / F.col("n"), "my": total("y") / F.col("n")})
    square = F.transform("pts", lambda p: (p["x"] - F.col("mx")) * (p["x"] - F.col("mx")) + (p["y"] - F.col("my")) * (p["y"] - F.col("my")))
    return rows.withColumn("q", square).select(
        "cluster_id",
        "t",
        "n",
        "mx",
        "my",
        F.sqrt(F.array_max("q")).alias("r"),
        (F.aggregate("q", F.lit(0.0), lambda s, v: s + v) / F.col("n")).alias("var"),
        F.array_min("pts.x").alias("minx"),
        F.array_max("pts.x").alias("maxx"),
        F.array_min("pts.y").alias("miny"),
        F.array_max("pts.y").alias("maxy"),
        "objs",
        "pts",
    )
