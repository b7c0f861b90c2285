"""Closed aggregations: the largest part of a crowd whose every cluster keeps enough participators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from groupflow.params import Params
from groupflow.storage import materialize


def _with_members(crowd: DataFrame, shape: DataFrame) -> DataFrame:
    """``crowd_id, s_lo, s_hi`` and ``chain``, the clusters of the crowd with their objects, in time order."""
    rows = crowd.select("crowd_id", "s_lo", "s_hi", F.explode("path").alias("cluster_id"))
    return (
        rows.join(shape.select("cluster_id", "objs"), "cluster_id")
        .groupBy("crowd_id", "s_lo", "s_hi")
        .agg(F.array_sort(F.collect_list(F.struct("cluster_id", "objs"))).alias("chain"))
    )


def participators(crowd: DataFrame, shape: DataFrame, k_p: int) -> DataFrame:
    """``crowd_id, obj_id, cnt``: objects in at least ``k_p`` clusters of the crowd."""
    rows = crowd.select("crowd_id", F.explode("path").alias("cluster_id")).join(shape.select("cluster_id", "objs"), "cluster_id")
    return rows.select("crowd_id", F.explode("objs").alias("obj_id")).groupBy("crowd_id", "obj_id").agg(F.count("*").alias("cnt")).filter(
        F.col("cnt") >= k_p
    )


def aggregation_check(crowd: DataFrame, shape: DataFrame, p: Params) -> DataFrame:
    """``crowd_id, least, is_aggregation``: the least number of participators in a cluster of the crowd."""
    rows = crowd.select("crowd_id", F.explode("path").alias("cluster_id")).join(shape.select("cluster_id", "objs"), "cluster_id")
    rows = rows.select("crowd_id", "cluster_id", F.explode("objs").alias("obj_id"))
    real = rows.join(participators(crowd, shape, p.k_p).select("crowd_id", "obj_id", F.lit(1).alias("one")), ["crowd_id", "obj_id"], "left")
    each = real.groupBy("crowd_id", "cluster_id").agg(F.count("one").alias("n"))
    return each.groupBy("crowd_id").agg(F.min("n").alias("least")).withColumn("is_aggregation", F.col("least") >= p.m_p)


def bind(value: Column, f) -> Column:
    """``f(value)`` with ``value`` worked out once, however often ``f`` and its lambdas use it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def frequent(every: Column, k: int) -> Column:
    """Sorted distinct elements that occur at least ``k`` times: in sorted order one equals that ``k - 1`` places on."""
    runs = bind(
        F.array_sort(every), lambda s: F.zip_with(s, F.slice(s, F.lit(k), F.size(s) + 1), lambda a, b: F.when(a == b, a))
    )
    return F.array_distinct(F.filter(runs, lambda v: v.isNotNull()))


def keep_valid(chain: Column, p: Params) -> Column:
    """One round: clusters that hold ``m_p`` participators of the chain."""
    real = frequent(F.flatten(F.transform(chain, lambda c: c["objs"])), p.k_p)
    return bind(real, lambda r: F.filter(chain, lambda c: F.size(F.array_intersect(c["objs"], r)) >= p.m_p))


def _peel_expr(rows: DataFrame, p: Params) -> DataFrame:
    # each round but the last drops a cluster, so w - k_c + 1 rounds reach the fixpoint or too few clusters
    rounds = F.sequence(F.lit(1), F.lit(p.w - p.k_c + 1))
    return rows.withColumn("chain", F.aggregate(rounds, F.col("chain"), lambda s, _: keep_valid(s, p)))


def _peel_relational(rows: DataFrame, p: Params) -> DataFrame:
    keys = ["crowd_id", "s_lo", "s_hi"]
    flat = rows.select(*keys, F.explode("chain").alias("c")).select(*keys, "c.cluster_id", F.explode("c.objs").alias("obj_id"))
    for _ in range(p.w - p.k_c + 1):
        real = flat.groupBy(*keys, "obj_id").agg(F.count("*").alias("n")).filter(F.col("n") >= p.k_p).drop("n")
        enough = flat.join(real, [*keys, "obj_id"]).groupBy(*keys, "cluster_id").agg(F.count("*").alias("n")).filter(F.col("n") >= p.m_p)
        flat = materialize(flat.join(enough.drop("n"), [*keys, "cluster_id"], "left_semi"), "peel")
    per = flat.groupBy(*keys, "cluster_id").agg(F.sort_array(F.collect_list("obj_id")).alias("objs"))
    return per.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("cluster_id", "objs"))).alias("chain"))


def peel(crowd: DataFrame, shape: DataFrame, p: Params, impl: str = "expr") -> DataFrame:
    """``agg(agg_id, path, s_lo, s_hi, members, size)``, the closed aggregation of each crowd that has one.

    The result is a unique greatest fixpoint, so the order of removals does not matter. ``'expr'`` runs all rounds
    inside one row, ``'relational'`` as joins, for crowds of very large clusters.
    """
    rows = _with_members(crowd, shape)
    rows = _peel_expr(rows, p) if impl == "expr" else _peel_relational(rows, p)
    rows = rows.filter(F.size("chain") >= p.k_c)
    members = frequent(F.flatten(F.col("chain.objs")), p.k_p)
    return rows.select(
        F.concat_ws("-", F.col("chain.cluster_id").cast("array<string>")).alias("agg_id"),
        F.col("chain.cluster_id").alias("path"),
        "s_lo",
        "s_hi",
        members.alias("members"),
    ).withColumn("size", F.size("members"))


def by_window(agg: DataFrame) -> DataFrame:
    """``win, agg_id, path, members``: one row for each window and distinct aggregation."""
    rows = agg.select(F.explode(F.sequence("s_lo", "s_hi")).alias("win"), "agg_id", "path", "members")
    return rows.dropDuplicates(["win", "agg_id"])


def closed(windows: DataFrame, closure: str = "global") -> DataFrame:
    """Aggregations that are part of no longer one in their window; ``'per_crowd'`` keeps all.

    A longer one holds the first cluster, so pairs meet by window and that cluster.
    """
    if closure == "per_crowd":
        return windows
    longer = windows.select("win", F.explode("path").alias("head"), F.col("path").alias("longer"))
    inside = (
        windows.withColumn("head", F.element_at("path", 1))
        .join(longer, ["win", "head"])
        .filter(F.size("longer") > F.size("path"))
        .filter(F.size(F.array_intersect("longer", "path")) == F.size("path"))
        .select("win", "agg_id")
    )
    return windows.join(inside, ["win", "agg_id"], "left_anti")


def groups(windows: DataFrame) -> DataFrame:
    """``win, group_id, members, size, n_aggs``: distinct member sets of a window's closed aggregations."""
    rows = windows.withColumn("names", F.concat_ws(",", F.col("members").cast("array<string>")))
    return (
        rows.groupBy("win", "names")
        .agg(F.first("members").alias("members"), F.count("*").alias("n_aggs"))
        .select("win", F.concat_ws(":", F.col("win").cast("string"), "names").alias("group_id"), "members", F.size("members").alias("size"), "n_aggs")
    )
