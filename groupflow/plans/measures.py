"""Cost and accuracy measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupflow.params import Params


def confusion(found: DataFrame, truth: DataFrame, by: list[str] = [], match: str = "exact", theta: float = 0.5) -> DataFrame:  # noqa: B006
    """``by, tp, fp, fn`` of distinct found member sets against the annotated ones.

    ``match``: ``'exact'`` sets; ``'jaccard'`` and ``'containment'`` take a found set for right whose overlap with an annotated
    one is at least ``theta`` of their union, or of the annotated set, and an annotated set for found likewise.
    """
    a = found.select(*by, F.col("members").alias("m")).distinct()
    b = truth.select(*by, F.col("members").alias("m")).distinct()
    if match == "exact":
        hit_a = a.join(b.withColumn("hit", F.lit(True)), [*by, "m"], "left")
        hit_b = b.join(a.withColumn("hit", F.lit(True)), [*by, "m"], "left")
    elif match in ("jaccard", "containment"):
        # only sets that share an object meet
        one = a.select(*by, F.col("m").alias("a"), F.explode("m").alias("o")).join(b.select(*by, F.col("m").alias("b"), F.explode("m").alias("o")), [*by, "o"])
        both = one.groupBy(*by, "a", "b").agg(F.count("*").alias("n"))
        whole = F.size("b") if match == "containment" else F.size("a") + F.size("b") - F.col("n")
        both = both.filter(F.col("n") >= F.lit(theta) * whole)
        hit_a = a.join(both.select(*by, F.col("a").alias("m"), F.lit(True).alias("hit")).distinct(), [*by, "m"], "left")
        hit_b = b.join(both.select(*by, F.col("b").alias("m"), F.lit(True).alias("hit")).distinct(), [*by, "m"], "left")
    else:
        raise ValueError("match is 'exact', 'jaccard' or 'containment'")
    got = hit_a.select(*by, F.when(F.col("hit"), "tp").otherwise("fp").alias("kind"))
    missed = hit_b.filter("hit is null").select(*by, F.lit("fn").alias("kind"))
    count = lambda kind: F.count_if(F.col("kind") == kind).alias(kind)
    return got.unionByName(missed).groupBy(*by).agg(count("tp"), count("fp"), count("fn"))


def precision_recall(found: DataFrame, truth: DataFrame, by: list[str] = [], **match) -> DataFrame:  # noqa: B006
    """``by, tp, fp, fn, precision, recall, f1``; a ratio without a denominator is null."""
    ratio = lambda a, b: F.when(b > 0, a / b)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return confusion(found, truth, by, **match).withColumns(
        {"precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": ratio(2 * tp, 2 * tp + fp + fn)}
    )


def pattern_counts(starts: DataFrame, origin: str = "2024-01-01") -> DataFrame:
    """``period, day_type, n`` of patterns by the hour and day in which they start (``t`` in hours since ``origin``)."""
    at = F.timestamp_micros((F.col("t") * 3_600_000_000 + F.unix_micros(F.to_timestamp(F.lit(origin)))).cast("long"))
    h = F.pmod("t", F.lit(24))
    period = F.when(h.between(7, 9), "07-10").when(h.between(10, 12), "10-13").when(h.between(13, 15), "13-16").when(h.between(16, 19), "16-20")
    kind = F.when(F.dayofweek(at).isin(1, 7), "weekend").otherwise("workday")
    return starts.select(period.alias("period"), kind.alias("day_type")).filter("period is not null").groupBy("period", "day_type").agg(
        F.count("*").alias("n")
    )


def pruning(decided: DataFrame) -> DataFrame:
    """``decided_by, n, share`` of candidate pairs; the shares of far and near add up to the pruning ratio."""
    each = decided.groupBy("decided_by").agg(F.count("*").alias("n"), F.count_if("linked").alias("linked"))
    total = each.agg(F.sum("n").alias("total"))
    return each.crossJoin(F.broadcast(total)).select("decided_by", "n", "linked", (F.col("n") / F.col("total")).alias("share"))


def average_length(chains: DataFrame) -> DataFrame:
    """``n, avg_timestamps, max_timestamps`` of evolving groups."""
    return chains.agg(
        F.count("*").alias("n"), F.avg("n_timestamps").alias("avg_timestamps"), F.max("n_timestamps").alias("max_timestamps")
    )


def equal_cut(chains: DataFrame, n: DataFrame) -> DataFrame:
    """``k_g, n, avg_timestamps``: the longest least length that leaves at least ``n`` chains (one row), and what it leaves; no row where
    there are fewer."""
    each = chains.groupBy("n_windows").agg(F.count("*").alias("c"), F.sum("n_timestamps").alias("s"))
    more = Window.orderBy(F.desc("n_windows"))  # one row for each length
    left = each.select("n_windows", F.sum("c").over(more).alias("n"), F.sum("s").over(more).alias("s"))
    ok = left.join(F.broadcast(n.select(F.col("n").alias("least"))), F.col("n") >= F.col("least"))
    best = ok.agg(F.max(F.struct("n_windows", "n", "s")).alias("b")).filter("b is not null")
    return best.select(F.col("b.n_windows").alias("k_g"), "b.n", (F.col("b.s") / F.col("b.n")).alias("avg_timestamps"))


def by_period(starts: DataFrame) -> DataFrame:
    """Counts of :func:`pattern_counts` with their totals over periods, day types and both, told apart by ``level``; without
    patterns the total over both is there and null."""
    cube = starts.cube("period", "day_type").agg(F.sum("n").alias("n"), F.grouping_id().cast("long").alias("level"))
    # a cube without rows has no total in Spark, an aggregation without keys has
    none = F.lit(None).cast("string")
    total = starts.agg(F.sum("n").alias("n")).select(none.alias("period"), none.alias("day_type"), F.lit(3).cast("long").alias("level"), "n")
    return cube.filter("level < 3").select("period", "day_type", "level", "n").unionByName(total)


def per_day(counts: DataFrame, days: DataFrame) -> DataFrame:
    """``period, day_type, n, per_day``: counts beside their mean over the days of a type, ``days(day_type, days)``."""
    return counts.join(F.broadcast(days), "day_type").select("period", "day_type", "n", (F.col("n") / F.col("days")).alias("per_day"))


def window_sizes(shape: DataFrame, link: DataFrame, crowd: DataFrame, group: DataFrame, w: int) -> DataFrame:
    """``win, clusters, links, crowds, groups`` that a window holds, for windows with clusters."""
    t = lambda c: F.shiftright(F.col(c), 32)
    spread = lambda df, lo, hi, name: df.select(F.explode(F.sequence(lo, hi)).alias("win")).groupBy("win").agg(F.count("*").alias(name))
    clusters = spread(shape, F.col("t") - (w - 1), F.col("t"), "clusters")
    links = spread(link.filter(t("dst") - t("src") < w), t("dst") - (w - 1), t("src"), "links")
    crowds = spread(crowd, F.col("s_lo"), F.col("s_hi"), "crowds")
    groups = group.groupBy("win").agg(F.count("*").alias("groups"))
    out = clusters.join(links, "win", "left").join(crowds, "win", "left").join(groups, "win", "left")
    ends = shape.agg(F.min("t").alias("lo"), (F.max("t") - (w - 1)).alias("hi"))
    return out.join(F.broadcast(ends), F.col("win").between(F.col("lo"), F.col("hi"))).drop("lo", "hi").fillna(0, ["links", "crowds", "groups"])


def case_graph(group: DataFrame, evo: DataFrame, depth: DataFrame, lo: int, hi: int) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges of the groups of windows ``lo`` to ``hi``: size, life and members of each group, common members of each edge."""
    some = F.col("win").between(lo, hi)
    life = F.col("depth_in") + F.col("depth_out") - 1
    nodes = group.filter(some).join(depth.select("group_id", life.alias("life")), "group_id").select("group_id", "win", "size", "life", "members")
    return nodes, evo.filter(F.col("win").between(lo, hi - 1)).select("src_group", "dst_group", "common")


def state_size(shape: DataFrame, link: DataFrame, crowd: DataFrame, group: DataFrame) -> DataFrame:
    """``clusters, links, crowds, groups`` counts."""
    one = lambda df, name: df.agg(F.count("*").alias(name))
    return (
        one(shape, "clusters")
        .crossJoin(one(link, "links"))
        .crossJoin(one(crowd, "crowds"))
        .crossJoin(one(group, "groups"))
    )


def cost_stats(decided: DataFrame, shape: DataFrame, crowd: DataFrame, w: int) -> DataFrame:
    """``m, q, k, l, alpha``: new clusters of a timestamp, ending ones that a new one meets, points of a cluster,
    candidates of a window (null without crowds), and the share of pairs that the rules decide."""
    pairs = decided.agg(F.count("*").alias("pairs"), F.count_if(F.col("decided_by") != "exact").alias("pruned"))
    one = shape.agg(F.count("*").alias("c"), F.avg("n").alias("k"), F.count_distinct("t").alias("times"), (F.max("t") - F.min("t") - (w - 2)).alias("windows"))
    held = crowd.agg(F.sum(F.col("s_hi") - F.col("s_lo") + 1).alias("held"))
    return pairs.crossJoin(one).crossJoin(held).select(
        (F.col("c") / F.col("times")).alias("m"),
        (F.col("pairs") / F.col("c")).alias("q"),
        "k",
        (F.col("held") / F.greatest("windows", F.lit(1))).alias("l"),
        (F.col("pruned") / F.greatest("pairs", F.lit(1))).alias("alpha"),
    )


def cost_model(stats: DataFrame, p: Params, n_parts: int = 8, n_rings: int = 2) -> DataFrame:
    """``crowd_cost, verify_cost, lineage_cost, partition_cost, part_space`` predicted from :func:`cost_stats`: comparisons of
    points, recounts of candidates, pairs of groups, sorting for space parts, and clusters that a part holds."""
    m, each = F.col("m"), F.col("m") / n_rings
    return stats.select(
        ((1 - F.col("alpha")) * m * F.col("q") * F.col("k") * F.col("k")).alias("crowd_cost"),
        (F.col("l") * (p.w - p.k_c) * F.col("k")).alias("verify_cost"),
        (F.col("l") * F.col("l")).alias("lineage_cost"),
        (m + m * F.log2(m) + n_rings * each * F.log2(each)).alias("partition_cost"),
        (m / n_parts + n_rings).alias("part_space"),
    )


def describe(snap: DataFrame) -> DataFrame:
    """``points, objects, snapshots, distance`` of a dataset; ``distance`` is the length of all tracks."""
    back = Window.partitionBy("obj_id").orderBy("t")
    step = F.hypot(F.col("x") - F.lag("x").over(back), F.col("y") - F.lag("y").over(back))
    return snap.select("t", "obj_id", step.alias("step")).agg(
        F.count("*").alias("points"), F.count_distinct("obj_id").alias("objects"), F.count_distinct("t").alias("snapshots"), F.sum("step").alias("distance")
    )


def timed(name: str, work) -> dict:
    """Seconds that ``work()`` took, and what it returned (a count)."""
    began = time.perf_counter()
    n = work()
    return {"method": name, "seconds": time.perf_counter() - began, "answers": int(n)}


def speedup(times: DataFrame, base: str) -> DataFrame:
    """``times(experiment, value, method, seconds, answers)`` with ``speedup`` over the method ``base`` of the same value."""
    of = times.filter(F.col("method") == base).select("experiment", "value", F.col("seconds").alias("base"))
    return times.join(of, ["experiment", "value"], "left").withColumn("speedup", F.col("base") / F.col("seconds")).drop("base")
