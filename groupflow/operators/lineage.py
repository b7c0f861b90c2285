"""How groups of adjacent windows continue one another."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.graph import components
from groupflow.storage import materialize


def edges(groups: DataFrame, m_g: float) -> DataFrame:
    """``evo(win, src_group, dst_group, common, ratio)``: a group evolved into one of the next window.

    Only groups that share an object meet; they must share ``m_g`` of the smaller one.
    """
    flat = groups.select("win", "group_id", "size", F.explode("members").alias("obj_id"))
    nxt = flat.select((F.col("win") - 1).alias("win"), F.col("group_id").alias("dst_group"), F.col("size").alias("dst_size"), "obj_id")
    return (
        flat.join(nxt, ["win", "obj_id"])
        .groupBy("win", F.col("group_id").alias("src_group"), "dst_group", "size", "dst_size")
        .agg(F.count("*").alias("common"))
        .withColumn("ratio", F.col("common") / F.least("size", "dst_size"))
        .filter(F.col("common") >= F.lit(m_g) * F.least("size", "dst_size"))
        .select("win", "src_group", "dst_group", "common", "ratio")
    )


def emerging(groups: DataFrame, evo: DataFrame) -> DataFrame:
    """Groups that continue none."""
    return groups.join(evo.select(F.col("dst_group").alias("group_id")), "group_id", "left_anti")


def events(groups: DataFrame, evo: DataFrame) -> DataFrame:
    """``group_id, win, size, n_in, n_out, starts, ends, splits, merges, grows, shrinks`` for each group.

    A group grows or shrinks that continues just one, with more or fewer objects.
    """
    out = evo.groupBy(F.col("src_group").alias("group_id")).agg(F.count("*").alias("n_out"))
    before = evo.join(groups.select(F.col("group_id").alias("src_group"), F.col("size").alias("was")), "src_group")
    into = before.groupBy(F.col("dst_group").alias("group_id")).agg(F.count("*").alias("n_in"), F.max("was").alias("was"))
    n = lambda c: F.coalesce(c, F.lit(0))
    one = F.coalesce(F.col("n_in") == 1, F.lit(False))
    return (
        groups.join(out, "group_id", "left")
        .join(into, "group_id", "left")
        .select("group_id", "win", "size", n("n_in").alias("n_in"), n("n_out").alias("n_out"), "was")
        .withColumns(
            {"starts": F.col("n_in") == 0, "ends": F.col("n_out") == 0, "splits": F.col("n_out") > 1, "merges": F.col("n_in") > 1,
             "grows": one & (F.col("size") > F.col("was")), "shrinks": one & (F.col("size") < F.col("was"))}
        )
        .withColumns({"grows": F.coalesce("grows", F.lit(False)), "shrinks": F.coalesce("shrinks", F.lit(False))})
        .drop("was")
    )


def chains(groups: DataFrame, evo: DataFrame, k_g: int, w: int, max_paths: int = 10_000_000) -> DataFrame:
    """``chain(chain_id, groups, first_win, last_win, n_windows, n_timestamps, closed)`` of at least ``k_g`` windows.

    A chain starts with an emerging group and goes on until nothing continues it. Splits and merges make
    several chains. It is closed when its last window is not the last one seen.
    """
    last_seen = groups.agg(F.max("win").alias("n")).first()["n"]
    links = materialize(evo.select(F.col("src_group").alias("tail"), "dst_group"), "evo")
    out = links.groupBy("tail").agg(F.count("*").alias("out"))
    paths = emerging(groups, evo).select(F.array("group_id").alias("groups"), "win", F.col("group_id").alias("tail"))
    done, n = None, 1
    while True:
        paths = materialize(paths.join(out, "tail", "left"), "chains")
        finished = paths.filter("out is null").select("groups", F.col("win").alias("first_win"), F.lit(n).alias("n_windows"))
        done = finished if done is None else done.unionByName(finished)
        ahead = paths.agg(F.sum("out").alias("n")).first()["n"] or 0
        if ahead > max_paths:
            raise RuntimeError(f"about {ahead} chains of groups; raise max_paths or m_g")
        if not ahead:
            break
        paths = paths.drop("out").join(links, "tail").select(
            F.array_append("groups", F.col("dst_group")).alias("groups"), "win", F.col("dst_group").alias("tail")
        )
        n += 1
    last = F.col("first_win") + F.col("n_windows") - 1
    return done.filter(F.col("n_windows") >= k_g).select(
        F.concat_ws("|", "groups").alias("chain_id"),
        "groups",
        "first_win",
        last.alias("last_win"),
        "n_windows",
        (F.col("n_windows") + (w - 1)).alias("n_timestamps"),
        (last < F.lit(last_seen)).alias("closed"),
    )


def depths(groups: DataFrame, evo: DataFrame) -> DataFrame:
    """``group_id, win, depth_in, depth_out``: windows of the longest chain that ends, and that starts, with each group.
    Where ``groups`` has a column ``since``, the first window of the longest chain that is known to end with a group, depths count from there.

    A chain goes on window by window, so its length follows from the earliest window that is reached backwards. Edges
    of 1, 2, 4, ... windows are composed, so the rounds are the logarithm of the longest chain.
    """
    first = F.coalesce("since", "win") if "since" in groups.columns else F.col("win")
    label = groups.select("group_id", "win", first.alias("lo"), F.col("win").alias("hi"))
    step = evo.select("src_group", "dst_group")
    while not step.isEmpty():
        back = step.join(label.select(F.col("group_id").alias("src_group"), "lo"), "src_group")
        back = back.groupBy(F.col("dst_group").alias("group_id")).agg(F.min("lo").alias("lo2"))
        ahead = step.join(label.select(F.col("group_id").alias("dst_group"), "hi"), "dst_group")
        ahead = ahead.groupBy(F.col("src_group").alias("group_id")).agg(F.max("hi").alias("hi2"))
        # groups that nothing reaches any more at this distance keep what they have
        label = materialize(
            label.join(back, "group_id", "left")
            .join(ahead, "group_id", "left")
            .select("group_id", "win", F.least("lo", "lo2").alias("lo"), F.greatest("hi", "hi2").alias("hi")),
            "depths",
        )
        nxt = step.select(F.col("src_group").alias("mid"), F.col("dst_group").alias("end"))
        step = materialize(step.select("src_group", F.col("dst_group").alias("mid")).join(nxt, "mid").select("src_group", F.col("end").alias("dst_group")).distinct(), "steps")
    return label.select(
        "group_id", "win", (F.col("win") - F.col("lo") + 1).alias("depth_in"), (F.col("hi") - F.col("win") + 1).alias("depth_out")
    )


def long_lived(groups: DataFrame, evo: DataFrame, k_g: int) -> DataFrame:
    """``group_id, win, n_windows``: groups on a chain of at least ``k_g`` windows, with the longest one's. No chain is listed."""
    n = F.col("depth_in") + F.col("depth_out") - 1
    return depths(groups, evo).select("group_id", "win", n.alias("n_windows")).filter(n >= k_g)


def families(groups: DataFrame, evo: DataFrame, k_g: int, w: int) -> DataFrame:
    """``family, n_groups, first_win, last_win, n_windows, n_timestamps, closed``: groups that chains of at least ``k_g``
    windows connect, whatever they split and merge on the way; ``n_windows`` of the longest chain.

    Chains of a family multiply with splits and merges, families do not. One is closed when no chain of it is in the last window.
    """
    name = materialize(long_lived(groups, evo, k_g).withColumn("node", F.monotonically_increasing_id()), "named")
    end = lambda c: name.select(F.col("group_id").alias(f"{c}_group"), F.col("node").alias(c))
    label = components(evo.join(end("src"), "src_group").join(end("dst"), "dst_group").select("src", "dst"))
    last = groups.agg(F.max("win").alias("last_seen"))
    found = name.join(label, "node", "left").groupBy(F.coalesce("component", "node").alias("c")).agg(
        F.min("group_id").alias("family"),
        F.count("*").alias("n_groups"),
        F.min("win").alias("first_win"),
        F.max("win").alias("last_win"),
        F.max("n_windows").alias("n_windows"),
    )
    return found.crossJoin(F.broadcast(last)).select(
        "family", "n_groups", "first_win", "last_win", "n_windows", (F.col("n_windows") + (w - 1)).alias("n_timestamps"), (F.col("last_win") < F.col("last_seen")).alias("closed")
    )
