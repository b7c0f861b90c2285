"""One timestamp more: candidates, verification and lineage carried from window to window.

The candidates of a window are its maximal chains of clusters, with links as in :mod:`groupflow.operators.links`.
When the window slides, heads that expired are cut off, and chains are extended by the new clusters.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators import lineage, links
from groupflow.operators.baselines import chains_with_members
from groupflow.operators.chains import time_of
from groupflow.operators.peel import bind, frequent, keep_valid
from groupflow.params import Params
from groupflow.storage import materialize, release

CANDIDATE = "path array<long>, times array<long>"


@dataclass(frozen=True)
class Window:
    """What one window leaves to the next: its clusters, its links and its candidates; ``start`` is the first timestamp seen."""

    t: int
    start: int
    shape: DataFrame
    link: DataFrame
    candidate: DataFrame


def crowd_step(state: Window | None, new: DataFrame, t: int, p: Params) -> tuple[Window, DataFrame]:
    """The state after the clusters ``new`` of timestamp ``t``, and the status of each end: match or unmatched.

    An end is matched where a new cluster follows it. All candidates of a matched end are extended, and so are the
    beginnings of candidates whose inner clusters a new cluster follows. A new cluster that follows none is a
    candidate of its own. Candidates that cannot reach ``k_c`` clusters inside a window any more are dropped.
    """
    one = new.select(F.array("cluster_id").alias("path"), F.array("t").alias("times"), "cluster_id")
    if state is None:
        first = materialize(one.drop("cluster_id"), "candidates")
        none = new.sparkSession.createDataFrame([], "src long, dst long, dt int, decided_by string")
        status = new.sparkSession.createDataFrame([], "tail long, status string")
        return Window(t, t, materialize(new, "shape"), none, first), status
    lo = t - p.w + 1
    shape = materialize(state.shape.filter(F.col("t") >= lo).unionByName(new), "shape")
    # new clusters against ending ones only
    fresh = links.build(state.shape.filter(F.col("t") >= max(lo, t - p.max_gap)).unionByName(new), p, since=t)
    link = materialize(state.link.filter(time_of(F.col("src")) >= lo).unionByName(fresh), "link")
    # cut expired heads; what is left starts with a cluster that follows none in the window, or another candidate holds it
    cut = F.filter(F.arrays_zip("path", "times"), lambda c: c["times"] >= lo)
    kept = state.candidate.select(cut.alias("c")).filter(F.size("c") > 0).select(F.col("c.path").alias("path"), F.col("c.times").alias("times")).distinct()
    old = link.filter(time_of(F.col("dst")) < t)
    kept = kept.join(old.select(F.col("dst").alias("h")).distinct(), F.element_at("path", 1) == F.col("h"), "left_anti")
    now = link.filter(time_of(F.col("dst")) == t).select("src", "dst")
    between = old.select("src", F.col("dst").alias("mid")).join(now.select(F.col("src").alias("mid"), "dst"), "mid")
    cover = materialize(now.join(between.select("src", "dst"), ["src", "dst"], "left_anti"), "cover")
    at = kept.select("path", "times", F.posexplode("path").alias("pos", "src"))
    grown = (
        at.join(cover, "src")
        .select(F.slice("path", F.lit(1), F.col("pos") + 1).alias("path"), F.slice("times", F.lit(1), F.col("pos") + 1).alias("times"), "dst")
        .distinct()
        .select(F.array_append("path", F.col("dst")).alias("path"), F.array_append("times", F.lit(t).cast("long")).alias("times"))
    )
    alone = one.join(cover.select(F.col("dst").alias("cluster_id")), "cluster_id", "left_anti").drop("cluster_id")
    tail = F.element_at("path", -1)
    matched = cover.select(F.col("src").alias("tail")).distinct()
    unmatched = kept.withColumn("tail", tail).join(matched, "tail", "left_anti").select("path", "times")
    everyone = unmatched.unionByName(grown).unionByName(alone)
    candidate = materialize(everyone.filter(_useful(p, t)), "candidates")
    status = kept.select(tail.alias("tail")).distinct().join(matched.withColumn("status", F.lit("match")), "tail", "left")
    status = status.select("tail", F.coalesce("status", F.lit("unmatched")).alias("status"))
    return Window(t, state.start, shape, link, candidate), status


def forget(state: Window) -> None:
    """Delete what an earlier state holds, once no plan reads it any more."""
    release(state.shape, state.link, state.candidate)


def _useful(p: Params, t: int):
    """Long enough, or able to get so from some head on: clusters from there on and timestamps left in its window."""
    n = F.size("path")
    reach = F.exists(F.transform("times", lambda v, j: n - j + v + (p.w - 1 - t)), lambda r: r >= p.k_c)
    return (n >= p.k_c) | reach


def crowds(state: Window, p: Params) -> DataFrame:
    """``win, crowd_id, path``: the closed crowds of the state's window; none while the first window is not complete."""
    win = state.t - p.w + 1
    found = state.candidate.filter(F.size("path") >= p.k_c)
    return found.filter(F.lit(win >= state.start)).select(
        F.lit(win).cast("long").alias("win"), F.concat_ws("-", F.col("path").cast("array<string>")).alias("crowd_id"), "path"
    )


def participator_step(before: DataFrame, change: DataFrame, shape: DataFrame) -> DataFrame:
    """``crowd_id, obj_id, cnt`` of changed crowds from the counts of those they came from.

    ``change(crowd_id, parent_id, expired, arrived)`` lists the clusters that left and came; only their objects are
    counted. Objects without a cluster left are gone.
    """
    base = change.select("crowd_id", F.col("parent_id").alias("p")).join(before.withColumnRenamed("crowd_id", "p"), "p").select("crowd_id", "obj_id", "cnt")
    moves = change.select("crowd_id", F.explode("arrived").alias("cluster_id"), F.lit(1).cast("long").alias("cnt")).unionByName(
        change.select("crowd_id", F.explode("expired").alias("cluster_id"), F.lit(-1).cast("long").alias("cnt"))
    )
    moved = moves.join(shape.select("cluster_id", F.explode("objs").alias("obj_id")), "cluster_id").select("crowd_id", "obj_id", "cnt")
    return base.unionByName(moved).groupBy("crowd_id", "obj_id").agg(F.sum("cnt").alias("cnt")).filter("cnt > 0")


def peel_step(crowd: DataFrame, before: DataFrame, p: Params) -> DataFrame:
    """``crowd_id, path, members, fell_back``: closed aggregations that reuse those of the window before.

    ``crowd(crowd_id, parent_id, chain)``: chains with their objects, as :func:`baselines.chains_with_members` gives them.
    ``before(crowd_id, path)``: the fixpoints of the chains they came from, of any length. Where the newest cluster holds
    too few participators, it is in no aggregation; the result then lies in the one before, and peeling starts from
    there. The result is the same as that of peeling the whole chain. Without a parent, peeling starts from the whole.
    """
    last = before.select(F.col("crowd_id").alias("parent_id"), F.col("path").alias("was"))
    rows = crowd.join(last, "parent_id", "left")
    real = frequent(F.flatten(F.col("chain.objs")), p.k_p)
    newest = bind(real, lambda r: F.size(F.array_intersect(F.element_at("chain", -1)["objs"], r)) < p.m_p)
    rows = rows.withColumn("fell_back", newest & F.col("was").isNotNull())
    start = F.when(F.col("fell_back"), F.filter("chain", lambda c: F.array_contains("was", c["cluster_id"]))).otherwise(F.col("chain"))
    rounds = F.sequence(F.lit(1), F.lit(p.w))
    whole = rows.withColumn("chain", F.aggregate(rounds, start, lambda s, _: keep_valid(s, p)))
    return whole.select(
        "crowd_id", F.col("chain.cluster_id").alias("path"), frequent(F.flatten(F.col("chain.objs")), p.k_p).alias("members"), "fell_back"
    )


def verify_step(crowd: DataFrame, shape: DataFrame, before: DataFrame, p: Params) -> DataFrame:
    """``crowd_id, path, s_lo, s_hi, kept, members, how``: crowds with what peeling keeps of them, from that of earlier crowds.

    ``before(crowd_id, path, kept, members)`` is what an earlier step gave. ``how`` is ``'same'`` for a crowd verified
    before, whose objects are not read again; ``'cut'`` for a run of an earlier crowd, where peeling starts from what was
    kept of that; ``'fell_back'`` for a crowd whose newest cluster holds too few participators and whose other clusters are
    such a run, with the same start; ``'whole'`` otherwise. Peeling is monotone, so what was kept of a longer chain holds
    all that is kept of its runs. Where fewer than ``k_c`` clusters are kept, they are a remainder and no aggregation.
    """
    done = crowd.select("crowd_id", "path", "s_lo", "s_hi").join(before.select("crowd_id", "kept", "members"), "crowd_id")
    fresh = crowd.select("crowd_id", "path", "s_lo", "s_hi").join(before.select("crowd_id"), "crowd_id", "left_anti")
    # chains follow covering links, so that two of them share whole runs and meet by equality
    n = F.size("path")
    runs = F.flatten(F.transform(F.sequence(F.lit(1), n), lambda i: F.transform(F.sequence(i, n), lambda j: F.slice("path", i, j - i + 1))))
    runs = before.select("crowd_id", "kept", F.explode(F.filter(runs, lambda r: F.size(r) >= max(p.k_c - 1, 1))).alias("run"))
    known = runs.groupBy("run").agg(F.min(F.struct(F.size("kept").alias("n"), "crowd_id", "kept"))["kept"].alias("was"))
    fresh = fresh.join(known.select(F.col("run").alias("path"), F.col("was").alias("cut")), "path", "left")
    fresh = fresh.withColumn("run", F.slice("path", F.lit(1), F.size("path") - 1)).join(known, "run", "left")
    rows = fresh.join(chains_with_members(fresh.select("crowd_id", "path").distinct(), shape), "crowd_id")
    real = frequent(F.flatten(F.col("chain.objs")), p.k_p)
    newest = bind(real, lambda r: F.size(F.array_intersect(F.element_at("chain", -1)["objs"], r)) < p.m_p)
    how = F.when(F.col("cut").isNotNull(), "cut").when(F.col("was").isNotNull() & newest, "fell_back").otherwise("whole")
    rows = rows.withColumn("how", how).withColumn("was", F.coalesce("cut", "was"))
    start = F.when(F.col("how") == "whole", F.col("chain")).otherwise(F.filter("chain", lambda c: F.array_contains("was", c["cluster_id"])))
    rounds = F.sequence(F.lit(1), F.lit(p.w - p.k_c + 1))
    rows = rows.withColumn("chain", F.aggregate(rounds, start, lambda s, _: keep_valid(s, p)))
    members = frequent(F.flatten(F.col("chain.objs")), p.k_p)
    rows = rows.select("crowd_id", "path", "s_lo", "s_hi", F.col("chain.cluster_id").alias("kept"), members.alias("members"), "how")
    return rows.unionByName(done.withColumn("how", F.lit("same")))


def aggregations(verified: DataFrame, p: Params) -> DataFrame:
    """``agg_id, path, s_lo, s_hi, members, size`` of verified crowds, as :func:`peel.peel` gives them."""
    agg_id = F.concat_ws("-", F.col("kept").cast("array<string>"))
    return verified.filter(F.size("kept") >= p.k_c).select(
        agg_id.alias("agg_id"), F.col("kept").alias("path"), "s_lo", "s_hi", "members", F.size("members").alias("size")
    )


def lineage_step(before: DataFrame, now: DataFrame, m_g: float) -> DataFrame:
    """``evo`` from the groups of the last window seen to those of later ones."""
    return lineage.edges(before.unionByName(now), m_g)


def chain_step(before: DataFrame, now: DataFrame, evo: DataFrame, k_g: int, last: int) -> tuple[DataFrame, DataFrame]:
    """Open chains after new windows, and the chains that they close.

    ``before(win, group_id, since)``: the groups of the last window seen, with the first window of the longest chain
    that ends with each. ``open``: the same for window ``last``. ``closed(group_id, first_win, last_win, n_windows)``:
    groups of earlier windows that nothing continues and on which a chain of at least ``k_g`` windows ends. Of the chains
    that end with a group the longest is kept, so the state has one row for each group.
    """
    every = before.select("win", "group_id", "since").unionByName(now.select("win", "group_id", F.lit(None).cast("long").alias("since")))
    deep = materialize(lineage.depths(every, evo), "deep")
    since = (F.col("win") - F.col("depth_in") + 1).alias("since")
    open_ = deep.filter(F.col("win") == last).select("win", "group_id", since)
    over = deep.filter((F.col("win") < last) & (F.col("depth_out") == 1) & (F.col("depth_in") >= k_g))
    closed = over.select("group_id", since.alias("first_win"), F.col("win").alias("last_win"), F.col("depth_in").cast("long").alias("n_windows"))
    return open_, closed
