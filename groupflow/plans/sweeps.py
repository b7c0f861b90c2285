"""Experiment workloads: how the method's measures move with its parameters.

Each sweep shares the work that its parameter does not touch, and returns one row for each value.
"""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators import chains, density, links, peel
from groupflow.operators import distances as distances_of
from groupflow.params import Params
from groupflow.storage import materialize


def _stack(frames: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def distances(shape: DataFrame, p: Params, values: tuple[float, ...]) -> DataFrame:
    """``d, pairs, linked``: all pairs within the gap bound, and those within ``d * dt``; one pass for all values."""
    pairs = links.candidates(shape, p, "none").select(F.col("a.cluster_id").alias("src"), F.col("b.cluster_id").alias("dst"), "dt")
    far = distances_of.with_squares(pairs, shape, p.max_gap).select("dt", F.sqrt("q").alias("h"))
    each = far.withColumn("d", F.explode(F.array(*[F.lit(v) for v in values])))
    return each.groupBy("d").agg(F.count("*").alias("pairs"), F.count_if(F.col("h") <= F.col("d") * F.col("dt")).alias("linked"))


def crowds(shape: DataFrame, link: DataFrame, settings: list[Params]) -> DataFrame:
    """``k_c, crowds, windows``; ``link`` has the gaps of the smallest ``k_c``."""

    def one(p: Params) -> DataFrame:
        found = chains.closed_crowds(shape, chains.cover(link.filter(F.col("dt") <= p.max_gap)), p)
        windows = F.coalesce(F.sum(F.col("s_hi") - F.col("s_lo") + 1), F.lit(0).cast("long"))
        return found.agg(F.count("*").alias("crowds"), windows.alias("windows")).select(F.lit(p.k_c).cast("long").alias("k_c"), "crowds", "windows")

    return _stack(one(p) for p in settings)


def verification(crowd: DataFrame, shape: DataFrame, settings: list[Params]) -> DataFrame:
    """The swept one of ``k_p, m_p`` with ``aggregations, members``: distinct results and the sum of their sizes."""
    swept = "k_p" if len({p.k_p for p in settings}) > 1 else "m_p"

    def one(p: Params) -> DataFrame:
        agg = peel.peel(crowd, shape, p).select("agg_id", "size").distinct()
        total = F.coalesce(F.sum("size"), F.lit(0).cast("long"))
        return agg.agg(F.count("*").alias("aggregations"), total.alias("members")).select(
            F.lit(getattr(p, swept)).cast("long").alias(swept), "aggregations", "members"
        )

    return _stack(one(p) for p in settings)


def sizes(shape: DataFrame, link: DataFrame, settings: list[Params]) -> DataFrame:
    """``m_c, links``: links between clusters that are large enough; a link does not depend on other clusters."""
    n = shape.select("cluster_id", "n")
    both = link.join(n.select(F.col("cluster_id").alias("src"), F.col("n").alias("a")), "src")
    both = both.join(n.select(F.col("cluster_id").alias("dst"), F.col("n").alias("b")), "dst").select(F.least("a", "b").alias("n"))
    each = [F.count_if(F.col("n") >= p.m_c).alias(str(p.m_c)) for p in settings]
    rows = F.explode(F.array(*[F.struct(F.lit(p.m_c).cast("long").alias("m_c"), F.col(str(p.m_c)).alias("links")) for p in settings]))
    return both.agg(*each).select(rows.alias("r")).select("r.*")


def objects(snap: DataFrame, p: Params, n: int) -> DataFrame:
    """``part, objects, points, clusters`` for the objects of the first ``part`` of ``n`` classes of ids.

    Positions are worked out once and stand on shared storage by timestamps, so that no part is moved to be clustered; objects and points
    are counted by class, in one pass for all parts.
    """
    snap = materialize(density.placed(snap), "positions")
    least = F.col("obj_id") % n + 1  # of the parts that hold the class
    size = density.flat(snap).groupBy(least.alias("k"), "obj_id").agg(F.count("*").alias("c")).groupBy("k").agg(F.count("*").alias("o"), F.sum("c").alias("c"))
    size = {r["k"]: (r["o"], r["c"]) for r in size.collect()}  # a row for each class

    def one(k: int) -> DataFrame:
        some = snap.withColumn("points", F.filter("points", lambda v: v["obj_id"] % n < k)) if k < n else snap
        found = density.cluster(some, p.eps, p.min_pts, plan="auto", least=p.m_c)
        held = [F.lit(sum(v[i] for j, v in size.items() if j <= k)).cast("long") for i in (0, 1)]
        clusters = found.agg(F.count_distinct("cluster_id").alias("clusters"))
        return clusters.select((F.lit(k) / n).alias("part"), held[0].alias("objects"), held[1].alias("points"), "clusters")

    return _stack(one(k) for k in range(1, n + 1))


def ablation(shape: DataFrame, p: Params) -> DataFrame:
    """``off, pairs, exact, links``: candidate pairs, those compared point by point, and links that crowds can use."""
    settings = {
        "nothing": {},
        "index": {"index": "none"},
        "pruning": {"prune": False},
        "gap_bound": {"max_gap": "window"},
    }

    def one(name: str, chosen: dict) -> DataFrame:
        pairs = links.candidates(shape, p, chosen.get("index", "box"), chosen.get("max_gap", "lemma"))
        decided = materialize(links.decide(pairs, shape, p, chosen.get("prune", True), max_gap=chosen.get("max_gap", "lemma")), "ablation")
        return decided.agg(
            F.count("*").alias("pairs"),
            F.count_if(F.col("decided_by") == "exact").alias("exact"),
            F.count_if(F.col("linked") & (F.col("dt") <= p.max_gap)).alias("links"),
        ).select(F.lit(name).alias("off"), "pairs", "exact", "links")

    return _stack(one(name, chosen) for name, chosen in settings.items())
