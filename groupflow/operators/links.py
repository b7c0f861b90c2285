"""Links: pairs of clusters close enough to be neighbours in a crowd.

Candidates meet in an equi-join on time and a grid cell whose side is the allowed distance at
that time gap, so the join is as selective as the rule allows. Only summaries are joined; points
are looked at for the pairs that the summaries leave undecided, and stand once for each snapshot.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.functions import pruning
from groupflow.operators import distances, sectors
from groupflow.params import Params
from groupflow.storage import materialize

_SUMMARY = ["cluster_id", "t", "n", "mx", "my", "r", "var", "minx", "maxx", "miny", "maxy"]
_BLOCK = 4  # cells of a block, each way
_NEIGHBOURS = [(i, j) for i in (-1, 0, 1) for j in (-1, 0, 1)]


def _gaps(shape: DataFrame, g: int) -> DataFrame:
    return shape.withColumn("dt", F.explode(F.sequence(F.lit(1), F.lit(g))))


def candidates(
    shape: DataFrame, p: Params, index: str = "box", max_gap: str = "lemma", n_parts: int = 8, halo: str = "gap", since: int | None = None
) -> DataFrame:
    """``a, b, dt``: structs of summaries of clusters ``dt`` timestamps apart that may be linked.

    ``index='box'`` meets by the lower corner of bounding boxes, ``'grid'`` by cells of points, ``'none'`` by time
    alone; ``'sector'`` in one of ``n_parts`` space parts, ``'random'`` spreads later clusters over ``n_parts`` tasks, each
    of which sees all earlier ones. ``max_gap='lemma'`` keeps gaps that a crowd can have, ``'window'`` all of a window.
    ``since``: only pairs whose later cluster is of this timestamp or after it, for links of new clusters.
    """
    g = p.max_gap if max_gap == "lemma" else p.w - 1
    summary = [F.col(c) for c in _SUMMARY]
    limit = F.lit(p.d) * F.col("dt")
    columns = [F.struct(*summary).alias("s"), "dt"]
    early = _gaps(shape, g).withColumn("at", F.col("t") + F.col("dt"))
    late = _gaps(shape, g).withColumn("at", F.col("t"))
    keys = ["at", "dt"]
    if index == "box":
        # rows meet by blocks of cells, so that few of them are sent to more than one; pairs are those of neighbouring cells
        cell = lambda c: F.floor(F.col(c) / limit)
        block = lambda q: F.floor(q / _BLOCK).cast("long")
        keys += ["bx", "by"]
        met = lambda c: F.explode(F.sequence(block(F.col(c) - 1), block(F.col(c) + 1)))
        early, late = (side.withColumns({"cx": cell("minx"), "cy": cell("miny")}) for side in (early, late))
        early = early.withColumn("bx", met("cx")).withColumn("by", met("cy"))
        late = late.withColumns({"bx": block(F.col("cx")), "by": block(F.col("cy"))})
        columns = [*columns, "cx", "cy"]
    elif index == "grid":
        # a cell is one number, as distinct numbers are found by hashing; should two cells share one, pairs more are looked at
        cell = lambda q: F.floor(q["x"] / limit) * F.lit(1 << 32) + F.floor(q["y"] / limit)
        keys += ["cell"]
        cells = F.array_distinct(F.transform("pts", cell))
        around = F.array_distinct(F.flatten(F.transform(cells, lambda c: F.array(*[c + F.lit((i << 32) + j) for i, j in _NEIGHBOURS]))))
        early, late = early.withColumn("cell", F.explode(around)), late.withColumn("cell", F.explode(cells))
    elif index == "sector":
        keys += ["part"]
        points = sectors.polar(shape, sectors.center(shape))
        part = materialize(sectors.divide(points, n_parts), "parts")
        early = _gaps(sectors.home(points, part), g).withColumn("at", F.col("t") + F.col("dt"))
        late = _gaps(points, g).withColumn("at", F.col("t"))
        reach = F.col("r") + sectors.halo_width(p.d, F.col("dt"), halo)
        late = sectors.reached(late, part, reach, F.col("t") - F.col("dt")).withColumn("part", F.explode("met"))
    elif index == "random":
        keys += ["part"]
        early = early.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_parts - 1).cast("long"))))
        late = late.withColumn("part", F.pmod(F.xxhash64("cluster_id"), F.lit(n_parts)))
    elif index != "none":
        raise ValueError("index is 'box', 'grid', 'sector', 'random' or 'none'")
    if since is not None:
        early, late = early.filter(F.col("at") >= since), late.filter(F.col("at") >= since)
    early, late = (side.select("at", *columns, *keys[2:]) for side in (early, late))
    if index == "box":
        late = late.withColumnsRenamed({"cx": "ux", "cy": "uy"})
    pairs = early.withColumnRenamed("s", "a").join(late.withColumnRenamed("s", "b"), keys)
    if index == "box":
        pairs = pairs.filter((F.abs(F.col("cx") - F.col("ux")) <= 1) & (F.abs(F.col("cy") - F.col("uy")) <= 1))
    pairs = pairs.select("a", "b", "dt")
    return pairs.dropDuplicates(["a", "b"]) if index == "grid" else pairs


def decide(
    pairs: DataFrame, shape: DataFrame, p: Params, prune: bool = True, far_rule: str = "hull", near_rule: str = "sound", max_gap: str = "lemma"
) -> DataFrame:
    """``src, dst, dt, linked, decided_by`` for each candidate of gaps up to ``max_gap``; ``decided_by`` is far, near or exact."""
    limit = F.lit(p.d) * F.col("dt")
    by = F.when(pruning.far("a", "b", limit, far_rule), "far").when(pruning.near("a", "b", limit, near_rule), "near")
    by = by.otherwise("exact") if prune else F.lit("exact")
    named = pairs.select(F.col("a.cluster_id").alias("src"), F.col("b.cluster_id").alias("dst"), "dt", by.alias("decided_by"))
    named = materialize(named, "decided")
    sure = named.filter("decided_by <> 'exact'").withColumn("linked", F.col("decided_by") == "near")
    open_ = distances.with_squares(named.filter("decided_by = 'exact'").drop("decided_by"), shape, p.w - 1 if max_gap == "window" else p.max_gap, p.d)
    open_ = open_.withColumns({"linked": F.col("q") <= limit * limit, "decided_by": F.lit("exact")})
    columns = ["src", "dst", "dt", "linked", "decided_by"]
    return sure.select(columns).unionByName(open_.select(columns))


def build(
    shape: DataFrame,
    p: Params,
    index: str = "box",
    prune: bool = True,
    max_gap: str = "lemma",
    n_parts: int = 8,
    halo: str = "gap",
    since: int | None = None,
    **rules: str,
) -> DataFrame:
    """``link(src, dst, dt, decided_by)``: cluster pairs within ``d * dt``, ``dt`` up to the gap bound;
    with ``since`` those of later clusters only."""
    pairs = candidates(shape, p, index, max_gap, n_parts, halo, since)
    if prune:
        # most pairs are far apart: they go before anything is written
        pairs = pairs.filter(~pruning.far("a", "b", F.lit(p.d) * F.col("dt"), rules.get("far_rule", "hull")))
    return decide(pairs, shape, p, prune, max_gap=max_gap, **rules).filter("linked").drop("linked")
