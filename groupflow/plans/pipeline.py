"""The whole three-phase method on a table of positions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from groupflow.operators import chains, density, lineage, links, peel, shapes
from groupflow.params import Params
from groupflow.storage import materialize


@dataclass(frozen=True)
class Discovery:
    member: DataFrame
    shape: DataFrame
    link: DataFrame
    cover: DataFrame
    crowd: DataFrame
    agg: DataFrame
    windows: DataFrame
    group: DataFrame
    evo: DataFrame


def clusters(snap: DataFrame, p: Params, plan: str = "auto") -> tuple[DataFrame, DataFrame]:
    """Members and summaries of the clusters of at least ``m_c`` objects, both on shared storage."""
    member = materialize(density.cluster(snap, p.eps, p.min_pts, plan=plan, least=p.m_c), "member")
    return member, materialize(shapes.summarize(member), "shape")


def discover(
    snap: DataFrame,
    p: Params,
    plan: str = "auto",
    index: str = "box",
    prune: bool = True,
    closure: str = "global",
    n_parts: int = 8,
    halo: str = "gap",
) -> Discovery:
    """Clusters, links, closed crowds, closed aggregations, groups and their evolution.

    ``index='sector'`` is the parallel method by space parts, ``'random'`` the one it is compared with,
    ``'none'`` the serial one without an index.
    """
    member, shape = clusters(snap, p, plan)
    return discover_in(member, shape, p, index, prune, closure, n_parts, halo)


def discover_in(
    member: DataFrame,
    shape: DataFrame,
    p: Params,
    index: str = "box",
    prune: bool = True,
    closure: str = "global",
    n_parts: int = 8,
    halo: str = "gap",
) -> Discovery:
    """The same from clusters on, for methods that differ from there."""
    link = materialize(links.build(shape, p, index, prune, n_parts=n_parts, halo=halo), "link")
    cover = materialize(chains.cover(link), "cover")
    crowd = chains.closed_crowds(shape, cover, p)
    agg = materialize(peel.peel(crowd, shape, p), "agg")
    windows = materialize(peel.closed(peel.by_window(agg), closure), "windows")
    group = materialize(peel.groups(windows), "group")
    return Discovery(member, shape, link, cover, crowd, agg, windows, group, lineage.edges(group, p.m_g))
