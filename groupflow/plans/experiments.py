"""Experiments that measure times: the methods beside their competitors, for each value of a parameter.

Each row has what a method answered beside its seconds, so that methods with the same answers can be told from others.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.operators import baselines, chains, links, peel
from groupflow.params import Params
from groupflow.plans.measures import timed
from groupflow.plans.pipeline import discover
from groupflow.storage import materialize

ROW = "experiment string, value double, method string, seconds double, answers long"


def _rows(spark: SparkSession, found: list[tuple[str, float, dict]]) -> DataFrame:
    rows = [(name, float(value), r["method"], r["seconds"], r["answers"]) for name, value, r in found]
    return spark.createDataFrame(rows, ROW)


def crowd_step(shape: DataFrame, name: str, settings: list[tuple[float, Params]]) -> DataFrame:
    """Links and closed crowds with pruning and with the grid index only, beside strict crowds on the grid.

    Links of strict crowds are of gap 1 whatever ``k_c``: settings that differ in nothing else share them, and each counts their seconds.
    """
    found, steps = [], {}
    for value, p in settings:
        for method, index, prune in (("pruned", "box", True), ("grid", "grid", False)):

            def run(p=p, index=index, prune=prune) -> int:
                cover = chains.cover(materialize(links.build(shape, p, index, prune), "link"))
                return chains.closed_crowds(shape, cover, p).count()

            found.append((name, value, timed(method, run)))

        q = p.but(k_c=p.w)
        if q not in steps:
            began = time.perf_counter()
            link = materialize(links.build(shape, q, "grid", False), "link")
            steps[q] = link, time.perf_counter() - began
        link, before = steps[q]
        strict = timed("strict", lambda p=p, link=link: baselines.strict_crowds(shape, link, p.k_c).count())
        found.append((name, value, strict | {"seconds": strict["seconds"] + before}))
    return _rows(shape.sparkSession, found)


def verifier(crowd: DataFrame, shape: DataFrame, name: str, settings: list[tuple[float, Params]]) -> DataFrame:
    """Peeling beside cutting at invalid clusters, over the same crowds."""
    found = []
    for value, p in settings:
        found.append((name, value, timed("peeling", lambda p=p: peel.peel(crowd, shape, p).count())))
        found.append((name, value, timed("cutting", lambda p=p: baselines.cut_at_invalid(crowd, shape, p.k_c, p.k_p, p.m_p).count())))
    return _rows(shape.sparkSession, found)


def whole(snap: DataFrame, settings: list[tuple[str, float, DataFrame, Params]]) -> DataFrame:
    """The whole method for growing numbers of objects or distances. The same table with the same parameters is measured once."""
    known: dict[tuple, dict] = {}
    for _, _, some, p in settings:
        if (id(some), p) not in known:
            known[id(some), p] = timed("whole", lambda some=some, p=p: discover(some, p).evo.count())
    return _rows(snap.sparkSession, [(name, value, known[id(some), p]) for name, value, some, p in settings])


def space_parts(shape: DataFrame, p: Params, values: tuple[int, ...]) -> DataFrame:
    """Links by space parts and by random distribution for growing numbers of parts, beside the serial method without an index."""
    found = [("parts", 1, timed("serial", lambda: links.build(shape, p, "none", False).count()))]
    for n in values:
        for method in ("sector", "random"):
            found.append(("parts", n, timed(method, lambda n=n, method=method: links.build(shape, p, method, n_parts=n).count())))
    return _rows(shape.sparkSession, found)


def objects(snap: DataFrame, p: Params, n: int) -> list[tuple[float, DataFrame, Params]]:
    """Growing parts of the objects, a ``n``-th to all of them."""
    some = [snap.filter(F.col("obj_id") % n < k) for k in range(1, n)] + [snap]
    return [(k / n, part, p) for k, part in enumerate(some, start=1)]
