"""Closed crowds as maximal chains.

Being linked is transitive, so a closed crowd is a maximal chain of the clusters in a window. Chains walk
the covering links (no cluster strictly between), and a chain is closed for one interval of
window starts, which stands in the row instead of a copy for each window.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.density import ID_BASE
from groupflow.operators.graph import components
from groupflow.params import Params
from groupflow.storage import materialize

_MANY = "raise max_paths or tighten d, m_c or k_c"
_BITS = ID_BASE.bit_length() - 1
_ONE_TASK = 50_000  # clusters of a slice that one task walks


def time_of(cluster_id):
    """The timestamp in a cluster id, by bits: a quotient of doubles would round for large ids."""
    return F.shiftright(cluster_id, _BITS)


def cover(link: DataFrame) -> DataFrame:
    """Links without a cluster strictly between their ends."""
    first = link.select("src", F.col("dst").alias("mid"))
    second = link.select(F.col("src").alias("mid"), "dst")
    return link.join(first.join(second, "mid").select("src", "dst"), ["src", "dst"], "left_anti")


_CROWD = "crowd_id string, path array<long>, times array<long>, len int, s_lo long, s_hi long"


def _walks(p: Params, first: int, last: int, slice_: int, max_paths: int):
    """Closed crowds that start in one slice of time, from the covering links of the slice and a window beyond it.

    Chains grow level by level as columns: a chain is its last cluster and the number of the chain it extends.
    """

    def run(table: pa.Table) -> pa.Table:
        src, dst, pred = (table.column(c).combine_chunks().fill_null(-1).to_numpy() for c in ("src", "dst", "last_pred"))
        known = dst >= 0
        slot = table.column("slot")[0].as_py()
        # all clusters of the slice and after it; for each the last cluster before it, and the first one after it
        nodes = np.unique(src)
        when = nodes >> _BITS
        a, b = np.searchsorted(nodes, src[known]), dst[known]
        late = b >> _BITS
        after = np.full(len(nodes), np.iinfo(np.int64).max // 4)
        np.minimum.at(after, a, late)
        place = np.searchsorted(nodes, b)
        inside = (place < len(nodes)) & (nodes[np.minimum(place, len(nodes) - 1)] == b)
        order = np.lexsort((b[inside], a[inside]))
        a, to = a[inside][order], place[inside][order]
        begin = np.searchsorted(a, np.arange(len(nodes) + 1))
        before = np.full(len(nodes), -1 << 40)
        np.maximum.at(before, np.searchsorted(nodes, src[pred >= 0]), pred[pred >= 0])
        # clusters that a chain can still reach from a node before its window ends
        reach = np.ones(len(nodes), np.int64)
        for _ in range(p.w - 1):
            longer = reach.copy()
            np.maximum.at(longer, a, reach[to] + 1)
            if (longer == reach).all():
                break
            reach = longer
        start = np.flatnonzero(when // slice_ == slot)
        tail, head, parent, levels, out = start, start, None, [], []
        for n in range(1, p.w + 1):
            # no window holds enough of what is left
            left = np.minimum(reach[tail] - 1, when[head] + p.w - 1 - when[tail])
            keep = n + left >= p.k_c
            tail, head = tail[keep], head[keep]
            parent = None if parent is None else parent[keep]
            levels.append((tail, parent))
            if len(tail) > max_paths:
                raise RuntimeError(f"{len(tail)} chains of {n} clusters; {_MANY}")
            if n >= p.k_c:
                lo = np.maximum(np.maximum(when[tail] - p.w + 1, before[head] + 1), first)
                hi = np.minimum(np.minimum(when[head], after[tail] - p.w), last - p.w + 1)
                good = np.flatnonzero(lo <= hi)
                path, at = np.empty((len(good), n), np.int64), good
                for k in range(n - 1, -1, -1):
                    path[:, k] = nodes[levels[k][0][at]]
                    at = at if levels[k][1] is None else levels[k][1][at]
                ends = np.arange(0, path.size + 1, n, dtype=np.int32)
                lists = [pa.ListArray.from_arrays(ends, pa.array(v.ravel())) for v in (path, path >> _BITS)]
                out.append(pa.table([*lists, pa.array(np.full(len(good), n, np.int32)), pa.array(lo[good]), pa.array(hi[good])], ["path", "times", "len", "s_lo", "s_hi"]))
            many = begin[tail + 1] - begin[tail]
            parent = np.repeat(np.arange(len(tail)), many)
            nxt = to[np.repeat(begin[tail], many) + np.arange(len(parent)) - np.repeat(np.cumsum(many) - many, many)]
            ok = when[nxt] - when[head[parent]] < p.w
            parent, tail = parent[ok], nxt[ok]
            head = head[parent]
        return pa.concat_tables(out)

    return run


def closed_crowds(
    shape: DataFrame, cover_links: DataFrame, p: Params, max_paths: int = 20_000_000, span: tuple[int, int] | None = None
) -> DataFrame:
    """``crowd(crowd_id, path, times, len, s_lo, s_hi)``: closed in every window that starts in ``[s_lo, s_hi]``.

    Windows lie inside ``span``, first and last timestamp, or else the time range of ``shape``. A chain lies inside
    one window, so time is cut into slices of a window's length: the task of a slice has the clusters and covering links
    of the slice and of the window after it, and walks the chains that start in the slice. Chains that can no longer
    reach ``k_c`` clusters are dropped before they are extended; more than ``max_paths`` of one length in a task raise an error.
    A chain also lies inside one component of the links: where slices hold more clusters than a task should, they are dealt out
    by components, which are taken for such tables only.
    """
    ends = shape.agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.count("*").alias("n")).first()
    if ends["lo"] is None:
        return shape.sparkSession.createDataFrame([], _CROWD)
    first, last = span or (ends["lo"], ends["hi"])
    links = cover_links.select("src", "dst")
    pred = links.groupBy(F.col("dst").alias("src")).agg(F.max(time_of(F.col("src"))).alias("last_pred"))
    rows = (
        shape.select(F.col("cluster_id").alias("src"))
        .join(pred, "src", "left")
        .select("src", F.lit(None).cast("long").alias("dst"), "last_pred")
        .unionByName(links.withColumn("last_pred", F.lit(None).cast("long")))
    )
    slot = F.floor(time_of(F.col("src")) / p.w).cast("long")
    rows = rows.withColumn("slot", F.explode(F.array(slot, slot - 1)))
    deal = max(1, -(-2 * ends["n"] * p.w // ((ends["hi"] - ends["lo"] + 1) * _ONE_TASK)))
    if deal > 1:
        label = components(links).select(F.col("node").alias("src"), "component")
        rows = rows.join(label, "src", "left").withColumn("deal", F.pmod(F.xxhash64(F.coalesce("component", "src")), F.lit(deal)))
    else:
        rows = rows.withColumn("deal", F.lit(0))
    rows = rows.select("slot", "deal", "src", "dst", "last_pred")
    found = rows.groupBy("slot", "deal").applyInArrow(_walks(p, first, last, p.w, max_paths), _CROWD.split(", ", 1)[1])
    try:
        # what a path tells is not written: names of fourteen clusters are many times as long as their path
        found = materialize(found.select("path", "s_lo", "s_hi"), "crowds")
    except PySparkException as e:
        if _MANY in str(e):
            raise RuntimeError(f"over {max_paths} chains of one length in a task; {_MANY}") from e
        raise
    crowd_id = F.concat_ws("-", F.col("path").cast("array<string>"))
    return found.select(crowd_id.alias("crowd_id"), "path", F.transform("path", time_of).alias("times"), F.size("path").alias("len"), "s_lo", "s_hi")


def closed_in(crowds: DataFrame, win_start: int) -> DataFrame:
    """The closed crowds of one window."""
    return crowds.filter((F.col("s_lo") <= win_start) & (F.col("s_hi") >= win_start))
