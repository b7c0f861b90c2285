"""Patterns of moving objects that the related literature describes: flocks and swarms."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators import closed_sets
from groupflow.operators.distances import _runs
from groupflow.storage import materialize

_PART = 1 << 20  # pairs, or members, looked at at once
_SLICE = 8  # first timestamps of a task's flocks
_BLOCKS, _TRACKS, _SHARES = 8, 256, 4  # blocks of swarms at least, tracks of a block, tasks of a block
_SETS = 10**12  # more swarms than can be listed


def _pieces(n: np.ndarray, most: int) -> Iterator[slice]:
    """Parts of the places of ``n`` that sum to ``most`` at most, or hold one place."""
    ends, at = np.cumsum(n), 0
    while at < len(n):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield slice(at, to)
        at = to


def _flocks_from(first: int, obj: np.ndarray, x: np.ndarray, y: np.ndarray, r: float, m: int) -> Iterator[pa.RecordBatch]:
    """Flocks of objects with positions ``x[j], y[j]`` at the ``j``-th of all timestamps from ``first`` on.

    Objects on one and the same track share their members, so tracks are compared and not objects.
    """
    tracks, of, n = np.unique(np.concatenate([x, y]).T, axis=0, return_inverse=True, return_counts=True)
    of = of.ravel()
    # a cell is a little wider than r, so that rounding takes no neighbour out of the cells around
    cx, cy = (np.floor(tracks[:, c] / (r * (1 + 1e-9))) for c in (0, len(x)))
    ux, rx = np.unique(cx, return_inverse=True)
    uy, ry = np.unique(cy, return_inverse=True)
    order = np.lexsort((ry, rx))
    tracks, n, cx, cy = tracks[order], n[order], cx[order], cy[order]
    code = (rx * len(uy) + ry)[order]
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    # objects of a track, one track after another
    objects = obj[np.lexsort((obj, place[of]))]
    begin = np.cumsum(n) - n
    xs, ys = tracks[:, : len(x)], tracks[:, len(x) :]
    low, high = np.searchsorted(uy, cy - 1), np.searchsorted(uy, cy + 1, side="right") - 1
    starts, counts = [], []
    for i in (-1, 0, 1):
        column = np.searchsorted(ux, cx + i)
        there = (column < len(ux)) & (ux[np.minimum(column, len(ux) - 1)] == cx + i) & ((i == 0) | (cx + i != cx))
        at = np.searchsorted(code, column * len(uy) + low)
        starts.append(at)
        counts.append(np.where(there, np.searchsorted(code, column * len(uy) + high, side="right") - at, 0))
    starts, counts = np.stack(starts, axis=1), np.stack(counts, axis=1)
    for some in _pieces(counts.sum(axis=1), _PART):
        many = counts[some]
        a = np.repeat(np.arange(some.start, some.stop), many.sum(axis=1))
        b = _runs(starts[some].ravel(), many.ravel())
        for j in range(len(x)):
            dx, dy = xs[a, j] - xs[b, j], ys[a, j] - ys[b, j]
            near = dx * dx + dy * dy <= r * r
            a, b = a[near], b[near]
        size = np.bincount(a - some.start, n[b], some.stop - some.start).astype(np.int64)
        good = np.flatnonzero(size >= m)
        # members of each track, then once for each anchor on it
        edge = np.searchsorted(a, [*(good + some.start), some.stop])
        for part in _pieces(size[good] * n[good + some.start], _PART):
            lists, who = [], []
            for g, lo in zip(good[part].tolist(), edge[part].tolist()):
                hi = int(np.searchsorted(a, g + some.start, side="right"))
                found = np.sort(objects[_runs(begin[b[lo:hi]], n[b[lo:hi]])])
                anchors = objects[begin[g + some.start] : begin[g + some.start] + n[g + some.start]]
                for few in _pieces(np.full(len(anchors), len(found)), 4 * _PART):
                    one = anchors[few]
                    if len(one) < len(anchors):
                        yield _flock_rows(first, [found], [one])
                    else:
                        lists.append(found)
                        who.append(one)
            if who:
                yield _flock_rows(first, lists, who)


def _flock_rows(first: int, lists: list[np.ndarray], who: list[np.ndarray]) -> pa.RecordBatch:
    """A row for each anchor in ``who``, with the list of members at the same place."""
    ends = np.cumsum([0, *(len(v) for v, w in zip(lists, who) for _ in range(len(w)))]).astype(np.int32)
    members = np.concatenate([np.tile(v, len(w)) for v, w in zip(lists, who)])
    anchors = np.concatenate(who)
    columns = [pa.array(anchors), pa.array(np.full(len(anchors), first)), pa.ListArray.from_arrays(pa.array(ends), pa.array(members))]
    return pa.RecordBatch.from_arrays(columns, ["anchor", "first_t", "members"])


def _slices(r: float, m: int, k: int):
    """Rows come in order of slice and timestamp: a slice is held with the ``k - 1`` timestamps after it."""

    def whole(slot: int, rows: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        t, obj, x, y = (np.concatenate(v) for v in zip(*rows))
        # a place that is no number is near to none
        some = np.isfinite(x) & np.isfinite(y)
        order = np.lexsort((obj[some], t[some]))
        t, obj, x, y = (v[some][order] for v in (t, obj, x, y))
        for first in range(slot * _SLICE, (slot + 1) * _SLICE):
            edges = np.searchsorted(t, np.arange(first, first + k + 1)).tolist()
            spans = [slice(*e) for e in zip(edges, edges[1:])]
            here = obj[spans[0]]
            for s in spans[1:]:
                here = here[np.isin(here, obj[s], assume_unique=True)]
            if len(here):
                at = [s.start + np.searchsorted(obj[s], here) for s in spans]
                yield from _flocks_from(first, here, np.stack([x[i] for i in at]), np.stack([y[i] for i in at]), r, m)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot, held = None, []
        for batch in batches:
            columns = [c.to_numpy() for c in batch.columns]
            for s in np.unique(columns[0]).tolist():
                if held and s != slot:
                    yield from whole(slot, held)
                    held = []
                mask = columns[0] == s
                slot = s
                held.append(tuple(c[mask] for c in columns[1:]))
        if held:
            yield from whole(slot, held)

    return run


def flocks(snap: DataFrame, r: float, m: int, k: int) -> DataFrame:
    """``anchor, first_t, members``: at least ``m`` objects that stay within ``r`` of one of them, the anchor, at all
    of the ``k`` timestamps from ``first_t`` on.

    Discs are those centred at an object; members hold the anchor. Time is cut into slices: the task of a slice has its snapshots
    and those of the ``k - 1`` timestamps after it, so pairs of objects meet by cells inside a task and are never joined or shuffled.
    """
    slot = lambda t: F.floor(t / _SLICE).cast("long")
    rows = snap.select(
        F.explode(F.sequence(slot(F.col("t") - (k - 1)), slot(F.col("t")))).alias("slot"),
        F.col("t").cast("long"),
        F.col("obj_id").cast("long"),
        F.col("x").cast("double"),
        F.col("y").cast("double"),
    )
    rows = rows.repartition("slot").sortWithinPartitions("slot", "t")
    return rows.mapInArrow(_slices(r, m, k), "anchor long, first_t long, members array<long>")


def _proof(m: int, k: int, tracks: int = 2_000, clusters: int = 1_000):
    """A number of closed sets that these tracks are proven to hold: the best of the crowns of the largest clusters."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists = [x for b in batches for x in b.column("clusters").to_pylist()][:tracks]
        names, code, n = np.unique(np.concatenate([np.empty(0, np.int64), *lists]), return_inverse=True, return_counts=True)
        some = np.argsort(-n, kind="stable")[:clusters]
        a = np.zeros((len(lists), len(names)), np.bool_)
        a[np.repeat(np.arange(len(lists)), [len(x) for x in lists]), code] = True
        most = max((closed_sets.at_least(*c, m, k) for c in closed_sets.crowns(a[:, some])), default=0)
        yield pa.RecordBatch.from_pydict({"n": [str(most)]})

    return run


def _swarms_of(m: int, k: int):
    """Rows come in order of block and share, fewest clusters first: a block is held with all tracks that may share ``k`` clusters with one of it."""

    def whole(rows: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(rows).combine_chunks()
        own = np.flatnonzero(table.column("own").combine_chunks().to_numpy(zero_copy_only=False))
        starts, clusters = _lists(table.column("clusters").combine_chunks())
        begin, objects = _lists(table.column("objs").combine_chunks())
        n = np.diff(begin)
        objs, shared, held = [], [], 0
        share = table.column("share")[0].as_py()
        for tracks, common in closed_sets.closed_sets(starts, clusters, own, k, share, _SHARES):
            size = int(n[tracks].sum())
            if size < m:
                continue
            objs.append(np.sort(objects[_runs(begin[tracks], n[tracks])]))
            shared.append(common)
            held += size + len(common)
            if held > _PART:
                yield _swarm_rows(objs, shared)
                objs, shared, held = [], [], 0
        if objs:
            yield _swarm_rows(objs, shared)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, held = None, []
        for batch in batches:
            of = batch.column("block").to_numpy() * _SHARES + batch.column("share").to_numpy()
            edges = [0, *(np.flatnonzero(of[1:] != of[:-1]) + 1).tolist(), len(of)]
            for lo, hi in zip(edges, edges[1:]):
                if lo == hi:
                    continue
                if held and of[lo] != block:
                    yield from whole(held)
                    held = []
                block = of[lo]
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from whole(held)

    return run


def _lists(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """Ends of the lists of a column, from 0 on, and their values."""
    ends = column.offsets.to_numpy().astype(np.int64)
    return ends - ends[0], column.flatten().to_numpy()


def _swarm_rows(*lists: list[np.ndarray]) -> pa.RecordBatch:
    columns = [pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, x)]).astype(np.int32)), pa.array(np.concatenate(x))) for x in lists]
    return pa.RecordBatch.from_arrays(columns, ["objs", "clusters"])


def swarms(member: DataFrame, m: int, k: int, max_sets: int = _SETS) -> DataFrame:
    """``objs, clusters``: at least ``m`` objects that share a cluster at ``k`` or more timestamps, consecutive or not,
    to which no object can be added without losing a timestamp.

    Objects with the same clusters are one track. Tracks are dealt out to blocks; the tasks of a block get the tracks that may share
    ``k`` clusters with one of its own, and go through the closed sets whose first track is its own, depth first: sets that are not
    closed are not made, and no set is kept after it was given. The tasks of a block have a share each of
    the sets that grow much. The number of closed sets is exponential in the worst case: where more than ``max_sets`` are
    proven to be there, which takes 2,000 tracks at most and no listing, that is an error.
    """
    each = member.select(F.col("obj_id").cast("long"), F.col("cluster_id").cast("long")).dropna()
    held = each.groupBy("obj_id").agg(F.array_sort(F.collect_set("cluster_id")).alias("clusters")).filter(F.size("clusters") >= k)
    track = materialize(
        held.groupBy("clusters").agg(F.array_sort(F.collect_list("obj_id")).alias("objs")).select(F.col("objs")[0].alias("track"), "objs", "clusters"),
        "swarms",
    )
    most = track.orderBy(F.desc(F.size("clusters")), "track").limit(2_000).select("clusters").coalesce(1)
    proven = max((int(r["n"]) for r in most.mapInArrow(_proof(m, k), "n string").collect()), default=0)
    if proven > max_sets:
        raise RuntimeError(f"at least {proven} closed sets; raise k or max_sets")
    blocks = max(_BLOCKS, -(-track.count() // _TRACKS))
    at = track.select("track", F.explode("clusters").alias("cluster_id"))
    block = F.pmod(F.xxhash64("track"), F.lit(blocks)).cast("long")
    touched = at.select(block.alias("block"), "cluster_id").distinct()
    near = touched.join(at, "cluster_id").groupBy("block", "track").count().filter(F.col("count") >= k).select("block", "track")
    rows = near.join(track, "track").select("block", (F.col("block") == block).alias("own"), F.size("clusters").alias("n"), "track", "objs", "clusters")
    rows = rows.withColumn("share", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(_SHARES - 1).cast("long"))))
    rows = rows.repartition(blocks * _SHARES, "block", "share").sortWithinPartitions("block", "share", "n", "track").drop("n", "track")
    return rows.mapInArrow(_swarms_of(m, k), "objs array<long>, clusters array<long>")
