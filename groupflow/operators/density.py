"""Density clusters of each snapshot.

Points are cut into cells whose diagonal is ``eps``: points of one cell are neighbours. A cell of
``min_pts`` points therefore holds core objects only, and needs no count of neighbours; just the
points of thinner cells look around. Components are taken over cells, not over points.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.graph import components
from groupflow.storage import materialize, release

#: A cluster id is its timestamp and its smallest core object, 31 and 32 bits.
ID_BASE = 1 << 32
_ONE_TASK = 1_000_000
_PART = 1 << 20  # pairs looked at at once
_ROWS = 50_000
_PIECE = 200_000  # positions of a row
_FIRST = 4  # points of a cell that are compared before all others

# offsets of cells that can hold a neighbour: all of 5 x 5 but the corners
_AROUND = [(i, j) for i in range(-2, 3) for j in range(-2, 3) if abs(i) + abs(j) < 4]
_FORWARD = [o for o in _AROUND if o > (0, 0)]


def cluster_id(t, obj):
    return t.cast("long") * F.lit(ID_BASE) + obj


def _cells(points: DataFrame, offsets: list[tuple[int, int]]) -> DataFrame:
    """One row for each point and offset, with the cell that the offset leads to."""
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in offsets])
    spread = points.withColumn("o", F.explode(steps))
    return spread.withColumns({"cx": F.col("cx") + F.col("o.i"), "cy": F.col("cy") + F.col("o.j")}).drop("o")


def _near(a: str, b: str, eps: float):
    dx, dy = F.col(f"{a}x") - F.col(f"{b}x"), F.col(f"{a}y") - F.col(f"{b}y")
    return dx * dx + dy * dy <= F.lit(eps * eps)


def core_objects(snap: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """``t, obj_id, x, y, cx, cy, is_core`` of every point; a point counts itself as a neighbour."""
    side = eps / math.sqrt(2) * (1 - 1e-12)
    points = snap.select("t", "obj_id", "x", "y", F.floor(F.col("x") / side).alias("cx"), F.floor(F.col("y") / side).alias("cy"))
    full = points.groupBy("t", "cx", "cy").agg((F.count("*") >= min_pts).alias("dense"))
    points = points.join(full, ["t", "cx", "cy"])
    look = _cells(points.filter("not dense"), _AROUND).select("t", "cx", "cy", "obj_id", F.col("x").alias("ax"), F.col("y").alias("ay"))
    seen = points.select("t", "cx", "cy", F.col("x").alias("bx"), F.col("y").alias("by"))
    enough = (
        look.join(seen, ["t", "cx", "cy"])
        .filter(_near("a", "b", eps))
        .groupBy("t", "obj_id")
        .agg(F.count("*").alias("n"))
        .filter(F.col("n") >= min_pts)
        .select("t", "obj_id", F.lit(True).alias("thin"))
    )
    return points.join(enough, ["t", "obj_id"], "left").select(
        "t", "obj_id", "x", "y", "cx", "cy", (F.col("dense") | F.coalesce("thin", F.lit(False))).alias("is_core")
    )


def _grid(snap: DataFrame, eps: float, min_pts: int, border: str) -> DataFrame:
    points = materialize(core_objects(snap, eps, min_pts), "points")
    cores = points.filter("is_core")
    nodes = cores.groupBy("t", "cx", "cy").agg(F.min("obj_id").alias("low"))
    cores = cores.join(nodes, ["t", "cx", "cy"]).withColumn("node", cluster_id(F.col("t"), F.col("low")))
    cores = materialize(cores.select("t", "cx", "cy", "obj_id", "x", "y", "node"), "cores")
    here = _cells(cores, _FORWARD).select("t", "cx", "cy", F.col("node").alias("src"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    there = cores.select("t", "cx", "cy", F.col("node").alias("dst"), F.col("x").alias("bx"), F.col("y").alias("by"))
    edges = here.join(there, ["t", "cx", "cy"]).filter(_near("a", "b", eps)).select("src", "dst").distinct()
    label = components(edges)
    found = cores.join(label, "node", "left").withColumn("cluster_id", F.coalesce("component", "node"))
    found = materialize(found.select("t", "cx", "cy", "obj_id", "x", "y", "cluster_id"), "clustered")
    member = found.select("t", "cluster_id", "obj_id", "x", "y", F.lit(True).alias("is_core"))
    if border == "none":
        return member
    look = _cells(points.filter("not is_core"), _AROUND).select(
        "t", "cx", "cy", "obj_id", F.col("x").alias("ax"), F.col("y").alias("ay")
    )
    seen = found.select("t", "cx", "cy", "cluster_id", F.col("x").alias("bx"), F.col("y").alias("by"))
    edge = look.join(seen, ["t", "cx", "cy"]).filter(_near("a", "b", eps))
    at = [F.first("ax").alias("x"), F.first("ay").alias("y")]
    if border == "all":
        edge = edge.groupBy("t", "obj_id", "cluster_id").agg(*at)
    elif border == "min_cluster":
        edge = edge.groupBy("t", "obj_id").agg(F.min("cluster_id").alias("cluster_id"), *at)
    else:
        raise ValueError("border is 'min_cluster', 'all' or 'none'")
    return member.unionByName(edge.select("t", "cluster_id", "obj_id", "x", "y", F.lit(False).alias("is_core")))


def _pairs(a_begin: np.ndarray, a_n: np.ndarray, b_begin: np.ndarray, b_n: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """All places ``(row, i, j)`` of the products of runs ``a`` and ``b``, in parts of bounded size; a long run is taken in pieces."""
    total = a_n * b_n
    large = total > _PART
    for k in np.flatnonzero(large):
        width = max(1, _PART // int(b_n[k]))
        for at in range(0, int(a_n[k]), width):
            i = np.arange(at, min(at + width, int(a_n[k])))
            for to in range(0, int(b_n[k]), _PART):
                j = np.arange(to, min(to + _PART, int(b_n[k])))
                yield np.full(len(i) * len(j), k), np.repeat(a_begin[k] + i, len(j)), np.tile(b_begin[k] + j, len(i))
    rows = np.flatnonzero(~large & (total > 0))
    ends = np.cumsum(total[rows])
    at = 0
    while at < len(rows):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _PART, side="right")))
        some = rows[at:to]
        n = total[some]
        row = np.repeat(some, n)
        place = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        yield row, a_begin[row] + place // b_n[row], b_begin[row] + place % b_n[row]
        at = to


def roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest node that each of ``n`` nodes is connected with, by hooking roots and halving paths."""
    label = np.arange(n)
    while True:
        x, y = label[a], label[b]
        low, high = np.minimum(x, y), np.maximum(x, y)
        apart = low < high
        if not apart.any():
            return label
        np.minimum.at(label, high[apart], low[apart])
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up


def _boxes(x: np.ndarray, y: np.ndarray, core: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """``lowest x, highest x, lowest y, highest y`` of the core points of each cell."""
    if not len(begin):
        return np.empty((4, 0))
    ends = [(np.minimum, x, np.inf), (np.maximum, x, -np.inf), (np.minimum, y, np.inf), (np.maximum, y, -np.inf)]
    return np.stack([f.reduceat(np.where(core, v, none), begin) for f, v, none in ends])


def _apart(box: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squares of the least and of the largest distance that points of two boxes can have."""
    near, far = 0.0, 0.0
    for lo, hi in ((0, 1), (2, 3)):
        gap = np.maximum(0.0, np.maximum(box[lo, a] - box[hi, b], box[lo, b] - box[hi, a]))
        wide = np.maximum(box[hi, a] - box[lo, b], box[hi, b] - box[lo, a])
        near, far = near + gap * gap, far + wide * wide
    return near, far


def _within(x: np.ndarray, y: np.ndarray, begin: np.ndarray, n: np.ndarray, box: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each run of points those within ``eps`` of a box: the points, and where each run begins among them and its length."""
    row = np.repeat(np.arange(len(n)), n)
    at = np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(len(row))
    dx = np.maximum(0.0, np.maximum(box[0, row] - x[at], x[at] - box[1, row]))
    dy = np.maximum(0.0, np.maximum(box[2, row] - y[at], y[at] - box[3, row]))
    keep = dx * dx + dy * dy <= eps * eps
    size = np.bincount(row[keep], minlength=len(n))
    return at[keep], np.cumsum(size) - size, size


def _clustered(t: np.ndarray, obj: np.ndarray, x: np.ndarray, y: np.ndarray, eps: float, min_pts: int, border: str, least: int) -> pa.RecordBatch:
    """Clusters of whole snapshots, any number of them at once. Work grows with the pairs in neighbouring cells that cells leave open."""
    side = eps / math.sqrt(2) * (1 - 1e-12)
    cx, cy = np.floor(x / side).astype(np.int64), np.floor(y / side).astype(np.int64)
    order = np.lexsort((obj, cy, cx, t))
    t, obj, x, y, cx, cy = (v[order] for v in (t, obj, x, y, cx, cy))
    # cells are numbered in the order of (t, cx, cy), and neighbours found by one search in a joint code
    new = np.ones(len(t), np.bool_)
    new[1:] = (t[1:] != t[:-1]) | (cx[1:] != cx[:-1]) | (cy[1:] != cy[:-1])
    begin = np.flatnonzero(new)
    size = np.diff(np.append(begin, len(t)))
    cell = np.cumsum(new) - 1
    fresh = np.ones(len(begin), np.bool_)
    fresh[1:] = (t[begin[1:]] != t[begin[:-1]]) | (cx[begin[1:]] != cx[begin[:-1]])
    columns, of = np.stack([t[begin], cx[begin]])[:, fresh], np.cumsum(fresh) - 1
    low_y = int(cy.min(initial=0)) - 2
    span = int(cy.max(initial=0)) - low_y + 3
    if columns.shape[1] * span >= 1 << 62:
        raise ValueError("positions are too far apart for eps")
    code = of * span + (cy[begin] - low_y)
    # columns are sorted by (t, cx), so one at most two further in x stands at most two places away
    column_of = {0: np.arange(columns.shape[1])}
    for i in (-2, -1, 1, 2):
        column_of[i] = np.full(columns.shape[1], -1)
        for step in range(1, abs(i) + 1):
            here = np.arange(max(0, -i // abs(i) * step), columns.shape[1] - max(0, i // abs(i) * step))
            there = here + i // abs(i) * step
            same = (columns[0][there] == columns[0][here]) & (columns[1][there] == columns[1][here] + i)
            column_of[i][here[same]] = there[same]

    def neighbours(cells: np.ndarray, i: int, j: int) -> tuple[np.ndarray, np.ndarray]:
        """Those of ``cells`` with a cell at the offset, and that cell."""
        there = column_of[i][of[cells]]
        want = there * span + (cy[begin[cells]] - low_y + j)
        at = np.minimum(np.searchsorted(code, want), len(code) - 1)
        ok = (there >= 0) & (code[at] == want)
        return cells[ok], at[ok]

    def close(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        dx, dy = x[i] - x[j], y[i] - y[j]
        return dx * dx + dy * dy <= eps * eps

    dense = size >= min_pts
    count = np.where(dense[cell], min_pts, 0)
    thin = np.flatnonzero(~dense)
    for i, j in _AROUND:
        a, b = neighbours(thin, i, j)
        for _, p, q in _pairs(begin[a], size[a], begin[b], size[b]):
            count += np.bincount(p[close(p, q)], minlength=len(count))
    core = count >= min_pts
    # core points stand first in their cell from here on
    order = np.lexsort((obj, ~core, cell))
    t, obj, x, y, core = (v[order] for v in (t, obj, x, y, core))
    n_core = np.add.reduceat(core.astype(np.int64), begin) if len(begin) else size
    some = np.flatnonzero(n_core)
    label = np.arange(len(begin))
    box = _boxes(x, y, core, begin)
    # nearest cells first: what they connect already needs no pairs of points
    for i, j in sorted(_FORWARD, key=lambda o: o[0] * o[0] + o[1] * o[1]):
        a, b = neighbours(some, i, j)
        open_ = (n_core[b] > 0) & (label[a] != label[b])
        a, b = a[open_], b[open_]
        # the nearest and the farthest that points of two boxes can be: rounding keeps the order, so both decide exactly
        gap, whole = _apart(box, a, b)
        linked = whole <= eps * eps
        at = np.flatnonzero(~linked & (gap <= eps * eps))
        # mostly the first pairs tell
        for row, p, q in _pairs(begin[a[at]], np.minimum(n_core[a[at]], _FIRST), begin[b[at]], np.minimum(n_core[b[at]], _FIRST)):
            linked[at[row[close(p, q)]]] = True
        at = at[~linked[at] & ((n_core[a[at]] > _FIRST) | (n_core[b[at]] > _FIRST))]
        # what is left compares only points in reach of the other box
        left = _within(x, y, begin[a[at]], n_core[a[at]], box[:, b[at]], eps)
        right = _within(x, y, begin[b[at]], n_core[b[at]], box[:, a[at]], eps)
        for row, p, q in _pairs(left[1], left[2], right[1], right[2]):
            hit = at[row[0]] if len(row) and row[0] == row[-1] else -1
            if hit >= 0 and linked[hit]:
                continue  # a later piece of a pair of crowded cells that is settled
            linked[at[row[close(left[0][p], right[0][q])]]] = True
        label = roots(len(begin), label[a[linked]], label[b[linked]])[label]
    lowest = np.full(len(begin), np.iinfo(np.int64).max)
    np.minimum.at(lowest, label[cell[core]], obj[core])
    name = lowest[label]  # of each cell with core points: the smallest core object of its cluster
    at, ids = [np.flatnonzero(core)], [name[cell[core]]]
    if border != "none":
        look_at, look_id = [at[0][:0]], [ids[0][:0]]
        for i, j in _AROUND:
            a, b = neighbours(np.arange(len(begin)), i, j)
            ok = (n_core[b] > 0) & (size[a] > n_core[a])
            a, b = a[ok], b[ok]
            for row, p, q in _pairs(begin[a] + n_core[a], size[a] - n_core[a], begin[b], n_core[b]):
                near = close(p, q)
                both = np.unique(np.stack([p[near], name[b[row[near]]]]), axis=1)
                look_at.append(both[0])
                look_id.append(both[1])
        both = np.unique(np.stack([np.concatenate(look_at), np.concatenate(look_id)]), axis=1)
        if border == "min_cluster":
            both = both[:, np.unique(both[0], return_index=True)[1]]
        elif border != "all":
            raise ValueError("border is 'min_cluster', 'all' or 'none'")
        at.append(both[0])
        ids.append(both[1])
    at, ids = np.concatenate(at), np.concatenate(ids)
    cluster = t[at] * ID_BASE + ids
    if least > 1:
        _, back, n = np.unique(cluster, return_inverse=True, return_counts=True)
        keep = n[back] >= least
        at, cluster = at[keep], cluster[keep]
    return pa.RecordBatch.from_arrays(
        [pa.array(t[at]), pa.array(cluster), pa.array(obj[at]), pa.array(x[at]), pa.array(y[at]), pa.array(core[at])],
        ["t", "cluster_id", "obj_id", "x", "y", "is_core"],
    )


def _snapshots(eps: float, min_pts: int, border: str, least: int):
    """Rows come in order of t: snapshots are clustered some thousands of points at a time, whole ones only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def cluster_all(rows: np.ndarray) -> pa.RecordBatch:
            t, obj = rows[0].view(np.int64), rows[1].view(np.int64)
            return _clustered(t, obj, rows[2], rows[3], eps, min_pts, border, least)

        for batch in batches:
            if not batch.num_rows:
                continue
            kinds = (np.int64, np.int64, np.float64, np.float64)
            held.append(np.stack([batch.column(i).to_numpy().astype(k).view(np.float64) for i, k in enumerate(kinds)]))
            if sum(h.shape[1] for h in held) >= _ROWS and held[-1][0].view(np.int64)[-1] != held[0][0].view(np.int64)[0]:
                rows = np.concatenate(held, axis=1)
                t = rows[0].view(np.int64)
                end = int(np.searchsorted(t, t[-1]))
                yield cluster_all(np.ascontiguousarray(rows[:, :end]))
                held = [rows[:, end:].copy()]
        if held:
            yield cluster_all(np.concatenate(held, axis=1))

    return run


def _checked(snap: DataFrame) -> DataFrame:
    good = F.col("obj_id").between(0, ID_BASE - 1) & F.col("t").between(0, (1 << 31) - 1)
    wrong = F.raise_error(F.concat(F.lit("object ids are from 0 to 2^32 - 1 and timestamps from 0 to 2^31 - 1, not "), F.struct("obj_id", "t").cast("string")))
    return snap.select(F.when(good, F.col("t")).otherwise(wrong.cast("long")).alias("t"), "obj_id", "x", "y")


def _packed(piece: int):
    """A row for each timestamp, from rows in order of t; pieces of one that no row should hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def row(t: int, held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            points = pa.concat_arrays([pa.StructArray.from_arrays([h.column(c) for c in (1, 2, 3)], ["obj_id", "x", "y"]) for h in held])
            pieces = -(-len(points) // piece)
            for i in range(pieces):
                some = points.slice(i * piece, piece)
                yield pa.RecordBatch.from_arrays([pa.array([t]), pa.array([pieces]), pa.ListArray.from_arrays(pa.array([0, len(some)], pa.int32()), some)], ["t", "pieces", "points"])

        now, held = None, []
        for batch in batches:
            t = batch.column(0).to_numpy()
            starts = np.flatnonzero(np.r_[True, t[1:] != t[:-1]]) if len(t) else []
            for i, j in zip(starts, [*starts[1:], len(t)]):
                if held and t[i] != now:
                    yield from row(now, held)
                    held = []
                now = int(t[i])
                held.append(batch.slice(i, j - i))
        if held:
            yield from row(now, held)

    return run


def placed(snap: DataFrame, piece: int = _PIECE) -> DataFrame:
    """``t, pieces, points``: the positions of a timestamp in one row, for what clusters several parts of them: :func:`cluster` works each row
    where it stands. Timestamps of very many positions are in several ``pieces``, and dealt anew when they are clustered."""
    rows = _checked(snap).select(F.col("t").cast("long"), F.col("obj_id").cast("long"), F.col("x").cast("double"), F.col("y").cast("double"))
    return rows.repartition("t").sortWithinPartitions("t").mapInArrow(_packed(piece), "t long, pieces long, points array<struct<obj_id:long,x:double,y:double>>")


def flat(snap: DataFrame) -> DataFrame:
    """``t, obj_id, x, y`` of :func:`placed`."""
    return snap.select("t", F.explode("points").alias("p")).select("t", "p.obj_id", "p.x", "p.y")


def _whole(eps: float, min_pts: int, border: str, least: int):
    """Rows hold whole snapshots; some thousands of points are clustered at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            t, points = batch.column("t").to_numpy(), batch.column("points")
            n = np.diff(points.offsets.to_numpy())
            obj, x, y = (v.to_numpy() for v in points.flatten().flatten())
            ends = np.cumsum(n)
            at = 0
            while at < len(t):
                to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _ROWS, side="right")))
                some = slice(ends[at - 1] if at else 0, ends[to - 1])
                yield _clustered(np.repeat(t[at:to], n[at:to]), obj[some], x[some], y[some], eps, min_pts, border, least)
                at = to

    return run


def cluster(snap: DataFrame, eps: float, min_pts: int, border: str = "min_cluster", plan: str = "auto", least: int = 1) -> DataFrame:
    """``member(t, cluster_id, obj_id, x, y, is_core)`` of clusters with at least ``least`` objects.

    ``border``: a border object belongs to the smallest of the clusters it touches, to all of them or to
    none. ``plan='snapshot'`` clusters whole snapshots inside tasks, in one shuffle; ``'grid'`` holds for
    snapshots that no task can hold. ``'auto'`` counts first and takes the former where no snapshot has more
    than a million objects. Both go by cells and give the same rows. ``snap`` may also be of :func:`placed`, which is not moved again.
    Object ids are from 0 to 2^32 - 1, timestamps from 0 to 2^31 - 1, others raise an error; one position for each object and t.
    """
    schema = "t long, cluster_id long, obj_id long, x double, y double, is_core boolean"
    if "points" in snap.columns:
        if plan == "auto" and snap.filter("pieces > 1").isEmpty():
            return snap.mapInArrow(_whole(eps, min_pts, border, least), schema)
        snap = flat(snap)
    snap = _checked(snap)
    if plan == "auto":
        largest = snap.groupBy("t").count().agg(F.max("count").alias("n")).first()["n"] or 0
        plan = "snapshot" if largest <= _ONE_TASK else "grid"
    if plan == "snapshot":
        rows = snap.select(F.col("t").cast("long"), F.col("obj_id").cast("long"), F.col("x").cast("double"), F.col("y").cast("double"))
        return rows.repartition("t").sortWithinPartitions("t").mapInArrow(_snapshots(eps, min_pts, border, least), schema)
    member = _grid(snap, eps, min_pts, border)
    return keep_large(member, least) if least > 1 else member


def keep_large(member: DataFrame, m_c: int) -> DataFrame:
    """Members of clusters with at least ``m_c`` objects."""
    large = member.groupBy("cluster_id").agg(F.count("*").alias("n")).filter(F.col("n") >= m_c).select("cluster_id")
    return member.join(large, "cluster_id", "left_semi").select(member.columns)
