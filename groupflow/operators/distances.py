"""Hausdorff distances of many pairs of clusters, snapshot by snapshot.

A pair does not carry its points: the task of a few timestamps holds each cluster of theirs and of the snapshots
within reach once, and the pairs only name them. A point that several objects share counts once. Pairs of few points are compared all at once;
in large ones a point looks for its partner in growing squares of cells, and stops where none can be nearer.
Squares are worked out as in :mod:`groupflow.functions.hausdorff`, so both give the same numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.density import ID_BASE

_PART = 1 << 20  # squares looked at at once
_FEW = 64
_SMALL = 1 << 14
_SLICE = 3  # timestamps of a task's later clusters
_BITS = ID_BASE.bit_length() - 1


class Points:
    """Distinct points of a cluster, and their cells once these are asked for."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.x, self.y = x, y
        self._cells = None

    def __len__(self) -> int:
        return len(self.x)

    def cells(self):
        """``x, y`` in the order of cells, first place of each cell, lower corner, side and numbers of cells."""
        if self._cells is None:
            low = np.array([self.x.min(), self.y.min()])
            wide = np.array([self.x.max(), self.y.max()]) - low
            side = max(float(np.sqrt(wide[0] * wide[1] * 2 / len(self))), float(wide.max()) * 2 / len(self)) or 1.0
            nx, ny = (int(w // side) + 1 for w in wide)
            cx = np.minimum(((self.x - low[0]) // side).astype(np.int64), nx - 1)
            cy = np.minimum(((self.y - low[1]) // side).astype(np.int64), ny - 1)
            code = cx * ny + cy
            order = np.argsort(code, kind="stable")
            self._cells = self.x[order], self.y[order], np.searchsorted(code[order], np.arange(nx * ny + 1)), low, side, nx, ny
        return self._cells


def _squares(ax, ay, bx, by) -> np.ndarray:
    dx, dy = ax - bx, ay - by
    return dx * dx + dy * dy


def _all_pairs(a: Points, b: Points, most: float, stop: float) -> float:
    rows = max(1, _PART // len(b))
    for at in range(0, len(a), rows):
        most = max(most, float(_nearest(a.x[at : at + rows], a.y[at : at + rows], b).max()))
        if stop < most:
            break
    return most


def _nearest(x: np.ndarray, y: np.ndarray, b: Points) -> np.ndarray:
    best = np.full(len(x), np.inf)
    for at in range(0, len(b), _PART):
        np.minimum(best, _squares(x[:, None], y[:, None], b.x[None, at : at + _PART], b.y[None, at : at + _PART]).min(axis=1), out=best)
    return best


def one_way(a: Points, b: Points, most: float = 0.0, stop: float = np.inf) -> float:
    """The larger of ``most`` and the largest square of the distance of a point of ``a`` to its nearest in ``b``; any value
    above ``stop`` may be returned once one is found."""
    finite = all(np.isfinite(v).all() for v in (a.x, a.y, b.x, b.y))
    if min(len(a), len(b)) <= _FEW or not finite:
        return _all_pairs(a, b, most, stop)
    bx, by, begin, low, side, nx, ny = b.cells()
    x, y = a.x, a.y
    # beyond the grid's edges a place is as good as one just outside, which keeps cell numbers small
    cx = np.clip(np.floor((x - low[0]) / side), -1, nx).astype(np.int64)
    cy = np.clip(np.floor((y - low[1]) / side), -1, ny).astype(np.int64)
    k, best = 1, np.full(len(x), np.inf)
    while len(x):
        for j in range(-k, k + 1):
            c = cx + j
            some = np.flatnonzero((c >= 0) & (c < nx) & (cy + k >= 0) & (cy - k < ny))
            first = begin[c[some] * ny + np.maximum(cy[some] - k, 0)]
            n = begin[c[some] * ny + np.minimum(cy[some] + k, ny - 1) + 1] - first
            some, first, n = some[n > 0], first[n > 0], n[n > 0]
            ends = np.cumsum(n)
            at = 0
            while at < len(some):
                to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _PART, side="right")))
                m = n[at:to]
                start = np.cumsum(m) - m
                place = np.repeat(first[at:to] - start, m) + np.arange(m.sum())
                q = _squares(np.repeat(x[some[at:to]], m), np.repeat(y[some[at:to]], m), bx[place], by[place])
                best[some[at:to]] = np.minimum(best[some[at:to]], np.minimum.reduceat(q, start))
                at = to
        # nothing outside the square of cells is nearer than k sides; a point that cannot raise the result needs no more
        whole = (cx - k <= 0) & (cx + k >= nx - 1) & (cy - k <= 0) & (cy + k >= ny - 1)
        known = whole | (best <= (k * side) ** 2 * (1 - 1e-9))
        if known.any():
            most = max(most, float(best[known].max()))
        if stop < most:
            return most
        if stop < (k * side) ** 2 * (1 - 1e-9) and (best[~known] > stop).any():
            return np.inf
        left = ~known & (best > most)
        x, y, cx, cy, best = x[left], y[left], cx[left], cy[left], best[left]
        k *= 2
    return most


def square(a: Points, b: Points, stop: float = np.inf) -> float:
    """The square of the distance of ``a`` and ``b``; any value above ``stop`` where it is above."""
    found = one_way(a, b, 0.0, stop)
    return found if found > stop else one_way(b, a, found, stop)


def _runs(begin: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The places of runs, one run after another."""
    return np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(n.sum())


def _small(x: np.ndarray, y: np.ndarray, begin: np.ndarray, size: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squares of the distances of pairs of few points, all pairs in blocks."""
    out, ends, at = np.empty(len(a)), np.cumsum(size[a] * size[b]), 0
    while at < len(a):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _PART, side="right")))
        worst = np.zeros(to - at)
        for u, v in ((a[at:to], b[at:to]), (b[at:to], a[at:to])):
            # each point of u against the run of its partner's points
            p, run = _runs(begin[u], size[u]), np.repeat(size[v], size[u])
            q, p = _runs(np.repeat(begin[v], size[u]), run), np.repeat(p, run)
            near = np.minimum.reduceat(_squares(x[p], y[p], x[q], y[q]), np.cumsum(run) - run)
            worst = np.maximum(worst, np.maximum.reduceat(near, np.cumsum(size[u]) - size[u]))
        out[at:to] = worst
        at = to
    return out


def squares(x: np.ndarray, y: np.ndarray, begin: np.ndarray, size: np.ndarray, a: np.ndarray, b: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """:func:`square` of each pair of clusters ``a, b``; the points of cluster ``i`` are ``size[i]`` ones from ``begin[i]`` on."""
    out, many = np.empty(len(a)), size[a] * size[b]
    few = many <= _SMALL
    out[few] = _small(x, y, begin, size, a[few], b[few])
    known: dict[int, Points] = {}

    def points(i: int) -> Points:
        if i not in known:
            part = slice(begin[i], begin[i] + size[i])
            known[i] = Points(x[part], y[part])
        return known[i]

    for i in np.flatnonzero(~few).tolist():
        out[i] = square(points(int(a[i])), points(int(b[i])), float(stop[i]))
    return out


def _distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Points of a cluster without repeats, as two lists."""
    for batch in batches:
        xs, ys = [], []
        for i in range(batch.num_rows):
            p = batch.column(2)[i].values
            x, y = p.field("x").to_numpy(), p.field("y").to_numpy()
            order = np.lexsort((y, x))
            x, y = x[order], y[order]
            first = np.ones(len(x), np.bool_)
            first[1:] = (x[1:] != x[:-1]) | (y[1:] != y[:-1])
            xs.append(x[first])
            ys.append(y[first])
        kind = pa.list_(pa.float64())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(xs, kind), pa.array(ys, kind)], ["cluster_id", "t", "xs", "ys"])


def with_squares(pairs: DataFrame, shape: DataFrame, gap: int, limit: float | None = None) -> DataFrame:
    """``src, dst, dt, q`` for ``pairs(src, dst, dt)`` of clusters at most ``gap`` timestamps apart, ``dst`` the later one: ``q`` is the
    square of their distance. With ``limit``, just any number above the square of ``limit * dt`` where it is above."""

    def run(named: pa.Table, held: pa.Table) -> pa.Table:
        src, dst, dt = (named.column(c).to_numpy() for c in ("src", "dst", "dt"))
        q = np.empty(0)
        if len(src):
            ids = held.column("cluster_id").to_numpy()
            xs, ys = (held.column(c).combine_chunks() for c in ("xs", "ys"))
            order = np.argsort(ids)
            a, b = (order[np.searchsorted(ids, c, sorter=order)] for c in (src, dst))
            ends = xs.offsets.to_numpy().astype(np.int64)
            most = np.full(len(src), np.inf) if limit is None else (limit * dt) ** 2
            q = squares(xs.values.to_numpy(), ys.values.to_numpy(), ends[:-1], np.diff(ends), a, b, most)
        return pa.table([pa.array(src), pa.array(dst), pa.array(dt, pa.int32()), pa.array(q, pa.float64())], ["src", "dst", "dt", "q"])

    slot = lambda t: F.floor(t / _SLICE).cast("long")
    named = pairs.select("src", "dst", F.col("dt").cast("int").alias("dt"), slot(F.shiftright("dst", _BITS)).alias("slot"))
    held = shape.select("cluster_id", "t", "pts").mapInArrow(_distinct, "cluster_id long, t long, xs array<double>, ys array<double>")
    held = held.select(F.explode(F.sequence(slot(F.col("t")), slot(F.col("t") + gap))).alias("slot"), "cluster_id", "xs", "ys")
    return named.groupBy("slot").cogroup(held.groupBy("slot")).applyInArrow(run, "src long, dst long, dt int, q double")
