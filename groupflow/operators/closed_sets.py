"""Closed sets of tracks that share clusters, one after another and each once, without keeping those found before."""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np

from groupflow.operators.distances import _runs

_CELLS = 1 << 18  # pairs of tracks looked at at once
_MANY, _DEEP = 16, 5  # a set that may grow by more tracks than that, up to that depth, is gone through by all shares


def _grown(a: np.ndarray, first: int, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """The rows of ``a``, from ``first`` on, by which a set grows: the row, those that have all its columns, and those left to grow by.

    A row is not given where one before it has all its columns: the set it leads to is found from there.
    """
    step = max(1, _CELLS // len(a))
    for lo in range(first, len(a), step):
        rows = np.arange(lo, min(lo + step, len(a)))
        wide = a.astype(np.float32)
        both = wide[rows] @ wide.T
        n = both[np.arange(len(rows)), rows][:, None]
        whole, left = both == n, (both >= k) & (both < n)
        del wide, both
        for j in np.flatnonzero(whole.argmax(axis=1) == rows).tolist():
            yield lo + j, whole[j], left[j]


def _owned(name: int, share: int, shares: int) -> bool:
    return hash((name,)) % shares == share


def _from(
    track: int, rows: np.ndarray, cols: np.ndarray, a: np.ndarray, k: int, share: int, shares: int
) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Closed sets whose first track is ``track``, as tracks and columns; ``a`` holds the ``rows`` that have ``k`` of its columns or more."""
    whole = a.all(axis=1)
    head = rows[whole]
    if head[0] != track:
        return
    rows, a = rows[~whole], a[~whole]
    after = int(np.searchsorted(rows, track))
    own, wide = _owned(track, share, shares), len(rows) - after > _MANY
    if own:
        yield head, cols
    # a set has a name where its larger ones are dealt out; those of any other are its share's
    stack = [(track if wide else None, head, rows, cols, a, _grown(a, after, k))] if after < len(rows) and (own or wide) else []
    while stack:
        name, head, rows, cols, a, more = stack[-1]
        found = next(more, None)
        if found is None:
            stack.pop()
            continue
        j, whole, left = found
        left = np.flatnonzero(left)
        after = int(np.searchsorted(left, j))
        own, wide, below = True, False, None
        if name is not None:
            below = hash((name, j))
            own, wide = _owned(below, share, shares), len(left) - after > _MANY and len(stack) < _DEEP
            if not (own or wide):
                continue
        on = a[j]
        grown, shared = np.concatenate([head, rows[whole]]), cols[on]
        if own:
            yield grown, shared
        if after < len(left):
            fewer = a[left][:, on]
            stack.append((below if wide else None, grown, rows[left], shared, fewer, _grown(fewer, after, k)))


def closed_sets(
    starts: np.ndarray, clusters: np.ndarray, own: np.ndarray, k: int, share: int = 0, shares: int = 1
) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Sets of tracks with the ``k`` or more clusters that all of them share, to which no track can be added without losing one.

    Track ``i`` has ``clusters[starts[i] : starts[i + 1]]``, each once. Given are the sets whose first track is one of ``own``; all
    tracks that share ``k`` clusters with one of them have to be there, with all their clusters. Each set is given by one of the ``shares``.
    """
    names, code = np.unique(clusters, return_inverse=True)
    n = np.bincount(code, minlength=len(names))
    begin = np.cumsum(n) - n
    members = np.repeat(np.arange(len(starts) - 1), np.diff(starts))[np.argsort(code, kind="stable")]
    for i in own.tolist():
        cols = np.sort(code[starts[i] : starts[i + 1]])
        if len(cols) < k:
            continue
        who = members[_runs(begin[cols], n[cols])]
        rows = np.flatnonzero(np.bincount(who, minlength=len(starts) - 1) >= k)
        if len(rows) <= _MANY and not _owned(i, share, shares):
            continue
        place = np.full(len(starts) - 1, -1)
        place[rows] = np.arange(len(rows))
        at, col = place[who], np.repeat(np.arange(len(cols)), n[cols])
        a = np.zeros((len(rows), len(cols)), np.bool_)
        a[at[at >= 0], col[at >= 0]] = True
        yield from _from(i, rows, names[cols], a, k, share, shares)


def crowns(a: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """Growing crowns of ``a`` (tracks by clusters), chosen greedily: ``q`` tracks and ``q`` clusters where each track is in all of
    the clusters but its own, and the numbers of other tracks in all of these clusters and of other clusters with all of these tracks."""
    q = 0
    while a.size:
        score = np.where(a, -1.0, np.outer(a.sum(axis=1), a.sum(axis=0)))
        row, col = np.unravel_index(int(score.argmax()), a.shape)
        if score[row, col] < 0:
            return
        a = a[a[:, col]][:, a[row]]
        q += 1
        yield q, *a.shape


def at_least(q: int, tracks: int, clusters: int, m: int, k: int) -> int:
    """Closed sets that a crown proves: what any ``j`` of its clusters share is another set for each choice, with its other ``q - j`` tracks."""
    with_tracks = sum(comb(q, j) for j in range(k, q + 1) if q - j + tracks >= m)
    with_clusters = sum(comb(q, j) for j in range(max(0, k - clusters), q + 1) if q - j >= m)
    return max(with_tracks, with_clusters)
