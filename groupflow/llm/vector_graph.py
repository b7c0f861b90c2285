"""Near-duplicate vectors by a robust-pruned flat graph.

1. Vectors of equal components form a class; only classes are indexed, with their sizes.
2. Centroids fitted on a bounded sample route each class to its nearest few: overlapping shards. The nearest one is
   the class's home. A shard of more than ``block`` classes is divided again by centroids of its own, until each fits
   into a task. Only a shard whose vectors are nearly all linked with one another is cut by hash instead,
   and every part of its queries meets every part of its index: there the links themselves are that many.
3. In each shard a graph is built: near neighbours and a few far ones, robustly pruned, with reverse
   edges. Adjacency lists of a class from all its shards are united.
4. Every class is searched in its home over the united lists: greedy beam search from the medoids of the shard's
   parts, then the range around the query is expanded along edges until it yields nothing new. Hits
   are verified in double precision.

A pair is met from either end once, in that end's home. Links leave a shard as counts and as a spanning forest;
pairs of a large group are never emitted. Work grows with the classes times the size of a shard, which is fixed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.graph import components
from groupflow.storage import materialize


@dataclass(frozen=True)
class VectorGraphParams:
    """``overlap``, ``again``: shards that hold a class at the first and at each further division; ``shard``: classes
    aimed at per shard, copies included; ``block``: classes at most that one task holds. ``sample``: vectors at most that
    the centroids of one division are fitted on. ``max_shards`` and ``centre_bytes`` bound the centroids of a division.
    ``dense``: share of linked pairs in a sample from which on a shard is cut by hash."""

    threshold: float = 0.95
    overlap: int = 4
    again: int = 2
    shard: int = 2000
    block: int = 4096
    max_shards: int = 2048
    centre_bytes: int = 64_000_000
    sample: int = 20_000
    dense: float = 0.1
    depth: int = 4
    degree: int = 16
    candidates: int = 32
    far: int = 8
    alpha: float = 1.2
    medoids: int = 24
    entries: int = 4
    beam: int = 32
    slack: float = 0.08


_ROW = "vec_id long, dim int, key binary, vector array<double>"


def _clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        keys, dims, vectors = [], [], []
        for value in batch.column(1):
            v = None
            if value.is_valid and value.values is not None and value.values.null_count == 0 and len(value.values):
                v = value.values.to_numpy(zero_copy_only=False).astype(np.float64) + 0.0
                if not np.isfinite(v).all() or not v.any() or not np.isfinite(v @ v) or v @ v == 0:
                    v = None
            keys.append(None if v is None else hashlib.md5(v.tobytes()).digest())
            dims.append(None if v is None else len(v))
            vectors.append(v)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(dims, pa.int32()), pa.array(keys, pa.binary()), pa.array(vectors, pa.list_(pa.float64()))],
            ["vec_id", "dim", "key", "vector"],
        )


def _matrix(column: pa.Array | pa.ChunkedArray, dim: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy().reshape(len(column), dim)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]


def fit_centroids(unit: np.ndarray, n: int, rounds: int = 6) -> np.ndarray:
    """Spherical k-means of unit vectors; empty centroids keep their place."""
    rng = np.random.default_rng(7)
    centres = unit[rng.choice(len(unit), min(n, len(unit)), replace=False)].copy()
    for _ in range(rounds):
        near = np.concatenate([(unit[a : a + 4096] @ centres.T).argmax(axis=1) for a in range(0, len(unit), 4096)])
        order = np.argsort(near, kind="stable")
        found, first = np.unique(near[order], return_index=True)
        total = np.add.reduceat(unit[order], first, axis=0)
        norm = np.sqrt(np.einsum("ij,ij->i", total, total))
        some = norm > 0
        centres[found[some]] = total[some] / norm[some, None]
    return centres


def _prune(sims: np.ndarray, lists: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Robust pruning of candidate lists (-1: none) for all nodes at once, from the similarities of the nodes.

    The nearest candidate left is taken; candidates that are closer to it, by the factor alpha, than to
    the node are dropped.
    """
    n = len(sims)
    live = np.arange(n)
    near = np.where(lists < 0, np.float32(-9), sims[live[:, None], lists])
    order = np.argsort(-near, axis=1, kind="stable")
    lists, near = np.take_along_axis(lists, order, axis=1), np.take_along_axis(near, order, axis=1)
    alive = (lists >= 0) & (lists != live[:, None])
    # the same candidate twice
    order = np.argsort(lists, axis=1, kind="stable")
    same = np.take_along_axis(lists, order, axis=1)
    again = np.zeros_like(alive)
    np.put_along_axis(again, order[:, 1:], same[:, 1:] == same[:, :-1], axis=1)
    alive &= ~again
    far, factor = 2 - 2 * near, np.float32(alpha * alpha)  # squared distances
    out = np.full((n, degree), -1, np.int32)
    for k in range(degree):
        live = live[alive[live].any(axis=1)]
        if not len(live):
            break
        first = alive[live].argmax(axis=1)
        chosen = lists[live, first]
        out[live, k] = chosen
        left = alive[live] & (factor * (2 - 2 * sims[chosen[:, None], lists[live]]) > far[live])
        left[np.arange(len(live)), first] = False
        alive[live] = left
    return out


def build_graph(unit: np.ndarray, p: VectorGraphParams) -> np.ndarray:
    """Adjacency lists (-1: none) of one shard: pruned near and far candidates, reverse edges, and one ring."""
    n = len(unit)
    if n == 1:
        return np.full((1, p.degree), -1, np.int32)
    unit = unit.astype(np.float32)
    sims = unit @ unit.T
    np.fill_diagonal(sims, -2)
    k = min(p.candidates, n - 1)
    near = np.concatenate([np.argpartition(-sims[a : a + 512], k - 1, axis=1)[:, :k] for a in range(0, n, 512)])
    rng = np.random.default_rng(n)
    lists = np.concatenate([near, rng.integers(0, n, (n, p.far))], axis=1).astype(np.int32)
    forward = _prune(sims, lists, p.degree, p.alpha)
    # reverse edges, as many as there is room for; then all are pruned once more
    src, dst = np.repeat(np.arange(n, dtype=np.int32), p.degree), forward.ravel()
    src, dst = src[dst >= 0], dst[dst >= 0]
    order = np.argsort(dst, kind="stable")
    src, dst = src[order], dst[order]
    place = np.arange(len(dst)) - np.searchsorted(dst, dst)
    back = np.full((n, 2 * p.degree), -1, np.int32)
    fits = place < back.shape[1]
    back[dst[fits], place[fits]] = src[fits]
    kept = _prune(sims, np.concatenate([forward, back], axis=1), p.degree, p.alpha)
    # a ring through a random order keeps the shard connected
    ring = rng.permutation(n)
    step = np.empty(n, np.int32)
    step[ring] = np.roll(ring, -1)
    return np.concatenate([kept, step[:, None]], axis=1)


def medoids(unit: np.ndarray, p: VectorGraphParams) -> np.ndarray:
    """The nodes nearest to the centres of the shard's parts."""
    return np.unique((fit_centroids(unit, p.medoids, 3) @ unit.T).argmax(axis=1)).astype(np.int32)


def search(
    unit: np.ndarray, graph: np.ndarray, queries: np.ndarray, starts: np.ndarray, p: VectorGraphParams
) -> tuple[np.ndarray, np.ndarray]:
    """Pairs ``(query, node)`` with cosine near or above the threshold, less ``slack`` at first, then less rounding."""
    n, m = len(unit), len(queries)
    wide = p.threshold - p.slack
    rows, width = np.arange(m), min(p.beam, n)
    seen = np.zeros((m, n), np.bool_)
    seen[:, starts] = True
    ids, sims, done = np.full((m, width), -1, np.int32), np.full((m, width), -3, np.float32), np.ones((m, width), np.bool_)
    first = queries @ unit[starts].T
    size = min(width, len(starts))
    best = np.argsort(-first, axis=1, kind="stable")[:, :size]
    ids[:, :size], sims[:, :size] = starts[best], np.take_along_axis(first, best, axis=1)
    done[:, : min(p.entries, size)] = False
    hits = [(np.repeat(rows, len(starts)), np.tile(starts, m), first.ravel())]
    hits = [tuple(x[hits[0][2] >= wide] for x in hits[0])]
    while True:
        open_sims = np.where(done, np.float32(-4), sims)
        pick = open_sims.argmax(axis=1)
        live = np.flatnonzero(open_sims[rows, pick] > -3.5)
        if not len(live):
            break
        done[live, pick[live]] = True
        around = graph[ids[live, pick[live]]]
        fresh = (around >= 0) & ~seen[live[:, None], around]
        at, r = np.nonzero(fresh)
        q, x = live[at], around[at, r]
        seen[q, x] = True
        s = np.einsum("ij,ij->i", queries[q], unit[x])
        close = s >= wide
        hits.append((q[close], x[close], s[close]))
        got = np.full(around.shape, -3, np.float32)
        got[at, r] = s
        every = [np.concatenate(c, axis=1) for c in ((ids[live], around), (sims[live], got), (done[live], ~fresh))]
        best = np.argpartition(-every[1], width - 1, axis=1)[:, :width]
        ids[live], sims[live], done[live] = (np.take_along_axis(c, best, axis=1) for c in every)
    edge = tuple(np.concatenate([h[i] for h in hits]) for i in (0, 1))
    while len(edge[0]):
        new = [(np.empty(0, np.int64),) * 2]
        for a in range(0, len(edge[0]), 20_000):
            q = np.repeat(edge[0][a : a + 20_000], graph.shape[1])
            x = graph[edge[1][a : a + 20_000]].ravel()
            some = x >= 0
            q, x = q[some], x[some]
            some = ~seen[q, x]
            both = np.unique(q[some].astype(np.int64) * n + x[some])
            q, x = both // n, both % n
            seen[q, x] = True
            for b in range(0, len(q), 50_000):
                i, j = q[b : b + 50_000], x[b : b + 50_000]
                s = np.einsum("ij,ij->i", queries[i], unit[j])
                close = s >= wide
                hits.append((i[close], j[close], s[close]))
                new.append((i[close], j[close]))
        edge = tuple(np.concatenate([h[i] for h in new]) for i in (0, 1))
    q, x, s = (np.concatenate([h[i] for h in hits]) for i in range(3))
    keep = s >= p.threshold - 1e-5
    return q[keep], x[keep]


def _roots(ids: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For each node the smallest id it is connected with by the pairs ``(a, b)`` of positions."""
    label = ids.copy()
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        if (new == label).all():
            return label
        label = new


def _nearest(unit: np.ndarray, centres: np.ndarray, k: int) -> np.ndarray:
    """The ``k`` nearest centres of each vector, the nearest one first."""
    sims = unit @ centres.T
    k = min(k, len(centres))
    top = np.argpartition(-sims, k - 1, axis=1)[:, :k]
    return np.take_along_axis(top, np.argsort(-np.take_along_axis(sims, top, axis=1), axis=1, kind="stable"), axis=1)


_PLACED = "shard long, home boolean, node long, mix long, weight long, vector array<double>"


def _spread(table: pa.Table | pa.RecordBatch, near: np.ndarray, parent: np.ndarray, home: np.ndarray) -> dict:
    """A row for each class and shard; the first shard of a class at home is its home."""
    k = near.shape[1]
    row = np.repeat(np.arange(len(near)), k)
    first = np.tile(np.arange(k) == 0, len(near))
    out = {"shard": pa.array(parent[row] * 4096 + near.ravel() + 1, pa.int64()), "home": pa.array(home[row] & first)}
    return out | {c: table.column(c).take(pa.array(row)) for c in ("node", "mix", "weight", "vector")}


def _router(shared, p: VectorGraphParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centres = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                some = batch.slice(at, 2048)
                near = _nearest(_unit(_matrix(some.column("vector"), centres.shape[1])), centres, p.overlap)
                n = some.num_rows
                yield pa.RecordBatch.from_pydict(_spread(some, near, np.zeros(n, np.int64), np.ones(n, np.bool_)))

    return run


def _fitter(p: VectorGraphParams, dim: int):
    """Centroids of a shard from a sample of it; none where it is dense."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("mix").slice(0, p.sample)
        unit = _unit(_matrix(table.column("vector"), dim))
        some = unit[:: max(1, len(unit) // 256)][:256]
        linked = ((some @ some.T >= p.threshold).sum() - len(some)) / max(len(some) * (len(some) - 1), 1)
        k = min(p.max_shards, max(2, p.centre_bytes // (8 * dim)), -(-table.column("n")[0].as_py() * p.again // p.shard))
        centres = fit_centroids(unit, k) if linked < p.dense else np.empty((0, dim))
        return pa.table({"shard": table.column("shard").slice(0, 1), "centres": pa.array([centres.ravel()], pa.list_(pa.float64()))})

    return run


def _divider(p: VectorGraphParams, dim: int):
    def run(rows: pa.Table, fitted: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return rows.select([f.split()[0] for f in _PLACED.split(", ")])
        near = _nearest(_unit(_matrix(rows.column("vector"), dim)), fitted.column("centres")[0].values.to_numpy().reshape(-1, dim), p.again)
        home = rows.column("home").combine_chunks().to_numpy(zero_copy_only=False)
        return pa.table(_spread(rows, near, rows.column("shard").to_numpy(), home))

    return run


def _divided(placed: DataFrame, dim: int, p: VectorGraphParams) -> DataFrame:
    """``placed`` with ``n``, the classes of a shard; shards above ``block`` are divided while that helps."""
    done = None
    for level in range(p.depth):
        size = placed.groupBy("shard").agg(F.count("*").alias("n"))
        placed = materialize(placed.join(size, "shard"), "placed")
        large = placed.filter(F.col("n") > p.block)
        if level == p.depth - 1 or large.isEmpty():
            break
        part = F.pmod(F.xxhash64("mix", F.lit(level)), F.lit(1 << 30)) / (1 << 30)
        sample = large.filter(part < 1.1 * p.sample / F.col("n")).select("shard", "mix", "n", "vector")
        fitted = materialize(sample.groupBy("shard").applyInArrow(_fitter(p, dim), "shard long, centres array<double>"), "centres")
        dense = fitted.filter(F.size("centres") == 0).select("shard")
        kept = placed.filter(F.col("n") <= p.block).unionByName(large.join(dense, "shard", "left_semi"))
        done = kept if done is None else done.unionByName(kept)
        # rows of a shard go to as many tasks as they need, each with the shard's centroids
        parts = F.ceil(F.col("n") / p.sample).cast("long")
        rows = large.join(dense, "shard", "left_anti").withColumn("part", F.pmod("mix", parts))
        each = large.select("shard", "n").distinct().join(fitted.filter(F.size("centres") > 0), "shard")
        each = materialize(each.select("shard", F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)).alias("part"), "centres"), "centres")
        placed = rows.drop("n").groupBy("shard", "part").cogroup(each.groupBy("shard", "part")).applyInArrow(_divider(p, dim), _PLACED)
    return placed if done is None else done.unionByName(placed)


def _builder(p: VectorGraphParams, dim: int):
    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("mix")
        nodes = table.column("node").to_numpy()
        graph = build_graph(_unit(_matrix(table.column("vector"), dim)), p)
        lists = [nodes[g[g >= 0]] for g in graph]
        return pa.table({"node": pa.array(nodes), "near": pa.array(lists, pa.list_(pa.int64()))})

    return run


def _searcher(p: VectorGraphParams, dim: int):
    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("mix")
        index, asks = (np.flatnonzero(table.column(c).to_numpy()) for c in ("index", "asks"))
        empty = pa.array([], pa.int64())
        if not len(index) or not len(asks):
            return pa.table({"node": empty, "links": empty, "root": empty})
        nodes = table.column("node").to_numpy()
        raw = _matrix(table.column("vector"), dim)
        weight = table.column("weight").to_numpy()
        unit = _unit(raw).astype(np.float32)
        inside = unit[index]
        # united lists name nodes of other shards too
        order = np.argsort(nodes[index])
        places = nodes[index][order]
        near = table.column("near").combine_chunks().take(pa.array(index))
        flat, sizes = near.flatten().to_numpy(), near.value_lengths().to_numpy()
        at = np.minimum(np.searchsorted(places, flat), len(places) - 1)
        known = places[at] == flat
        row, local = np.repeat(np.arange(len(sizes)), sizes)[known], order[at[known]]
        count = np.bincount(row, minlength=len(index))
        graph = np.full((len(index), max(int(count.max(initial=0)), 1)), -1, np.int32)
        graph[row, np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)] = local
        starts = medoids(inside, p)
        norm = np.sqrt(np.einsum("ij,ij->i", raw, raw))
        links, ends = np.zeros(len(nodes), np.int64), [(asks[:0], asks[:0])]
        for some in np.array_split(asks, -(-len(asks) // 512)):
            q, x = search(inside, graph, unit[some], starts, p)
            q, x = some[q], index[x]
            good = np.zeros(len(q), np.bool_)
            for b in range(0, len(q), 50_000):
                i, j = q[b : b + 50_000], x[b : b + 50_000]
                good[b : b + 50_000] = (i != j) & (np.einsum("ij,ij->i", raw[i], raw[j]) / (norm[i] * norm[j]) >= p.threshold)
            q, x = q[good], x[good]
            links += np.bincount(q, weight[x], len(nodes)).astype(np.int64)
            # what is kept of the pairs is a forest: a root for each end
            root = _roots(np.arange(len(nodes)), q, x)
            tied = np.flatnonzero(root != np.arange(len(nodes)))
            ends.append((tied, root[tied]))
        root = _roots(nodes, *(np.concatenate([e[i] for e in ends]) for i in (0, 1)))
        out = np.flatnonzero((links > 0) | (root != nodes))
        return pa.table({"node": nodes[out], "links": links[out], "root": root[out]})

    return run


def _linked(classes: DataFrame, dim: int, p: VectorGraphParams) -> DataFrame:
    """``node, links, root`` rows of one dimension, to be summed and joined up."""
    spark = classes.sparkSession
    n = classes.count()
    k = min(p.max_shards, max(1, p.centre_bytes // (8 * dim)), -(-n * p.overlap // p.shard))
    rows = classes.select("node", "mix", "weight", "vector")
    if n <= p.block:
        placed = rows.select(F.lit(0).cast("long").alias("shard"), F.lit(True).alias("home"), "*", F.lit(n).cast("long").alias("n"))
    else:
        part = F.pmod("mix", F.lit(1 << 30)) / (1 << 30)
        sample = rows.filter(part < 1.1 * p.sample / n).limit(p.sample).select("vector").toArrow()
        shared = spark.sparkContext.broadcast(fit_centroids(_unit(_matrix(sample.column("vector"), dim)), k))
        placed = materialize(_divided(rows.mapInArrow(_router(shared, p), _PLACED), dim, p), "shards")
    # only dense shards have several parts
    placed = placed.withColumn("parts", F.ceil(F.col("n") / p.block).cast("long")).withColumn("own", F.pmod("mix", "parts"))
    near = (
        placed.groupBy("shard", "own")
        .applyInArrow(_builder(p, dim), "node long, near array<long>")
        .groupBy("node")
        .agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near"))
    )
    placed = placed.join(materialize(near, "adjacency"), "node")
    every = F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)
    index = placed.withColumn("asking", F.explode(every)).withColumns(
        {"holding": F.col("own"), "index": F.lit(True), "asks": F.col("home") & (F.col("asking") == F.col("own"))}
    )
    queries = placed.filter("home").withColumn("holding", F.explode(F.filter(every, lambda b: b != F.col("own")))).withColumns(
        {"asking": F.col("own"), "index": F.lit(False), "asks": F.lit(True), "near": F.array().cast("array<long>")}
    )
    columns = ["shard", "holding", "asking", "index", "asks", "node", "mix", "weight", "vector", "near"]
    return (
        index.select(columns)
        .unionByName(queries.select(columns))
        .groupBy("shard", "holding", "asking")
        .applyInArrow(_searcher(p, dim), "node long, links long, root long")
    )


def near_duplicates(vectors: DataFrame, p: VectorGraphParams = VectorGraphParams()) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` for each row of ``vectors(vec_id, embedding)``.

    Null, empty and zero vectors, vectors with a null or non-finite component, and rows with a null
    vec_id link with nothing. Vectors of different lengths never link. Rows that repeat a vec_id
    are separate vectors, each with its own links and component. An empty table gives an empty result;
    other columns are not read.
    """
    clean = materialize(vectors.select(F.col("vec_id").cast("long"), "embedding").mapInArrow(_clean, _ROW), "vectors")
    # nodes are numbers of classes, not vec_ids: those may repeat
    classes = materialize(
        clean.filter("key is not null and vec_id is not null")
        .groupBy("key")
        .agg(
            F.min("vec_id").alias("low"),
            F.count("*").alias("weight"),
            F.first("dim").alias("dim"),
            F.first("vector").alias("vector"),
        )
        .select("*", F.monotonically_increasing_id().alias("node"), F.xxhash64("key").alias("mix")),
        "classes",
    )
    dims = sorted(r["dim"] for r in classes.select("dim").distinct().limit(33).collect())
    if len(dims) > 32:
        raise ValueError("vectors of more than 32 different lengths")
    found = None
    for dim in dims:
        part = _linked(classes.filter(F.col("dim") == dim), dim, p)
        found = part if found is None else found.unionByName(part)
    ids = clean.select("vec_id", "key")
    if found is None:
        found = vectors.sparkSession.createDataFrame([], "node long, links long, root long")
    found = materialize(found, "links")
    comp = materialize(components(found.select(F.col("node").alias("src"), F.col("root").alias("dst"))), "comp")
    named = comp.join(classes.select("node", "low"), "node").groupBy("component").agg(F.min("low").alias("component_id"))
    total = found.groupBy("node").agg(F.sum("links").alias("links"))
    by_class = (
        classes.select("key", "node", "weight", "low")
        .join(total, "node", "left")
        .join(comp.join(named, "component").select("node", "component_id"), "node", "left")
        .select(
            "key",
            (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"),
            F.coalesce("component_id", "low").alias("component_id"),
        )
    )
    return (
        ids.join(by_class, "key", "left")
        .withColumn("component_id", F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", "vec_id")))
        .select(
            "vec_id",
            F.when(F.col("vec_id").isNull(), 0).otherwise(F.coalesce("n_links", F.lit(0))).cast("long").alias("n_links"),
            "component_id",
            F.col("vec_id").eqNullSafe(F.col("component_id")).alias("kept"),
        )
    )


def audit_recall(vectors: DataFrame, result: DataFrame, p: VectorGraphParams = VectorGraphParams(), every: int = 50, block: int = 2000) -> DataFrame:
    """``n_queries, true_links, found_links, recall`` for the rows whose id is divisible by ``every``.

    The truth is brute force, all rows against the queries in broadcast blocks of bounded size; links
    found are all verified, so recall is found over true.
    """
    clean = materialize(vectors.select(F.col("vec_id").cast("long"), "embedding").mapInArrow(_clean, _ROW).filter("key is not null and vec_id is not null"), "audit")
    asked = clean.filter(F.col("vec_id") % every == 0)
    n = max(1, -(-asked.count() // block))
    truth = None
    for k in range(n):
        rows = asked.filter(F.pmod(F.xxhash64("vec_id"), F.lit(n)) == k).select("vec_id", "vector").collect()
        for dim in sorted({len(r["vector"]) for r in rows}):
            some = [r for r in rows if len(r["vector"]) == dim]
            shared = vectors.sparkSession.sparkContext.broadcast(
                (np.array([r["vec_id"] for r in some]), np.array([r["vector"] for r in some]))
            )

            def run(batches: Iterator[pa.RecordBatch], shared=shared, dim=dim) -> Iterator[pa.RecordBatch]:
                ids, q = shared.value
                q = _unit(q)
                total = np.zeros(len(ids), np.int64)
                for batch in batches:
                    if batch.num_rows:
                        total += (_unit(_matrix(batch.column(0), dim)) @ q.T >= p.threshold).sum(axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(total)], ["vec_id", "n"])

            part = clean.filter(F.col("dim") == dim).select("vector").mapInArrow(run, "vec_id long, n long")
            truth = part if truth is None else truth.unionByName(part)
    if truth is None:
        truth = vectors.sparkSession.createDataFrame([], "vec_id long, n long")
    true = truth.groupBy("vec_id").agg((F.sum("n") - 1).alias("true"))
    return true.join(result.select("vec_id", "n_links"), "vec_id").agg(
        F.count("*").alias("n_queries"),
        F.coalesce(F.sum("true"), F.lit(0)).alias("true_links"),
        F.coalesce(F.sum(F.least("true", "n_links")), F.lit(0)).alias("found_links"),
    ).withColumn("recall", F.when(F.col("true_links") == 0, 1.0).otherwise(F.col("found_links") / F.col("true_links")))
