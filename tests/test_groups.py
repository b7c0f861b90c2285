"""Worked examples, counterexamples and equalities of the moving-group method."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from groupflow.functions import hausdorff, pruning
from groupflow.operators import baselines, chains, density, distances, graph, lineage, links, patterns, peel, shapes
from groupflow.operators.density import ID_BASE
from groupflow.params import Params
from groupflow.plans import measures
from groupflow.plans.pipeline import discover
from groupflow.storage import materialize


def member_of(spark, clusters):
    """``clusters``: (t, [(obj, x, y), ...]); the cluster id is t and the smallest object."""
    rows = []
    for t, points in clusters:
        low = min(o for o, _, _ in points)
        rows += [(t, t * ID_BASE + low, o, float(x), float(y), True) for o, x, y in points]
    return spark.createDataFrame(rows, "t long, cluster_id long, obj_id long, x double, y double, is_core boolean")


def crowds_of(spark, clusters, p):
    shape = materialize(shapes.summarize(member_of(spark, clusters)))
    cover = chains.cover(links.build(shape, p))
    return shape, cover, chains.closed_crowds(shape, cover, p)


def names(crowd, label, win):
    return sorted("".join(label[c] for c in r["path"]) for r in chains.closed_in(crowd, win).collect())


def test_sliding_crowds(spark):
    p = Params(w=4, k_c=3, d=1.0, m_c=3, k_p=1, m_p=1)
    places = {"B": (1, 2.0), "X": (1, 3.5), "C": (2, 0.0), "D": (3, 1.0), "E": (4, 2.0), "F": (5, 2.0), "G": (5, 0.0)}
    clusters, label = [], {}
    for i, (n, (t, y)) in enumerate(places.items()):
        clusters.append((t, [(10 * i + k, 0.0, y) for k in range(3)]))
        label[t * ID_BASE + 10 * i] = n
    _, cover, crowd = crowds_of(spark, clusters, p)
    assert {label[r["src"]] + label[r["dst"]] for r in cover.collect()} == {"CD", "BD", "DE", "EF", "DG"}
    assert names(crowd, label, 1) == ["BDE", "CDE"]
    assert names(crowd, label, 2) == ["CDEF", "CDG"]


def test_early_match_is_not_closed(spark):
    p = Params(w=4, k_c=2, d=1.0, m_c=1, k_p=1, m_p=1)
    clusters = [(t, [(1, 0.0, 0.0)]) for t in (1, 2, 3)] + [(4, [(9, 99.0, 99.0)])]
    _, _, crowd = crowds_of(spark, clusters, p)
    assert [r["len"] for r in crowd.collect()] == [3]


def test_peeling(spark):
    p = Params(w=8, k_c=6, k_p=5, m_p=3, d=1.0, m_c=3)
    sets = {1: {1, 2, 3, 6}, 2: {1, 2, 3, 5, 6}, 3: {1, 4, 6}, 4: {2, 3, 5, 6}, 5: {1, 2, 3, 5}, 7: {1, 2, 3, 4, 5}, 8: {1, 2, 3, 5, 6}, 9: {2, 3, 5}}
    shape, _, crowd = crowds_of(spark, [(t, [(o, 0, 0) for o in s]) for t, s in sets.items()], p)
    for impl in ("expr", "relational"):
        rows = peel.closed(peel.by_window(peel.peel(crowd, shape, p, impl))).collect()
        found = {r["win"]: (sorted(r["members"]), [c // ID_BASE for c in r["path"]]) for r in rows}
        assert found == {1: ([1, 2, 3, 5], [1, 2, 4, 5, 7, 8]), 2: ([2, 3, 5], [2, 4, 5, 7, 8, 9])}
    group = peel.groups(peel.closed(peel.by_window(peel.peel(crowd, shape, p))))
    evo = lineage.edges(group, 0.7).collect()
    assert [(r["win"], r["common"]) for r in evo] == [(1, 3)]


def test_evolved_for_any_share(spark):
    group = spark.createDataFrame([(1, "a", [1, 2, 3, 4], 4), (2, "b", [1, 2, 3, 4, 6], 5)], "win long, group_id string, members array<long>, size int")
    assert lineage.edges(group, 1.0).count() == 1


def test_global_closure_drops_nested(spark):
    rows = [(1, "abc", [1, 2, 3], [7]), (1, "abcy", [1, 2, 3, 4], [7]), (2, "abc", [1, 2, 3], [7])]
    windows = spark.createDataFrame(rows, "win long, agg_id string, path array<long>, members array<long>")
    assert sorted((r["win"], r["agg_id"]) for r in peel.closed(windows).collect()) == [(1, "abcy"), (2, "abc")]
    assert peel.closed(windows, "per_crowd").count() == 3


def test_short_rule_counterexample(spark):
    clusters = [(1, [(1, 0, 1), (2, 0, -1)]), (2, [(3, 1, 0), (4, -1, 0)])]
    shape = shapes.summarize(member_of(spark, clusters))
    p = Params(d=1.0)
    pair = links.candidates(shape, p, "none")
    said = pair.select(
        pruning.near("a", "b", F.lit(1.0), "printed").alias("printed"), pruning.near("a", "b", F.lit(1.0)).alias("sound")
    ).first()
    assert said["printed"] and not said["sound"]
    assert links.build(shape, p).count() == 0


def test_gathering(spark):
    p3 = [(t, [(o, 0, 0) for o in s]) for t, s in ((1, {1, 2, 3}), (2, {1, 2, 3, 4}), (3, {2, 3, 4}))]
    shape = shapes.summarize(member_of(spark, p3))
    crowd = baselines.strict_crowds(shape, links.build(shape, Params(d=1.0)), 3)
    assert baselines.gatherings(crowd, shape, 2, 3).count() == 1
    assert baselines.cut_at_invalid(crowd, shape, 3, 2, 3).count() == 1
    assert baselines.gatherings(crowd, shape, 3, 3).count() == 0


@pytest.mark.parametrize("slice_", [2, 5, 48])
def test_convoys_by_slices(spark, slice_):
    """As all pairs of found sets say, wherever time is cut, with snapshots that are missing; live sets go through a slice once."""
    rng, rows = random.Random(slice_), []
    for t in [*range(3, 15), *range(17, 24)]:
        of = {o: (o // 4 + (rng.random() < 0.12) * rng.randint(1, 3)) % 4 for o in range(14) if rng.random() < 0.95}
        rows += [(t, t * ID_BASE + c, o) for o, c in of.items()]
    member = spark.createDataFrame(rows, "t long, cluster_id long, obj_id long")
    got = [(tuple(r["objs"]), r["first_t"], r["last_t"]) for r in baselines.convoys(member, 2, 3, slice_=slice_).collect()]
    held = {}
    for t, c, o in rows:
        held.setdefault(t, {}).setdefault(c, set()).add(o)
    live = {(frozenset(s), t, t) for t in held for s in held[t].values() if len(s) >= 2}
    every = set(live)
    while live:
        live = {(s & x, f, t + 1) for s, f, t in live for x in held.get(t + 1, {}).values() if len(s & x) >= 2}
        every |= live
    every = {c for c in every if c[2] - c[1] >= 2}
    want = {c for c in every if not any(b != c and b[0] >= c[0] and b[1] <= c[1] and b[2] >= c[2] for b in every)}
    assert sorted(got) == sorted((tuple(sorted(s)), f, t) for s, f, t in want) and len(want) > 5
    plain = baselines._overlapping(member, 2, 3).collect() if slice_ == 48 else None
    assert plain is None or len(plain) == len(want)


def test_hausdorff_brute_force(spark):
    rng = random.Random(3)
    rows = [([(rng.uniform(0, 9), rng.uniform(0, 9)) for _ in range(rng.randint(1, 6))] for _ in range(2)) for _ in range(60)]
    rows = [tuple(r) for r in rows]
    df = spark.createDataFrame(rows, "a array<struct<x:double,y:double>>, b array<struct<x:double,y:double>>")
    got = df.select(hausdorff.distance(F.col("a"), F.col("b")).alias("h"), hausdorff.within(F.col("a"), F.col("b"), F.lit(4.0)).alias("w")).collect()
    for (a, b), r in zip(rows, got):
        one = lambda u, v: max(min(((p[0] - q[0]) ** 2 + (p[1] - q[1]) ** 2) ** 0.5 for q in v) for p in u)
        h = max(one(a, b), one(b, a))
        assert r["h"] == pytest.approx(h) and r["w"] == (h <= 4.0)


def test_distances_of_large_clusters(spark, monkeypatch):
    """As brute force, over repeated points, far and single ones; a large pair is not compared point by point."""
    rng, seen = np.random.default_rng(3), []
    monkeypatch.setattr(distances, "_squares", lambda *v, squares=distances._squares: (seen.append(np.broadcast(*v).size), squares(*v))[1])
    draw = lambda n, wide, at=0: distances.Points(*(rng.exponential(wide, (2, n)) + at))
    one = lambda u, v: np.min((u.x[:, None] - v.x) * (u.x[:, None] - v.x) + (u.y[:, None] - v.y) * (u.y[:, None] - v.y), axis=1).max()
    line = distances.Points(np.arange(300.0), np.zeros(300))
    for a, b in [(draw(900, 5), draw(700, 50)), (draw(200, 1), draw(900, 1, 99)), (line, draw(400, 9)), (draw(500, 3), line), (line, line), (draw(1, 1), draw(99, 1))]:
        q = max(one(a, b), one(b, a))
        assert distances.square(a, b) == q
        assert all((distances.square(a, b, q * k) <= q * k) == (k >= 1) for k in (0.5, 1, 2) if q)
    seen.clear()
    a, b = draw(20_000, 40), draw(20_000, 40)
    distances.square(a, b, 25.0)
    assert sum(seen) < 20_000**2 / 20
    clusters = [(t, [(100 * c + i, x, y) for i, (x, y) in enumerate([*rng.uniform(c, c + 9, (n, 2)).round(1).tolist()] * 2)]) for t in (1, 2, 3, 4, 7) for c, n in ((0, 40), (5, 3), (9, 1))]
    shape = materialize(shapes.summarize(member_of(spark, clusters)))
    pairs = materialize(links.candidates(shape, Params(w=6), "none", "window").select(F.col("a.cluster_id").alias("src"), F.col("b.cluster_id").alias("dst"), "dt"))
    both = distances.with_squares(pairs, shape, 5).select("src", "dst", F.sqrt("q").alias("h"))
    pts = shape.select("cluster_id", "pts")
    plain = pairs.join(pts.toDF("src", "a"), "src").join(pts.toDF("dst", "b"), "dst").select("src", "dst", hausdorff.distance(F.col("a"), F.col("b")).alias("h"))
    assert sorted(both.collect()) == sorted(plain.collect()) and both.count() == pairs.count() > 50


def test_components(spark):
    rng = random.Random(5)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    got = {r["node"]: r["component"] for r in graph.components(spark.createDataFrame(pairs, "src long, dst long")).collect()}
    assert got == {n: find(n) for p in pairs if p[0] != p[1] for n in p}


@pytest.mark.parametrize("border", ["min_cluster", "all", "none"])
def test_cluster_plans_agree(spark, border):
    rng = random.Random(11)
    rows = [(t, o, rng.choice([0.0, rng.uniform(0, 12)]), rng.uniform(0, 12)) for t in range(4) for o in range(90)]
    snap = spark.createDataFrame(rows, "t long, obj_id long, x double, y double")
    a, b = (sorted(map(tuple, density.cluster(snap, 1.0, 3, border, plan).collect())) for plan in ("grid", "snapshot"))
    assert a == b and a


def test_empty_and_single(spark):
    snap = spark.createDataFrame([], "t long, obj_id long, x double, y double")
    found = discover(snap, Params())
    assert found.group.count() == found.crowd.count() == found.evo.count() == 0
    one = spark.createDataFrame([(0, 1, 0.0, 0.0)], snap.schema)
    assert density.cluster(one, 1.0, 1).count() == 1


def test_indexes_agree(spark):
    rng = random.Random(2)
    clusters = [(t, [(10 * c + k, rng.uniform(0, 30) + k, rng.uniform(0, 30)) for k in range(3)]) for t in range(6) for c in range(6)]
    shape = materialize(shapes.summarize(member_of(spark, clusters)))
    p = Params(w=5, k_c=4, d=8.0)
    found = [sorted(map(tuple, links.build(shape, p, i, prune).select("src", "dst", "dt").collect())) for i, prune in (("box", True), ("grid", True), ("none", False))]
    assert found[0] == found[1] == found[2] and found[0]


def test_path_guard(spark):
    clusters = [(t, [(c, 0, 0)]) for t in range(6) for c in range(5)]
    shape = shapes.summarize(member_of(spark, clusters))
    cover = materialize(chains.cover(links.build(shape, Params(m_c=1))))
    with pytest.raises(RuntimeError):
        chains.closed_crowds(shape, cover, Params(m_c=1), max_paths=1000)


def test_measures_without_patterns(spark):
    """As in SQL, the total over all of no patterns is a row, and nothing is predicted from crowds that are not there."""
    none = spark.createDataFrame([], "period string, day_type string, n long")
    assert [tuple(r) for r in measures.by_period(none).collect()] == [(None, None, 3, None)]
    some = spark.createDataFrame([("07-10", "weekend", 2)], none.schema)
    assert sorted((r["level"], r["n"]) for r in measures.by_period(some).collect()) == [(0, 2), (1, 2), (2, 2), (3, 2)]
    shape, _, crowd = crowds_of(spark, [(t, [(o, 9.0 * t, 0) for o in range(3)]) for t in range(1, 9)], Params(d=1.0))
    decided = links.decide(links.candidates(shape, Params(d=1.0), "none"), shape, Params(d=1.0))
    assert crowd.count() == 0 and measures.cost_stats(decided, shape, crowd, 6).first()["l"] is None


@pytest.mark.parametrize("k", [1, 3])
def test_flocks_brute_force(spark, monkeypatch, k):
    """As every pair of objects at every timestamp says, in small parts: tracks that several objects share, snapshots and objects
    that are missing, places at the rim, far away and not a number; nothing is broadcast or joined."""
    monkeypatch.setattr(patterns, "_SLICE", 2)
    rng, rows = random.Random(k), []
    for t in [*range(-3, 6), *range(8, 12)]:
        at = [(rng.choice([0.0, 3.0, 6.0, rng.uniform(-8, 8), 1e17]), rng.choice([0.0, 4.0, rng.uniform(-8, 8)])) for _ in range(9)]
        rows += [(t, o, *at[o % 9]) for o in range(16) if rng.random() < 0.95]
    rows += [(t, 50 + o, float("nan"), 0.0) for t in range(5) for o in range(3)]
    snap = spark.createDataFrame(rows, "t long, obj_id long, x double, y double")
    found = patterns.flocks(snap, 5.0, 3, k)
    place = {(t, o): (x, y) for t, o, x, y in rows}
    near = lambda t, a, b: (t, a) in place and (t, b) in place and sum((u - v) ** 2 for u, v in zip(place[t, a], place[t, b])) <= 25.0
    ids = sorted({o for _, o, _, _ in rows})
    want = [(a, t, [b for b in ids if all(near(t + j, a, b) for j in range(k))]) for t in range(-3, 12) for a in ids]
    assert sorted(map(tuple, found.collect())) == sorted((a, t, b) for a, t, b in want if len(b) >= 3)
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    ids, at = np.arange(40), np.array([[float(o // 4 % 7), float(o % 3)] for o in range(40)])
    rows = []
    for part in (1 << 20, 2):
        monkeypatch.setattr(patterns, "_PART", part)
        rows.append(sorted(str(r) for b in patterns._flocks_from(0, ids, at[:, :1].T, at[:, 1:].T, 1.0, 3) for r in b.to_pylist()))
    assert rows[0] == rows[1] and len(rows[0]) == 40


def test_crowds_by_components(spark, monkeypatch):
    """Slices that are dealt out by components give the same crowds, and no task walks more than its share."""
    rng, p = random.Random(5), Params(w=4, k_c=3, d=1.0, m_c=1)
    clusters = [(t, [(o, 100.0 * (o % 12) + rng.choice([0.0, 0.8, 3.0]), 0)]) for t in range(1, 12) for o in range(24)]
    shape, cover, crowd = crowds_of(spark, clusters, p)
    whole = sorted(map(str, crowd.collect()))
    walks, seen = chains._walks, spark.sparkContext.accumulator(0)

    def counted(*arguments):
        run = walks(*arguments)

        def walk(table):
            seen.add(1)
            return run(table)

        return walk

    monkeypatch.setattr(chains, "_walks", counted)
    monkeypatch.setattr(chains, "_ONE_TASK", 20)
    assert sorted(map(str, chains.closed_crowds(shape, cover, p).collect())) == whole and len(whole) > 20
    assert seen.value > 8  # four slices of time


def test_clusters_are_shared(spark, monkeypatch):
    """Methods that differ from links on find no clusters anew."""
    from groupflow.plans import pipeline, queries

    sf = "/root/testdata/sf0.001"
    queries._all(spark, sf)
    monkeypatch.setattr(pipeline, "clusters", None)
    assert [r["differences"] for r in queries.parallel_differences(spark, sf).collect()] == [0, 0]


def test_positions_are_shared(spark):
    """A sweep over objects works positions out once."""
    from groupflow.plans import sweeps

    rng, read = random.Random(3), spark.sparkContext.accumulator(0)
    rows = [(t, o, rng.uniform(0, 20), rng.uniform(0, 20)) for t in range(3) for o in range(40)]

    def seen(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    snap = spark.createDataFrame(rows, "t long, obj_id long, x double, y double")
    found = sweeps.objects(snap.mapInArrow(seen, snap.schema), Params(), 5).collect()
    assert [(r["objects"], r["points"]) for r in found] == [(8 * k, 24 * k) for k in range(1, 6)] and read.value == 120


def test_convoys_write_each_object_once(spark, monkeypatch):
    """Found convoys stand on storage by place and size: many convoys of the same objects do not repeat them."""
    written, write = [], baselines.materialize
    monkeypatch.setattr(baselines, "materialize", lambda df, name: written.append((name, write(df, name))) or written[-1][1])
    # 300 objects, of which one leaves for good at each timestamp
    rows = [(t, t * ID_BASE, o) for t in range(40) for o in range(300) if o >= t]
    member = spark.createDataFrame(rows, "t long, cluster_id long, obj_id long")
    got = sorted((r["first_t"], r["last_t"], len(r["objs"])) for r in baselines.convoys(member, 2, 3).collect())
    assert got == [(0, t, 300 - t) for t in range(2, 40)]
    stored = sum(df.select(F.sum(F.size("objs"))).first()[0] for name, df in written if name == "convoys")
    assert stored < 40 * 300 + 100
