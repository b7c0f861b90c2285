"""Space parts: no link is lost, loads are even, and few clusters or equal places do no harm."""

import math
import random

import pytest
from pyspark.sql import functions as F
from test_groups import member_of

from groupflow.operators import links, patterns, sectors, shapes
from groupflow.params import Params
from groupflow.storage import materialize

P = Params(w=6, k_c=4, m_c=1, k_p=1, m_p=1, d=2.0)


def _shape(spark, clusters):
    return materialize(shapes.summarize(member_of(spark, clusters)))


def _random(spark, seed, n=12):
    rnd = random.Random(seed)
    clusters, o = [], 0
    for t in range(6):
        for _ in range(n):
            x, y = rnd.uniform(-15, 15), rnd.uniform(-15, 15)
            clusters.append((t, [(o + k, x + rnd.uniform(-2, 2), y + rnd.uniform(-2, 2)) for k in range(3)]))
            o += 3
    return _shape(spark, clusters)


def _pairs(df):
    return sorted((r["src"], r["dst"]) for r in df.collect())


def test_no_link_is_lost(spark):
    shape = _random(spark, 1)
    want = _pairs(links.build(shape, P, "none", False))
    assert want
    for n in (1, 4, 6, 7):
        assert _pairs(links.build(shape, P, "sector", n_parts=n)) == want
    assert _pairs(links.build(shape, P, "random", n_parts=3)) == want


def test_narrow_halo_misses_long_gaps(spark):
    # on both sides of the polar axis, further apart than the width of one timestamp; two rings of two sectors at t = 0
    rest = [(-10.0, 2.5), (-20.0, -20.0), (20.0, 20.5)]
    shape = _shape(spark, [(0, [(1, 10.0, 2.5)]), (3, [(301, 10.0, -2.5)])] + [(0, [(10 * i, x, y)]) for i, (x, y) in enumerate(rest, start=2)])
    want = _pairs(links.build(shape, P, "none", False))
    assert _pairs(links.build(shape, P, "sector", n_parts=4)) == want
    narrow = _pairs(links.build(shape, P, "sector", n_parts=4, halo="printed"))
    assert set(narrow) < set(want)


def test_balanced_and_approximate(spark):
    shape = _random(spark, 2, 24)
    points = sectors.polar(shape, sectors.center(shape))
    for how in ("exact", "approx"):
        part = sectors.divide(points, 4, how)
        homes = sectors.home(points, part)
        assert homes.filter("part is null").count() == 0
        assert sectors.balance(homes, 4).agg(F.max("imbalance")).first()[0] <= 1.5


def test_equal_places_and_empty(spark):
    same = _shape(spark, [(t, [(10 * t + i, 1.0, 1.0)]) for t in range(3) for i in range(5)])
    assert _pairs(links.build(same, P, "sector", n_parts=6)) == _pairs(links.build(same, P, "none", False))
    assert links.build(same.filter("t < 0"), P, "sector").count() == 0


def test_radii_stay_until_the_load_shifts(spark):
    shape = _random(spark, 3, 20)
    points = sectors.polar(shape, (0.0, 0.0))
    before = sectors.rings(points.filter("t = 0"), 2)
    _, anew = sectors.update(before, points.filter("t = 1"), 4, tolerance=1.8)
    assert not anew
    inner = points.filter("t = 1").withColumn("rho", F.col("rho") / 1000)
    part, anew = sectors.update(before, inner, 4, tolerance=1.8)
    assert anew and sectors.home(inner, part).filter("part is null").count() == 0


def test_flocks_and_swarms(spark):
    rows = [(t, o, float(o), 0.0) for t in range(5) for o in (1, 2, 3)] + [(t, 9, 50.0, 50.0) for t in range(5)]
    snap = spark.createDataFrame(rows, "t long, obj_id long, x double, y double")
    got = {(r["anchor"], r["first_t"], tuple(r["members"])) for r in patterns.flocks(snap, 1.0, 3, 4).collect()}
    assert got == {(2, 0, (1, 2, 3)), (2, 1, (1, 2, 3))}
    member = member_of(spark, [(1, [(1, 0, 0), (2, 0, 0), (3, 0, 0)]), (4, [(1, 0, 0), (2, 0, 0), (3, 0, 0)]), (7, [(1, 0, 0), (2, 0, 0)])])
    swarms = {tuple(r["objs"]): len(r["clusters"]) for r in patterns.swarms(member, 2, 2).collect()}
    assert swarms == {(1, 2): 3, (1, 2, 3): 2}


def _swarms(spark, sets, m, k, **more):
    rows = [(c << 32, c, o) for o, held in sets.items() for c in held]
    member = spark.createDataFrame(rows, "cluster_id long, t long, obj_id long")
    return [(tuple(r["objs"]), tuple(c >> 32 for c in r["clusters"])) for r in patterns.swarms(member, m, k, **more).collect()]


def test_swarms_against_brute_force(spark):
    from itertools import combinations

    rng = random.Random(6)
    for n, c, p, m, k in ((9, 12, 0.5, 2, 2), (10, 8, 0.8, 3, 3), (7, 6, 0.3, 1, 1), (3, 2, 0.0, 1, 1)):
        sets = {o: {t for t in range(c) if rng.random() < p} for o in range(n)}
        want = set()
        for size in range(1, n + 1):
            for some in combinations(sets, size):
                common = set.intersection(*[sets[o] for o in some])
                objs = tuple(o for o in sets if common <= sets[o])
                if len(common) >= k and len(objs) >= m:
                    want.add((objs, tuple(sorted(common))))
        got = _swarms(spark, sets, m, k)
        assert sorted(got) == sorted(want)


def test_swarms_list_no_parts_of_copies(spark):
    """Forty objects on one track have 2 ** 40 subsets and one closed set; larger sets are made by closed ones only."""
    sets = {o: range(12) for o in range(40)} | {100 + o: range(6, 18) for o in range(40)}
    some = tuple(range(40)), tuple(range(100, 140))
    want = [(some[0], tuple(range(12))), (some[0] + some[1], tuple(range(6, 12))), (some[1], tuple(range(6, 18)))]
    assert sorted(_swarms(spark, sets, 3, 5)) == want


def test_swarms_too_many_to_list_are_an_error_before_they_are_listed(spark):
    """Each object misses a cluster of its own: any of the clusters share another set."""
    sets = {o: set(range(60)) - {o} for o in range(60)}
    with pytest.raises(RuntimeError, match="at least 1152921"):
        _swarms(spark, sets, 3, 12)
    few = {o: set(range(8)) - {o} for o in range(8)}
    assert len(_swarms(spark, few, 3, 2)) == sum(math.comb(8, j) for j in range(2, 6))
    with pytest.raises(RuntimeError, match="at least 210 "):
        _swarms(spark, few, 3, 2, max_sets=209)


def test_sql_distances_do_not_carry_repeated_points(spark):
    from types import SimpleNamespace

    from groupflow.functions import hausdorff
    from groupflow.plans import surface

    rng = random.Random(4)
    lists = [None, [], [(0.0, 0.0)], [(rng.random() * 9, rng.random() * 9) for _ in range(300)], [(float(i % 3), 1.0) for i in range(300)]]
    shape = spark.createDataFrame([(i, 0, x) for i, x in enumerate(lists[2:])], "cluster_id long, t long, pts array<struct<x: double, y: double>>")
    none = shape.limit(0)
    found = SimpleNamespace(member=none, shape=shape, link=none, cover=none, crowd=none, windows=none, group=none, evo=none)
    surface.register(spark, none, found)
    few = {r["cluster_id"]: r["pts"] for r in spark.sql("SELECT cluster_id, pts FROM shapes").collect()}
    assert {i: sorted(map(tuple, x)) for i, x in few.items()} == {i: sorted(set(x)) for i, x in enumerate(lists[2:])}
    rows = spark.createDataFrame([(a, b, most) for a in lists for b in lists for most in (1.0, 8.0)], "a array<struct<x: double, y: double>>, b array<struct<x: double, y: double>>, most double")
    got = rows.selectExpr("hausdorff(a, b) AS q", "hausdorff_within(a, b, most) AS w").collect()
    want = rows.select(hausdorff.distance(F.col("a"), F.col("b")).alias("q"), hausdorff.within(F.col("a"), F.col("b"), F.col("most")).alias("w")).collect()
    known = [None not in (a, b) for a in lists for b in lists for _ in range(2)]
    assert [tuple(r) for r, k in zip(got, known, strict=True) if k] == [tuple(r) for r, k in zip(want, known, strict=True) if k]
    assert all(r["q"] is None and r["w"] is None for r, k in zip(got, known, strict=True) if not k)


def test_experiments_measure_equal_work_once(spark, monkeypatch):
    from types import SimpleNamespace

    from groupflow.plans import experiments

    asked, built, build = [], [], links.build
    monkeypatch.setattr(experiments, "discover", lambda some, p: SimpleNamespace(evo=SimpleNamespace(count=lambda: asked.append(p) or len(asked))))
    monkeypatch.setattr(links, "build", lambda shape, p, *a, **k: built.append(p) or build(shape, p, *a, **k))
    snap = spark.range(4).withColumnRenamed("id", "obj_id")
    settings = [*[("objects", *x) for x in experiments.objects(snap, P, 2)], ("d", 2.0, snap, P), ("d", 3.0, snap, P.but(d=3.0))]
    rows = {(r["experiment"], r["value"]): r for r in experiments.whole(snap, settings).collect()}
    assert len(rows) == 4 and [p.d for p in asked] == [2.0, 2.0, 3.0]
    assert rows["objects", 1.0][2:] == rows["d", 2.0][2:] and rows["objects", 0.5]["answers"] == 1
    got = experiments.crowd_step(_random(spark, 2, 4), "k_c", [(k, P.but(k_c=k)) for k in (4, 5)]).collect()
    assert len(got) == 6 and len(built) == 5
    assert all(r["seconds"] > 0 for r in got)
