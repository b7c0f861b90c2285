"""Density clusters of crowded snapshots."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from groupflow.operators import chains, density, links, shapes
from groupflow.params import Params
from groupflow.storage import materialize


def test_crowded_cells_are_not_compared_point_by_point():
    """Cells that others connect, or whose boxes tell, need few pairs of points; far and near boxes decide alike."""
    rng = np.random.default_rng(1)
    n = 60_000
    # crowded cells; two bands apart by just over eps and by less
    x, y = rng.uniform(0, 60, n), rng.choice([0.0, 5.0 + 1e-9, 9.0], n)
    looked, pairs = [0], density._pairs

    def counted(*runs):
        for row, i, j in pairs(*runs):
            looked[0] += len(row)
            yield row, i, j

    density._pairs = counted
    try:
        found = density._clustered(np.zeros(n, np.int64), np.arange(n), x, y, 5.0, 3, "min_cluster", 3)
    finally:
        density._pairs = pairs
    clusters = {}
    for o, c in zip(found.column(2).to_pylist(), found.column(1).to_pylist()):
        clusters.setdefault(c, set()).add(y[o])
    assert found.num_rows == n and sorted(map(sorted, clusters.values())) == [[0.0], [5.0 + 1e-9, 9.0]]
    assert looked[0] < 50 * n


@pytest.mark.parametrize("piece", [200_000, 7])
def test_placed_snapshots_are_clustered_where_they_stand(spark, piece):
    """Rows of whole snapshots give the same clusters, without a shuffle; pieces of larger ones are dealt anew."""
    rng = np.random.default_rng(2)
    rows = [(t, o, float(x), float(y)) for t in range(9) for o, (x, y) in enumerate(rng.uniform(0, 30, (40 - t, 2)))]
    snap = spark.createDataFrame(rows, "t long, obj_id long, x double, y double")
    placed = density.materialize(density.placed(snap, piece), "placed")
    assert (placed.count() == 9) == (piece > 40) and sorted(map(tuple, density.flat(placed).collect())) == sorted(rows)
    some = placed.withColumn("points", F.filter("points", lambda v: v["obj_id"] % 3 < 2))
    for got, of in ((placed, snap), (some, snap.filter("obj_id % 3 < 2"))):
        found = density.cluster(got, 5.0, 3, least=3)
        assert sorted(found.collect()) == sorted(density.cluster(of, 5.0, 3, least=3).collect())
        assert ("Exchange" in found._jdf.queryExecution().toString()) == (piece == 7)


def test_box_index_sends_few_copies(spark):
    """Clusters meet those of neighbouring cells, each pair once, and are not sent to nine cells each."""
    rng = np.random.default_rng(3)
    rows = [(t * density.ID_BASE + 4 * i + k, t, 4 * i + k, float(x), float(y)) for t in range(5) for i, (x, y) in enumerate(rng.uniform(-90, 90, (60, 2))) for k in range(1)]
    member = spark.createDataFrame([(c, t, o, x, y) for c, t, o, x, y in rows], "cluster_id long, t long, obj_id long, x double, y double")
    p, shape = Params(w=6, k_c=5, d=5.0), shapes.summarize(member)
    got = sorted((r["a"]["cluster_id"], r["b"]["cluster_id"], r["dt"]) for r in links.candidates(shape, p).collect())
    near = lambda v, w, dt: abs(v // (p.d * dt) - w // (p.d * dt)) <= 1
    want = [(a[0], b[0], b[1] - a[1]) for a in rows for b in rows if 0 < (dt := b[1] - a[1]) <= p.max_gap and near(a[3], b[3], dt) and near(a[4], b[4], dt)]
    assert got == sorted(want) and len(got) > 200
    plan = links.candidates(materialize(shape, "shape"), p)._jdf.queryExecution().optimizedPlan().toString()
    assert "bx" in plan and plan.count("Generate explode") == 4


def test_crowds_are_written_as_paths(spark):
    shape = shapes.summarize(spark.createDataFrame([(t * density.ID_BASE, t, o, 0.0, 0.0) for t in range(8) for o in range(3)], "cluster_id long, t long, obj_id long, x double, y double"))
    p = Params()
    crowd = chains.closed_crowds(shape, chains.cover(links.build(shape, p)), p)
    r = crowd.orderBy("s_lo").first()
    assert r["crowd_id"] == "-".join(map(str, r["path"])) and r["times"] == [c >> 32 for c in r["path"]] and r["len"] == len(r["path"])
    assert spark.read.parquet(crowd.inputFiles()[0].rsplit("/", 1)[0]).columns == ["path", "s_lo", "s_hi"]
