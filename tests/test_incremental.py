"""The incremental steps and the stream give what the batch plan gives."""

import random

import pytest
from pyspark.sql import functions as F
from test_groups import crowds_of, member_of

from groupflow.operators import baselines, incremental, lineage, links, peel, shapes
from groupflow.operators.density import ID_BASE
from groupflow.params import Params
from groupflow.plans.pipeline import discover
from groupflow.storage import materialize
from groupflow.streaming import engine

FX1 = {"B": (1, 2.0), "X": (1, 3.5), "C": (2, 0.0), "D": (3, 1.0), "E": (4, 2.0), "F": (5, 2.0), "G": (5, 0.0)}


def test_status_trace(spark):
    p = Params(w=4, k_c=3, d=1.0, m_c=3, k_p=1, m_p=1)
    clusters, label = [], {}
    for i, (n, (t, y)) in enumerate(FX1.items()):
        clusters.append((t, [(10 * i + k, 0.0, y) for k in range(3)]))
        label[t * ID_BASE + 10 * i] = n
    shape = materialize(shapes.summarize(member_of(spark, clusters)))
    state, trace, closed = None, {}, {}
    for t in range(1, 6):
        state, status = incremental.crowd_step(state, shape.filter(F.col("t") == t), t, p)
        trace[t] = {label[r["tail"]]: r["status"] for r in status.collect()}
        closed[t] = sorted("".join(label[c] for c in r["path"]) for r in incremental.crowds(state, p).collect())
    assert trace[2] == {"B": "unmatched", "X": "unmatched"}
    assert trace[3] == {"B": "match", "X": "unmatched", "C": "match"}
    assert trace[4]["D"] == "match" and trace[5] == {"E": "match"}
    assert closed == {1: [], 2: [], 3: [], 4: ["BDE", "CDE"], 5: ["CDEF", "CDG"]}


def test_steps_equal_batch(spark):
    p = Params(w=5, k_c=3, d=1.5, m_c=1, k_p=1, m_p=1)
    rnd = random.Random(5)
    clusters = [(t, [(10 * i, rnd.uniform(0, 6), rnd.uniform(0, 2))]) for t in (1, 2, 3, 4, 6, 7, 8, 9) for i in range(rnd.randint(1, 3))]
    shape, _, crowd = crowds_of(spark, clusters, p)
    want = {(w, r["crowd_id"]) for r in crowd.collect() for w in range(r["s_lo"], r["s_hi"] + 1)}
    state, got = None, set()
    for t in range(1, 10):
        state, _ = incremental.crowd_step(state, shape.filter(F.col("t") == t), t, p)
        got |= {(r["win"], r["crowd_id"]) for r in incremental.crowds(state, p).collect()}
    assert want and got == want


@pytest.mark.parametrize("newest, fell_back", [({2, 3, 5}, False), ({70, 71, 72}, True)])
def test_peel_step_equals_peeling(spark, newest, fell_back):
    p = Params(w=8, k_c=3, k_p=5, m_p=3, d=1.0, m_c=3)
    sets = {1: {1, 2, 3, 6}, 2: {1, 2, 3, 5, 6}, 3: {1, 4, 6}, 4: {2, 3, 5, 6}, 5: {1, 2, 3, 5}, 7: {1, 2, 3, 4, 5}, 8: {1, 2, 3, 5, 6}, 9: newest}
    shape = materialize(shapes.summarize(member_of(spark, [(t, [(o, 0, 0) for o in s]) for t, s in sets.items()])))
    ids = {t: t * ID_BASE + min(s) for t, s in sets.items()}
    old, new = [ids[t] for t in sets if t < 9], [ids[t] for t in sets if t > 1]
    crowd = spark.createDataFrame([("old", None, old), ("new", "old", new)], "crowd_id string, parent_id string, path array<long>")
    rows = baselines.chains_with_members(crowd, shape).join(crowd.select("crowd_id", "parent_id"), "crowd_id")
    nothing = spark.createDataFrame([], "crowd_id string, path array<long>")
    before = incremental.peel_step(rows.filter("crowd_id = 'old'"), nothing, p)
    reused = incremental.peel_step(rows.filter("crowd_id = 'new'"), before, p).first()
    scratch = incremental.peel_step(rows.filter("crowd_id = 'new'"), nothing, p).first()
    assert reused["fell_back"] is fell_back and not scratch["fell_back"]
    assert (reused["path"], reused["members"]) == (scratch["path"], scratch["members"]) and reused["path"]
    # counts of participators: only the expired and the new cluster are counted
    every = peel.participators(crowd, shape, 1)
    change = spark.createDataFrame([("new", "old", old[:1], new[-1:])], "crowd_id string, parent_id string, expired array<long>, arrived array<long>")
    step = incremental.participator_step(every.filter("crowd_id = 'old'"), change, shape)
    assert sorted(map(tuple, step.collect())) == sorted(map(tuple, every.filter("crowd_id = 'new'").collect()))


def test_verify_step_equals_peeling(spark):
    """Random crowds of a window that slides: reuse of each kind gives what peeling from scratch gives."""
    p = Params(w=6, k_c=3, k_p=3, m_p=2, d=1.0, m_c=1)
    rnd, seen = random.Random(3), set()
    for empty in (None, 7, 6):
        # where only one object is left, the newest cluster is in no aggregation
        clusters = {t: {o for o in range(1, 7) if t != empty and rnd.random() < 0.55} | {0} for t in range(12)}
        shape = materialize(shapes.summarize(member_of(spark, [(t, [(o, 0, 0) for o in s]) for t, s in clusters.items()])))
        ids = [t * ID_BASE for t in clusters]
        before = spark.createDataFrame([], engine.VERIFIED)
        for lo, hi in ((0, 6), (1, 6), (1, 7), (2, 8), (2, 8), (6, 12)):
            crowd = spark.createDataFrame([("-".join(map(str, ids[lo:hi])), ids[lo:hi], lo, lo)], "crowd_id string, path array<long>, s_lo long, s_hi long")
            done = materialize(incremental.verify_step(crowd, shape, before, p), "done")
            want = peel.peel(crowd, shape, p).collect()
            got = incremental.aggregations(done, p).collect()
            assert [(r["agg_id"], r["path"], r["members"], r["s_lo"]) for r in got] == [(r["agg_id"], r["path"], r["members"], r["s_lo"]) for r in want]
            seen |= {r["how"] for r in done.select("how").collect()}
            before = done.select("crowd_id", "path", "kept", "members")
    assert seen == {"same", "cut", "fell_back", "whole"}


def _walks(spark):
    rnd = random.Random(11)
    rows = [(t, o, 10.0 * (o // 4) + rnd.uniform(0, 1) + (30 if rnd.random() < 0.1 else 0), rnd.uniform(0, 1)) for t in range(12) for o in range(12)]
    # the first four part for good
    rows = [(t, o, x + 200.0 * (o + 1) if o < 4 and t > 6 else x, y) for t, o, x, y in rows]
    return spark.createDataFrame(rows, engine.SNAP)


def test_stream_equals_batch_and_repeats(spark, tmp_path):
    p = Params(eps=2.0, min_pts=2, w=4, k_c=3, m_c=2, k_p=2, m_p=2, d=3.0, m_g=0.5, k_g=1)
    snap = _walks(spark)
    found = discover(snap, p, plan="snapshot")
    sink = engine.GroupStream(f"file://{tmp_path}/out", p, "snapshot")
    for number, (lo, hi) in enumerate([(0, 4), (5, 5), (6, 11)]):
        sink.batch(snap.filter(F.col("t").between(lo, hi)), number)
    sink.batch(snap.filter(F.col("t").between(6, 11)), 2)  # run again after a failure
    key = lambda df: sorted((r["win"], r["group_id"], r["n_aggs"]) for r in df.collect())
    assert key(sink.groups(spark)) == key(found.group) and found.group.count() > 3
    crowds = sink.crowds(spark).collect()
    assert {(r["crowd_id"], w) for r in crowds for w in range(r["s_lo"], r["s_hi"] + 1)} == {
        (r["crowd_id"], w) for r in found.crowd.collect() for w in range(r["s_lo"], r["s_hi"] + 1)
    }
    assert {r["how"] for r in crowds} <= {"same", "cut", "fell_back", "whole"}
    aggs = lambda df: sorted((r["win"], r["agg_id"], r["members"]) for r in df.collect())
    assert aggs(sink.aggregations(spark)) == aggs(found.windows)
    edges = lambda df: sorted((r["src_group"], r["dst_group"], r["common"]) for r in df.collect())
    assert edges(sink.evolution(spark)) == edges(found.evo)
    deep = lineage.depths(found.group, found.evo).filter("depth_out = 1")
    want = {(r["group_id"], r["win"], r["depth_in"]) for r in deep.collect() if r["win"] < 11 - p.w + 1}
    assert {(r["group_id"], r["last_win"], r["n_windows"]) for r in sink.closed(spark).collect()} == want and want
    with pytest.raises(ValueError):
        sink.batch(snap.filter("t = 3"), 3)
    # state of the last two batches only
    assert sorted(x.name for x in (tmp_path / "out/shape").iterdir() if x.name.startswith("batch=")) == ["batch=1", "batch=2"]


def test_a_step_compares_new_with_ending_clusters(spark):
    clusters = [(t, [(10 * i, float(i), 0.0)]) for t in range(6) for i in range(4)]
    shape = materialize(shapes.summarize(member_of(spark, clusters)))
    p = Params(w=5, k_c=3, d=1.5, m_c=1, k_p=1, m_p=1)
    pairs = links.candidates(shape, p, "none", since=5).select("a.t", F.col("b.t").alias("u")).collect()
    assert len(pairs) == 4 * 4 * p.max_gap and {r["u"] for r in pairs} == {5} and {r["t"] for r in pairs} == {2, 3, 4}


def test_stream_without_rows(spark, tmp_path):
    sink = engine.GroupStream(f"file://{tmp_path}/out", Params(), "snapshot")
    empty = spark.createDataFrame([], engine.SNAP)
    sink.batch(empty, 0)
    sink.batch(empty, 1)
    assert sink.groups(spark).count() == 0


def test_stream_snapshots_drop_late_and_repeated(spark, tmp_path):
    schema = "event_id long, obj_id long, ts timestamp, x double, y double"
    parts = [[(1, 1, 5, 1.0), (2, 1, 20, 2.0), (2, 1, 20, 2.0)], [(3, 1, 130, 3.0)], [(4, 1, 10, 9.0)], [(5, 1, 400, 5.0)]]
    for rows in parts:
        df = spark.createDataFrame(rows, "event_id long, obj_id long, m long, x double")
        ts = F.timestamp_seconds(F.lit(1_704_067_200) + F.col("m") * 60)
        df.select("event_id", "obj_id", ts.alias("ts"), "x", F.lit(0.0).alias("y")).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/in")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/in")
    query = engine.snapshots(stream, "1 hour", "30 minutes").writeStream.format("memory").queryName("snaps").outputMode("append")
    query.option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start().awaitTermination()
    assert sorted((r["x"]) for r in spark.table("snaps").collect()) == [2.0, 3.0]


def test_depths(spark):
    group = spark.createDataFrame([(w, g) for g, w in {"a": 1, "b": 2, "c": 2, "d": 3, "e": 4, "z": 4}.items()], "win long, group_id string")
    evo = spark.createDataFrame([("a", "b"), ("b", "d"), ("c", "d"), ("d", "e")], "src_group string, dst_group string")
    got = {r["group_id"]: (r["depth_in"], r["depth_out"]) for r in lineage.depths(group, evo).collect()}
    assert got == {"a": (1, 4), "b": (2, 3), "c": (1, 3), "d": (3, 2), "e": (4, 1), "z": (1, 1)}
