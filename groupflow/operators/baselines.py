"""The patterns and methods that the moving-group method is compared with."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.operators.peel import bind, frequent
from groupflow.storage import materialize


def strict_crowds(shape: DataFrame, link: DataFrame, k_c: int, max_len: int = 10_000, max_paths: int = 10_000_000) -> DataFrame:
    """``crowd(crowd_id, path, len)``: runs of clusters at consecutive timestamps, each linked with the next, that
    cannot be extended and have at least ``k_c`` clusters. ``link`` is of gap 1; there is no window."""
    step = materialize(link.filter("dt = 1").select("src", "dst"), "steps")
    out = step.groupBy("src").agg(F.count("*").alias("out"))
    heads = shape.select("cluster_id").join(step.select(F.col("dst").alias("cluster_id")), "cluster_id", "left_anti")
    paths = heads.select(F.array("cluster_id").alias("path"), F.col("cluster_id").alias("src"))
    done, n = None, 1
    while n <= max_len:
        paths = materialize(paths.join(out, "src", "left"), "strict")
        ended = paths.filter("out is null").select("path", F.lit(n).alias("len"))
        if n >= k_c:
            done = ended if done is None else done.unionByName(ended)
        ahead = paths.agg(F.sum("out").alias("n")).first()["n"] or 0
        if not ahead:
            break
        if ahead > max_paths:
            raise RuntimeError(f"about {ahead} strict chains; raise max_paths or tighten d or m_c")
        paths = paths.drop("out").join(step, "src").select(F.array_append("path", F.col("dst")).alias("path"), F.col("dst").alias("src"))
        n += 1
    if done is None:
        return shape.sparkSession.createDataFrame([], "crowd_id string, path array<long>, len int")
    return done.select(F.concat_ws("-", F.col("path").cast("array<string>")).alias("crowd_id"), "path", "len")


def _valid(chain, k_p: int, m_p: int):
    real = frequent(F.flatten(F.transform(chain, lambda c: c["objs"])), k_p)
    return bind(real, lambda r: F.transform(chain, lambda c: F.size(F.array_intersect(c["objs"], r)) >= m_p))


def gatherings(crowd: DataFrame, shape: DataFrame, k_p: int, m_p: int) -> DataFrame:
    """Crowds whose every cluster has ``m_p`` participators (objects in at least ``k_p`` of its clusters)."""
    rows = chains_with_members(crowd, shape)
    return rows.filter(F.forall(_valid(F.col("chain"), k_p, m_p), lambda v: v)).select(
        "crowd_id", F.col("chain.cluster_id").alias("path"), F.size("chain").alias("len")
    )


def chains_with_members(crowd: DataFrame, shape: DataFrame) -> DataFrame:
    """``crowd_id, chain``: the clusters of each crowd with their objects, in time order."""
    rows = crowd.select("crowd_id", F.explode("path").alias("cluster_id"))
    return (
        rows.join(shape.select("cluster_id", "objs"), "cluster_id")
        .groupBy("crowd_id")
        .agg(F.array_sort(F.collect_list(F.struct("cluster_id", "objs"))).alias("chain"))
    )


def cut_at_invalid(crowd: DataFrame, shape: DataFrame, k_c: int, k_p: int, m_p: int, max_rounds: int = 10_000) -> DataFrame:
    """Closed gatherings: a crowd with invalid clusters is cut at them, and the runs of at least ``k_c`` clusters are
    tested again, until all that is left is a gathering."""
    now = chains_with_members(crowd, shape).select("chain").withColumn("n", F.size("chain"))
    done = None
    for _ in range(max_rounds):
        now = materialize(now.withColumn("valid", _valid(F.col("chain"), k_p, m_p)), "divide")
        whole = now.filter(F.forall("valid", lambda v: v)).select("chain")
        done = whole if done is None else done.unionByName(whole)
        rest = now.filter(F.exists("valid", lambda v: ~v)).withColumn("id", F.monotonically_increasing_id())
        if rest.isEmpty():
            break
        at = rest.select("id", F.posexplode(F.arrays_zip("chain", "valid")).alias("pos", "c")).filter("c.valid")
        # runs of kept clusters: their place minus their number among the kept ones does not change inside a run
        kept = F.row_number().over(_by_id())
        run = at.withColumn("run", F.col("pos") - kept)
        now = (
            run.groupBy("id", "run")
            .agg(F.array_sort(F.collect_list("c.chain")).alias("chain"), F.count("*").alias("n"))
            .filter(F.col("n") >= k_c)
            .select("chain", "n")
        )
    return done.select(F.concat_ws("-", F.col("chain.cluster_id").cast("array<string>")).alias("crowd_id"), F.col("chain.cluster_id").alias("path")).distinct()


def _by_id():
    from pyspark.sql import Window

    return Window.partitionBy("id").orderBy("pos")


_CONVOY = "objs array<long>, first_t long, last_t long"
_HELD = "t long, objs array<long>, clusters array<long>, twice boolean"
_STATE = "kind int, lane long, first_t long, last_t long, objs array<long>, at array<long>, sets array<long>"
_LIVE, _PLACED, _ENDED = 0, 1, 2
_STATES = 4_000_000  # objects in the sets of a lane
_TOLD = 1 << 20  # objects of convoys that are given at once


def _rows_of(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows with their lists as numpy arrays."""
    for batch in batches:
        columns = {}
        for name, column in zip(batch.schema.names, batch.columns):
            if pa.types.is_list(column.type):
                column = column.fill_null([])
                flat, ends = column.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(pc.list_value_length(column).to_numpy())])
                columns[name] = [flat[i:j] for i, j in zip(ends, ends[1:])]
            else:
                columns[name] = column.to_pylist()
        for i in range(batch.num_rows):
            yield {name: column[i] for name, column in columns.items()}


def _lists(values: list[np.ndarray]) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, values)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.empty(0, np.int64), *values])))


def _snapshots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each timestamp, from rows in order of t: objects in order, and their clusters by number."""

    def packed(rows: list[pa.RecordBatch]) -> pa.RecordBatch:
        t, obj, cluster = (np.concatenate([r.column(i).to_numpy() for r in rows]) for i in range(3))
        order = np.lexsort((obj, t))
        t, obj, cluster = t[order], obj[order], cluster[order]
        starts = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
        some = [slice(i, j) for i, j in zip(starts, [*starts[1:], len(t)])]
        twice = [bool((obj[i][1:] == obj[i][:-1]).any()) for i in some]
        number = [np.unique(cluster[i], return_inverse=True)[1].astype(np.int64) for i in some]
        return pa.RecordBatch.from_arrays([pa.array(t[starts]), _lists([obj[i] for i in some]), _lists(number), pa.array(twice)], ["t", "objs", "clusters", "twice"])

    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        t = batch.column(0).to_numpy()
        if held and held[0].column(0)[0].as_py() != t[-1]:
            cut = int(np.searchsorted(t, t[-1]))
            yield packed([*held, batch.slice(0, cut)] if cut else held)
            held, batch = [], batch.slice(cut)
        elif not held and t[0] != t[-1]:
            cut = int(np.searchsorted(t, t[-1]))
            yield packed([batch.slice(0, cut)])
            batch = batch.slice(cut)
        held.append(batch)
    if held:
        yield packed(held)


class _Sets:
    """The sets of one start time that still live: objects with their places, sets one after another.

    All objects of a start time have a place. Places of a set are a run, and its parts are runs inside it: however a set is
    parted later, its objects stand at the places it had.
    """

    def __init__(self, objs: np.ndarray, size: np.ndarray, place: np.ndarray):
        self.objs, self.size, self.place = objs, size, place

    def part(self, cluster: np.ndarray, m: int) -> tuple[_Sets, np.ndarray, np.ndarray]:
        """The parts of ``m`` objects in one cluster (-1: in none), the size of the largest one of each set, and with their places the objects in none."""
        # places of a set are dealt anew in the order of its parts
        wide = int(cluster.max(initial=0)) + 2
        key = np.repeat(np.arange(len(self.size)) * wide, self.size) + (cluster + 1)
        order = np.argsort(key, kind="stable")
        objs, key = self.objs[order], key[order]
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.empty(0, np.int64)
        size = np.diff(np.r_[starts, len(key)])
        of = key[starts] // wide
        place = self.place[of] + starts - (np.cumsum(self.size) - self.size)[of]
        lives = (size >= m) & (key[starts] % wide > 0)
        largest = np.zeros(len(self.size), np.int64)
        np.maximum.at(largest, of[lives], size[lives])
        keep = np.repeat(lives, size)
        at = np.repeat((place - starts)[~lives], size[~lives]) + np.flatnonzero(~keep)
        return _Sets(objs[keep], size[lives], place[lives]), largest, np.stack([objs[~keep], at])


def _carry(m: int, k: int, slice_: int, n: int, hi: int):
    """Round ``n``: one slice of time further for the sets of a lane, the start times of a slice and the one before.

    Rows come by lanes: the sets that live, then the timestamps. Given are sets that live at the last timestamp of the slice, objects
    that no set holds any more with their places, and the convoys that came to their end, by place and size.
    """

    def row(kind: int, lane: int, first: int, last: int, *lists: np.ndarray) -> pa.RecordBatch:
        lists = [*lists, *[np.empty(0, np.int64)] * (3 - len(lists))]
        return pa.RecordBatch.from_arrays(
            [pa.array([kind], pa.int32()), *[pa.array([int(v)], pa.int64()) for v in (lane, first, last)], *[_lists([v]) for v in lists]],
            ["kind", "lane", "first_t", "last_t", "objs", "at", "sets"],
        )

    def step(lane: int, now: dict[int, _Sets], t: int, obj: np.ndarray, cluster: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Replaces the sets of ``now``, live at ``t - 1``, by those that live at ``t``."""
        own, before = lane * slice_, (None, None)
        for f in sorted(now):
            sets = now[f]
            at = np.minimum(np.searchsorted(obj, sets.objs), max(len(obj) - 1, 0))
            found = np.where(obj[at] == sets.objs, cluster[at], -1) if len(obj) else np.full(len(sets.objs), -1)
            now[f], largest, gone = sets.part(found, m)
            if not len(now[f].objs):
                del now[f]
            before, earlier = (f, sets), before[1] if before[0] == f - 1 else None
            if f < own:
                continue
            if gone.size:
                yield row(_PLACED, lane, f, t - 1, *gone)
            ended = np.flatnonzero(sets.size > largest) if t - f >= k else np.empty(0, np.int64)
            if len(ended) and earlier is not None:
                # the earlier set of an object is part of its set from f on: the same where it is as large
                first = sets.objs[(np.cumsum(sets.size) - sets.size)[ended]]
                order = np.argsort(first)
                at = np.minimum(np.searchsorted(first[order], earlier.objs), len(first) - 1)
                hit = np.flatnonzero(first[order][at] == earlier.objs)
                size = np.zeros(len(first), np.int64)
                size[order[at[hit]]] = earlier.size[np.searchsorted(np.cumsum(earlier.size), hit, side="right")]
                ended = ended[size != sets.size[ended]]
            if len(ended):
                yield row(_ENDED, lane, f, t - 1, sets.size[ended], sets.place[ended])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lane, now, t = None, {}, 0
        none = np.empty(0, np.int64)

        def close() -> Iterator[pa.RecordBatch]:
            """The rest of the slice, without clusters; after the last timestamp of all nothing lives on."""
            nonlocal t
            end = min((lane + n + 1) * slice_ - 1, hi)
            while now and t <= (hi + 1 if end == hi else end):
                yield from step(lane, now, t, none, none)
                t += 1
            for f, sets in now.items():
                yield row(_LIVE, lane, f, end, sets.objs, sets.place, sets.size)

        for r in _rows_of(batches):
            if r["lane"] != lane:
                if lane is not None:
                    yield from close()
                lane, now, t = r["lane"], {}, (r["lane"] + n) * slice_ - (n == 0)
            if r["t"] is None:
                now[r["first_t"]] = _Sets(r["objs"].copy(), r["sets"].copy(), r["at"].copy())
                continue
            while t < r["t"]:
                yield from step(lane, now, t, none, none)
                t += 1
            yield from step(lane, now, t, r["objs"], r["clusters"])
            if n == 0:
                # a start: the clusters themselves
                now[t], _, gone = _Sets(r["objs"], np.array([len(r["objs"])]), np.array([0])).part(r["clusters"], m)
                if gone.size and t >= lane * slice_:
                    yield row(_PLACED, lane, t, t, *gone)
            t += 1
        if lane is not None:
            yield from close()

    return run


def _told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Convoys with their objects, from the places of all objects of a start time; rows come by start times."""

    def expand(first: int, rows: list[dict]) -> Iterator[pa.RecordBatch]:
        ended = [r for r in rows if r["kind"] == _ENDED]
        if not ended:
            return
        placed = [r for r in rows if r["kind"] == _PLACED]
        place = np.empty(sum(len(r["at"]) for r in placed), np.int64)
        for r in placed:
            place[r["at"]] = r["objs"]
        objs, last, held = [], [], 0
        for r in ended:
            for size, at in zip(r["objs"].tolist(), r["at"].tolist()):
                objs.append(np.sort(place[at : at + size]))
                last.append(r["last_t"])
                held += size
                if held >= _TOLD:
                    yield pa.RecordBatch.from_arrays([_lists(objs), pa.array([first] * len(last)), pa.array(last)], ["objs", "first_t", "last_t"])
                    objs, last, held = [], [], 0
        if objs:
            yield pa.RecordBatch.from_arrays([_lists(objs), pa.array([first] * len(last)), pa.array(last)], ["objs", "first_t", "last_t"])

    first, rows = None, []
    for r in _rows_of(batches):
        if r["first_t"] != first:
            if rows:
                yield from expand(first, rows)
            first, rows = r["first_t"], []
        rows.append(r)
    if rows:
        yield from expand(first, rows)


def convoys(member: DataFrame, m: int, k: int, slice_: int | None = None) -> DataFrame:
    """``convoy(objs, first_t, last_t)``: at least ``m`` objects in one cluster at ``k`` or more consecutive timestamps.

    Sets shrink as they are carried from snapshot to snapshot; a convoy is given when its set no longer lives on
    unchanged, unless the same set was together a timestamp before it. Where an object is in one cluster of a timestamp at most,
    the sets of a start time are disjoint, and no other set can hold a convoy for its whole life. Start times go by lanes of ``slice_``
    timestamps (48, fewer where snapshots are large); a round carries each lane that still has a set one slice on. Written are live sets, each object
    of a start time once with its place, and convoys by place and size: their objects are listed as the result is read.
    """
    spark = member.sparkSession
    rows = member.select(F.col("t").cast("long"), F.col("obj_id").cast("long"), F.col("cluster_id").cast("long"))
    snaps = materialize(rows.repartition("t").sortWithinPartitions("t").mapInArrow(_snapshots, _HELD), "sets")
    ends = snaps.agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.max(F.size("objs")).alias("n"), F.max("twice").alias("twice")).first()
    if ends["lo"] is None:
        return spark.createDataFrame([], _CONVOY)
    if ends["twice"]:
        return _overlapping(member, m, k)
    slice_ = slice_ or max(1, min(48, _STATES // ends["n"]))
    live, found, n = None, None, 0
    while True:
        # round n carries lane s over slice s + n; its first one starts with the timestamp before the lane
        lane = F.explode(F.array_distinct(F.array(*[F.floor((F.col("t") + d) / slice_).cast("long") - n for d in ((0, 1) if n == 0 else (0,))])))
        held = snaps.select("t", lane.alias("lane"), "objs", "clusters").filter(F.col("lane") >= ends["lo"] // slice_)
        if live is None:
            held = held.select("lane", "t", F.lit(None).cast("long").alias("first_t"), "objs", "clusters", *[F.lit(None).cast("array<long>").alias(c) for c in ("at", "sets")])
        else:
            held = held.join(F.broadcast(live.select("lane").distinct()), "lane", "left_semi")
            held = held.select("lane", "t", "objs", "clusters").unionByName(live.select("lane", "first_t", "objs", "at", "sets"), allowMissingColumns=True)
        dealt = held.repartition("lane").sortWithinPartitions("lane", F.col("t").asc_nulls_first(), "first_t")
        step = materialize(dealt.mapInArrow(_carry(m, k, slice_, n, ends["hi"]), _STATE), "convoys")
        over = step.filter(F.col("kind") != _LIVE).select("kind", "first_t", "last_t", "objs", "at")
        found = over if found is None else found.unionByName(over)
        live = step.filter(F.col("kind") == _LIVE)
        if live.isEmpty():
            break
        n += 1
    return found.repartition("first_t").sortWithinPartitions("first_t").mapInArrow(_told, _CONVOY)


def _overlapping(member: DataFrame, m: int, k: int, max_len: int = 10_000) -> DataFrame:
    """:func:`convoys` where an object may be in several clusters of a timestamp: sets inside a larger one of the same or
    longer life are found by joining them."""
    sets = materialize(
        member.groupBy("t", "cluster_id").agg(F.array_sort(F.collect_set("obj_id")).alias("objs")).filter(F.size("objs") >= m).select("t", "objs"),
        "sets",
    )
    live = sets.select(F.col("t").alias("first_t"), F.col("t").alias("last_t"), "objs")
    found, n = None, 1
    while n <= max_len:
        live = materialize(live, "convoys")
        if n >= k:
            found = live if found is None else found.unionByName(live)
        flat = live.withColumn("obj", F.explode("objs")).withColumn("t", F.col("last_t") + 1)
        nxt = sets.select("t", F.col("objs").alias("other"), F.explode("objs").alias("obj"))
        grown = (
            flat.join(nxt, ["t", "obj"])
            .groupBy("first_t", "objs", "t", "other")
            .agg(F.array_sort(F.collect_set("obj")).alias("both"))
            .filter(F.size("both") >= m)
            .select("first_t", F.col("t").alias("last_t"), F.col("both").alias("objs"))
            .distinct()
        )
        live = grown
        if live.isEmpty():
            break
        n += 1
    if found is None:
        return member.sparkSession.createDataFrame([], "objs array<long>, first_t long, last_t long")
    found = materialize(found.select("objs", "first_t", "last_t").distinct(), "convoys")
    other = found.select(F.explode("objs").alias("o"), F.col("objs").alias("big"), F.col("first_t").alias("f2"), F.col("last_t").alias("l2"))
    inside = (
        found.withColumn("o", F.element_at("objs", 1))
        .join(other, "o")
        .filter("f2 <= first_t and l2 >= last_t and (f2 < first_t or l2 > last_t or size(big) > size(objs))")
        .filter(F.size(F.array_intersect("objs", "big")) == F.size("objs"))
        .select("objs", "first_t", "last_t")
    )
    return found.join(inside, ["objs", "first_t", "last_t"], "left_anti")
