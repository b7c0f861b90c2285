"""The method on a stream of positions.

Every micro-batch holds whole timestamps, later than those before. What a batch needs of the past are the clusters
and links of one window, its verified crowds, the groups of the last window and the open chains that end with them: bounded by
the window, not by the stream. New clusters are compared with ending ones only, and crowds are verified from what is kept
of those before. State and results are written under the batch's
number, a batch that is run again overwrites its own files only, and state older than the batch before is deleted.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.operators import chains, incremental, links, peel
from groupflow.operators.chains import time_of
from groupflow.params import Params
from groupflow.plans.pipeline import clusters
from groupflow.storage import materialize, release, release_path, scratch_path

SNAP = "t long, obj_id long, x double, y double"
GROUP = "win long, group_id string, members array<long>, size int, n_aggs long"
EVO = "win long, src_group string, dst_group string, common long, ratio double"
SHAPE = (
    "cluster_id long, t long, n int, mx double, my double, r double, var double, minx double, maxx double, miny double, maxy double, "
    "objs array<long>, pts array<struct<x: double, y: double>>"
)
LINK = "src long, dst long, dt int, decided_by string"
OPEN = "win long, group_id string, since long"
CLOSED = "group_id string, first_win long, last_win long, n_windows long"
VERIFIED = "crowd_id string, path array<long>, kept array<long>, members array<long>"
CROWD = "crowd_id string, s_lo long, s_hi long, how string"
AGG = "win long, agg_id string, members array<long>"
_STATE = ("shape", "link", "verified", "last_groups", "open")


@dataclass(frozen=True)
class GroupStream:
    """A sink of snapshots: pass :meth:`batch` to ``foreachBatch``. ``out`` is a shared folder."""

    out: str
    p: Params
    plan: str = "auto"

    def _path(self, table: str, number: int) -> str:
        return f"{self.out}/{table}/batch={number}"

    def _read(self, spark: SparkSession, table: str, number: int, schema: str) -> DataFrame:
        return spark.read.schema(schema).parquet(self._path(table, number)) if number >= 0 else spark.createDataFrame([], schema)

    def _range(self, spark: SparkSession, number: int) -> dict:
        """First and last timestamp with clusters before batch ``number``."""
        if number <= 0:
            return {"first": None, "last": None}
        return json.loads(spark.read.text(self._path("range", number - 1)).first()[0])

    def batch(self, snap: DataFrame, number: int) -> None:
        spark, p = snap.sparkSession, self.p
        seen = self._range(spark, number)
        member, new = clusters(snap.select("t", "obj_id", "x", "y"), p, self.plan)
        ends = new.agg(F.min("t").alias("lo"), F.max("t").alias("hi")).first()
        now = {"first": seen["first"], "last": seen["last"]}
        if ends["lo"] is not None:
            if seen["last"] is not None and ends["lo"] <= seen["last"]:
                raise ValueError(f"timestamp {ends['lo']} came after {seen['last']}")
            now = {"first": ends["lo"] if seen["first"] is None else seen["first"], "last": ends["hi"]}
        # windows that end in this batch reach back to here
        since = now["first"] if seen["last"] is None else max(now["first"], seen["last"] - p.w + 2)
        old = self._read(spark, "shape", number - 1, SHAPE)
        shape, link = old.unionByName(new), self._read(spark, "link", number - 1, LINK)
        last = self._read(spark, "last_groups", number - 1, GROUP)
        group, evo = spark.createDataFrame([], GROUP), spark.createDataFrame([], EVO)
        verified = self._read(spark, "verified", number - 1, VERIFIED)
        crowds, aggs = spark.createDataFrame([], CROWD), spark.createDataFrame([], AGG)
        open_, closed, held = self._read(spark, "open", number - 1, OPEN), spark.createDataFrame([], CLOSED), [member, new]
        if ends["lo"] is not None:
            shape = shape.filter(F.col("t") >= since)
            fresh = links.build(shape, p, since=ends["lo"])
            link = materialize(link.filter(time_of(F.col("src")) >= since).unionByName(fresh), "link")
            crowd = chains.closed_crowds(shape, chains.cover(link), p, span=(since, ends["hi"]))
            done = materialize(incremental.verify_step(crowd, shape, verified, p), "verified")
            crowds, verified = done.select("crowd_id", "s_lo", "s_hi", "how"), done.select("crowd_id", "path", "kept", "members").dropDuplicates(["crowd_id"])
            windows = materialize(peel.closed(peel.by_window(incremental.aggregations(done, p))), "windows")
            aggs = windows.select("win", "agg_id", "members")
            group = materialize(peel.groups(windows), "group")
            evo = materialize(incremental.lineage_step(last, group, p.m_g), "evo")
            open_, closed = incremental.chain_step(open_, group, evo, p.k_g, ends["hi"] - p.w + 1)
            last = group.filter(F.col("win") == ends["hi"] - p.w + 1)
            held += [link, crowd, done, windows, group, evo]
        keep = now["last"] - p.w + 2 if now["last"] is not None else 0
        tables = {
            "shape": shape.filter(F.col("t") >= keep),
            "link": link.filter(time_of(F.col("src")) >= keep),
            # a run that a later crowd shares ends with a cluster of the window
            "verified": verified.filter(time_of(F.element_at("path", -1)) >= keep),
            "last_groups": last,
            "crowds": crowds,
            "aggregations": aggs,
            "groups": group,
            "evolution": evo,
            "open": open_,
            "closed": closed,
        }
        for name, df in tables.items():
            df.write.mode("overwrite").parquet(self._path(name, number))
        spark.createDataFrame([(json.dumps(now),)], "value string").coalesce(1).write.mode("overwrite").text(self._path("range", number))
        release(*held)
        if number > 1:
            for name in _STATE:
                release_path(spark, self._path(name, number - 2))

    def groups(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema(GROUP).parquet(f"{self.out}/groups").drop("batch")

    def crowds(self, spark: SparkSession) -> DataFrame:
        """Closed crowds of each batch's windows and how they were verified; one that goes on in the next batch is there again."""
        return spark.read.schema(CROWD).parquet(f"{self.out}/crowds").drop("batch")

    def aggregations(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema(AGG).parquet(f"{self.out}/aggregations").drop("batch")

    def closed(self, spark: SparkSession) -> DataFrame:
        """Evolving groups that came to their end, by their last group."""
        return spark.read.schema(CLOSED).parquet(f"{self.out}/closed").drop("batch")

    def evolution(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema(EVO).parquet(f"{self.out}/evolution").drop("batch")


def run(stream: DataFrame, sink: GroupStream, **trigger) -> None:
    """Feed ``stream`` to ``sink`` until the source is used up, or with the given trigger."""
    query = (
        stream.writeStream.foreachBatch(sink.batch)
        .option("checkpointLocation", f"{sink.out}/offsets")
        .trigger(**(trigger or {"availableNow": True}))
        .start()
    )
    query.awaitTermination()


def replay(snap: DataFrame, n: int) -> DataFrame:
    """A stream that brings ``snap`` in ``n`` batches of consecutive timestamps, one file each."""
    spark = snap.sparkSession
    path = scratch_path(spark, "replay")
    ends = snap.agg(F.min("t").alias("lo"), F.max("t").alias("hi")).first()
    lo, hi = (ends["lo"], ends["hi"]) if ends["lo"] is not None else (0, 0)
    step = -(-(hi - lo + 1) // n)
    for i in range(n):
        part = snap.filter(F.col("t").between(lo + i * step, lo + (i + 1) * step - 1))
        part.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(SNAP).option("maxFilesPerTrigger", 1).parquet(path)


def snapshots(fix: DataFrame, step: str, late: str) -> DataFrame:
    """``t_from, obj_id, x, y`` from a stream of fixes: the last position of each object and interval of length ``step``.

    Repeated fixes (``event_id``) count once; those later than ``late`` behind the newest are dropped. Rows come when
    the watermark passes the interval.
    """
    rows = fix.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    last = F.max_by(F.struct("x", "y"), F.struct("ts", "event_id"))
    return rows.groupBy(F.window("ts", step).alias("w"), "obj_id").agg(last.alias("p")).select(F.col("w.start").alias("t_from"), "obj_id", "p.x", "p.y")
