"""Track views over the given tables: streams of ``fix(obj_id, ts, x, y)`` or ``snap(t, obj_id, x, y)``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.operators import snapshots
from groupflow.sources.tables import load

HOUR = 3_600_000_000
WEEK = 168 * HOUR
#: Microseconds of 2024-01-01, the origin of hourly snapshots.
EVENT_ORIGIN = 1_704_067_200_000_000


def event_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positions of users: value against the property ``k``."""
    events = load(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("double")
    return events.select(F.col("user_id").alias("obj_id"), "ts", F.col("value").alias("x"), k.alias("y"), "event_id").filter(
        "obj_id is not null and ts is not null and x is not null and y is not null"
    )


def hourly_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly interpolated positions of users."""
    return snapshots.interpolate(event_fixes(spark, sf_dir), HOUR, EVENT_ORIGIN)


def lineitem_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts seen at the place of their supplier on their ship dates; sightings of one instant averaged."""
    lines = load(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", F.col("l_shipdate").cast("timestamp").alias("ts"))
    places = load(spark, sf_dir, "supplier").select(
        F.col("s_suppkey").alias("l_suppkey"),
        (F.col("s_acctbal").cast("double") / 100).alias("px"),
        (F.col("s_nationkey") * 4).cast("double").alias("py"),
    )
    return (
        lines.join(places, "l_suppkey")
        .groupBy(F.col("l_partkey").alias("obj_id"), "ts")
        .agg(F.avg("px").alias("x"), F.avg("py").alias("y"))
        .withColumn("event_id", F.lit(0).cast("long"))
    )


def weekly_lineitems(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weekly interpolated positions of parts, over all weeks."""
    fixes = lineitem_fixes(spark, sf_dir)
    low = fixes.agg(F.min(F.unix_micros("ts")).alias("low")).first()["low"] or 0
    return snapshots.interpolate(fixes, WEEK, low // WEEK * WEEK)


def _triangle(v):
    return F.abs(v % 600 - 300)


#: Customers of one district, and the distance of districts.
DISTRICT = 120
APART = 10_000


def planted_walks(spark: SparkSession, sf_dir: str, length: int = 42) -> DataFrame:
    """Walks of all customers in planted groups of four; two of three groups walk together, some with brief separations.

    Customers walk in districts of 120, each on a ground of its own, so that the crowd stays as dense however many they are.
    """
    k = F.col("c_custkey") % DISTRICT
    base = load(spark, sf_dir, "customer").select(
        F.col("c_custkey").alias("obj_id"), k.alias("k"), F.floor(k / 4).alias("g"), F.floor(F.col("c_custkey") / DISTRICT).alias("district")
    )
    base = base.withColumn("a", F.when(F.col("g") % 3 != 2, F.col("g")).otherwise(F.col("k") + 1000))
    rows = base.withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(length - 1).cast("long"))))
    a, t, o = F.col("a"), F.col("t"), F.col("k")
    s = F.when((F.col("g") % 3 == 1) & ((t + F.col("g")) % 9 == 4), 20.0).otherwise(1.0)
    return rows.select(
        "t",
        "obj_id",
        (F.col("district") * APART + (_triangle(a * 377 + (a % 5 + 1) * t) + s * ((o % 4) * 0.6 - 0.9))).alias("x"),
        (_triangle(a * 911 + (a % 7 + 1) * t) + s * ((o * 7 + t) % 3 * 0.2)).alias("y"),
    )


def planted_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``district, group_id, members`` of the planted groups that walk together."""
    k = F.col("c_custkey")
    return (
        load(spark, sf_dir, "customer")
        .groupBy(F.floor(k / DISTRICT).alias("district"), F.floor(k / 4).alias("group_id"))
        .agg(F.sort_array(F.collect_list(k)).alias("members"))
        .filter(F.floor((F.col("group_id") * 4) % DISTRICT / 4) % 3 != 2)
    )


def embedding_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of components as positions one after another: a negative control without groups."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obj_id"), "embedding").filter(F.size("embedding") > 1)
    at = rows.withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.floor(F.size("embedding") / 2) - 1)))
    part = lambda k: F.get("embedding", (F.col("t") * 2 + k).cast("int")).cast("double")
    return at.select("t", "obj_id", part(0).alias("x"), part(1).alias("y"))
