"""Space parts of balanced load: rings around the centre, cut into sectors.

Every timestamp has its own parts. A cluster's home is the part of its mean; a later cluster looks only into the
parts that its circle, widened by the allowed distance, meets. Where two clusters are linked, the mean of the earlier
one is in that circle, because it is in the hull of its points; so each linked pair meets in one part, and just once.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

_TURN = 2 * math.pi
_SLACK = 1e-9


def ring_count(n_parts: int) -> int:
    """Rings for ``n_parts`` parts: the largest divisor up to the root, so that all rings have equally many sectors."""
    if n_parts < 1:
        raise ValueError("n_parts is at least 1")
    return max(k for k in range(1, math.isqrt(n_parts) + 1) if n_parts % k == 0)


def center(shape: DataFrame) -> tuple[float, float]:
    """The middle of the box of all means; the origin where there are none."""
    r = shape.agg(((F.min("mx") + F.max("mx")) / 2).alias("x"), ((F.min("my") + F.max("my")) / 2).alias("y")).first()
    return (r["x"] or 0.0, r["y"] or 0.0)


def polar(shape: DataFrame, middle: tuple[float, float]) -> DataFrame:
    """``shape`` with ``rho`` and ``theta`` (0 to 2 pi) of its means about ``middle``."""
    dx, dy = F.col("mx") - F.lit(middle[0]), F.col("my") - F.lit(middle[1])
    angle = F.atan2(dy, dx)
    return shape.withColumns({"rho": F.sqrt(dx * dx + dy * dy), "theta": F.when(angle < 0, angle + _TURN).otherwise(angle)})


def _cuts(rows: DataFrame, keys: list[str], value: str, n: int, name: str, how: str) -> DataFrame:
    """``keys, name, lo, hi``: ``n`` intervals of equal load that cover the whole axis from 0 on."""
    if how == "exact":
        order = Window.partitionBy(*keys).orderBy(value, "cluster_id")
        low = rows.select(*keys, value, F.ntile(n).over(order).alias(name)).groupBy(*keys, name).agg(F.min(value).alias("lo"))
    elif how == "approx":
        at = F.array(*[F.lit(i / n) for i in range(n)])
        low = rows.groupBy(*keys).agg(F.percentile_approx(value, at, F.lit(10_000)).alias("q"))
        low = low.select(*keys, F.posexplode("q").alias(name, "lo")).withColumn(name, F.col(name) + 1)
    else:
        raise ValueError("how is 'exact' or 'approx'")
    order = Window.partitionBy(*keys).orderBy(name)
    return low.select(
        *keys, name, F.when(F.col(name) == 1, 0.0).otherwise(F.col("lo")).alias("lo"), F.lead("lo", 1, math.inf).over(order).alias("hi")
    )


def rings(points: DataFrame, n_rings: int, how: str = "exact") -> DataFrame:
    """``t, ring, r_lo, r_hi``: rings of equally many clusters of each timestamp.

    ``'exact'`` sorts the radii of a timestamp, ``'approx'`` takes mergeable quantile sketches and never
    gathers a timestamp's clusters.
    """
    return _cuts(points, ["t"], "rho", n_rings, "ring", how).withColumnsRenamed({"lo": "r_lo", "hi": "r_hi"})


def in_ring(points: DataFrame, ring: DataFrame) -> DataFrame:
    """``points`` with the ring that holds their mean. A timestamp has few rings, so they join as one array."""
    one = ring.groupBy("t").agg(F.array_sort(F.collect_list(F.struct("ring", "r_lo", "r_hi"))).alias("all"))
    held = F.filter("all", lambda g: (g["r_lo"] <= F.col("rho")) & (F.col("rho") < g["r_hi"]))
    return points.join(one, "t").withColumn("ring", F.get(held, F.lit(0))["ring"]).drop("all")


def parts(points: DataFrame, ring: DataFrame, per_ring: int, how: str = "exact") -> DataFrame:
    """``t, parts``: an array of ``part, ring, r_lo, r_hi, a_lo, a_hi`` for each timestamp."""
    cut = _cuts(in_ring(points, ring), ["t", "ring"], "theta", per_ring, "sector", how)
    # a ring in which nothing lies (equal radii) holds no home either, and needs no sector
    rows = cut.join(ring, ["t", "ring"]).select(
        "t",
        F.struct(
            ((F.col("ring") - 1) * per_ring + F.col("sector") - 1).alias("part"),
            "ring",
            "r_lo",
            "r_hi",
            F.col("lo").alias("a_lo"),
            F.col("hi").alias("a_hi"),
        ).alias("p"),
    )
    return rows.groupBy("t").agg(F.array_sort(F.collect_list("p")).alias("parts"))


def divide(points: DataFrame, n_parts: int, how: str = "exact") -> DataFrame:
    """The parts of every timestamp, from ``points`` with polar means."""
    n = ring_count(n_parts)
    return parts(points, rings(points, n, how), n_parts // n, how)


def _holds(p: Column) -> Column:
    rho, theta = F.col("rho"), F.col("theta")
    return (p["r_lo"] <= rho) & (rho < p["r_hi"]) & (p["a_lo"] <= theta) & (theta < p["a_hi"])


def _meets(p: Column, reach: Column) -> Column:
    """Whether a circle of radius ``reach`` about the mean may meet the part; never false where it does."""
    rho, theta = F.col("rho"), F.col("theta")
    wide = reach * (1 + _SLACK) + _SLACK
    half = F.when(wide >= rho, F.lit(math.pi)).otherwise(F.asin(wide / rho)) + _SLACK
    turn = None
    for k in (-1, 0, 1):
        one = (theta - half + k * _TURN < p["a_hi"]) & (theta + half + k * _TURN >= p["a_lo"])
        turn = one if turn is None else turn | one
    return (rho + wide >= p["r_lo"]) & (rho - wide <= p["r_hi"]) & turn


def home(points: DataFrame, part: DataFrame) -> DataFrame:
    """``points`` with ``part``, the one that holds their mean."""
    found = F.get(F.filter("parts", _holds), F.lit(0))["part"]
    return points.join(part, "t").withColumn("part", found).drop("parts")


def reached(points: DataFrame, part: DataFrame, reach: Column, at: Column) -> DataFrame:
    """``points`` with ``met``, the parts of timestamp ``at`` that their widened circle meets."""
    then = part.select(F.col("t").alias("part_t"), "parts")
    met = F.transform(F.filter("parts", lambda p: _meets(p, reach)), lambda p: p["part"])
    return points.withColumn("part_t", at).join(then, "part_t").withColumn("met", met).drop("parts", "part_t")


def halo_width(d: float, dt: Column, halo: str) -> Column:
    """``'gap'``: the distance allowed at the time gap; ``'printed'``: that of one timestamp, which misses links of longer gaps."""
    if halo == "gap":
        return F.lit(d) * dt
    if halo == "printed":
        return F.lit(d)
    raise ValueError("halo is 'gap' or 'printed'")


def assign(points: DataFrame, part: DataFrame, d: float, dt: int = 1, halo: str = "gap") -> DataFrame:
    """``cluster_id, t, kind, met``: clusters against the parts of ``dt`` timestamps before.

    Kind 1 lies in one part and outside all boundary zones; kind 2 meets several.
    """
    reach = F.col("r") + halo_width(d, F.lit(dt), halo)
    return reached(points, part, reach, F.col("t") - dt).select(
        "cluster_id", "t", F.when(F.size("met") <= 1, 1).otherwise(2).alias("kind"), "met"
    )


def update(before: DataFrame, points: DataFrame, n_parts: int, tolerance: float = 1.5, how: str = "exact") -> tuple[DataFrame, bool]:
    """Parts of a new timestamp and whether they have new radii.

    The radii of ``before`` (rings of the timestamp before) stay while the fullest ring holds at most ``tolerance``
    times the mean load; the sectors are always cut anew.
    """
    n = ring_count(n_parts)
    now = points.agg(F.max("t").alias("t")).first()["t"]
    kept = before.withColumn("t", F.lit(now))
    load = in_ring(points, kept).groupBy("ring").count().agg((F.max("count") * n / F.sum("count")).alias("load")).first()["load"]
    anew = load is None or load > tolerance
    return parts(points, rings(points, n, how) if anew else kept, n_parts // n, how), anew


def balance(homes: DataFrame, n_parts: int) -> DataFrame:
    """``t, clusters, fullest, imbalance``: the load of the fullest part over the mean load."""
    each = homes.groupBy("t", "part").agg(F.count("*").alias("n"))
    return each.groupBy("t").agg(F.sum("n").alias("clusters"), F.max("n").alias("fullest")).withColumn(
        "imbalance", F.col("fullest") * n_parts / F.col("clusters")
    )
