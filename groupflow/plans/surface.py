"""The method for users of SQL: views of its tables, and functions over lists of points."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.operators import distances
from groupflow.plans.pipeline import Discovery
from groupflow.storage import materialize


def _squares(a: pa.Array, b: pa.Array, stop: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Squares of the distances of lists of points (any number above ``stop`` where they are above), NaN where one is null or empty;
    numbers of points, -1 for null."""
    size = [np.where(v.is_valid(), v.value_lengths().fill_null(0), -1).astype(np.int64) for v in (a, b)]
    out, good = np.full(len(a), np.nan), np.flatnonzero((size[0] > 0) & (size[1] > 0))
    if len(good):
        x, y = (np.concatenate([v.values.field(c).to_numpy(zero_copy_only=False) for v in (a, b)]) for c in ("x", "y"))
        begin = np.concatenate([a.offsets.to_numpy()[:-1].astype(np.int64), b.offsets.to_numpy()[:-1].astype(np.int64) + len(a.values)])
        most = np.full(len(good), np.inf) if stop is None else stop[good]
        out[good] = distances.squares(x, y, begin, np.concatenate(size), good, good + len(a), most)
    return out, *size


def _hausdorff(a: pa.Array, b: pa.Array) -> pa.Array:
    found, _, _ = _squares(a, b)
    return pa.array(np.sqrt(found), pa.float64(), mask=np.isnan(found))


def _within(a: pa.Array, b: pa.Array, most: pa.Array) -> pa.Array:
    limit = most.cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False) ** 2
    found, na, nb = _squares(a, b, np.where(np.isnan(limit), np.inf, limit))
    # an empty list is covered by any, and covers empty ones only
    holds = (found <= limit) | ((na == 0) & (nb == 0))
    return pa.array(holds, pa.bool_(), mask=(na < 0) | (nb < 0) | (np.isnan(limit) & (na + nb > 0)))


def functions(spark: SparkSession) -> None:
    """``hausdorff(a, b)`` and ``hausdorff_within(a, b, limit)`` as SQL functions of lists of points with finite ``x, y``. They go by
    :mod:`groupflow.operators.distances`, where a point of a large list meets near ones only."""
    spark.udf.register("hausdorff", F.arrow_udf(_hausdorff, "double"))
    spark.udf.register("hausdorff_within", F.arrow_udf(_within, "boolean"))


def _distinct_points(shape: DataFrame) -> DataFrame:
    """``shape`` with each point of a cluster once in ``pts``, however many of its objects stand there."""
    at = shape.columns.index("pts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            few = next(distances._distinct(iter([batch.select(["cluster_id", "t", "pts"])])))
            xs, ys = few.column(2), few.column(3)
            kind = batch.schema.field(at).type
            points = pa.StructArray.from_arrays([xs.values, ys.values], fields=[kind.value_type.field(c) for c in ("x", "y")])
            columns = batch.columns
            columns[at] = pa.ListArray.from_arrays(xs.offsets, points, type=kind)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    return shape.mapInArrow(run, shape.schema)


def register(spark: SparkSession, snap: DataFrame, found: Discovery) -> None:
    """Views ``snapshots, members, shapes, links, covers, crowds, aggregations, groups, evolution`` and the functions.

    ``pts`` of ``shapes`` holds no point twice: distances do not depend on it, and a row is joined for each link.
    """
    views = {
        "snapshots": snap,
        "members": found.member,
        "shapes": materialize(_distinct_points(found.shape), "shapes"),
        "links": found.link,
        "covers": found.cover,
        "crowds": found.crowd,
        "aggregations": found.windows,
        "groups": found.group,
        "evolution": found.evo,
    }
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    functions(spark)
