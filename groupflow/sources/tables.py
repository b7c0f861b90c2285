"""The given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; its timestamps without time zone are read as UTC."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    local = [c for c, kind in df.dtypes if kind == "timestamp_ntz"]
    return df.withColumns({c: F.from_utc_timestamp(F.col(c).cast("timestamp"), F.current_timezone()) for c in local}) if local else df


def require(df: DataFrame, columns: dict[str, str]) -> DataFrame:
    """``df`` with just ``columns`` (name -> type), cast; raises where one is missing."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    return df.select([df[c].cast(kind).alias(c) for c, kind in columns.items()])
