"""Global order without a single-task window: range shuffle, local sort, and a place for every row."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.tables import work_dir


def sorted_ranges(df: DataFrame, order: list[str | Column]) -> tuple[DataFrame, dict[int, int]]:
    """`df` with `place` (range number << 33, plus the row's number in its range), written in order, and the rows of each range.

    The driver gets one number for each range. Rows of one range stand in ascending place, so a filter on it prunes row groups.
    """
    spark = df.sparkSession
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    path = f"{work_dir(spark)}/ranges-{uuid.uuid4().hex}"
    df.repartitionByRange(width, *order).sortWithinPartitions(*order).withColumn("place", F.monotonically_increasing_id()).write.parquet(path)
    out = spark.read.parquet(path)
    counts = out.groupBy(F.shiftright("place", 33).alias("part")).agg(F.count("*").alias("n"))
    return out, {r.part: r.n for r in counts.collect()}


def global_rank(df: DataFrame, order: list[str | Column], name: str = "position") -> DataFrame:
    """`df` with its 1-based position in this order."""
    out, sizes = sorted_ranges(df, order)
    starts, total = [], 0
    for part in sorted(sizes):
        starts.append((part, total))
        total += sizes[part]
    base = df.sparkSession.createDataFrame(starts, "part long, base long")
    placed = out.withColumn("part", F.shiftright("place", 33)).join(F.broadcast(base), "part")
    return placed.withColumn(name, F.col("base") + F.col("place").bitwiseAND((1 << 33) - 1) + 1).drop("part", "base", "place")
