"""Readers, generated inputs and sinks around the methods."""

from __future__ import annotations

import math
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "csv", "json", "orc", "text")


def load(spark: SparkSession, folder: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_table(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """A file table by explicit schema, never an inferred one."""
    if fmt not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    return spark.read.format(fmt).schema(schema).load(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> DataFrame:
    """Written from the executors and read again by its schema; the rows never visit the driver."""
    df.write.format(fmt).mode(mode).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).load(path)


def exists(spark: SparkSession, path: str) -> bool:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)


def work_dir(spark: SparkSession) -> str:
    """The shared folder of the session; a folder of this machine only for a local session that names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return tempfile.mkdtemp(prefix="rootfinal-")


def uniform(spark: SparkSession, n: int, parts: int, seed: int = 0) -> DataFrame:
    """x in [0, 1), the same under any partitioning."""
    return spark.range(0, n, 1, parts).select((F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 53)) / F.lit(float(1 << 53))).alias("x"))


def normal(spark: SparkSession, n: int, parts: int, seed: int = 0) -> DataFrame:
    u = [(F.pmod(F.xxhash64("id", F.lit(2 * seed + i)), F.lit(1 << 53)) + 1) / F.lit(float(1 << 53)) for i in (0, 1)]
    return spark.range(0, n, 1, parts).select((F.sqrt(-2 * F.log(u[0])) * F.cos(2 * math.pi * u[1])).alias("x"))


def ordered(spark: SparkSession, n: int, parts: int, reverse: bool = False) -> DataFrame:
    return spark.range(0, n, 1, parts).select((F.lit(n - 1) - F.col("id") if reverse else F.col("id")).cast("double").alias("x"))


def constant(spark: SparkSession, n: int, parts: int, value: float = 1.0) -> DataFrame:
    return spark.range(0, n, 1, parts).select(F.lit(value).alias("x"))


def grown(df: DataFrame, col: str, copies: int, step: float = 1e-6) -> DataFrame:
    """`copies` of every row, each copy moved by its own small step: the input of growth sweeps."""
    return df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).select((F.col(col) + F.col("copy") * F.lit(step)).alias("x"))


def logistic_bands(top: int = 30, middle: float = 25_165_824, slope: float = 5e-7) -> list[tuple[int, int]]:
    """(count, last rank of that count): counts fall with the rank along a logistic curve, rounded half up."""
    out = []
    for c in range(top, 0, -1):
        # the curve is at least c - 1/2 up to this rank
        out.append((c, max(0, math.floor(middle + math.log(top / (c - 0.5) - 1) / slope))))
    return out


def logistic_items(spark: SparkSession, scale: int, parts: int, top: int = 30, middle: float = 25_165_824, slope: float = 5e-7, tail: int = 75_497_470, seed: int = 0) -> DataFrame:
    """`item` rows of the profile shrunk by `scale`, with `tail / scale` further items of count one, dealt by hash."""
    bands = logistic_bands(top, middle / scale, slope * scale)
    last = bands[-1][1]
    count = F.lit(1)
    for c, end in reversed(bands):
        count = F.when(F.col("id") < end, c).otherwise(count)
    items = spark.range(0, last + tail // scale, 1, parts).select(F.col("id").alias("item"), F.explode(F.sequence(F.lit(1), count)).alias("copy"))
    return items.repartition(parts, F.xxhash64("item", "copy", F.lit(seed))).select("item")
