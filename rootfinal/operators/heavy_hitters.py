"""Most frequent items by bounded counters, exact counts, and the measures that compare them."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import work_dir
from ..summary import CountMin, CounterSummary, IsomorphicSpaceSaving, MisraGries, SpaceSaving, StreamMisraGries, StreamSummary
from ..tree import class_states, finish_classes, finished
from .ranking import global_rank

METHODS = {
    "space_saving": SpaceSaving,
    "space_saving_isomorphic": IsomorphicSpaceSaving,
    "stream_summary": StreamSummary,
    "misra_gries": MisraGries,
    "stream_misra_gries": StreamMisraGries,
}


def _labels(df: DataFrame, col: str, nulls: str) -> tuple[Column, T.DataType, Callable]:
    """The label column as a type that summaries take, that type, and the way back for a column of them.

    Structs, long decimals and, with nulls="label", null itself go as JSON text.
    """
    if nulls not in ("drop", "label"):
        raise ValueError("nulls is drop or label")
    kind = df.schema[col].dataType
    packed = isinstance(kind, T.StructType) or isinstance(kind, T.DecimalType) and kind.precision > 18 or nulls == "label"
    if not packed:
        return F.col(col), kind, lambda c: c
    schema = T.StructType([T.StructField("v", kind)])
    label = F.to_json(F.struct(F.col(col).alias("v")))
    if nulls == "drop":
        label = F.when(F.col(col).isNotNull(), label)
    return label, T.StringType(), lambda c: F.from_json(c, schema)["v"]


def _items(df: DataFrame, col: str, method: str, weight_col: str | None, nulls: str) -> tuple[DataFrame, T.DataType, Callable]:
    if weight_col and method.startswith("stream"):
        raise ValueError("this method counts single items")
    label, kind, back = _labels(df, col, nulls)
    weight = [F.coalesce(F.col(weight_col).cast("long"), F.lit(0)).alias("w")] if weight_col else []
    return df.select(label.alias("item"), *weight).where("item IS NOT NULL"), kind, back


def heavy_hitters(df: DataFrame, col: str, k: int, method: str = "space_saving", root: str = "finalize", capacity: int | None = None, depth: int = 2, weight_col: str | None = None, nulls: str = "drop", export: str = "rows", count_type: str = "auto", partitions: int | None = None) -> DataFrame:
    """rank, item, estimate, error, guaranteed, lost, survivors; at most k rows. Weights are positive integers.

    With export="arrays" one row of labels, counts and their bytes.
    """
    x, kind, back = _items(df, col, method, weight_col, nulls)
    found = finished(x, METHODS[method](k, capacity or 5 * k, kind, export, count_type), depth, root, partitions)
    if export == "arrays":
        return found.withColumn("labels", F.transform("labels", back))
    return found.withColumn("item", back(F.col("item")))


def whole_states(x: DataFrame, summary: CounterSummary, depth: int = 2, partitions: int | None = None, root: str = "finalize", folder: str | None = None) -> DataFrame:
    """States over classes of labels (column `item`) that give up no label, written to `folder`: one class if the counters cover all labels,
    otherwise as many as leave them half empty, and four times as many while one overflows."""
    labels = x.agg(F.approx_count_distinct("item")).first()[0]
    classes = 1 if 1.1 * labels <= summary.capacity else math.ceil(2 * labels / summary.capacity)
    folder = folder or f"{work_dir(x.sparkSession)}/hitters-{uuid.uuid4().hex}"
    while True:
        states = class_states(x, summary, classes, depth, partitions, root)
        states.write.mode("overwrite").parquet(folder)
        stored = x.sparkSession.read.schema(states.schema).parquet(folder)
        if stored.where("NOT whole").isEmpty():
            return stored
        classes *= 4


def exact_hitters(df: DataFrame, col: str, k: int, method: str = "space_saving", root: str = "finalize", capacity: int | None = None, depth: int = 2, weight_col: str | None = None, nulls: str = "drop", export: str = "rows", count_type: str = "auto", partitions: int | None = None) -> DataFrame:
    """What heavy_hitters returns with a counter for every label, however many there are: the same sketch with `capacity` counters for each
    of several classes of labels by hash, and the first k of the classes' answers."""
    x, kind, back = _items(df, col, method, weight_col, nulls)
    summary = METHODS[method](k, capacity or 5 * k, kind)
    # a driver root merges only there, where a class may overflow once more
    found = finish_classes(whole_states(x, summary, depth, partitions, root), summary, root)
    if root == "driver" and not found.where("NOT whole").isEmpty():
        found = finish_classes(whole_states(x, summary, depth, partitions), summary, root)
    top = found.orderBy(F.col("estimate").desc(), "item").limit(k)
    if export == "arrays":
        packed = SpaceSaving(k, k, kind, export, count_type)
        return finished(top.select("item", F.col("estimate").alias("w")), packed, 1).withColumn("labels", F.transform("labels", back))
    place = F.row_number().over(Window.orderBy(F.col("estimate").desc(), "item"))
    labels = found.where("rank = 1").agg(F.sum("survivors").alias("survivors"))
    return top.drop("survivors").crossJoin(F.broadcast(labels)).select(place.alias("rank"), back(F.col("item")).alias("item"), "estimate", "error", "guaranteed", "lost", "survivors")


def exact_top_k(df: DataFrame, col: str, k: int) -> DataFrame:
    counts = df.where(F.col(col).isNotNull()).groupBy(F.col(col).alias("item")).count()
    return counts.orderBy(F.col("count").desc(), "item").limit(k)


def builtin_top_k(df: DataFrame, col: str, k: int, max_items: int) -> DataFrame:
    """item, count: the built-in sketch, which is exact up to `max_items` labels, over as many classes of labels by hash as hold no more each.

    Every class gives all its labels, so that ties at the end are broken by label.
    """
    x = df.select(F.col(col).alias("item"))
    labels, classes = x.distinct(), 1
    of = lambda: F.pmod(F.xxhash64("item"), F.lit(classes))
    while (most := labels.groupBy(of().alias("class")).count().agg(F.max("count")).first()[0] or 0) > max_items:
        classes *= -(-2 * most // max_items)
    found = x.groupBy(of().alias("class")).agg(F.expr(f"approx_top_k(item, {max_items}, {max_items})").alias("r")).select(F.inline("r"))
    return found.orderBy(F.col("count").desc(), "item").limit(k)


def measures(found: DataFrame, df: DataFrame, col: str, k: int) -> DataFrame:
    """precision, recall, rank_mae, each strict and tolerant of ties, of `found(rank, item)` against exact counts.

    True ranks come from one distributed sort, so a block of millions of tied items is no task of its own.
    """
    counts = df.where(F.col(col).isNotNull()).groupBy(F.col(col).alias("item")).count()
    placed = global_rank(counts, [F.col("count").desc(), "item"], "strict")
    # one row for each distinct count
    ranges = placed.groupBy("count").agg(F.min("strict").alias("first"), F.max("strict").alias("last"))
    hit = found.select("rank", "item").join(placed, "item", "left").join(F.broadcast(ranges), "count", "left")
    gap = F.greatest(F.lit(0), F.col("first") - F.col("rank"), F.col("rank") - F.col("last"))
    got = hit.agg(F.count("*").alias("n"), F.count_if(F.col("strict") <= k).alias("right"), F.count_if(F.col("first") <= k).alias("right_tied"), F.avg(F.abs(F.col("strict") - F.col("rank"))).alias("rank_mae"), F.avg(gap).alias("rank_mae_tied"))
    frontier = ranges.where(F.col("first") <= k).agg(F.max("last").alias("truth_tied"))
    return got.crossJoin(frontier).select((F.col("right") / F.nullif(F.col("n"), F.lit(0))).alias("precision"), (F.col("right") / F.lit(k)).alias("recall"), "rank_mae", (F.col("right_tied") / F.nullif(F.col("n"), F.lit(0))).alias("precision_tied"), (F.col("right_tied") / F.col("truth_tied")).alias("recall_tied"), "rank_mae_tied")


def hh_status(found: DataFrame, k: int) -> DataFrame:
    """returned, survivors, decremented, collapsed: whether fewer rows came back than were asked for."""
    return found.agg(F.count("*").alias("returned"), F.coalesce(F.max("survivors"), F.lit(0)).alias("survivors"), F.max("lost").alias("decremented"), (F.count("*") < k).alias("collapsed"))


def count_min_estimate(df: DataFrame, col: str, items: list | DataFrame, eps: float = 0.001, confidence: float = 0.99, depth: int = 2, partitions: int | None = None) -> DataFrame:
    """item, estimate, total: never under the true count, over it by at most eps * total with this confidence.

    Counters are merged up the tree and leave the root as rows (row, place, count), their number fixed by eps and confidence.
    `items` is a list or a table of one column; their lookups are joins with those rows.
    """
    spark = df.sparkSession
    width, rows = math.ceil(math.e / eps), max(1, math.ceil(math.log(1 / (1 - confidence))))
    kind = df.schema[col].dataType
    if not isinstance(items, DataFrame):
        items = spark.createDataFrame([(v,) for v in items], T.StructType([T.StructField("item", kind)]))
    asked = items.toDF("item").distinct()
    place = lambda i: F.pmod(F.xxhash64(F.col("item"), F.lit(i)), F.lit(width)).cast("int")
    counters = finished(df.select(F.col(col).alias("item")).where("item IS NOT NULL").select(*[place(i).alias(f"h{i}") for i in range(rows)]), CountMin(width, rows), depth, partitions=partitions)
    looked = asked.select("item", F.posexplode(F.array(*[place(i) for i in range(rows)])).alias("row", "place"))
    found = looked.join(F.broadcast(counters), ["row", "place"])
    return found.groupBy("item").agg(F.min("count").alias("estimate"), F.max("total").alias("total"))


def frequent_items(df: DataFrame, col: str, support: float) -> DataFrame:
    """Baseline: the built-in candidate list of items above a share of the rows."""
    return df.freqItems([col], support).select(F.explode(f"{col}_freqItems").alias("item"))
