"""Exact quantiles: sketch, exact rank of its answer, then the values between it and the wanted rank."""

from __future__ import annotations

import math
from decimal import Decimal
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.order_code import OrderCode
from ..summary import GKSummary, NearestOfMany, NearestValues, WindowSummary, rank_of
from ..tree import depth_for_fan_in, finished, partition_count
from .ranking import sorted_ranges

_PLACES = pa.schema([("no", pa.int32()), ("q", pa.float64()), ("k", pa.int64()), ("n", pa.int64())])


def _one(df: DataFrame, col: str) -> tuple[DataFrame, T.DataType]:
    """The column alone, without nulls, and its type."""
    x = df.select(F.col(col).alias("x")).where("x IS NOT NULL")
    return x, x.schema["x"].dataType


def _lit(value, kind: T.DataType):
    """A literal of the column's own type, so that comparisons reach the scan."""
    if isinstance(kind, T.TimestampNTZType):
        return F.lit(value.isoformat(sep=" ")).cast(kind)
    if isinstance(kind, T.DayTimeIntervalType):
        return F.lit(value)
    return F.lit(value).cast(kind)


def _codes(values: list, kind: T.DataType) -> list:
    code = OrderCode(kind)
    return code.encode(pa.array(values, code.arrow)).tolist()


def _check(qs: list[float]) -> None:
    if any(not 0 <= q <= 1 for q in qs):
        raise ValueError("q must lie between 0 and 1")


def _answers(kind: T.DataType) -> T.StructType:
    return T.StructType([T.StructField("q", T.DoubleType()), T.StructField("k", T.LongType()), T.StructField("n", T.LongType()), T.StructField("value", kind)])


def gk_quantile(df: DataFrame, col: str, qs: list[float], eps: float = 0.01, root: str = "finalize", depth: int = 2, head: int | str = 50_000, partitions: int | None = None) -> DataFrame:
    """q, n, value of the sketch alone: rank error at most eps * n. `head` as GKSummary takes it."""
    x, kind = _one(df, col)
    return finished(x, GKSummary(qs, eps, kind, head), depth, root, partitions).select("q", "n", "value")


def gk_select_many(df: DataFrame, col: str, qs: list[float], eps: float = 0.01, depth: int = 2, root: str = "finalize", fan_in: int | None = None, engine: str = "tree", merge_policy: str = "trim", sketch_depth: int = 2, sketch_root: str | None = None, head: int | str = 50_000, partitions: int | None = None) -> DataFrame:
    """q, k, n, value: exact. One sketch, one rank pass and one candidate pass for all q together.

    The candidate pass reads only between values that are sure to enclose the ranks; a q whose pivot run holds its rank needs none.
    """
    _check(qs)
    spark = df.sparkSession
    x, kind = _one(df, col)
    if fan_in:
        depth = depth_for_fan_in(partitions or partition_count(x), fan_in)
    pivots = finished(x, GKSummary(qs, eps, kind, head), sketch_depth, sketch_root or root, partitions).collect()
    if not pivots:
        return spark.createDataFrame([], _answers(kind))
    values = [_lit(p.value, kind) for p in pivots]
    ranks = x.agg(F.count("*").alias("n"), *[e for i, v in enumerate(values) for e in (F.count_if(F.col("x") < v).alias(f"b{i}"), F.count_if(F.col("x") == v).alias(f"e{i}"))]).first()
    if ranks.n != pivots[0].n:
        raise RuntimeError("the input changed between passes")
    codes = _codes([p.value for p in pivots], kind)
    known, open_, windows = [], [], []
    for i, p in enumerate(pivots):
        k, below, equal = rank_of(p.q, p.n), ranks[f"b{i}"], ranks[f"e{i}"]
        if below < k <= below + equal:
            known.append((float(p.q), k, p.n, p.value))
            continue
        least = k > below
        open_.append((i, codes[i], k - below - equal if least else below - k + 1, least))
        windows.append((F.col("x") > values[i]) & (F.col("x") <= _lit(p.high, kind)) if least else (F.col("x") < values[i]) & (F.col("x") >= _lit(p.low, kind)))
    if not open_:
        return spark.createDataFrame(known, _answers(kind))
    # an Arrow table stays with the plan, rows would be a job of their own
    places = spark.createDataFrame(pa.Table.from_pylist([{"no": i, "q": float(pivots[i].q), "k": rank_of(pivots[i].q, pivots[i].n), "n": pivots[i].n} for i, *_ in open_]).cast(_PLACES))
    if engine == "catalyst":
        found = []
        for (i, _, m, least), window in zip(open_, windows, strict=True):
            near = x.where(window).orderBy(F.col("x").asc() if least else F.col("x").desc()).limit(m)
            found.append(near.agg((F.max if least else F.min)("x").alias("value")).select(F.lit(i).alias("no"), "value"))
        got = reduce(DataFrame.unionByName, found)
    else:
        got = finished(x.where(reduce(lambda a, b: a | b, windows)), NearestOfMany(open_, kind, merge_policy == "trim"), depth, root, partitions)
    found = got.join(F.broadcast(places), "no").select("q", "k", "n", "value")
    return spark.createDataFrame(known, _answers(kind)).unionByName(found) if known else found


def gk_select(df: DataFrame, col: str, q: float, **options) -> DataFrame:
    return gk_select_many(df, col, [q], **options)


def full_sort_quantile(df: DataFrame, col: str, q: float) -> DataFrame:
    """Baseline: range shuffle and local sort of everything, written once; the row of the wanted rank is read by its place."""
    _check([q])
    spark = df.sparkSession
    x, kind = _one(df, col)
    ranked, sizes = sorted_ranges(x, ["x"])
    n = sum(sizes.values())
    if not n:
        return spark.createDataFrame([], _answers(kind))
    k = left = rank_of(q, n)
    for part in sorted(sizes):
        if left <= sizes[part]:
            break
        left -= sizes[part]
    place = (part << 33) + left - 1
    return ranked.where(F.col("place") == F.lit(place)).select(F.lit(float(q)).alias("q"), F.lit(k).cast("long").alias("k"), F.lit(n).cast("long").alias("n"), F.col("x").alias("value"))


def builtin_percentile_disc(df: DataFrame, col: str, q: float) -> DataFrame:
    """Baseline. Equal values are dealt to one task, so the one task that merges every task's map of counts meets each value once."""
    x, _ = _one(df, col)
    return x.repartition("x").agg(F.lit(float(q)).alias("q"), F.expr(f"percentile_disc({q!r}) WITHIN GROUP (ORDER BY x)").alias("value"))


def builtin_approx(df: DataFrame, col: str, q: float, eps: float) -> DataFrame:
    x, _ = _one(df, col)
    return x.agg(F.lit(float(q)).alias("q"), F.percentile_approx("x", q, int(1 / eps)).alias("value"))


def top_values(df: DataFrame, col: str, k: int, root: str = "finalize", partitions: int | None = None) -> DataFrame:
    x, kind = _one(df, col)
    return finished(x, NearestValues(k, False, kind, every=True), 2, root, partitions)


def rank_error(df: DataFrame, col: str, value, k: int) -> int:
    """Distance of k from the ranks that `value` holds."""
    x, kind = _one(df, col)
    v = _lit(value, kind)
    r = x.agg(F.count_if(F.col("x") < v).alias("b"), F.count_if(F.col("x") == v).alias("e")).first()
    return max(0, r.b + 1 - k, k - r.b - r.e)


def gk_select_two_round(df: DataFrame, col: str, q: float, eps: float = 0.01, depth: int = 2, partitions: int | None = None) -> DataFrame:
    """q, k, n, value: the sketch gives a window sure to hold the answer, one more pass counts below it and keeps it."""
    spark = df.sparkSession
    x, kind = _one(df, col)
    p = finished(x, GKSummary([q], eps, kind), 2, partitions=partitions).first()
    if p is None:
        return spark.createDataFrame([], _answers(kind))
    k = rank_of(q, p.n)
    low, high = _codes([p.low, p.high], kind)
    answer = finished(x, WindowSummary(low, high, k, kind), depth, partitions=partitions)
    return answer.select(F.lit(float(q)).alias("q"), F.lit(k).cast("long").alias("k"), F.lit(p.n).cast("long").alias("n"), "value")


def gk_select_narrowing(df: DataFrame, col: str, q: float, eps: float = 0.01, max_candidates: int = 1_000_000, depth: int = 2, partitions: int | None = None) -> DataFrame:
    """q, k, n, value: the window around the rank is sketched again until it holds at most `max_candidates` rows.

    Each round shrinks it to about 4 * eps of itself; a window of one value ends the search whatever its size.
    """
    _check([q])
    spark = df.sparkSession
    x, kind = _one(df, col)
    n = inside = x.count()
    if not n:
        return spark.createDataFrame([], _answers(kind))
    k = left = rank_of(q, n)
    window, low, high = x, None, None
    while inside > max_candidates and (low is None or low != high):
        place = Decimal(left) / Decimal(inside)
        p = finished(window, GKSummary([place], eps, kind), 2, partitions=partitions).first()
        low, high = p.low, p.high
        within = F.col("x").between(_lit(low, kind), _lit(high, kind))
        counts = window.agg(F.count_if(F.col("x") < _lit(low, kind)).alias("below"), F.count_if(within).alias("inside")).first()
        if counts.inside == inside:
            break
        left, inside = left - counts.below, counts.inside
        window = x.where(within)
    one = low is not None and _codes([low], kind) == _codes([high], kind)
    answer = spark.createDataFrame([(low,)], T.StructType([T.StructField("value", kind)])) if one else finished(window, NearestValues(left, True, kind), depth, partitions=partitions)
    return answer.select(F.lit(float(q)).alias("q"), F.lit(k).cast("long").alias("k"), F.lit(n).cast("long").alias("n"), "value")


def gk_select_by(df: DataFrame, keys: list[str], col: str, q: float, eps: float = 0.001) -> DataFrame:
    """keys, k, n, value: exact for each group, all in the JVM.

    A sketch for each group encloses its rank; values inside are counted by value before one window over each
    group's few distinct candidates finds the rank, so a hot group costs about 4 * eps of its rows there.
    """
    x, _ = _one(df.select(F.col(col)), col)
    rows = df.select(*keys, F.col(col).cast(x.schema["x"].dataType).alias("x")).where("x IS NOT NULL")
    ends = [max(0.0, q - 2 * eps), min(1.0, q + 2 * eps)]
    sketch = rows.groupBy(*keys).agg(F.count("*").alias("n"), F.percentile_approx("x", ends, int(1 / eps)).alias("e"), F.min("x").alias("least"), F.max("x").alias("most"))
    k = F.greatest(F.lit(1), F.ceil(F.lit(Decimal(str(q))) * F.col("n"))).cast("long")
    low = F.when(F.lit(q - 2 * eps) * F.col("n") < 1, F.col("least")).otherwise(F.col("e")[0])
    high = F.when(F.lit(1 - q - 2 * eps) * F.col("n") < 1, F.col("most")).otherwise(F.col("e")[1])
    bounds = sketch.select(*[F.col(c).alias(f"__{c}") for c in keys], "n", k.alias("k"), low.alias("low"), high.alias("high"))
    both = rows.join(bounds, reduce(lambda a, b: a & b, [rows[c].eqNullSafe(bounds[f"__{c}"]) for c in keys]))
    # rows below the window are counted as one value, its row comes first by order
    spot = F.when(F.col("x") < F.col("low"), F.lit(None)).otherwise(F.col("x"))
    counted = both.where("x <= high").groupBy(*keys, "n", "k", spot.alias("value")).count()
    running = F.sum("count").over(Window.partitionBy(*keys).orderBy(F.col("value").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0))
    reached = counted.withColumn("upto", running).where("upto >= k AND upto - count < k")
    return reached.select(*keys, "k", "n", "value")


def kll_quantile(df: DataFrame, col: str, q: float) -> DataFrame:
    """Baseline: the built-in KLL sketch, its answer read in the JVM."""
    x, kind = _one(df, col)
    form = "bigint" if isinstance(kind, T.LongType) else "double"
    return x.agg(F.expr(f"kll_sketch_get_quantile_{form}(kll_sketch_agg_{form}(CAST(x AS {form})), {float(q)}D)").alias("value")).select(F.lit(float(q)).alias("q"), "value")


def choose_epsilon(n: int, partitions: int, budget_bytes: int, tuple_bytes: int = 24) -> float:
    """The eps that balances the sketch's (1/eps) * log(eps * n / P) tuples with the eps * n candidates.

    Raises if neither fits the budget at the balance; then the window must be narrowed in more rounds.
    """
    low, high = 1.0 / max(n, 2), 0.5
    for _ in range(60):
        eps = math.sqrt(low * high)
        sketch, candidates = tuple_bytes / eps * max(1.0, math.log(max(eps * n / partitions, math.e))), 8 * eps * n
        low, high = (eps, high) if sketch > candidates else (low, eps)
    if max(sketch, candidates) > budget_bytes:
        raise ValueError("no eps keeps both the sketch and the candidates within the budget")
    return eps
