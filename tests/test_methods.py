import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rootfinal.operators import heavy_hitters as hh
from rootfinal.operators import measures as ms
from rootfinal.operators import quantiles as qt
from rootfinal.sources import tables
from rootfinal.summary import NearestValues, StreamSummary, TaggedSummary
from rootfinal.tree import checkpointed_states, finish_states, tagged_tree_aggregate, tree_reduce


@pytest.mark.parametrize("q", [0.0, 0.01, 0.5, 0.9, 1.0])
def test_every_exact_method_agrees(spark, q):
    df = spark.range(2003).select((F.col("id") * 7919 % 97).cast("double").alias("x")).repartition(5)
    want = sorted((i * 7919) % 97 for i in range(2003))
    k = qt.rank_of(q, 2003)
    for found in (qt.gk_select_two_round(df, "x", q, 0.05), qt.gk_select_narrowing(df, "x", q, 0.05, max_candidates=50), qt.full_sort_quantile(df, "x", q)):
        assert (found.first().k, found.first().value) == (k, want[k - 1])


@pytest.mark.parametrize("q", [0.0, 0.3, 0.5, 0.999, 1.0])
def test_grouped_select_with_a_hot_group_and_a_null_key(spark, q):
    df = spark.range(3000).select(F.when(F.col("id") % 3 > 0, F.lit("hot")).when(F.col("id") % 2 == 0, F.lit("b")).alias("g"), (F.col("id") * 37 % 211).cast("double").alias("x"))
    rows = [(("hot" if i % 3 else "b" if i % 2 == 0 else None), i * 37 % 211) for i in range(3000)]
    for r in qt.gk_select_by(df, ["g"], "x", q).collect():
        own = sorted(v for g, v in rows if g == r.g)
        assert (r.n, r.value) == (len(own), own[r.k - 1])
    assert qt.gk_select_by(df, ["g"], "x", q).count() == 3


def test_tagged_state_finishes_once_and_takes_no_more(spark):
    df = spark.range(100).select(F.col("id").cast("double").alias("x")).repartition(3)
    inner = NearestValues(3, False, T.DoubleType(), every=True)
    assert tagged_tree_aggregate(df, inner, 100).column("value").to_pylist() == [99.0, 98.0, 97.0]
    with pytest.raises(ValueError):
        tagged_tree_aggregate(df, inner, 101)
    tagged = TaggedSummary(inner, 2)
    batch = pa.RecordBatch.from_arrays([pa.array([1.0, 2.0])], names=["x"])
    done = tagged.fold(tagged.zero(), batch)
    with pytest.raises(ValueError):
        tagged.merge(done, ("open", 1, None))


def test_reduce_and_resume(spark, tmp_path):
    df = spark.range(50).select(F.col("id").cast("double").alias("x")).repartition(4)
    assert tree_reduce(df, "x", max) == 49.0
    assert tree_reduce(df.where("x < 0"), "x", max) is None
    s = NearestValues(2, True, T.DoubleType(), every=True)
    checkpointed_states(df, s, str(tmp_path))
    again = checkpointed_states(df.where("x < 0"), s, str(tmp_path))  # complete levels are read, not run
    assert [r.value for r in finish_states(again, s).collect()] == [0.0, 1.0]


def test_stream_summary_keeps_its_bounds():
    rng = np.random.default_rng(3)
    x = rng.zipf(1.4, 5000) % 400
    s, state = StreamSummary(10, 50, T.LongType()), None
    for part in np.array_split(x, 5):
        state = s.fold(state, pa.RecordBatch.from_arrays([pa.array(part)], names=["x"]))
    state = s.arrays(state)
    for item, c, e in zip(*(a.tolist() for a in state[:3]), strict=True):
        true = int((x == item).sum())
        assert c - e <= true <= c
    assert state[1].sum() == len(x) and len(state[0]) == 50


def test_count_min_and_status(spark):
    df = spark.range(1000).select((F.col("id") % 10).alias("x")).repartition(4)
    for r in hh.count_min_estimate(df, "x", [1, 5, 77]).collect():
        assert (0 if r.item == 77 else 100) <= r.estimate <= 101 and r.total == 1000
    assert hh.hh_status(hh.heavy_hitters(df, "x", 20, capacity=50), 20).first().collapsed


def test_growth_profile_and_costs(spark):
    bands = dict(tables.logistic_bands())
    total = sum(c * (bands[c] - bands.get(c + 1, 0)) for c in bands) + 75_497_470
    assert (bands[1] + 75_497_470, total) == (108_818_368, 830_472_175)
    items = tables.logistic_items(spark, 1_000_000, 4)
    assert items.groupBy("item").count().agg(F.max("count")).first()[0] == 30
    assert ms.cost("select_driver", 9_000_000_000, 120)["driver_memory"] > ms.cost("select_finalize", 9_000_000_000, 120)["driver_memory"]
    assert ms.feasible_range([("a", 8, True), ("a", 9, False), ("b", 2, True)]) == {"a": 8, "b": 2}
    assert 0 < qt.choose_epsilon(10**9, 120, 1 << 30) < 0.1
    with pytest.raises(ValueError):
        qt.choose_epsilon(10**12, 120, 1 << 10)


def test_outcomes():
    assert ms.classify_outcome(0, "", 1) == "ok"
    assert ms.classify_outcome(1, "java.lang.OutOfMemoryError", 1) == "driver_crash"
    assert ms.classify_outcome(1, "ExecutorLostFailure", 1) == "executor_loss"
    assert ms.classify_outcome(None, "", 2000) == "driver_hang"
