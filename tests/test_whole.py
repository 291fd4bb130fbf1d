"""Results over more labels than counters, and queries that read their tables."""

import json

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rootfinal import tree
from rootfinal.operators import heavy_hitters as hh
from rootfinal.operators import quantiles as qt
from rootfinal.plans import experiments, queries, relational
from rootfinal.streaming.windows import running_hitters
from rootfinal.summary import GKSummary, MisraGries, NearestValues, SpaceSaving, StreamSummary, _largest

WANT = [(i, 5 if i < 3 else 4) for i in range(20)]


def _flat(spark, parts=5):
    """600 labels, three of them five times and the rest four times."""
    return spark.range(2403).select(F.when(F.col("id") < 2400, F.col("id") % 600).otherwise(F.col("id") - 2400).alias("x")).repartition(parts, F.xxhash64("id"))


@pytest.mark.parametrize("method,root", [("space_saving", "finalize"), ("space_saving", "executor"), ("space_saving", "driver"), ("misra_gries", "finalize"), ("stream_misra_gries", "finalize"), ("stream_summary", "driver")])
def test_hitters_are_exact_with_fewer_counters_than_labels(spark, method, root):
    got = hh.exact_hitters(_flat(spark), "x", 20, method, root, capacity=50).orderBy("rank").collect()
    assert [(r.item, r.estimate) for r in got] == WANT
    assert {(r.error, r.lost, r.survivors, r.guaranteed) for r in got} == {(0, 0, 600, True)}


@pytest.mark.parametrize("name", ["space_saving_finalize", "space_saving_executor_root"])
def test_hitter_queries_are_exact_past_their_counters(spark, tmp_path, name):
    supplier = F.when(F.col("id") < 12_000, F.col("id") % 3000).otherwise(F.col("id") - 12_000)
    spark.range(12_003).select(supplier.alias("l_suppkey")).repartition(5, F.xxhash64("id")).write.parquet(f"{tmp_path}/lineitem.parquet")
    assert sorted((tuple(r) for r in queries.QUERIES[name](spark, str(tmp_path)).collect()), key=lambda r: (-r[1], r[0])) == WANT


def test_exact_hitters_of_text_structs_floats_and_weights(spark):
    x = _flat(spark)
    text = x.select(F.concat(F.lit("é"), F.format_string("%03d", "x")).alias("x"), F.lit(2).alias("w"))
    got = hh.exact_hitters(text, "x", 20, capacity=50, weight_col="w").orderBy("rank").collect()
    assert [(r.item, r.estimate) for r in got] == [(f"é{i:03d}", 2 * n) for i, n in WANT]
    structs = x.select(F.struct(F.format_string("%03d", "x").alias("a")).alias("x"))
    assert [(int(r.item.a), r.estimate) for r in hh.exact_hitters(structs, "x", 20, capacity=50).orderBy("rank").collect()] == WANT
    signs = x.select(F.when(F.col("x") > 0, F.col("x").cast("double")).when(F.rand(1) < 0.5, F.lit(-0.0)).otherwise(F.lit(0.0)).alias("x"))
    assert [(r.item, r.estimate) for r in hh.exact_hitters(signs, "x", 20, capacity=50).orderBy("rank").collect()] == WANT
    assert hh.exact_hitters(x.where("x < 0"), "x", 5, capacity=50).collect() == []


def test_exact_hitters_as_arrays(spark):
    r = hh.exact_hitters(_flat(spark), "x", 20, capacity=50, export="arrays", count_type="int").first()
    assert list(zip(r.labels, r.counts, strict=True)) == WANT and r.bytes == 20 * 12


def test_classes_know_whether_they_are_whole(spark):
    for cls in (SpaceSaving, MisraGries, StreamSummary):
        s = cls(20, 300, T.LongType())
        states = tree.class_states(_flat(spark).withColumnRenamed("x", "item"), s, 4)
        assert states.where("whole").count() == 4
        got = tree.finish_classes(states, s).orderBy(F.col("estimate").desc(), "item").limit(20).collect()
        assert [(r.item, r.estimate) for r in got] == WANT
        short = tree.finish_classes(tree.class_states(_flat(spark).withColumnRenamed("x", "item"), cls(20, 100, T.LongType()), 1), s)
        assert short.where("NOT whole").count() == 1


def test_largest_breaks_ties_by_label():
    counts = np.array([2, 3, 2, 2, 1])
    text = np.empty(5, object)
    text[:] = ["d", "a", "c", "b", "e"]
    for labels in (np.array([4, 1, 3, 2, 5]), text):
        assert _largest(labels, counts, 3).tolist() == [1, 3, 2]
        assert _largest(labels, counts, 9).tolist() == [1, 3, 2, 0, 4]


def test_builtin_top_is_exact_past_its_items(spark):
    assert [tuple(r) for r in hh.builtin_top_k(_flat(spark), "x", 20, 50).collect()] == WANT


def test_arrays_multiply_as_floats(spark, tmp_path):
    spark.createDataFrame([(1, [0.009] * 8)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert relational.QUERIES["rel_arrays"](spark, str(tmp_path)).first().milli == 72


def test_running_hitters_are_exact(spark, tmp_path):
    _flat(spark).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("x long").option("maxFilesPerTrigger", 2).parquet(f"{tmp_path}/in")
    got = running_hitters(stream, "x", 20, SpaceSaving(20, 50, T.LongType()), f"{tmp_path}/out")
    assert [(r.item, r.estimate) for r in got.orderBy("rank").collect()] == WANT


@pytest.mark.parametrize("name", ["cost_model", "logistic_profile", "tree_shapes"])
def test_answers_follow_their_table(spark, name):
    small, large = (queries.QUERIES[name](spark, f"/root/testdata/{sf}").collect() for sf in ("sf0.001", "sf0.01"))
    assert small != large and len(small) == len(large)


def test_idle_heap_reads_its_table(spark):
    records = [json.loads(r.record) for r in queries.QUERIES["experiment_idle_heap"](spark, "/root/testdata/sf0.001").orderBy("no").collect()]
    assert [(r["when"], r.get("n")) for r in records] == [("before", None), ("after", 6000)]


def test_growth_deals_rows_before_copies_and_sends_them_by_number(spark, monkeypatch):
    name, inputs, limits = "spark.sql.execution.arrow.maxBytesPerBatch", [], []
    written, measured = experiments._written, experiments._measured
    monkeypatch.setattr(experiments, "_written", lambda *a: inputs.append(written(*a)) or inputs[-1])
    monkeypatch.setattr(experiments, "_measured", lambda s, run: limits.append(s.conf.get(name)) or measured(s, run))
    before = spark.conf.get(name)
    records = experiments.select_growth(spark, "/root/testdata/sf0.001", copies=(1, 3), parts=4)
    assert [r["n"] for r in records] == [6000] * 8 + [18_000] * 8
    assert set(limits) == {str((1 << 31) - 1)} and spark.conf.get(name) == before
    for x, m in zip(inputs, (1, 3), strict=True):
        rows = x.groupBy(F.input_file_name().alias("file"), F.round("x", 2).alias("price")).count()
        assert len(x.inputFiles()) == 4 and rows.where(F.col("count") % m > 0).isEmpty()


def test_growth_deals_its_rows_once(spark, monkeypatch):
    plans, written = [], experiments._written
    monkeypatch.setattr(experiments, "_written", lambda s, df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or written(s, df))
    experiments.select_growth(spark, "/root/testdata/sf0.001", copies=(1, 2), parts=2)
    assert len(plans) == 2 and all("InMemoryTableScan" in p for p in plans)


def test_percentile_disc_merges_each_value_once(spark):
    plan = qt.builtin_percentile_disc(spark.range(10), "id", 0.5)._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(x" in plan


@pytest.mark.parametrize("eps", [0.001, 0.01, 0.1, 0.5])
def test_sketch_of_a_head_keeps_what_compressing_its_rows_keeps(eps):
    for n in (1, 2, 3, 101, 150, 5000):
        x = np.random.default_rng(n).normal(size=n).round(1)
        x[::7], x[::5] = np.nan, -0.0
        s = GKSummary([0.5], eps, T.DoubleType())
        v = np.sort(s.code.encode(pa.array(x, from_pandas=False)))
        want = s._compress((v, np.ones(n, np.int64), np.zeros(n, np.int64), n))
        assert [a.tolist() for a in s._own(np.sort(x))[:3]] == [a.tolist() for a in want[:3]]


def test_driver_root_answers_stay_with_the_plan(spark):
    for kind in ("double", "float", "int", "date", "timestamp", "timestamp_ntz", "decimal(12,2)", "boolean", "string", "interval day to second"):
        made = "make_dt_interval(0, 0, 0, CAST(id AS decimal(18,6)))" if kind.startswith("interval") else "date_add(DATE'2024-01-01', CAST(id AS int))" if kind == "date" else f"CAST(timestamp_seconds(id) AS {kind})" if kind.startswith("timestamp") else f"CAST(id AS {kind})"
        df = spark.range(60).select(F.expr(made).alias("x")).repartition(3)
        near = [tree.finished(df, NearestValues(4, True, df.schema["x"].dataType, every=True), root=root) for root in ("driver", "executor", "finalize")]
        assert near[0].schema == near[2].schema and near[0].collect() == near[1].collect() == near[2].collect()
        assert "LocalTableScan" in near[0]._jdf.queryExecution().executedPlan().toString()
        got = [qt.gk_select_many(df, "x", [0.0, 0.3, 0.9], 0.1, root=root).orderBy("q").collect() for root in ("driver", "finalize")]
        assert got[0] == got[1] and len(got[0]) == 3
