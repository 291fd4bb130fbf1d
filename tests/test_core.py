import math
import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rootfinal.functions.order_code import code_floats
from rootfinal.operators import heavy_hitters as hh
from rootfinal.operators import quantiles as qt
from rootfinal.summary import GKSummary, MisraGries, SpaceSaving, rank_of
from rootfinal.tree import depth_for_fan_in, plan_tree


def _batch(x):
    return pa.RecordBatch.from_arrays([pa.array(x)], names=["x"])


@pytest.mark.parametrize("depth,fan_in,states,combines", [(1, 120, 120, 119), (2, 11, 10, 9), (4, 4, 1, 0), (6, 3, 4, 3)])
def test_tree_shapes(depth, fan_in, states, combines):
    p = plan_tree(120, depth)
    assert (p.scale, p.root_fan_in, p.root_combines) == (fan_in, states, combines)


def test_depth():
    assert depth_for_fan_in(120, 4) == 4
    assert depth_for_fan_in(1, 4) == 1


def test_rank():
    assert [rank_of(q, 10) for q in (0, 0.1, 0.5, 1)] == [1, 1, 5, 10]


@pytest.mark.parametrize("eps,head", [(0.1, 500), (0.01, 500), (0.01, 50_000), (0.01, "proportional"), (0.05, "classical")])
def test_sketch_error_over_any_grouping(eps, head):
    rng = np.random.default_rng(1)
    x = np.round(rng.normal(size=20_000), 2)
    s = GKSummary([0.5], eps, T.DoubleType(), head=head)
    states = [s.fold(None, _batch(part)) for part in np.array_split(x, 7)]
    random.Random(1).shuffle(states)
    while len(states) > 1:
        states.append(s.merge(states.pop(0), states.pop(0)))
    v, g, d, n = s.settled(states[0])
    assert n == len(x) and g.sum() == n and (g + d)[1:].max() <= max(1, 2 * eps * n)
    y = np.sort(x)
    for q in (0.0, 0.01, 0.3, 0.5, 0.9, 1.0):
        k, a = rank_of(q, n), code_floats(np.array([s.quantile(states[0], q)]))[0]
        low, high = np.searchsorted(y, a, "left") + 1, np.searchsorted(y, a, "right")
        assert max(0, low - k, k - high) <= math.ceil(eps * n)


def test_space_saving_bounds_and_misra_gries_bound():
    rng = np.random.default_rng(2)
    x = rng.zipf(1.3, 30_000) % 3000
    true = Counter(x.tolist())
    for cls in (SpaceSaving, MisraGries):
        s = cls(20, 100, T.LongType())
        state = None
        for part in np.array_split(x, 9):
            state = s.fold(state, _batch(part))
        labels, counts, errors, lost = state
        assert len(labels) <= 100
        for item, c, e in zip(labels.tolist(), counts.tolist(), errors.tolist()):
            if cls is SpaceSaving:
                assert c - e <= true[item] <= c
            else:
                assert c <= true[item] <= c + lost
        assert lost <= len(x) / 100 * 10


@pytest.mark.parametrize("root", ["driver", "executor", "finalize"])
def test_select_equals_sort(spark, root):
    df = spark.range(501).select((F.col("id") * 37 % 101).cast("double").alias("x")).repartition(5)
    want = sorted((i * 37) % 101 for i in range(501))
    for r in qt.gk_select_many(df, "x", [0.0, 0.3, 0.5, 1.0], eps=0.1, root=root).collect():
        assert r.value == want[r.k - 1] and r.n == 501


def test_select_empty_null_single(spark):
    empty = spark.createDataFrame([], "x double")
    assert qt.gk_select(empty, "x", 0.5).collect() == []
    assert qt.gk_select(spark.createDataFrame([(None,), (3.0,)], "x double"), "x", 0.5).first().value == 3.0
    assert qt.full_sort_quantile(empty, "x", 0.5).collect() == []


def test_hitters_exact_when_capacity_covers(spark):
    df = spark.range(1000).select((F.col("id") % 13 * F.col("id") % 17).alias("x")).repartition(4)
    want = [tuple(r) for r in hh.exact_top_k(df, "x", 5).collect()]
    for method in hh.METHODS:
        got = hh.heavy_hitters(df, "x", 5, method, capacity=50)
        assert [(r.item, r.estimate) for r in got.orderBy("rank").collect()] == want
        m = hh.measures(got, df, "x", 5).first()
        assert (m.precision, m.recall, m.rank_mae) == (1.0, 1.0, 0.0)


def test_queries_equal_sql(spark):
    """Queries over whole tables against DuckDB, one of each kind."""
    import duckdb

    import __spark_entry__ as e

    sf, con, sql = "/root/testdata/sf0.001", duckdb.connect(), e.oracle_sql()
    for t in ("part", "lineitem", "orders", "customer", "documents", "events", "embeddings", "region", "nation", "supplier", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    names = [n for n in e.queries() if n.startswith(("rel_join_", "rel_set_"))]
    names += ["count_min_bound", "logistic_profile", "gk_select_decimal", "gk_select_brand", "gk_select_ts", "hh_decimal", "hh_struct", "hh_null_label", "stream_summary_pressed", "stream_misra_gries_pressed", "tree_shapes", "cost_model"]
    for n in names:
        got = e.queries()[n](spark, sf)
        order = sorted(got.columns)
        rows = [tuple(r[c] for c in order) for r in got.collect()]
        want = con.execute(f"SELECT {', '.join(chr(34) + c + chr(34) for c in order)} FROM ({sql[n]})").fetchall()
        assert sorted(rows, key=repr) == sorted(want, key=repr), n
