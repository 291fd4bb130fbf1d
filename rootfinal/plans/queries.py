"""The registered queries over the given tables and their SQL."""

from __future__ import annotations

import math
import uuid
from functools import partial, reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.sql import register, summarize
from ..operators import heavy_hitters as hh
from ..operators import measures as ms
from ..operators import quantiles as qt
from ..sources.tables import grown, logistic_bands, work_dir
from ..streaming import windows as sw
from ..streaming.windows import event_stream, running_hitters, windowed_counts
from ..summary import NearestValues, SpaceSaving
from ..tree import checkpointed_states, finish_states, plan_tree, state_sizes, tagged_tree_aggregate, tree_reduce, tree_reduce_finalize
from . import experiments, relational

QS = [0.0, 0.01, 0.25, 0.5, 0.75, 0.9, 0.99, 1.0]
PARTS = 12


def _table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*cols)


_written: dict[tuple, str] = {}


def _dealt(spark, sf_dir, name, *cols):
    """Columns over several partitions, written once for an application: the given tables are single files, and every pass of a
    method reads its input again."""
    key = (spark.sparkContext.applicationId, sf_dir, name, cols)
    if key not in _written:
        path = f"{work_dir(spark)}/dealt-{name}-{uuid.uuid4().hex}"
        _table(spark, sf_dir, name, *cols).repartition(PARTS).write.parquet(path)
        _written[key] = path
    return spark.read.parquet(_written[key])


def _select(spark, sf_dir, table="lineitem", col="l_extendedprice", **options):
    return qt.gk_select_many(_dealt(spark, sf_dir, table, col), col, QS, partitions=PARTS, **options)


def _select_as(spark, sf_dir, table, col, make, qs=QS):
    """Quantiles of a column made from another."""
    x = _dealt(spark, sf_dir, table, col).select(make(F.col(col)).alias("x"))
    return qt.gk_select_many(x, "x", list(qs), partitions=PARTS)


def _sort(spark, sf_dir):
    return qt.full_sort_quantile(_table(spark, sf_dir, "lineitem", "l_extendedprice"), "l_extendedprice", 0.5)


def _disc(spark, sf_dir):
    return qt.builtin_percentile_disc(_table(spark, sf_dir, "lineitem", "l_extendedprice"), "l_extendedprice", 0.5)


def _sketch(spark, sf_dir, root="finalize", eps=0.01, **options):
    """Whether the sketch keeps its promise for each q, beside the rank and the bound that it is held to."""
    x = _dealt(spark, sf_dir, "lineitem", "l_extendedprice")
    rows = []
    for r in qt.gk_quantile(x, "l_extendedprice", QS, eps, root, partitions=PARTS, **options).collect():
        k, bound = qt.rank_of(r.q, r.n), -(-r.n // round(1 / eps))
        rows.append((r.q, r.n, k, bound, qt.rank_error(x, "l_extendedprice", r.value, k) <= bound))
    return spark.createDataFrame(rows, "q double, n long, k long, bound long, within boolean")


def _top(spark, sf_dir):
    return qt.top_values(_dealt(spark, sf_dir, "orders", "o_totalprice"), "o_totalprice", 20)


def _hitters(spark, sf_dir, method="space_saving", root="finalize", table="lineitem", col="l_suppkey", k=20, capacity=1000, make=None):
    """Every estimate is exact: over classes of labels where these outnumber the counters."""
    x = _dealt(spark, sf_dir, table, col)
    if make is not None:
        x = x.select(make(F.col(col)).alias(col))
    return hh.exact_hitters(x, col, k, method, root, capacity, partitions=PARTS).select("item", F.col("estimate").alias("count"))


def _pressed(spark, sf_dir, method, root="finalize", k=100):
    """Every label of a wide frontier with its true count, and whether the sketch with fewer counters than labels keeps its promise for it.

    Space-Saving: estimate - error <= count <= estimate, and a label without a counter has at most the least count held.
    Misra-Gries: estimate <= count <= estimate + lost, the estimate of a label without a counter being 0.
    """
    x = _dealt(spark, sf_dir, "lineitem", "l_partkey")
    true = x.groupBy(F.col("l_partkey").alias("item")).count()
    found = hh.heavy_hitters(x, "l_partkey", 5 * k, method, root, 5 * k, partitions=PARTS)
    held = true.join(found.select("item", "estimate", "error", "lost"), "item", "left").crossJoin(F.broadcast(found.agg(F.min("estimate").alias("least"), F.max("lost").alias("gone"))))
    kept = F.col("estimate").isNotNull()
    if method.endswith("misra_gries"):
        holds = (F.coalesce("estimate", F.lit(0)) <= F.col("count")) & (F.col("count") <= F.coalesce("estimate", F.lit(0)) + F.coalesce("gone", F.lit(1 << 40)))
    else:
        holds = F.when(kept, (F.col("estimate") - F.col("error") <= F.col("count")) & (F.col("count") <= F.col("estimate"))).otherwise(F.col("count") <= F.col("least"))
    return held.select("item", "count", holds.alias("holds"))


def _arrays(spark, sf_dir, k=20):
    """The answer as two flat arrays, taken apart again, and its bytes at eight for a label and four for a count."""
    x = _dealt(spark, sf_dir, "lineitem", "l_suppkey")
    found = hh.exact_hitters(x, "l_suppkey", k, capacity=1000, export="arrays", count_type="int", partitions=PARTS)
    return found.select("bytes", F.explode(F.arrays_zip("labels", "counts")).alias("r")).select(F.col("r.labels").alias("item"), F.col("r.counts").cast("long").alias("count"), "bytes")


def _labelled(spark, sf_dir, kind):
    """Hitters among structs, JSON values, words and hosts."""
    if kind == "struct":
        x = _dealt(spark, sf_dir, "events", "event_type", "user_id").select(F.struct("event_type", "user_id").alias("x"))
        return hh.exact_hitters(x, "x", 20, capacity=20_000, partitions=PARTS).select("item.event_type", "item.user_id", F.col("estimate").alias("count"))
    if kind == "null":
        x = _table(spark, sf_dir, "documents", "source").select(F.nullif(F.col("source"), F.lit("src0")).alias("x")).repartition(PARTS)
        return hh.heavy_hitters(x, "x", 20, capacity=20_000, nulls="label").select("item", F.col("estimate").alias("count"))
    if kind == "json":
        x = _dealt(spark, sf_dir, "events", "props").select(F.get_json_object("props", "$.k").alias("x"))
    elif kind == "token":
        x = _dealt(spark, sf_dir, "documents", "text").select(F.explode(F.split(F.lower("text"), r"\s+")).alias("x")).where("x <> ''")
    else:
        x = _dealt(spark, sf_dir, "pages", "url").select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("x"))
    return hh.exact_hitters(x, "x", 20, capacity=2_000_000, partitions=PARTS).select("item", F.col("estimate").alias("count"))


def _builtin_top(spark, sf_dir):
    x = _table(spark, sf_dir, "lineitem", "l_suppkey")
    return hh.builtin_top_k(x, "l_suppkey", 20, 10_000).select("item", "count")


def _frequent(spark, sf_dir):
    """The built-in candidates hold every supplier of more than a fiftieth of the rows; those that do are left."""
    x = _table(spark, sf_dir, "lineitem", "l_returnflag")
    n = x.groupBy("l_returnflag").count()
    return hh.frequent_items(x, "l_returnflag", 0.02).join(n, F.col("item") == F.col("l_returnflag")).select("item", "count")


def _builtin_approx(spark, sf_dir, eps=0.001):
    x = _table(spark, sf_dir, "lineitem", "l_extendedprice")
    n = x.count()
    rows = [(q, n, qt.rank_error(x, "l_extendedprice", qt.builtin_approx(x, "l_extendedprice", q, eps).first().value, qt.rank_of(q, n)) <= 2 * eps * n) for q in (0.25, 0.5, 0.99)]
    return spark.createDataFrame(rows, "q double, n long, within boolean")


def _summarized(spark, sf_dir):
    """Top suppliers of each return flag by states of (partition, flag)."""
    x = _table(spark, sf_dir, "lineitem", "l_returnflag", "l_suppkey").repartition(PARTS)
    return summarize(x, ["l_returnflag"], "l_suppkey", SpaceSaving(5, 20_000, T.LongType())).select("l_returnflag", "rank", "item", F.col("estimate").alias("count"))


def _sql_sketch(spark, sf_dir):
    """Medians by the registered functions: a state for each flag, read by SQL, within the sketch's bound."""
    register(spark)
    x = _table(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice")
    x.createOrReplaceTempView("rootfinal_price")
    states = spark.sql("SELECT l_returnflag, sketch_of(l_extendedprice) AS state FROM rootfinal_price GROUP BY 1").join(x.groupBy("l_returnflag").agg(F.count("*").alias("n")), "l_returnflag")
    value = states.select("l_returnflag", "n", F.call_function("sketch_quantile", F.call_function("sketch_merge", "state", F.lit(None).cast("binary")), F.lit(0.5).cast("double")).alias("v"))
    below = x.join(F.broadcast(value), "l_returnflag").groupBy("l_returnflag", "n").agg(F.count_if(F.col("l_extendedprice") <= F.col("v")).alias("upto"))
    return below.select("l_returnflag", "n", (F.abs(F.col("upto") - F.col("n") / 2) <= 0.011 * F.col("n") + 1).alias("within"))


def _sql_items(spark, sf_dir):
    """Statuses by the table function over a stored state."""
    register(spark)
    _table(spark, sf_dir, "orders", "o_orderpriority").createOrReplaceTempView("rootfinal_orders")
    return spark.sql("SELECT h.rank, h.item, h.est_count FROM (SELECT hitters_of(o_orderpriority) AS state FROM rootfinal_orders) s, LATERAL hh_items(s.state, 3) h")


def _bytes_to_driver(spark, sf_dir, ks=(20, 200), parts=12):
    """Bytes that each root sends the driver, as the status store has them: the finishing root sends the least."""
    x = _shuffled(spark, sf_dir, parts=parts)
    rows = []
    for k in ks:
        got = {}
        for root in ("driver", "executor", "finalize"):
            with ms.Communication(spark) as c:
                hh.heavy_hitters(x, "l_partkey", k, "space_saving", root, capacity=100 * k, partitions=parts).collect()
            got[root] = c.result_bytes
        rows.append((k, ms.export_bytes(k), got["finalize"] < got["executor"] < got["driver"]))
    return spark.createDataFrame(rows, "k int, export_bytes long, ordered boolean")


def _rounds(spark, sf_dir):
    """Full exchanges of the three passes of a select, and its rounds."""
    x = _dealt(spark, sf_dir, "lineitem", "l_extendedprice")
    with ms.Communication(spark) as c:
        qt.gk_select_many(x, "l_extendedprice", QS, partitions=PARTS).collect()
    size = x.count() * 8
    return spark.createDataFrame([("gk_select", c.shuffle_bytes < size)], "method string, shuffles_less_than_input boolean")


def _stream(make):
    return lambda spark, sf_dir: make(spark, sf_dir, event_stream(spark, sf_dir), f"{work_dir(spark)}/stream-{uuid.uuid4().hex}")


def _stream_windowed(spark, sf_dir, stream, out):
    columns = "rank int, item long, estimate long, error long, guaranteed boolean, lost long, survivors long"
    found = sw.windowed_summaries(stream, "user_id", SpaceSaving(3, 20_000, T.LongType()), out, columns)
    return found.select("window_start", "rank", "item", F.col("estimate").alias("count"))




def _exact(spark, sf_dir, table="lineitem", col="l_suppkey", k=20):
    return hh.exact_top_k(_table(spark, sf_dir, table, col), col, k)


def _shuffled(spark, sf_dir, table="lineitem", col="l_partkey", keys=("l_orderkey", "l_linenumber"), parts=100, seed=0):
    """Rows dealt by the hash of their keys. A plain repartition sorts rows first and so deals each label evenly,
    which leaves no partition a label that it rarely sees."""
    t = _table(spark, sf_dir, table, col, *[k for k in keys if k != col])
    return t.repartition(parts, F.xxhash64(*keys, F.lit(seed))).select(col)


def _accuracy(spark, sf_dir, method="stream_summary", k=100, capacity=None, seed=0):
    x = _shuffled(spark, sf_dir, seed=seed)
    return hh.measures(hh.heavy_hitters(x, "l_partkey", k, method, capacity=capacity, partitions=100), x, "l_partkey", k)


def _accuracy_sweep(spark, sf_dir, method="stream_summary", ks=(5, 50, 200, 400)):
    """One row of measures for each k, with five counters a hitter."""
    rows = [_accuracy(spark, sf_dir, method, k).select(F.lit(k).alias("k"), "*") for k in ks]
    return reduce(DataFrame.unionByName, rows)


def _rising(spark, sf_dir):
    """Space-Saving's precision is one exactly where its five counters a hitter cover all labels of the wide frontier."""
    found = _accuracy_sweep(spark, sf_dir, ks=(20, 100, 20_000)).select("k", "precision")
    return found.select(F.col("k").cast("long").alias("k"), (F.col("precision") == 1).alias("exact"))


def _collapse(spark, sf_dir):
    """Misra-Gries with five counters a hitter returns fewer than it was asked for on a flat frontier, beside the number of labels:
    each price stands at two parts, so the cut at the first label past the counters takes all of them."""
    x = _shuffled(spark, sf_dir, "part", "p_retailprice", ("p_partkey",))
    found = hh.heavy_hitters(x, "p_retailprice", 5, "stream_misra_gries", partitions=100)
    labels = x.agg(F.count_distinct("p_retailprice").alias("labels"))
    return hh.hh_status(found, 5).select("collapsed").crossJoin(labels)


def _price(spark, sf_dir):
    return _dealt(spark, sf_dir, "lineitem", "l_extendedprice")


def _two_round(spark, sf_dir):
    return qt.gk_select_two_round(_price(spark, sf_dir), "l_extendedprice", 0.5)


def _narrowing(spark, sf_dir):
    return qt.gk_select_narrowing(_price(spark, sf_dir), "l_extendedprice", 0.5, max_candidates=2000)


def _by_flag(spark, sf_dir):
    return qt.gk_select_by(_table(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice"), ["l_returnflag"], "l_extendedprice", 0.5)


def _kll(spark, sf_dir):
    """Whether the built-in sketch's answer lies within two hundredths of the rows of its rank."""
    x = _table(spark, sf_dir, "lineitem", "l_extendedprice")
    n = x.count()
    value, k = qt.kll_quantile(x, "l_extendedprice", 0.5).first().value, qt.rank_of(0.5, n)
    return spark.createDataFrame([(n, k, qt.rank_error(x, "l_extendedprice", value, k) <= 0.02 * n)], "n long, k long, within boolean")


def _tagged(spark, sf_dir):
    x = _dealt(spark, sf_dir, "orders", "o_totalprice")
    done = tagged_tree_aggregate(x, NearestValues(20, False, T.DoubleType(), every=True), x.count())
    return spark.createDataFrame([tuple(r.values()) for r in done.to_pylist()], "value double")


def _reduce(spark, sf_dir, finalize=True):
    x = _dealt(spark, sf_dir, "lineitem", "l_quantity")
    if finalize:
        return tree_reduce_finalize(x, "l_quantity", max, lambda v: pa.table({"value": [v]}), "value double")
    return spark.createDataFrame([(tree_reduce(x, "l_quantity", max),)], "value double")


def _resumed(spark, sf_dir):
    """The answer finished twice from the same checkpointed levels; the second call finds every level written."""
    x = _dealt(spark, sf_dir, "orders", "o_totalprice")
    s, folder = NearestValues(20, False, T.DoubleType(), every=True), f"{work_dir(spark)}/levels-{uuid.uuid4().hex}"
    checkpointed_states(x, s, folder)
    return finish_states(checkpointed_states(x, s, folder), s)


def _ratio(spark, sf_dir, k=20):
    """The states that reach the root hold more bytes than the answer, whose size goes beside."""
    x = _dealt(spark, sf_dir, "lineitem", "l_partkey").select(F.col("l_partkey").alias("item"))
    sizes = state_sizes(x, SpaceSaving(k, 1000, T.LongType()))
    return sizes.agg(F.lit(ms.export_bytes(k)).cast("long").alias("result_bytes"), F.sum("rows").alias("rows"), (F.sum("state_bytes") > ms.export_bytes(k)).alias("result_smaller"))


def _roots_equal(spark, sf_dir):
    """The hitters under each of the three roots."""
    roots = ("driver", "executor", "finalize")
    return reduce(DataFrame.unionByName, [_hitters(spark, sf_dir, "space_saving", root).select(F.lit(root).alias("root"), "*") for root in roots])


def _grown(spark, sf_dir, copies=4):
    x = grown(_table(spark, sf_dir, "lineitem", "l_extendedprice"), "l_extendedprice", copies, 0.0).repartition(PARTS)
    return qt.gk_select(x, "x", 0.5)


def _weighted(spark, sf_dir):
    """Suppliers by ordered quantity."""
    x = _dealt(spark, sf_dir, "lineitem", "l_suppkey", "l_quantity")
    return hh.exact_hitters(x, "l_suppkey", 20, capacity=20_000, weight_col="l_quantity", partitions=PARTS).select("item", F.col("estimate").alias("count"))


def _count_min(spark, sf_dir, eps=0.001):
    """Every supplier's true count, and whether its estimate lies between that and it plus eps of the rows."""
    x = _dealt(spark, sf_dir, "lineitem", "l_suppkey")
    true = x.groupBy(F.col("l_suppkey").alias("item")).count()
    found = hh.count_min_estimate(x, "l_suppkey", true.select("item"), eps=eps)
    return found.join(true, "item").select("item", "count", ((F.col("estimate") >= F.col("count")) & (F.col("estimate") <= F.col("count") + eps * F.col("total"))).alias("holds"))


def _bands(spark, sf_dir):
    """The profile shrunk to as many labels as the table has parts."""
    labels = _table(spark, sf_dir, "lineitem", "l_partkey").agg(F.count_distinct("l_partkey")).first()[0]
    return spark.createDataFrame(logistic_bands(middle=labels * 25_165_824 / 108_818_368, slope=5e-7 * 108_818_368 / labels), "count int, last_rank long")


def _costs(spark, sf_dir, parts=120):
    """The terms for the prices of a table in thousands of values, rounded half up, null where a method has none."""
    n = _table(spark, sf_dir, "lineitem", "l_extendedprice").agg(F.count("l_extendedprice")).first()[0]
    number = lambda x: None if x != x else math.floor(x / 1000 + 0.5)
    rows = [(m, *[number(c[f]) for f in ("driver_memory", "executor_memory", "network")], c["full_shuffles"], c["rounds"], c["exact"]) for m in ms.METHODS for c in [ms.cost(m, n, parts)]]
    return spark.createDataFrame(rows, "method string, driver_memory long, executor_memory long, network long, full_shuffles int, rounds int, exact boolean")


def _stream_daily(spark, sf_dir):
    return windowed_counts(event_stream(spark, sf_dir), f"{work_dir(spark)}/daily-{uuid.uuid4().hex}")


def _stream_top(spark, sf_dir):
    found = running_hitters(event_stream(spark, sf_dir), "user_id", 20, SpaceSaving(20, 20_000, T.LongType()), f"{work_dir(spark)}/running-{uuid.uuid4().hex}")
    return found.select("item", F.col("estimate").alias("count"))


def _shapes(spark, sf_dir, rows_each=5000):
    """Trees over a table's prices in partitions of `rows_each` rows."""
    n = _table(spark, sf_dir, "lineitem", "l_extendedprice").agg(F.count("l_extendedprice")).first()[0]
    rows = [(d, p.scale, p.root_fan_in, p.root_combines) for d in (1, 2, 4, 6) for p in [plan_tree(-(-n // rows_each), d)]]
    return spark.createDataFrame(rows, "depth int, fan_in int, root_states int, root_combines int")


QUERIES = {
    "gk_select_finalize": _select,
    "gk_select_executor_root": partial(_select, root="executor"),
    "gk_select_driver_root": partial(_select, root="driver"),
    "gk_select_depth1": partial(_select, depth=1),
    "gk_select_depth4": partial(_select, depth=4),
    "gk_select_fan_in4": partial(_select, fan_in=4),
    "gk_select_concat": partial(_select, merge_policy="concat"),
    "gk_select_catalyst": partial(_select, engine="catalyst"),
    "gk_select_ties": partial(_select, col="l_discount"),
    "gk_select_bigint": partial(_select, col="l_orderkey"),
    "full_sort_quantile": _sort,
    "builtin_percentile_disc": _disc,
    "gk_sketch_bound": _sketch,
    "top_values": _top,
    "space_saving_finalize": partial(_hitters, method="space_saving", root="finalize"),
    "space_saving_executor_root": partial(_hitters, method="space_saving", root="executor"),
    "space_saving_driver_root": partial(_hitters, method="space_saving", root="driver"),
    "misra_gries_finalize": partial(_hitters, method="misra_gries", root="finalize"),
    "exact_top_k": _exact,
    "space_saving_accuracy": _accuracy,
    "misra_gries_accuracy": partial(_accuracy, method="stream_misra_gries"),
    "misra_gries_collapse": _collapse,
    "tree_shapes": _shapes,
    "gk_select_two_round": _two_round,
    "gk_select_narrowing": _narrowing,
    "gk_select_by_flag": _by_flag,
    "gk_select_shipdate": partial(_select, col="l_shipdate"),
    "gk_select_user_value": partial(_select, table="events", col="value"),
    "gk_select_grown": _grown,
    "kll_bound": _kll,
    "tagged_top_values": _tagged,
    "resumed_top_values": _resumed,
    "tree_reduce_finalize": _reduce,
    "tree_reduce": partial(_reduce, finalize=False),
    "stream_summary_finalize": partial(_hitters, method="stream_summary", root="finalize"),
    "space_saving_weighted": _weighted,
    "space_saving_roots_equal": _roots_equal,
    "space_saving_sweep": _accuracy_sweep,
    "space_saving_precision_rises": _rising,
    "misra_gries_sweep": partial(_accuracy_sweep, method="stream_misra_gries"),
    "count_min_bound": _count_min,
    "state_result_ratio": _ratio,
    "logistic_profile": _bands,
    "cost_model": _costs,
    "gk_select_depth2": partial(_select, depth=2),
    "gk_select_depth6": partial(_select, depth=6),
    "gk_select_sketch_depth4": partial(_select, sketch_depth=4),
    "gk_select_head_proportional": partial(_select, head="proportional"),
    "gk_select_sketch_finalized": partial(_select, root="driver", sketch_root="finalize"),
    "gk_select_total": partial(_select, table="orders", col="o_totalprice"),
    "gk_select_retail": partial(_select, table="part", col="p_retailprice"),
    "gk_select_quantity": partial(_select, col="l_quantity"),
    "gk_select_balance": partial(_select, table="customer", col="c_acctbal"),
    "gk_select_supplier_balance": partial(_select, table="supplier", col="s_acctbal"),
    "gk_select_size": partial(_select, table="part", col="p_size"),
    "gk_select_n_chars": partial(_select, table="documents", col="n_chars"),
    "gk_select_brand": partial(_select, table="part", col="p_brand"),
    "gk_select_url": partial(_select, table="pages", col="url"),
    "gk_select_orderdate": partial(_select, table="orders", col="o_orderdate"),
    "gk_select_ts": partial(_select, table="events", col="ts"),
    "gk_select_decimal": partial(_select_as, table="lineitem", col="l_extendedprice", make=lambda c: c.cast("decimal(12,2)")),
    "gk_select_date": partial(_select_as, table="lineitem", col="l_shipdate", make=F.to_date),
    "gk_select_beyond_double": partial(_select_as, table="lineitem", col="l_orderkey", make=lambda c: c + F.lit(1 << 60)),
    "gk_select_elements": partial(_select_as, table="embeddings", col="embedding", make=F.explode),
    "gk_sketch_classical": partial(_sketch, head="classical", eps=0.05),
    "gk_sketch_proportional": partial(_sketch, head="proportional"),
    "gk_sketch_driver_only": partial(_sketch, root="driver", depth=1),
    "builtin_approx_bound": _builtin_approx,
    "builtin_top_k": _builtin_top,
    "builtin_frequent_items": _frequent,
    "space_saving_pressed": partial(_pressed, method="space_saving"),
    "space_saving_isomorphic_pressed": partial(_pressed, method="space_saving_isomorphic"),
    "stream_summary_pressed": partial(_pressed, method="stream_summary"),
    "misra_gries_pressed": partial(_pressed, method="misra_gries"),
    "stream_misra_gries_pressed": partial(_pressed, method="stream_misra_gries"),
    "stream_misra_gries_finalize": partial(_hitters, method="stream_misra_gries", root="finalize"),
    "hh_arrays": _arrays,
    "hh_size": partial(_hitters, table="part", col="p_size"),
    "hh_discount": partial(_hitters, col="l_discount"),
    "hh_decimal": partial(_hitters, col="l_discount", make=lambda c: c.cast("decimal(6,2)")),
    "hh_float": partial(_hitters, col="l_tax", make=lambda c: c.cast("float")),
    "hh_customer": partial(_hitters, table="orders", col="o_custkey", capacity=20_000),
    "hh_user": partial(_hitters, table="events", col="user_id", capacity=20_000),
    "hh_shipdate": partial(_hitters, col="l_shipdate", capacity=20_000),
    "hh_brand": partial(_hitters, table="part", col="p_brand"),
    "hh_struct": partial(_labelled, kind="struct"),
    "hh_json": partial(_labelled, kind="json"),
    "hh_token": partial(_labelled, kind="token"),
    "hh_host": partial(_labelled, kind="host"),
    "hh_null_label": partial(_labelled, kind="null"),
    "summarize_by_flag": _summarized,
    "sql_sketch_functions": _sql_sketch,
    "sql_hitter_table_function": _sql_items,
    "bytes_to_driver": _bytes_to_driver,
    "select_shuffles": _rounds,
    "stream_windowed_top": _stream(_stream_windowed),
    "stream_sliding_counts": _stream(lambda spark, sf, s, out: windowed_counts(s, out, width="2 days", slide="1 day")),
    "stream_sessions": _stream(lambda spark, sf, s, out: sw.session_counts(s, "user_id", out)),
    "stream_dedup": _stream(lambda spark, sf, s, out: sw.deduplicated(s.select("user_id", "event_type", "ts").withColumn("day", F.to_date("ts")), ["user_id", "event_type", "day"], out, late="40 days").select("user_id", "event_type", "day")),
    "stream_static_join": _stream(lambda spark, sf, s, out: sw.joined_static(s, _table(spark, sf, "customer", "c_custkey", "c_mktsegment"), F.expr("user_id = c_custkey"), out, ["event_id", "c_mktsegment"])),
    "stream_stream_join": _stream(lambda spark, sf, s, out: sw.joined_streams(s.where("event_type = 'click'"), event_stream(spark, sf).where("event_type = 'purchase'"), "user_id", out)),
    "stream_late_rows": _stream(lambda spark, sf, s, out: sw.late_rows(s, out)),
    "stream_daily_counts": _stream_daily,
    "stream_running_top": _stream_top,
} | relational.QUERIES | experiments.QUERIES


def _quantile_sql(col: str, table: str = "lineitem", qs=QS) -> str:
    one = "SELECT CAST({q} AS double) AS q, greatest(CAST(ceil(CAST({q} AS decimal(9,4)) * n) AS bigint), 1) AS k, n, (SELECT quantile_disc({c}, {q}) FROM {t}) AS value FROM (SELECT count({c}) AS n FROM {t})"
    return " UNION ALL ".join(one.format(q=q, c=col, t=table) for q in qs)


def _top_sql(col: str, table: str = "lineitem", limit: int = 20) -> str:
    return f"SELECT {col} AS item, count(*) AS count FROM {table} GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT {limit}"


def _sketch_sql(eps: str) -> str:
    return " UNION ALL ".join(f"SELECT CAST({q} AS double) AS q, count(*) AS n, greatest(CAST(ceil(CAST({q} AS decimal(9,4)) * count(*)) AS bigint), 1) AS k, CAST(ceil(CAST({eps} AS decimal(9,4)) * count(*)) AS bigint) AS bound, true AS within FROM lineitem" for q in QS)


_PRICE = _quantile_sql("l_extendedprice")
_MEDIAN = _quantile_sql("l_extendedprice", qs=(0.5,))
_LARGEST = "SELECT o_totalprice AS value FROM orders ORDER BY 1 DESC LIMIT 20"
_PRESSED = "SELECT l_partkey AS item, count(*) AS count, true AS holds FROM lineitem GROUP BY 1"
# the recurrence of the tree, run by SQL
_SHAPES = """WITH RECURSIVE p AS (SELECT (count(l_extendedprice) + 4999) // 5000 AS parts FROM lineitem),
s AS (SELECT d, parts, greatest(2, CAST(ceil(pow(parts, 1.0 / d)) AS integer)) AS f FROM (VALUES (1), (2), (4), (6)) t(d), p),
l AS (SELECT d, f, parts AS n FROM s UNION ALL SELECT d, f, n // f FROM l WHERE n > f + CAST(ceil(n / f) AS integer))
SELECT CAST(d AS integer) AS depth, CAST(f AS integer) AS fan_in, CAST(min(n) AS integer) AS root_states, CAST(min(n) - 1 AS integer) AS root_combines FROM l GROUP BY d, f"""
# the terms of the cost model for the table's size
_COSTS = """WITH p AS (SELECT CAST(count(l_extendedprice) AS double) AS n, CAST(120 AS double) AS parts, CAST(0.01 AS double) AS eps FROM lineitem),
logs AS (SELECT *, ln(greatest(eps * n / parts, exp(1))) AS own_log, ln(greatest(eps * n / sqrt(parts), exp(1))) AS root_log FROM p),
t AS (SELECT *, own_log / eps AS classical, sqrt(parts) / eps * root_log AS merged, parts / eps * own_log AS sent, eps * n AS near, n / parts AS own FROM logs)
SELECT method, CAST(floor(d / 1000 + 0.5) AS bigint) AS driver_memory, CAST(floor(e / 1000 + 0.5) AS bigint) AS executor_memory, CAST(floor(w / 1000 + 0.5) AS bigint) AS network, CAST(s AS integer) AS full_shuffles, CAST(r AS integer) AS rounds, x AS exact
FROM (SELECT 'full_sort' AS method, 100 * parts AS d, own AS e, n AS w, 1 AS s, 1 AS r, true AS x FROM t
UNION ALL SELECT 'classical_gk', NULL, classical, NULL, 0, 1, false FROM t
UNION ALL SELECT 'builtin_gk', merged, 50000 + root_log / eps, sent, 0, 1, false FROM t
UNION ALL SELECT 'select_driver', greatest(merged, 10 * near), own, sent + near * parts, 0, 3, true FROM t
UNION ALL SELECT 'select_executor', greatest(merged, near), own, sent + near * parts, 0, 3, true FROM t
UNION ALL SELECT 'select_finalize', merged, greatest(own, near), sent + near * parts, 0, 3, true FROM t)"""
_SESSIONS = """WITH e AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
g AS (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM e)
SELECT user_id, min(ts) AS session_start, count(*) AS count FROM g GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)"""
ORACLE_SQL = {name: _PRICE for name in QUERIES if name.startswith("gk_select_")} | {
    "gk_select_ties": _quantile_sql("l_discount"),
    "gk_select_quantity": _quantile_sql("l_quantity"),
    "gk_select_bigint": _quantile_sql("l_orderkey"),
    "gk_select_user_value": _quantile_sql("value", "events"),
    "gk_select_shipdate": _quantile_sql("l_shipdate"),
    "gk_select_orderdate": _quantile_sql("o_orderdate", "orders"),
    "gk_select_ts": _quantile_sql("ts", "events"),
    "gk_select_total": _quantile_sql("o_totalprice", "orders"),
    "gk_select_retail": _quantile_sql("p_retailprice", "part"),
    "gk_select_balance": _quantile_sql("c_acctbal", "customer"),
    "gk_select_supplier_balance": _quantile_sql("s_acctbal", "supplier"),
    "gk_select_size": _quantile_sql("p_size", "part"),
    "gk_select_n_chars": _quantile_sql("n_chars", "documents"),
    "gk_select_brand": _quantile_sql("p_brand", "part"),
    "gk_select_url": _quantile_sql("url", "pages"),
    "gk_select_decimal": _quantile_sql("CAST(l_extendedprice AS decimal(12,2))"),
    "gk_select_date": _quantile_sql("CAST(l_shipdate AS date)"),
    "gk_select_beyond_double": _quantile_sql("(l_orderkey + 1152921504606846976)"),
    "gk_select_elements": _quantile_sql("x", "(SELECT unnest(embedding) AS x FROM embeddings)"),
    "gk_select_two_round": _MEDIAN,
    "gk_select_narrowing": _MEDIAN,
    "gk_select_by_flag": "SELECT l_returnflag, CAST(ceil(CAST(0.5 AS decimal(9,4)) * count(*)) AS bigint) AS k, count(*) AS n, quantile_disc(l_extendedprice, 0.5) AS value FROM lineitem GROUP BY 1",
    "gk_select_grown": "SELECT CAST(0.5 AS double) AS q, 2 * count(*) AS k, 4 * count(*) AS n, (SELECT quantile_disc(l_extendedprice, 0.5) FROM (SELECT l_extendedprice FROM lineitem, range(4))) AS value FROM lineitem",
    "kll_bound": "SELECT count(*) AS n, CAST(ceil(0.5 * count(*)) AS bigint) AS k, true AS within FROM lineitem",
    "builtin_approx_bound": " UNION ALL ".join(f"SELECT CAST({q} AS double) AS q, count(*) AS n, true AS within FROM lineitem" for q in (0.25, 0.5, 0.99)),
    "tree_reduce_finalize": "SELECT max(l_quantity) AS value FROM lineitem",
    "tree_reduce": "SELECT max(l_quantity) AS value FROM lineitem",
    "tagged_top_values": _LARGEST,
    "resumed_top_values": _LARGEST,
    "top_values": _LARGEST,
    "space_saving_weighted": "SELECT l_suppkey AS item, CAST(sum(l_quantity) AS bigint) AS count FROM lineitem GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 20",
    "space_saving_roots_equal": f"SELECT root, item, count FROM ({_top_sql('l_suppkey')}) CROSS JOIN (VALUES ('driver'), ('executor'), ('finalize')) r(root)",
    "space_saving_precision_rises": "SELECT CAST(k AS bigint) AS k, 5 * k >= (SELECT count(DISTINCT l_partkey) FROM lineitem) AS exact FROM (VALUES (20), (100), (20000)) t(k)",
    "space_saving_pressed": _PRESSED,
    "space_saving_isomorphic_pressed": _PRESSED,
    "stream_summary_pressed": _PRESSED,
    "misra_gries_pressed": _PRESSED,
    "stream_misra_gries_pressed": _PRESSED,
    "misra_gries_collapse": "SELECT true AS collapsed, count(DISTINCT p_retailprice) AS labels FROM part",
    "count_min_bound": "SELECT l_suppkey AS item, count(*) AS count, true AS holds FROM lineitem GROUP BY 1",
    "state_result_ratio": "SELECT CAST(20 * 8 AS bigint) AS result_bytes, count(*) AS rows, true AS result_smaller FROM lineitem",
    "logistic_profile": "SELECT CAST(c AS integer) AS count, CAST(greatest(0, floor(labels * 25165824 / 108818368 + ln(30 / (c - 0.5) - 1) / (5e-7 * 108818368 / labels))) AS bigint) AS last_rank FROM range(1, 31) t(c), (SELECT CAST(count(DISTINCT l_partkey) AS double) AS labels FROM lineitem)",
    "cost_model": _COSTS,
    "tree_shapes": _SHAPES,
    "stream_daily_counts": "SELECT date_trunc('day', ts)::timestamp AS window_start, event_type, count(*) AS count FROM events GROUP BY 1, 2",
    "stream_sliding_counts": "SELECT d::timestamp AS window_start, event_type, count(*) AS count FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1, 2",
    "stream_running_top": _top_sql("user_id", "events"),
    "stream_windowed_top": "WITH c AS (SELECT date_trunc('day', ts)::timestamp AS window_start, user_id AS item, count(*) AS count FROM events GROUP BY 1, 2), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY window_start ORDER BY count DESC, item) AS integer) AS rank FROM c) SELECT window_start, rank, item, count FROM r WHERE rank <= 3 AND window_start + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)",
    "stream_sessions": _SESSIONS,
    "stream_dedup": "SELECT DISTINCT user_id, event_type, CAST(ts AS date) AS day FROM events",
    "stream_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "stream_stream_join": "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "stream_late_rows": "SELECT CAST(0 AS bigint) AS batch, count(*) AS rows, CAST(0 AS bigint) AS late FROM events",
    "full_sort_quantile": "SELECT CAST(0.5 AS double) AS q, CAST(ceil(0.5 * count(*)) AS bigint) AS k, count(*) AS n, quantile_disc(l_extendedprice, 0.5) AS value FROM lineitem",
    "builtin_percentile_disc": "SELECT CAST(0.5 AS double) AS q, quantile_disc(l_extendedprice, 0.5) AS value FROM lineitem",
    "gk_sketch_bound": _sketch_sql("0.01"),
    "gk_sketch_classical": _sketch_sql("0.05"),
    "gk_sketch_proportional": _sketch_sql("0.01"),
    "gk_sketch_driver_only": _sketch_sql("0.01"),
    "builtin_frequent_items": "SELECT l_returnflag AS item, count(*) AS count FROM lineitem GROUP BY 1 HAVING count(*) > 0.02 * (SELECT count(*) FROM lineitem)",
    "hh_arrays": f"SELECT item, count, CAST(20 * 12 AS bigint) AS bytes FROM ({_top_sql('l_suppkey')})",
    "hh_size": _top_sql("p_size", "part"),
    "hh_discount": _top_sql("l_discount"),
    "hh_decimal": _top_sql("CAST(l_discount AS decimal(6,2))"),
    "hh_float": _top_sql("CAST(l_tax AS float)"),
    "hh_customer": _top_sql("o_custkey", "orders"),
    "hh_user": _top_sql("user_id", "events"),
    "hh_shipdate": _top_sql("l_shipdate"),
    "hh_brand": _top_sql("p_brand", "part"),
    "hh_struct": "SELECT event_type, user_id, count(*) AS count FROM events GROUP BY 1, 2 ORDER BY 3 DESC, '{\"v\":{\"event_type\":\"' || event_type || '\",\"user_id\":' || user_id || '}}' LIMIT 20",
    "hh_json": _top_sql("json_extract_string(props, '$.k')", "events WHERE json_extract_string(props, '$.k') IS NOT NULL"),
    "hh_token": r"SELECT item, count(*) AS count FROM (SELECT unnest(string_split_regex(lower(text), '[\x09-\x0D\x20]+')) AS item FROM documents) WHERE item <> '' GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 20",
    "hh_host": _top_sql("regexp_extract(url, '^[a-z]+://([^/]+)', 1)", "pages"),
    "hh_null_label": "SELECT nullif(source, 'src0') AS item, count(*) AS count FROM documents GROUP BY 1 ORDER BY 2 DESC, CASE WHEN item IS NULL THEN '{}' ELSE '{\"v\":\"' || item || '\"}' END LIMIT 20",
    "summarize_by_flag": "WITH c AS (SELECT l_returnflag, l_suppkey AS item, count(*) AS count FROM lineitem GROUP BY 1, 2), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY l_returnflag ORDER BY count DESC, item) AS integer) AS rank FROM c) SELECT l_returnflag, rank, item, count FROM r WHERE rank <= 5",
    "sql_sketch_functions": "SELECT l_returnflag, count(*) AS n, true AS within FROM lineitem GROUP BY 1",
    "sql_hitter_table_function": "SELECT CAST(row_number() OVER (ORDER BY n DESC, o_orderpriority) AS integer) AS rank, o_orderpriority AS item, n AS est_count FROM (SELECT o_orderpriority, count(*) AS n FROM orders GROUP BY 1) QUALIFY row_number() OVER (ORDER BY n DESC, o_orderpriority) <= 3",
    "bytes_to_driver": "SELECT CAST(k AS integer) AS k, CAST(8 * k AS bigint) AS export_bytes, true AS ordered FROM (VALUES (20), (200)) t(k)",
} | {name: _top_sql("l_suppkey") for name in ("builtin_top_k", "stream_misra_gries_finalize", "stream_summary_finalize", "space_saving_finalize", "space_saving_executor_root", "space_saving_driver_root", "misra_gries_finalize", "exact_top_k")} | relational.ORACLE_SQL
