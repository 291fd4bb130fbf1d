"""Relational operators around the methods, each with its SQL: preparing inputs, ground truth and evaluation."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.sql import order_code
from ..operators.quantiles import gk_select_many
from ..operators.ranking import global_rank
from ..sources.tables import load

_money = lambda c: F.col(c).cast("decimal(18,2)")


def _join(how: str, hint: str | None = None) -> Callable:
    """Days with orders and days with shipments: each side has days that the other lacks."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        ordered = load(spark, sf, "orders").groupBy(F.to_date("o_orderdate").alias("ordered")).agg(F.count("*").alias("orders"))
        shipped = load(spark, sf, "lineitem").groupBy(F.to_date("l_shipdate").alias("shipped")).agg(F.count("*").alias("lines"))
        return ordered.join(shipped.hint(hint) if hint else shipped, ordered.ordered == shipped.shipped, how)

    return run


_ORDERED = "(SELECT CAST(o_orderdate AS date) AS ordered, count(*) AS orders FROM orders GROUP BY 1)"
_SHIPPED = "(SELECT CAST(l_shipdate AS date) AS shipped, count(*) AS lines FROM lineitem GROUP BY 1)"


def _join_sql(how: str) -> str:
    return f"SELECT * FROM {_ORDERED} o {how} JOIN {_SHIPPED} s ON o.ordered = s.shipped"


def _sets(method: str) -> Callable:
    """Keys of ordering customers against keys of shipping suppliers: whole columns with repeats, and keys that one side lacks."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        a = load(spark, sf, "orders").select(F.col("o_custkey").alias("key"))
        b = load(spark, sf, "lineitem").select(F.col("l_suppkey").alias("key"))
        return getattr(a, method)(b)

    return run


def _sets_sql(op: str) -> str:
    return f"SELECT o_custkey AS key FROM orders {op} SELECT l_suppkey AS key FROM lineitem"


def _window(**columns) -> Callable:
    """Columns over customers of a nation by balance."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        w = Window.partitionBy("c_nationkey").orderBy(F.col("c_acctbal").desc(), "c_custkey")
        t = load(spark, sf, "customer", "c_custkey", "c_nationkey", "c_acctbal")
        return t.select("c_custkey", *[make(w).alias(name) for name, make in columns.items()])

    return run


def _window_sql(**columns) -> str:
    return f"SELECT c_custkey, {', '.join(f'{e} AS {n}' for n, e in columns.items())} FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)"


def _star(spark: SparkSession, sf: str) -> DataFrame:
    t = load(spark, sf, "lineitem", "l_orderkey", "l_extendedprice").join(load(spark, sf, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    t = t.join(load(spark, sf, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    t = t.join(load(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(load(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return t.groupBy("r_name").agg(F.sum(_money("l_extendedprice")).cast("string").alias("total"), F.count("*").alias("n"))


def _asof(spark: SparkSession, sf: str) -> DataFrame:
    """Each purchase with the same user's latest earlier click: one sort per user instead of a range join."""
    e = load(spark, sf, "events", "event_id", "user_id", "ts", "event_type").where("event_type IN ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("click_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "click_id")


def _interval(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of one user's events within an hour: an equi-join on user and hour, each event in its own and the next."""
    e = load(spark, sf, "events", "event_id", "user_id", "ts")
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("at"), F.date_trunc("hour", "ts").alias("hour"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("bt"), F.date_trunc("hour", "ts").alias("own")).withColumn("hour", F.explode(F.array("own", F.expr("own - INTERVAL 1 HOUR")))).drop("own")
    return a.join(b, ["user_id", "hour"]).where("bt > at AND bt <= at + INTERVAL 1 HOUR").groupBy("user_id").agg(F.count("*").alias("pairs"))


def _salted(spark: SparkSession, sf: str, salts: int = 16) -> DataFrame:
    """Words joined with their counts, hot words dealt over salts on one side and copied on the other, the others unsalted."""
    words = load(spark, sf, "documents").select(F.explode(F.split(F.lower("text"), r"\s+")).alias("word")).where("word <> ''")
    counts = words.withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy("word", "salt").count()
    total = counts.groupBy("word").agg(F.sum("count").alias("n"))
    copied = total.where("n >= 100").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    joined = counts.join(copied, ["word", "salt"]).select("word", "count")
    joined = joined.unionByName(counts.join(total.where("n < 100"), "word").select("word", "count"))
    return joined.groupBy("word").agg(F.sum("count").alias("n"))


def _group(mode: str) -> Callable:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        t = load(spark, sf, "lineitem", "l_returnflag", "l_linestatus")
        return getattr(t, mode)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))

    return run


def _histogram(spark: SparkSession, sf: str) -> DataFrame:
    counts = load(spark, sf, "lineitem", "l_partkey").groupBy("l_partkey").agg(F.count("*").alias("times"))
    return counts.groupBy("times").agg(F.count("*").alias("labels"))


def _two_level(spark: SparkSession, sf: str, width: int = 11) -> DataFrame:
    """A depth-two tree over built-in aggregates."""
    t = load(spark, sf, "lineitem", "l_orderkey", "l_extendedprice")
    nodes = t.groupBy(F.pmod("l_orderkey", F.lit(width)).alias("node")).agg(F.sum(_money("l_extendedprice")).alias("s"), F.count("*").alias("c"), F.max("l_extendedprice").alias("m"))
    return nodes.agg(F.sum("s").cast("string").alias("total"), F.sum("c").alias("n"), F.max("m").alias("most"))


def _scalars(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "events", "event_id", "ts", "value", "props")
    return e.select("event_id", F.floor("value").cast("long").alias("whole"), F.date_trunc("day", "ts").alias("day"), F.get_json_object("props", "$.k").cast("string").alias("k"), F.year("ts").cast("long").alias("y"), F.greatest("value", F.lit(10.0)).alias("least10"))


def _hosts(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "pages", "url").groupBy(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("n"))


def _elements(spark: SparkSession, sf: str) -> DataFrame:
    v = load(spark, sf, "embeddings", "label", "embedding").select("label", F.explode("embedding").alias("x"))
    return v.groupBy("label").agg(F.max("x").cast("double").alias("most"), F.count("*").alias("n"))


def _simple(table: str, make: Callable[[DataFrame], DataFrame]) -> Callable:
    return lambda spark, sf: make(load(spark, sf, table))


def sampled(df: DataFrame, key: str, one_of: int) -> DataFrame:
    """About one row of `one_of` (a power of two up to 16) by the key's md5: the same rows under any partitioning."""
    return df.where(F.md5(F.col(key).cast("string")) < F.lit(f"{16 // one_of:x}"))


def _roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Every value and time coded and decoded again."""
    e = load(spark, sf, "events", "event_id", "value", "ts")
    coded = order_code(order_code(e, "value", "c1", "value_back"), "ts", "c2", "ts_back").where("ts = ts_back")
    return coded.select("event_id", F.col("value_back").alias("value"), F.col("c2").alias("at"))


def _nested(spark: SparkSession, sf: str) -> DataFrame:
    r, n = load(spark, sf, "region"), load(spark, sf, "nation")
    return r.join(F.broadcast(n), (F.col("r_regionkey") != F.col("n_regionkey")) & (F.length("r_name") < F.length("n_name"))).select("r_name", "n_name")


def _buckets(spark: SparkSession, sf: str) -> DataFrame:
    """Prices by the exact quartiles: a join on ranges with as many rows as there are buckets."""
    x = load(spark, sf, "lineitem", "l_extendedprice")
    cuts = [r.value for r in gk_select_many(x, "l_extendedprice", [0.25, 0.5, 0.75]).orderBy("q").collect()]
    edges = [float("-inf"), *cuts, float("inf")]
    bounds = spark.createDataFrame([(i, edges[i], edges[i + 1]) for i in range(4)], "bucket int, low double, high double")
    return x.join(F.broadcast(bounds), (F.col("l_extendedprice") >= F.col("low")) & (F.col("l_extendedprice") < F.col("high"))).groupBy("bucket").agg(F.count("*").alias("n"))


def _same_nation(spark: SparkSession, sf: str) -> DataFrame:
    s = load(spark, sf, "supplier", "s_suppkey", "s_nationkey")
    return s.alias("a").join(s.alias("b"), (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


def _approx_distinct(spark: SparkSession, sf: str) -> DataFrame:
    t = load(spark, sf, "lineitem", "l_returnflag", "l_partkey").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.01).alias("about"))
    return t.select("l_returnflag", "exact", (F.abs(F.col("about") - F.col("exact")) <= 0.05 * F.col("exact")).alias("near"))


def _grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    t = load(spark, sf, "lineitem", "l_returnflag", "l_linestatus")
    flag, status = F.col("l_returnflag"), F.col("l_linestatus")
    return t.groupingSets([[flag], [status], []], flag, status).agg(F.count("*").alias("n"))


def _percentiles(spark: SparkSession, sf: str) -> DataFrame:
    t = load(spark, sf, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag")
    return t.agg(F.expr("percentile_disc(0.25) WITHIN GROUP (ORDER BY l_quantity)").alias("disc"), F.expr("percentile_cont(0.25) WITHIN GROUP (ORDER BY l_quantity)").alias("cont"), F.median("l_quantity").alias("mid"))


def _near_balance(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal").rangeBetween(-500, 500)
    return load(spark, sf, "customer").select("c_custkey", F.count("*").over(w).alias("near"))


def _within(spark: SparkSession, sf: str) -> DataFrame:
    """Rows numbered within their supplier off partitions sorted by it."""
    t = load(spark, sf, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber").repartition("l_suppkey").sortWithinPartitions("l_suppkey", "l_orderkey", "l_linenumber")
    w = Window.partitionBy("l_suppkey").orderBy("l_orderkey", "l_linenumber")
    return t.select("*", F.row_number().over(w).cast("long").alias("place"))


def _maps(spark: SparkSession, sf: str) -> DataFrame:
    counts = load(spark, sf, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))
    m = counts.groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m"))
    return m.select("l_returnflag", F.coalesce(F.try_element_at("m", F.lit("O")), F.lit(0)).cast("long").alias("open"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


REL: dict[str, tuple[Callable, str | None]] = {
    "rel_project_prune": (_simple("lineitem", lambda t: t.select("l_extendedprice")), "SELECT l_extendedprice FROM lineitem"),
    "rel_project_expr": (_simple("part", lambda t: t.select("p_partkey", (_money("p_retailprice") * 2).cast("string").alias("twice"))), "SELECT p_partkey, CAST(CAST(p_retailprice AS decimal(18,2)) * 2 AS varchar) AS twice FROM part"),
    "rel_filter_between": (_simple("lineitem", lambda t: t.where(F.col("l_extendedprice").between(50000, 51000)).select("l_orderkey", "l_linenumber")), "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_extendedprice BETWEEN 50000 AND 51000"),
    "rel_filter_in_like": (_simple("part", lambda t: t.where(F.col("p_brand").like("Brand#1%") & F.col("p_size").isin(1, 5, 9)).select("p_partkey")), "SELECT p_partkey FROM part WHERE p_brand LIKE 'Brand#1%' AND p_size IN (1, 5, 9)"),
    "rel_filter_null": (_simple("documents", lambda t: t.where("source IS NULL OR text IS NOT NULL").select("doc_id")), "SELECT doc_id FROM documents WHERE source IS NULL OR text IS NOT NULL"),
    "rel_join_hash": (_join("inner", "shuffle_hash"), _join_sql("INNER")),
    "rel_join_sortmerge": (_join("inner", "merge"), _join_sql("INNER")),
    "rel_join_left": (_join("left"), _join_sql("LEFT")),
    "rel_join_right": (_join("right"), _join_sql("RIGHT")),
    "rel_join_full": (_join("full"), _join_sql("FULL")),
    "rel_join_semi": (_join("left_semi"), _join_sql("SEMI")),
    "rel_join_anti": (_join("left_anti"), _join_sql("ANTI")),
    "rel_join_star": (_star, "SELECT r_name, CAST(sum(CAST(l_extendedprice AS decimal(18,2))) AS varchar) AS total, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"),
    "rel_join_asof": (_asof, "WITH e AS (SELECT * FROM events WHERE event_type IN ('click', 'purchase')), s AS (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click_id FROM e) SELECT event_id, click_id FROM s WHERE event_type = 'purchase'"),
    "rel_join_interval": (_interval, "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1"),
    "rel_join_skew_salted": (_salted, r"SELECT word, count(*) AS n FROM (SELECT unnest(string_split_regex(lower(text), '[\x09-\x0D\x20]+')) AS word FROM documents) WHERE word <> '' GROUP BY 1"),
    "rel_agg_group": (_simple("lineitem", lambda t: t.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(_money("l_extendedprice")).cast("string").alias("total"), F.min("l_quantity").alias("least"))), "SELECT l_returnflag, count(*) AS n, CAST(sum(CAST(l_extendedprice AS decimal(18,2))) AS varchar) AS total, min(l_quantity) AS least FROM lineitem GROUP BY 1"),
    "rel_agg_partial_final": (_two_level, "SELECT CAST(sum(CAST(l_extendedprice AS decimal(18,2))) AS varchar) AS total, count(*) AS n, max(l_extendedprice) AS most FROM lineitem"),
    "rel_agg_distinct": (_simple("lineitem", lambda t: t.agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))), "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem"),
    "rel_agg_filtered": (_simple("lineitem", lambda t: t.agg(F.count_if(F.col("l_quantity") < 25).alias("below"), F.count_if(F.col("l_quantity") == 25).alias("equal"))), "SELECT count(*) FILTER (l_quantity < 25) AS below, count(*) FILTER (l_quantity = 25) AS equal FROM lineitem"),
    "rel_agg_cube": (_group("cube"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "rel_agg_rollup": (_group("rollup"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "rel_agg_having": (_simple("lineitem", lambda t: t.groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600")), "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 600"),
    "rel_agg_count_histogram": (_histogram, "SELECT times, count(*) AS labels FROM (SELECT count(*) AS times FROM lineitem GROUP BY l_partkey) GROUP BY 1"),
    "rel_agg_max_by": (_simple("part", lambda t: t.groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("dearest"))), "SELECT p_brand, arg_max(p_partkey, {'a': p_retailprice, 'b': p_partkey}) AS dearest FROM part GROUP BY 1"),
    "rel_win_ranks": (_window(rn=lambda w: F.row_number().over(w).cast("long"), rk=lambda w: F.rank().over(w).cast("long"), dr=lambda w: F.dense_rank().over(w).cast("long"), nt=lambda w: F.ntile(4).over(w).cast("long")), _window_sql(rn="row_number() OVER w", rk="rank() OVER w", dr="dense_rank() OVER w", nt="ntile(4) OVER w")),
    "rel_win_neighbours": (_window(before=lambda w: F.lag("c_acctbal").over(w), after=lambda w: F.lead("c_acctbal").over(w), top=lambda w: F.first("c_acctbal").over(w)), _window_sql(before="lag(c_acctbal) OVER w", after="lead(c_acctbal) OVER w", top="first_value(c_acctbal) OVER w")),
    "rel_win_rows_frame": (_window(near=lambda w: F.max("c_acctbal").over(w.rowsBetween(-2, 2)), upto=lambda w: F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0))), "SELECT c_custkey, max(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near, count(*) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey ROWS UNBOUNDED PRECEDING) AS upto FROM customer"),
    "rel_win_topk_per_group": (_simple("part", lambda t: t.withColumn("r", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc(), "p_partkey"))).where("r <= 3").select("p_brand", "p_partkey")), "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3"),
    "rel_topk_plan": (_simple("orders", lambda t: t.orderBy(F.col("o_totalprice").desc(), "o_orderkey").select("o_orderkey", "o_totalprice").limit(10)), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    "rel_topk_offset": (_simple("orders", lambda t: t.orderBy(F.col("o_totalprice").desc(), "o_orderkey").select("o_orderkey").offset(10).limit(10)), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 10"),
    "rel_set_union_all": (_sets("unionAll"), _sets_sql("UNION ALL")),
    "rel_set_intersect": (_sets("intersect"), _sets_sql("INTERSECT")),
    "rel_set_intersect_all": (_sets("intersectAll"), _sets_sql("INTERSECT ALL")),
    "rel_set_except": (_sets("subtract"), _sets_sql("EXCEPT")),
    "rel_set_except_all": (_sets("exceptAll"), _sets_sql("EXCEPT ALL")),
    "rel_scalars": (_scalars, "SELECT event_id, CAST(floor(value) AS bigint) AS whole, date_trunc('day', ts) AS day, json_extract_string(props, '$.k') AS k, year(ts) AS y, greatest(value, 10.0) AS least10 FROM events"),
    "rel_hosts": (_hosts, "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1"),
    "rel_elements": (_elements, "SELECT label, CAST(max(x) AS double) AS most, count(*) AS n FROM (SELECT label, unnest(embedding) AS x FROM embeddings) GROUP BY 1"),
}
REL |= {
    "rel_filter_pushdown_window": (_simple("lineitem", lambda t: t.where((F.col("l_extendedprice") > 52000.5) & (F.col("l_extendedprice") <= 53000.25)).select("l_extendedprice")), "SELECT l_extendedprice FROM lineitem WHERE l_extendedprice > 52000.5 AND l_extendedprice <= 53000.25"),
    "rel_sample_fraction": (lambda spark, sf: sampled(load(spark, sf, "orders", "o_orderkey"), "o_orderkey", 8), "SELECT o_orderkey FROM orders WHERE md5(CAST(o_orderkey AS varchar)) < '2'"),
    "rel_order_code_roundtrip": (_roundtrip, "SELECT event_id, CASE WHEN value = 0 THEN 0 ELSE value END AS value, epoch_us(ts) AS at FROM events"),
    "rel_join_broadcast": (_join("inner", "broadcast"), _join_sql("INNER")),
    "rel_join_nested_loop": (_nested, "SELECT r_name, n_name FROM region JOIN nation ON r_regionkey <> n_regionkey AND length(r_name) < length(n_name)"),
    "rel_join_range": (_buckets, "WITH b AS (SELECT quantile_disc(l_extendedprice, [0.25, 0.5, 0.75]) AS c FROM lineitem) SELECT CAST(CASE WHEN l_extendedprice < c[1] THEN 0 WHEN l_extendedprice < c[2] THEN 1 WHEN l_extendedprice < c[3] THEN 2 ELSE 3 END AS integer) AS bucket, count(*) AS n FROM lineitem, b GROUP BY 1"),
    "rel_join_cross": (lambda spark, sf: load(spark, sf, "region", "r_name").crossJoin(load(spark, sf, "nation", "n_name")), "SELECT r_name, n_name FROM region CROSS JOIN nation"),
    "rel_join_self": (_same_nation, "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey"),
    "rel_agg_approx_distinct": (_approx_distinct, "SELECT l_returnflag, count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem GROUP BY 1"),
    "rel_agg_grouping_sets": (_grouping_sets, "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"),
    "rel_agg_percentiles": (_percentiles, "SELECT l_returnflag, quantile_disc(l_quantity, 0.25) AS disc, quantile_cont(l_quantity, 0.25) AS cont, median(l_quantity) AS mid FROM lineitem GROUP BY 1"),
    "rel_agg_mode": (_simple("lineitem", lambda t: t.groupBy("l_linenumber").agg(F.count("*").alias("n")).agg(F.max_by("l_linenumber", F.struct("n", -F.col("l_linenumber"))).alias("commonest"))), "SELECT arg_max(l_linenumber, {'a': n, 'b': -l_linenumber}) AS commonest FROM (SELECT l_linenumber, count(*) AS n FROM lineitem GROUP BY 1)"),
    "rel_agg_collect": (_simple("nation", lambda t: t.groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1"),
    "rel_agg_pivot": (_simple("lineitem", lambda t: t.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()), "SELECT l_returnflag, nullif(count(*) FILTER (l_linestatus = 'F'), 0) AS F, nullif(count(*) FILTER (l_linestatus = 'O'), 0) AS O FROM lineitem GROUP BY 1"),
    "rel_agg_sort_based": (_simple("nation", lambda t: t.groupBy("n_regionkey").agg(F.max("n_name").alias("last"), F.min(F.struct("n_name", "n_nationkey")).alias("first")).select("n_regionkey", "last", "first.n_nationkey")), "SELECT n_regionkey, max(n_name) AS last, arg_min(n_nationkey, n_name) AS n_nationkey FROM nation GROUP BY 1"),
    "rel_win_distribution": (_window(pr=lambda w: F.percent_rank().over(w), cd=lambda w: F.cume_dist().over(w)), _window_sql(pr="percent_rank() OVER w", cd="cume_dist() OVER w")),
    "rel_win_nth": (_window(third=lambda w: F.nth_value("c_acctbal", 3).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), low=lambda w: F.last("c_acctbal").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))), "SELECT c_custkey, nth_value(c_acctbal, 3) OVER v AS third, last_value(c_acctbal) OVER v AS low FROM customer WINDOW v AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
    "rel_win_range_frame": (_near_balance, "SELECT c_custkey, count(*) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS near FROM customer"),
    "rel_sort_global": (_simple("orders", lambda t: t.orderBy(F.col("o_totalprice").desc(), "o_orderkey").select("o_orderkey", "o_totalprice")), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey"),
    "rel_sort_multi_nulls": (lambda spark, sf: global_rank(load(spark, sf, "documents", "doc_id", "source", "lang"), [F.col("source").desc_nulls_first(), F.col("lang").asc_nulls_last(), "doc_id"]).select("doc_id", "position"), "SELECT doc_id, row_number() OVER (ORDER BY source DESC NULLS FIRST, lang ASC NULLS LAST, doc_id) AS position FROM documents"),
    "rel_sort_within_partitions": (_within, "SELECT l_suppkey, l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber) AS place FROM lineitem"),
    "rel_set_union": (_sets("union"), _sets_sql("UNION ALL")),
    "rel_set_union_distinct": (lambda spark, sf: _sets("union")(spark, sf).distinct(), _sets_sql("UNION")),
    "rel_strings": (_simple("part", lambda t: t.select("p_partkey", F.upper(F.trim("p_brand")).alias("up"), F.substring("p_type", 1, 4).alias("head"), F.length("p_name").cast("long").alias("size"), F.concat_ws("-", "p_brand", "p_type").alias("both"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("mute"), F.split("p_type", " ")[0].alias("word"))), "SELECT p_partkey, upper(trim(p_brand)) AS up, substring(p_type, 1, 4) AS head, length(p_name) AS size, concat_ws('-', p_brand, p_type) AS both, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS mute, string_split(p_type, ' ')[1] AS word FROM part"),
    "rel_arrays": (_simple("embeddings", lambda t: t.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("above"), F.element_at(F.array_sort("embedding"), 1).cast("double").alias("least"), F.size(F.slice("embedding", 3, 5)).cast("long").alias("five"), F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("float") * F.lit(1000).cast("float")).cast("long")), F.lit(0).cast("long"), lambda a, x: a + x).alias("milli"))), "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS above, CAST(list_min(embedding) AS double) AS least, CAST(5 AS bigint) AS five, CAST(list_sum(list_transform(embedding, lambda x: CAST(floor(CAST(x AS float) * CAST(1000 AS float)) AS bigint))) AS bigint) AS milli FROM embeddings"),
    "rel_maps": (_maps, "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'O') AS open, CAST(count(DISTINCT l_linestatus) AS bigint) AS kinds FROM lineitem GROUP BY 1"),
    "rel_conditionals": (_simple("customer", lambda t: t.select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 1000, "low").otherwise("high").alias("class"), F.coalesce(F.nullif(F.col("c_mktsegment"), F.lit("BUILDING")), F.lit("none")).alias("seg"), F.md5("c_name").alias("print"))), "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'high' END AS class, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, md5(c_name) AS print FROM customer"),
}
QUERIES = {name: q for name, (q, _) in REL.items()}
ORACLE_SQL = {name: sql for name, (_, sql) in REL.items() if sql}
