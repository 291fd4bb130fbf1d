"""Mixing sources to target weights along a time-varying curriculum. DataFrame functions only.

Sources by code point, null last, weigh 1, 2, 3, repeating; they share the words of all documents, none taking more
than `cap` times its own. The excess of capped sources is reshared by weight: sorted by size over weight, the
capped sources are a prefix, so one pass of running sums finds them.

Within a source documents stand in the order of md5(doc_id), doc_id and are read in passes; a pass takes a document whose middle
word lies within the target. A source's weight moves over the run as 1 + slope * (2t - 1); the cumulative demand
t + slope * (t*t - t) is inverted at the middle word of each copy, one pass further for each further copy, which is
the copy's training position in [0, 1].

Null and empty texts have size 0 and are never taken; a text of any length counts whole. Identical rows tie and fare alike up to their
order, which changes no row; an empty table gives no rows. `mix` packs a document's own columns, so none of them can clash.
Running sums are two-level (blocks of a source by leading hash digits), so a hot source is spread over tasks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

CAP = 3
BLOCK_DIGITS = 3  # leading hex digits: 4096 blocks a source


def targets(sized: DataFrame) -> DataFrame:
    """source, source_size, target: one row for each source."""
    sizes = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    w = sizes.withColumn("weight", (F.row_number().over(by_name) - 1) % 3 + 1)
    order = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    total = F.sum("source_size").over(Window.partitionBy())
    w = w.select("*", total.alias("total"), F.coalesce(F.sum("source_size").over(before), F.lit(0)).alias("size_before"), F.sum("weight").over(after).alias("weight_after"))
    # capped if its cap is below what the words left over give it
    w = w.withColumn("capped", CAP * F.col("source_size") * F.col("weight_after") <= F.col("weight") * (F.col("total") - CAP * F.col("size_before")))
    everyone = Window.partitionBy()
    w = w.withColumn("left", F.col("total") - CAP * F.coalesce(F.sum(F.when(F.col("capped"), F.col("source_size"))).over(everyone), F.lit(0)))
    w = w.withColumn("weights", F.sum(F.when(~F.col("capped"), F.col("weight"))).over(everyone))
    target = F.when(F.col("capped"), (CAP * F.col("source_size")).cast("double")).otherwise(F.col("weight") * F.col("left") / F.col("weights"))
    return w.select("source", "weight", "source_size", target.alias("target"))


def assign(docs: DataFrame, slope: float = 0.5, payload: list[str] = ()) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken, positions (one for each copy, ascending)."""
    size = F.coalesce(F.expr(r"regexp_count(text, '[^\\x20\\x09-\\x0D]+')"), F.lit(0)).cast("long")
    h = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    sized = docs.select("doc_id", "source", size.alias("size"), h.alias("h"), F.substring(h, 1, BLOCK_DIGITS).alias("block"), *payload)
    blocks = sized.groupBy("source", "block").agg(F.sum("size").alias("size"))
    shares = targets(blocks)
    running = Window.partitionBy("source").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = blocks.withColumn("block_start", F.coalesce(F.sum("size").over(running), F.lit(0))).select(F.col("source").alias("s"), F.col("block").alias("b"), "block_start")
    inside = Window.partitionBy("source", "block").orderBy("h", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    placed = sized.withColumn("in_block", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    placed = placed.join(offsets, F.col("source").eqNullSafe(F.col("s")) & (F.col("block") == F.col("b"))).drop("s", "b")
    shares = shares.select(F.col("source").alias("s"), "weight", "source_size", "target")
    placed = placed.join(shares, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    mid = F.col("block_start") + F.col("in_block") + F.col("size") / 2
    copies = F.when((F.col("size") == 0) | (mid > F.col("target")), 0).otherwise(F.floor((F.col("target") - mid) / F.col("source_size")) + 1).cast("long")
    placed = placed.withColumn("mid", mid).withColumn("copies", F.least(copies, F.lit(CAP).cast("long")))
    # demand runs up for a source of odd weight and down for an even one
    a = F.when(F.col("weight") % 2 == 1, F.lit(slope)).otherwise(F.lit(-slope))
    d = lambda copy: (F.col("mid") + (copy - 1) * F.col("source_size")) / F.col("target")
    t = lambda copy: 2 * d(copy) / (1 - a + F.sqrt((1 - a) * (1 - a) + 4 * a * d(copy)))
    positions = F.when(F.col("copies") > 0, F.transform(F.sequence(F.lit(1).cast("long"), F.col("copies")), t)).otherwise(F.array().cast("array<double>"))
    return placed.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), positions.alias("positions"), *payload)


def schedule(docs: DataFrame, slope: float = 0.5, payload: list[str] = ()) -> DataFrame:
    """assign's columns but positions, and copy, position: one row for each copy, range-sorted by position.

    A document that is not taken keeps one row, of copy 0 and a null position, before the others.
    """
    placed = assign(docs, slope, payload)
    rows = placed.select(*[c for c in placed.columns if c != "positions"], F.posexplode_outer("positions").alias("at", "position"))
    return rows.withColumn("copy", F.coalesce(F.col("at") + 1, F.lit(0)).cast("long")).drop("at").orderBy("position", "doc_id", "copy")


def mix(docs: DataFrame, slope: float = 0.5) -> DataFrame:
    """The columns of `docs`, one row for each copy taken, range-sorted by training position."""
    names = docs.columns
    whole = F.struct(*[F.col(f"`{c}`") for c in names]).alias("__doc")
    return schedule(docs.select("doc_id", "source", "text", whole), slope, ["__doc"]).where("copy > 0").select("__doc.*")
