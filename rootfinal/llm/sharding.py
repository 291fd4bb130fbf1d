"""Extendible hashing into shards of bounded bytes.

A directory is indexed by leading bits of a hash of (doc_id, text). All buckets start at depth 0; only a bucket over the byte
limit splits on its next bit. The directory is a table, never a list on the driver: a round sums the bytes under each prefix of up to
`step` more bits of the buckets still open, closes the prefixes that fit, and leaves the others open for the next round. Only the
depths that occur, 64 at most, and the number of open buckets come to the driver.

Null and empty texts count 0 bytes; a text of any length is one row. A single text over the limit, or identical rows that no bit
separates, form an `oversized` shard. Ties cannot occur: a row's hash names its shard. Other columns of the input, whatever their names,
are not read. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import discard, sized, written

BITS = 64


def _prefix(bits: int) -> Column:
    return F.shiftrightunsigned("h", BITS - bits) if bits else F.lit(0).cast("long")


def _round(rows: DataFrame, depth: int, step: int, limit: int) -> DataFrame:
    """Nodes of depth `depth` .. `depth + step` under which `rows` lie: bytes, and whether a node fits or cannot split."""
    finest = rows.groupBy(_prefix(depth + step).alias("p")).agg(F.sum("n_bytes").alias("b"), F.min("h").alias("a"), F.max("h").alias("z"))
    levels = F.sequence(F.lit(0 if depth == 0 else 1), F.lit(step))
    nodes = finest.withColumn("down", F.explode(levels)).withColumn("up", F.lit(step) - F.col("down"))
    nodes = nodes.withColumn("prefix", F.when(F.col("down") + depth == 0, 0).otherwise(F.expr("shiftrightunsigned(p, up)")).cast("long"))
    nodes = nodes.groupBy((F.col("down") + depth).alias("depth"), "prefix").agg(F.sum("b").alias("shard_bytes"), F.min("a").alias("a"), F.max("z").alias("z"))
    return nodes.withColumn("closed", (F.col("shard_bytes") <= limit) | (F.col("a") == F.col("z")))


def directory(spark: SparkSession, hashed: DataFrame, limit: int, step: int = 8) -> DataFrame:
    """depth, prefix, shard_bytes, oversized of the leaves."""
    leaves, open_buckets, depth = None, None, 0
    while depth < BITS:
        rows = hashed
        if open_buckets is not None:
            rows = hashed.join(sized(open_buckets), _prefix(depth) == F.col("open"), "left_semi")
        nodes = written(spark, _round(rows, depth, step, limit), "shard-nodes")
        shut = nodes.where("closed").select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("above")).hint("merge")
        # a leaf is closed and its parent is not; parents of the round's first level were left open by the round before
        child = nodes.where("closed").withColumn("above", F.shiftrightunsigned("prefix", 1))
        found = child.join(shut, ["depth", "above"], "left_anti").select("depth", "prefix", "shard_bytes", (F.col("shard_bytes") > limit).alias("oversized"))
        found = written(spark, found, "shard-leaves")
        leaves = found if leaves is None else leaves.unionByName(found)
        depth += step
        before, open_buckets = open_buckets, written(spark, nodes.where((F.col("depth") == depth) & ~F.col("closed")).select(F.col("prefix").alias("open")), "shard-open")
        discard(spark, nodes)
        if before is not None:
            discard(spark, before)
        if open_buckets.isEmpty():
            break
    return leaves


def shard(spark: SparkSession, docs: DataFrame, limit: int) -> DataFrame:
    """doc_id, n_bytes, shard (its bits), depth, shard_bytes, oversized."""
    hashed = docs.select("doc_id", F.xxhash64("doc_id", "text").alias("h"), F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))
    hashed = written(spark, hashed, "shard-hash")
    leaves = directory(spark, hashed, limit)
    depths = sorted(r.depth for r in leaves.select("depth").distinct().collect()) or [0]
    # one row finds its leaf by its prefix at each depth that occurs; exactly one of them is a leaf
    keyed = hashed.withColumn("k", F.explode(F.array(*[F.struct(F.lit(d).alias("depth"), _prefix(d).alias("prefix")) for d in depths]))).select("doc_id", "n_bytes", "k.depth", "k.prefix")
    found = keyed.join(sized(leaves, 1_000_000), ["depth", "prefix"])
    return found.select("doc_id", "n_bytes", F.when(F.col("depth") == 0, "").otherwise(F.lpad(F.bin("prefix"), F.col("depth"), F.lit("0"))).alias("shard"), "depth", "shard_bytes", "oversized")
