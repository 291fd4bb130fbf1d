"""Connected components over an edge table, without gathering nodes or links anywhere.

Each round ties every node's neighbours below it to the least of them and jumps pointers (root of root). A root of many
nodes is no hot key: only roots that moved are looked up, and nodes meet copies of them dealt over `SALTS` keys. Rounds are
written to the shared folder, so a lost executor redoes one round; a round's table goes when the next one is written.

Edges may repeat, run either way, and join a node to itself (such edges are passed over); nulls join nothing. Nodes without
edges are absent, and an empty table gives no rows. Each round at least halves the longest chain of roots, so rounds are
about as many as the logarithm of the longest path; `ROUNDS` only guards against a fault.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import discard, written

SALTS, ROUNDS = 16, 200


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(v, component) of every node in `edges(a, b)`; nodes without edges are absent."""
    pairs = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("m")).distinct()
    pairs = written(spark, pairs, "cc-edges")
    salted = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
    for _ in range(ROUNDS):
        # every node's least neighbour below it; the other neighbours are tied to that one instead
        star = pairs.groupBy("u").agg(F.min("m").alias("m"))
        tied = pairs.join(star.select("u", F.col("m").alias("r")), "u").where("m <> r").select(F.greatest("m", "r").alias("u"), F.least("m", "r").alias("m"))
        # pointer jump: a node's root takes its own root
        moved = star.select("m").distinct().join(star.select(F.col("u").alias("m"), F.col("m").alias("top")), "m")
        moved = moved.withColumn("salt", salted)
        jumped = star.withColumn("salt", F.pmod(F.xxhash64("u"), F.lit(SALTS)).cast("int")).join(moved, ["m", "salt"], "left")
        jumped = jumped.select("u", F.coalesce("top", "m").alias("m"), F.col("top").isNotNull().alias("moved"))
        new = written(spark, jumped.unionByName(tied.withColumn("moved", F.lit(True))).groupBy("u", "m").agg(F.max("moved").alias("moved")), "cc-edges")
        discard(spark, pairs)
        pairs = new
        if pairs.where("moved").isEmpty():
            break
    else:
        raise RuntimeError("components did not settle")
    roots = pairs.select(F.col("m").alias("v"), F.col("m").alias("component")).distinct()
    out = pairs.select(F.col("u").alias("v"), F.col("m").alias("component")).unionByName(roots)
    out.written_path = pairs.written_path
    return out
