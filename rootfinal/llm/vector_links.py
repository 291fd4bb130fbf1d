"""Links between vectors of high cosine by Euclidean p-stable hashing.

A table's key is a vector of `width`-quantised Gaussian projections of the normalised vector, and its length: vectors
of different lengths never link. Vectors that share a key
in some table are compared by cosine in double precision. A pair counts in the first table where it meets, so
counts need no pair table. A bucket over `cell` rows is cut into blocks and every two blocks meet in a cell of their
own: a hot bucket is spread over tasks and no pair is lost. Each cell returns a count for each vector and
the edges of a spanning forest, never its pairs.

At cosine 0.9 ten projections of width 2 agree with probability 0.14, so 40 tables find 99.8 % of the links there and
more of those above it. Vectors that are null, zero, or hold null or non-finite components link with nothing;
rows that repeat a vec_id are one vector to each other and link with others by each of their rows.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .shared import shuffle_width, written

PROJECTIONS, TABLES, WIDTH, CELL, SEED = 10, 40, 2.0, 1024, 20
_ODD = np.array([2 * i + 1 for i in range(PROJECTIONS)], np.uint64) * np.uint64(0x9E3779B97F4A7C15)


@functools.lru_cache(4)
def _planes(length: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng([SEED, length])
    return rng.standard_normal((length, TABLES * PROJECTIONS)), rng.uniform(0, WIDTH, TABLES * PROJECTIONS)


def _keys(unit: np.ndarray) -> np.ndarray:
    """Bucket keys, one column for each table."""
    a, b = _planes(unit.shape[1])
    # row by row, so that a vector's keys never depend on which others stand in its batch
    moved = np.stack([u @ a for u in unit]) + b
    q = np.floor(moved / WIDTH).astype(np.int64).astype(np.uint64).reshape(len(unit), TABLES, PROJECTIONS)
    mixed = (q + np.uint64(0x51ED27)) * _ODD
    mixed ^= mixed >> np.uint64(29)
    of_length = np.uint64(unit.shape[1] * 0xD6E8FEB86659FD93 % (1 << 64))
    return (mixed.sum(axis=2, dtype=np.uint64) * np.uint64(0xBF58476D1CE4E5B9) ^ of_length).view(np.int64)


def _unit(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _hash_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        dtype = np.float32 if pa.types.is_float32(batch.column("embedding").type.value_type) else np.float64
        by_size: dict[int, list] = {}
        for i, v in zip(batch.column("vec_id").to_pylist(), batch.column("embedding").to_pylist(), strict=True):
            if i is None or not v or None in v:
                continue
            x = np.array(v, dtype)
            if np.isfinite(x).all() and x.any():
                by_size.setdefault(len(v), []).append((i, x))
        for rows in by_size.values():
            ids = np.array([i for i, _ in rows], np.int64)
            x = np.stack([x for _, x in rows])
            keys = _keys(_unit(x))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array([u.tobytes() for u in x], pa.binary()), pa.array([np.dtype(dtype).itemsize] * len(x), pa.int32()), pa.array(list(keys), pa.list_(pa.int64()))], names=["vec_id", "vec", "width", "keys"])


def _compare(ids, unit, side, table: int, threshold: float):
    """Counts and forest edges of one cell; `side` tells the two blocks of a mixed cell apart, None for a single block."""
    linked = unit @ unit.T >= threshold
    linked &= ids[:, None] != ids[None, :]
    if side is not None:
        linked &= side[:, None] != side[None, :]
    rows = np.flatnonzero(linked.any(axis=1))
    if not len(rows):
        return None
    keys = _keys(unit[rows])
    linked = linked[np.ix_(rows, rows)]
    counts = np.zeros(len(rows), np.int64)
    for i in range(len(rows)):
        others = np.flatnonzero(linked[i])
        counts[i] = ((keys[others] == keys[i]).argmax(axis=1) == table).sum()
    root = np.full(len(rows), -1)
    for i in range(len(rows)):
        if root[i] < 0:
            seen = np.zeros(len(rows), bool)
            front = np.array([i])
            seen[i] = True
            while len(front):
                reached = linked[front].any(axis=0) & ~seen
                seen |= reached
                front = np.flatnonzero(reached)
            root[seen] = np.flatnonzero(seen)[ids[rows][seen].argmin()]
    return ids[rows], counts, ids[rows][root]


def _cells(threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None

        def done(t: pa.Table):
            cols = [t.column(c).to_numpy() for c in ("t", "k", "bi", "bj")]
            cuts = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
            edges = [0, *cuts.tolist(), t.num_rows]
            ids, mine = t.column("vec_id").to_numpy(), t.column("mine").to_numpy()
            vecs, widths = t.column("vec").to_pylist(), t.column("width").to_numpy()
            out = []
            for a, b in zip(edges, edges[1:], strict=False):
                by_length: dict[int, list[int]] = {}
                for i in range(a, b):
                    by_length.setdefault(len(vecs[i]), []).append(i)
                # the key holds the length, so there is one group but for clashes of the hash
                for rows in by_length.values():
                    if len(rows) < 2:
                        continue
                    unit = _unit(np.frombuffer(b"".join([vecs[i] for i in rows]), np.float32 if widths[a] == 4 else np.float64).reshape(len(rows), -1))
                    side = mine[rows] != cols[2][rows] if cols[2][a] != cols[3][a] else None
                    got = _compare(ids[rows], unit, side, int(cols[0][a]), threshold)
                    if got:
                        out.append(got)
            if out:
                return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], names=["vec_id", "n", "root"])
            return None

        for batch in batches:
            t = pa.Table.from_batches([batch])
            held = pa.concat_tables([held, t]) if held is not None else t
            if held.num_rows < 2:
                continue
            cols = [held.column(c).to_numpy() for c in ("t", "k", "bi", "bj")]
            cuts = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
            if len(cuts):
                got = done(held.slice(0, int(cuts[-1])))
                held = held.slice(int(cuts[-1]))
                if got is not None:
                    yield got
        if held is not None and held.num_rows:
            got = done(held)
            if got is not None:
                yield got

    return run


def link(spark: SparkSession, vectors: DataFrame, threshold: float = 0.9) -> DataFrame:
    """vec_id, n_links, component_id, kept: one row for each row of `vectors`."""
    base = vectors.select("vec_id", "embedding")
    hashed = written(spark, base.mapInArrow(_hash_rows, "vec_id long, vec binary, width int, keys array<long>"), "vec-hash")
    entries = hashed.select("vec_id", F.posexplode("keys").alias("t", "k"))
    sizes = entries.groupBy("t", "k").count().where("count > 1")
    many = sizes.select("t", "k", F.ceil(F.col("count") / CELL).cast("int").alias("blocks"))
    dealt = entries.join(many, ["t", "k"]).withColumn("mine", F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int"))
    met = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cells = met.select("vec_id", "t", "k", "mine", F.least("mine", "other").alias("bi"), F.greatest("mine", "other").alias("bj"))
    width = max(shuffle_width(spark), 2)
    loaded = cells.join(hashed.select("vec_id", "vec", "width"), "vec_id").repartition(width, "t", "k", "bi", "bj").sortWithinPartitions("t", "k", "bi", "bj", "vec_id")
    found = written(spark, loaded.select("vec_id", "vec", "width", "t", "k", "mine", "bi", "bj").mapInArrow(_cells(threshold), "vec_id long, n long, root long"), "vec-links")
    counts = found.groupBy("vec_id").agg(F.sum("n").alias("n"))
    parts = components(spark, found.select(F.col("vec_id").alias("a"), F.col("root").alias("b")))
    joined = base.select("vec_id").join(counts, "vec_id", "left").join(parts.withColumnRenamed("v", "vec_id"), "vec_id", "left")
    out = joined.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
