"""The methods as functions of SQL: a sketch as an aggregate of small groups, readers of stored states, a table of hitters."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..summary import GKSummary, SpaceSaving, Summary, rank_of
from .order_code import OrderCode, code_floats, float_codes

EPS, COUNTERS = 0.01, 1000
_ITEMS = T.StructType([T.StructField("rank", T.IntegerType()), T.StructField("item", T.StringType()), T.StructField("est_count", T.LongType()), T.StructField("max_error", T.LongType())])


def _sketch() -> GKSummary:
    return GKSummary([0.5], EPS, T.DoubleType())


def _hitters() -> SpaceSaving:
    return SpaceSaving(COUNTERS, COUNTERS, T.StringType())


def _batch(column: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([column], names=["x"])


@F.arrow_udf(T.BinaryType())
def sketch_of(x: pa.Array) -> bytes:
    """Aggregate: the rank sketch of a group of doubles, as its stored state."""
    s = _sketch()
    return s.dump(s.fold(s.zero(), _batch(x)))


@F.arrow_udf(T.BinaryType())
def hitters_of(x: pa.Array) -> bytes:
    """Aggregate: the counters of a group of strings, as their stored state."""
    s = _hitters()
    return s.dump(s.fold(s.zero(), _batch(x)))


@F.arrow_udf(T.DoubleType())
def sketch_quantile(state: pa.Array, q: pa.Array) -> pa.Array:
    s = _sketch()
    held = [None if b is None else s.load(b) for b in state.to_pylist()]
    return pa.array([None if v is None or p is None else float(code_floats(np.array([s.quantile(v, p)]))[0]) for v, p in zip(held, q.to_pylist(), strict=True)], pa.float64())


@F.arrow_udf(T.LongType())
def sketch_rank(state: pa.Array, value: pa.Array) -> pa.Array:
    """About how many of the sketch's rows are at most `value`."""
    s = _sketch()

    def rank(data, at):
        if data is None or at is None or s.load(data) is None:
            return None
        v, g, d, n = s.settled(s.load(data))
        i = int(np.searchsorted(v, float_codes(np.array([at]))[0], side="right"))
        return 0 if not i else n if i == len(v) else int(g[:i].sum() + d[i - 1] // 2)

    return pa.array([rank(*x) for x in zip(state.to_pylist(), value.to_pylist(), strict=True)], pa.int64())


@F.arrow_udf(T.BinaryType())
def sketch_merge(a: pa.Array, b: pa.Array) -> pa.Array:
    s = _sketch()
    pairs = zip(a.to_pylist(), b.to_pylist(), strict=True)
    return pa.array([s.dump(s.merge(*(None if x is None else s.load(x) for x in p))) for p in pairs], pa.binary())


@F.arrow_udf(T.ArrayType(T.StringType()))
def sketch_top_k(state: pa.Array, k: pa.Array) -> pa.Array:
    s = _hitters()
    out = [None if b is None or s.load(b) is None else s.finalize(s.load(b)).column("item").to_pylist()[:n] for b, n in zip(state.to_pylist(), k.to_pylist(), strict=True)]
    return pa.array(out, pa.list_(pa.string()))


@F.udtf(returnType=_ITEMS)
class HitterItems:
    """Rows of a stored state of counters: `hh_items(state, k)`."""

    def eval(self, state: bytes, k: int):
        held = None if state is None else _hitters().load(bytes(state))
        if held is not None:
            for r in _hitters().finalize(held).slice(0, k).to_pylist():
                yield r["rank"], r["item"], r["estimate"], r["error"]


def register(spark: SparkSession) -> None:
    """All of them under their names, for spark.sql."""
    for f in (sketch_of, hitters_of, sketch_quantile, sketch_rank, sketch_merge, sketch_top_k):
        spark.udf.register(f.__name__ if hasattr(f, "__name__") else f._name, f)
    spark.udtf.register("hh_items", HitterItems)


def summarize(df: DataFrame, keys: list[str], col: str, summary: Summary) -> DataFrame:
    """keys and the finished answer of `summary` over `col` for each group: partial states of (partition, group), then one merge a group.

    A hot group is folded where its rows lie; only states are shuffled.
    """
    schema = T.StructType([*[df.schema[k] for k in keys], T.StructField("state", T.BinaryType())])
    answer = T.StructType([*[df.schema[k] for k in keys], *(summary.result_schema if isinstance(summary.result_schema, T.StructType) else T.StructType.fromDDL(summary.result_schema))])

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, object] = {}
        kind = None
        for batch in batches:
            t = pa.Table.from_batches([batch])
            kind = t.select(keys).schema
            groups = t.select(keys).append_column("__at", pa.array(np.arange(len(t)))).group_by(keys).aggregate([("__at", "list")])
            for row in groups.to_pylist():
                at = row.pop("__at_list")
                key = tuple(row[k] for k in keys)
                part = pa.RecordBatch.from_arrays([batch.column(len(keys)).take(pa.array(at))], names=["x"])
                held[key] = summary.fold(held.get(key, summary.zero()), part)
        if held:
            columns = [pa.array([k[i] for k in held], kind.field(i).type) for i in range(len(keys))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([summary.dump(s) for s in held.values()], pa.binary())], names=[*keys, "state"])

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, any_ = None, False
        for b in batches:
            for data in b.column("state").to_pylist():
                own = summary.load(data)
                state, any_ = (summary.merge(state, own) if any_ else own), True
        done = summary.finalize(state).combine_chunks()
        named = [pa.array([k.as_py()] * done.num_rows, k.type) for k in key]
        yield pa.RecordBatch.from_arrays([*named, *[c.combine_chunks() for c in done.columns]], names=[*keys, *done.column_names])

    states = df.select(*keys, F.col(col).alias("x")).where("x IS NOT NULL").mapInArrow(fold, schema)
    return states.groupBy(*keys).applyInArrow(merge, answer)


def order_code(df: DataFrame, col: str, name: str = "code", back: str = "back") -> DataFrame:
    """`df` with the int64 order code of a column and the value decoded from it again; both null for null."""
    kind = df.schema[col].dataType
    code = OrderCode(kind)
    if not code.plain:
        raise TypeError("strings and binaries have no integer code")
    schema = T.StructType([*df.schema.fields, T.StructField(name, T.LongType()), T.StructField(back, kind)])
    place = df.columns.index(col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(place)
            codes = code.encode(column)
            valid = np.flatnonzero(column.is_valid().to_numpy(zero_copy_only=False))
            spread = pa.array(np.where(np.isin(np.arange(len(column)), valid), np.cumsum(column.is_valid().to_numpy(zero_copy_only=False)) - 1, 0), mask=~column.is_valid().to_numpy(zero_copy_only=False))
            decoded = code.decode(codes)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(codes, pa.int64()).take(spread), decoded.take(spread)], names=[*batch.schema.names, name, back])

    return df.mapInArrow(run, schema)


__all__ = ["EPS", "HitterItems", "hitters_of", "order_code", "rank_of", "register", "sketch_merge", "sketch_of", "sketch_quantile", "sketch_rank", "sketch_top_k", "summarize"]
