"""What the operators of this subpackage share: the shared folder, written intermediate tables, text slices."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_written: dict[str, list[str]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: `spark.checkpoint.dir` of the session.

    Only where the session names none (single-machine tests) is a folder of this machine made and set.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    context = spark.sparkContext
    current = context.getCheckpointDir()
    if current is None:
        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="rootfinal-"))
        current = context.getCheckpointDir()
    return current.rstrip("/")


def written(spark: SparkSession, df: DataFrame, label: str) -> DataFrame:
    """`df` written once as Parquet in the shared folder and read again.

    Cuts the lineage like a checkpoint, survives lost executors, and lets later reads prune columns.
    """
    path = f"{shared_dir(spark)}/rootfinal-{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.setdefault(spark.sparkContext.applicationId, []).append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_path = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def finished(spark: SparkSession, path: str) -> bool:
    """Whether a table was written there to its end."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)


def discard(spark: SparkSession, table: DataFrame) -> None:
    """Delete a table of `written` that no later step and no result reads."""
    path = getattr(table, "written_path", None)
    if path:
        _written.get(spark.sparkContext.applicationId, [path]).remove(path)
        _delete(spark, path)


@contextlib.contextmanager
def intermediates(spark: SparkSession):
    """Deletes, at its end, the tables that `written` made inside; for work whose result is itself written by then."""
    app = spark.sparkContext.applicationId
    before = set(_written.get(app, []))
    yield
    for path in [p for p in _written.get(app, []) if p not in before]:
        _written[app].remove(path)
        _delete(spark, path)


def drop_written(spark: SparkSession) -> int:
    """Delete the intermediate tables of this application; results not yet read become unreadable."""
    paths = _written.pop(spark.sparkContext.applicationId, [])
    for path in paths:
        _delete(spark, path)
    return len(paths)


def sized(ids: DataFrame, most: int = 4_000_000) -> DataFrame:
    """`ids`, a written table of a few narrow columns, broadcast while its counted rows stay within `most` (some 40 MB).

    Beyond that a join with it shuffles both sides; the rows that it finds are the same.
    """
    return F.broadcast(ids) if ids.count() <= most else ids.hint("merge")


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def code_point_words(column: str):
    """Number of words `[^\\x20\\x09-\\x0D]+` of a string column, 0 for null; JVM only."""
    return F.coalesce(F.expr(f"regexp_count({column}, '[^\\\\x20\\\\x09-\\\\x0D]+')"), F.lit(0)).cast("long")


def carried(keep: list[str], outputs: list[str]) -> list:
    """The kept columns; one that is named like an output (in any case) or like another gets `_in` behind its name."""
    taken, out = {o.lower() for o in (*outputs, "__text", "__html")}, []
    for k in keep:
        name = k
        while name.lower() in taken:
            name += "_in"
        taken.add(name.lower())
        out.append(F.col(f"`{k}`").alias(name))
    return out


def text_array(column: pa.Array) -> pa.Array:
    """The strings of a batch column, null as empty."""
    return pc.fill_null(column, "")


def slices(texts: pa.Array, max_bytes: int = 8 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of at most `max_bytes` of text each (a longer text stands alone)."""
    ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
    low, n = 0, len(texts)
    while low < n:
        done = ends[low - 1] if low else 0
        high = max(low + 1, int(np.searchsorted(ends, done + max_bytes, side="right")))
        yield low, high
        low = high


@functools.cache
def _trim():
    """The C library's call that gives freed memory back, or None."""
    try:
        return ctypes.CDLL(None).malloc_trim
    except (OSError, AttributeError):
        return None


def trimmed(run: Callable) -> Callable:
    """`run` over a task's batches; what it freed goes back to the system at its end, as workers live on between tasks."""

    def inner(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            if _trim() is not None:
                _trim()(0)

    return inner


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions of concatenated runs: `starts[i], starts[i]+1, ...` for `lengths[i]` steps each."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lengths)
    out = np.arange(total, dtype=np.int64)
    out += np.repeat(starts - (ends - lengths), lengths)
    return out


def sums_by_run(values: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sum of `values` in each run, the runs ending at `ends` (ascending, exclusive); empty runs give 0."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])[ends]
    return np.diff(np.concatenate([[0], total]))
