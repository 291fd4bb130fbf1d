"""Tree aggregation over DataFrames with three placements of the root.

Level 0 folds each partition into one state; each later level merges the states of a slot class in one task. With
`root="driver"` the last states come to the driver and are merged there; with "executor" one more level leaves
one state, which comes to the driver; with "finalize" that level also finishes it, so only the answer leaves.
"""

from __future__ import annotations

import random
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .sources.tables import exists
from .summary import ReduceSummary, Summary, TaggedSummary

# a state travels in pieces, so that no cell nears the 2 GiB of an Arrow column
STATE_SCHEMA = "slot int, piece int, pieces int, state binary, rows long"
PIECE_BYTES = 64 << 20
# states of classes of labels: `whole` says that none of a class's labels was given up
CLASS_SCHEMA = "class int, slot long, piece int, pieces int, state binary, rows long, whole boolean"
# counters that one task holds over all its classes before it sends their states on, and bytes of batches joined for one fold
HELD_COUNTERS, BATCH_BYTES = 1 << 20, 32 << 20


@dataclass(frozen=True)
class TreePlan:
    """`levels` are the numbers of states after each merge level; the rest describes a driver root."""

    partitions: int
    scale: int
    levels: tuple[int, ...]

    @property
    def root_fan_in(self) -> int:
        return self.levels[-1] if self.levels else self.partitions

    @property
    def root_combines(self) -> int:
        return max(0, self.root_fan_in - 1)


def _root_up(n: int, d: int) -> int:
    """Least integer whose d-th power reaches n."""
    r = max(1, round(n ** (1 / d)))
    while r**d < n:
        r += 1
    while r > 1 and (r - 1) ** d >= n:
        r -= 1
    return r


def plan_tree(partitions: int, depth: int = 2, exact_root: bool = False) -> TreePlan:
    if depth < 1:
        raise ValueError("depth must be at least 1")
    scale = max(2, _root_up(partitions, depth) if exact_root else -int(-(partitions ** (1 / depth)) // 1))
    levels, left = [], partitions
    while left > scale + -(-left // scale):
        left //= scale
        levels.append(left)
    return TreePlan(partitions, scale, tuple(levels))


def depth_for_fan_in(partitions: int, fan_in: int) -> int:
    """Least depth whose tree of this constant fan-in covers the partitions."""
    depth, reach = 1, fan_in
    while reach < partitions:
        depth, reach = depth + 1, reach * fan_in
    return depth


def partition_count(df: DataFrame) -> int:
    """Partitions of a plain scan; of a plan with an exchange the session's shuffle width, as asking it would run the exchange.

    Answers never depend on this number, only the tree's shape does.
    """
    plan = df._jdf.queryExecution().sparkPlan().toString()
    if any(word in plan for word in ("Exchange", "Aggregate", "Join", "Window", "Sort ", "InArrow", "InPandas")):
        return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(1, df.rdd.getNumPartitions())


@contextmanager
def narrow_rows(spark: SparkSession) -> Iterator[None]:
    """For rows of a few bytes each: batches for Python end by their number of rows alone. A limit of bytes, which such a batch never
    nears, makes Spark add up the sizes of all buffers again for every row. Holds for what is run inside the block."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str((1 << 31) - 1))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def _rows_of(summary: Summary, slot: int, state, rows: int) -> Iterator[pa.RecordBatch]:
    data = summary.dump(state)
    pieces = max(1, -(-len(data) // PIECE_BYTES))
    for i in range(pieces):
        part = data[i * PIECE_BYTES : (i + 1) * PIECE_BYTES]
        yield pa.RecordBatch.from_arrays(
            [pa.array([slot], pa.int32()), pa.array([i], pa.int32()), pa.array([pieces], pa.int32()), pa.array([part], pa.binary()), pa.array([rows if i == 0 else 0], pa.int64())],
            names=["slot", "piece", "pieces", "state", "rows"],
        )


def _joined(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Batches of at least `rows` rows or BATCH_BYTES, the last one aside."""
    waiting, n, size = [], 0, 0
    for b in batches:
        waiting, n, size = [*waiting, b], n + b.num_rows, size + b.nbytes
        if n >= rows or size >= BATCH_BYTES:
            yield from pa.Table.from_batches(waiting).combine_chunks().to_batches()
            waiting, n, size = [], 0, 0
    if n:
        yield from pa.Table.from_batches(waiting).combine_chunks().to_batches()


def _fold(df: DataFrame, summary: Summary) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, rows = summary.zero(), 0
        for b in _joined(batches, summary.batch_rows) if summary.batch_rows else batches:
            if b.num_rows:
                state, rows = summary.fold(state, b), rows + b.num_rows
        if rows:
            yield from _rows_of(summary, TaskContext.get().partitionId(), state, rows)

    return df.mapInArrow(run, STATE_SCHEMA)


class _Merger:
    """Merges states as their last pieces arrive; only states not yet whole wait."""

    def __init__(self, summary: Summary):
        self.summary, self.waiting, self.state, self.any, self.rows = summary, {}, None, False, 0

    def add(self, slot: int, piece: int, pieces: int, data: bytes, rows: int) -> None:
        self.rows += rows
        parts = self.waiting.setdefault(slot, {})
        parts[piece] = data
        if len(parts) < pieces:
            return
        del self.waiting[slot]
        state = self.summary.load(b"".join(parts[i] for i in range(pieces)))
        self.state = self.summary.merge(self.state, state) if self.any else state
        self.any = True

    def add_batch(self, batch: pa.RecordBatch) -> None:
        for row in zip(*(batch.column(c).to_pylist() for c in ("slot", "piece", "pieces", "state", "rows")), strict=True):
            self.add(*row)


def _merge_level(states: DataFrame, width: int, summary: Summary) -> DataFrame:
    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger = _Merger(summary)
        for b in batches:
            merger.add_batch(b)
        yield from _rows_of(summary, key[0].as_py(), merger.state, merger.rows)

    return states.groupBy(F.pmod("slot", F.lit(width)).alias("node")).applyInArrow(run, STATE_SCHEMA)


def partial_states(df: DataFrame, summary: Summary, depth: int = 2, partitions: int | None = None) -> DataFrame:
    """States after the planned levels."""
    states = _fold(df, summary)
    for width in plan_tree(partitions or partition_count(df), depth).levels:
        states = _merge_level(states, width, summary)
    return states


def tree_aggregate_finalize(df: DataFrame, summary: Summary, depth: int = 2, partitions: int | None = None) -> DataFrame:
    """The answer's rows, finished once on the root's executor; no row for empty input."""
    return finish_states(partial_states(df, summary, depth, partitions), summary)


def tree_aggregate(df: DataFrame, summary: Summary, depth: int = 2, root: str = "driver", finalize: bool | None = None, partitions: int | None = None):
    """The whole state on the driver (None for empty input), or with `finalize` what tree_aggregate_finalize returns."""
    if finalize or root == "finalize":
        return tree_aggregate_finalize(df, summary, depth, partitions)
    states = partial_states(df, summary, depth, partitions)
    if root == "executor":
        states = _merge_level(states, 1, summary)
    # the baselines' point is that the states come to the driver, all at once and as many as the root's fan-in
    merger = _Merger(summary)
    for r in states.collect():
        merger.add(r.slot, r.piece, r.pieces, bytes(r.state), r.rows)
    return merger.state if merger.any else None


def finished(df: DataFrame, summary: Summary, depth: int = 2, root: str = "finalize", partitions: int | None = None) -> DataFrame:
    """The answer as a DataFrame under any of the three placements."""
    if root == "finalize":
        return tree_aggregate_finalize(df, summary, depth, partitions)
    state = tree_aggregate(df, summary, depth, root, partitions=partitions)
    # an Arrow table stays with the plan, rows would be a job of their own
    return df.sparkSession.createDataFrame(summary.finalize(state) if state is not None else [], summary.result_schema)


def _class_rows(summary: Summary, part: int, slot: int, state, rows: int) -> Iterator[pa.RecordBatch]:
    whole = summary.whole(state)
    for b in _rows_of(summary, 0, state, rows):
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([slot], pa.int64()), *b.columns[1:], pa.array([whole])], names=["class", "slot", "piece", "pieces", "state", "rows", "whole"])


def _counted(b: pa.RecordBatch | pa.Table) -> pa.Table:
    """class, item, w with the weights of a label summed."""
    table = pa.Table.from_batches([b]) if isinstance(b, pa.RecordBatch) else b
    return table.group_by(["class", "item"], use_threads=False).aggregate([("w", "sum")]).rename_columns(["class", "item", "w"]).combine_chunks()


def _fold_classes(df: DataFrame, summary: Summary, classes: int) -> DataFrame:
    """A state for each class of a partition's labels, by hash. A task that comes to hold HELD_COUNTERS counters sends its states on and starts anew."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, states, rows, sent = TaskContext.get().partitionId(), {}, {}, 0

        def send():
            for c, state in states.items():
                yield from _class_rows(summary, c, place + (sent << 32), state, rows[c])

        def take(b):
            part = b.column("class").to_numpy()
            b = b.drop_columns(["class"])
            if classes > 1:
                order = np.argsort(part, kind="stable")
                part, b = part[order], b.take(pa.array(order))
            met, starts = np.unique(part, return_index=True)
            for c, low, high in zip(met.tolist(), starts.tolist(), [*starts.tolist()[1:], len(part)], strict=True):
                states[c] = summary.fold(states.get(c, summary.zero()), b.slice(low, high - low))
                rows[c] = rows.get(c, 0) + high - low

        if not summary.batch_rows:
            for b in _joined(batches, 1 << 19 if classes > 1 else 1):
                take(b)
                if classes > 1 and sum(map(summary.held, states.values())) >= HELD_COUNTERS:
                    yield from send()
                    states, rows, sent = {}, {}, sent + 1
            yield from send()
            return
        # labels are counted as Arrow before they enter the sketches as weighted ones
        counted, least = None, 0
        for b in _joined(batches, summary.batch_rows):
            own = _counted(b if "w" in b.schema.names else b.append_column("w", pa.array(np.ones(b.num_rows, np.int64))))
            counted = own if counted is None else pa.concat_tables([counted, own])
            if counted.num_rows > 2 * least + HELD_COUNTERS // 2:
                counted = _counted(counted)
                least = counted.num_rows
                if least >= HELD_COUNTERS:
                    take(counted.to_batches()[0])
                    yield from send()
                    states, rows, sent, counted, least = {}, {}, sent + 1, None, 0
        if counted is not None:
            take(_counted(counted).to_batches()[0])
        yield from send()

    of = F.pmod(F.xxhash64("item"), F.lit(classes)).cast("int") if classes > 1 else F.lit(0)
    return df.select(of.alias("class"), "*").mapInArrow(run, CLASS_SCHEMA)


def _merge_classes(states: DataFrame, width: int, summary: Summary) -> DataFrame:
    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger = _Merger(summary)
        for b in batches:
            merger.add_batch(b)
        yield from _class_rows(summary, key[0].as_py(), key[1].as_py(), merger.state, merger.rows)

    return states.groupBy("class", F.pmod("slot", F.lit(width)).alias("node")).applyInArrow(run, CLASS_SCHEMA)


def class_states(df: DataFrame, summary: Summary, classes: int, depth: int = 2, partitions: int | None = None, root: str = "finalize") -> DataFrame:
    """States by class of labels (column `item`) after the planned levels, and unless the root is the driver one of each class."""
    states = _fold_classes(df, summary, classes)
    levels = plan_tree(partitions or partition_count(df), depth).levels
    for width in levels if root == "driver" else (*levels, 1):
        states = _merge_classes(states, width, summary)
    return states


def finish_classes(states: DataFrame, summary: Summary, root: str = "finalize") -> DataFrame:
    """Every class's answer and whether it is whole; a class that is not gives one row of nulls. Finished on executors, or on the driver for its own and the executors' root."""
    schema = T.StructType([*summary.result_schema.fields, T.StructField("whole", T.BooleanType())])

    def rows(merger: _Merger) -> pa.Table:
        if not summary.whole(merger.state):
            return pa.Table.from_pylist([{"whole": False}], schema=to_arrow_schema(schema))
        found = summary.finalize(merger.state).combine_chunks()
        return found.append_column("whole", pa.array([True] * found.num_rows, pa.bool_()))

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger = _Merger(summary)
        for b in batches:
            merger.add_batch(b)
        yield from rows(merger).to_batches()

    if root == "finalize":
        return states.groupBy("class").applyInArrow(run, schema)
    mergers: dict[int, _Merger] = {}
    for r in states.collect():
        mergers.setdefault(r["class"], _Merger(summary)).add(r.slot, r.piece, r.pieces, bytes(r.state), r.rows)
    found = [tuple(r.values()) for m in mergers.values() for r in rows(m).to_pylist()]
    return states.sparkSession.createDataFrame(found, schema)


def attach(spark: SparkSession) -> None:
    """The tree calls as methods of DataFrame: `df.treeAggregate(summary, finalize=True)`, `df.treeReduce(col, f)`."""
    cls = type(spark.range(0))
    cls.treeAggregate, cls.treeReduce, cls.treeReduceFinalize = tree_aggregate, tree_reduce, tree_reduce_finalize


def assert_mergeable(summary: Summary, batches: list[pa.RecordBatch], same, groupings: int = 5, seed: int = 0) -> None:
    """The closure law: folds of disjoint batches merged in any grouping give states that `same(a, b)` accepts."""
    rng = random.Random(seed)
    want = None
    for _ in range(groupings):
        states = [summary.load(summary.dump(summary.fold(summary.zero(), b))) for b in batches]
        while len(states) > 1:
            a, b = (states.pop(rng.randrange(len(states))) for _ in range(2))
            states.append(summary.load(summary.dump(summary.merge(a, b))))
        want = states[0] if want is None else want
        if not same(want, states[0]):
            raise AssertionError("a regrouping changed what the state stands for")


def driver_loss_inventory(spark: SparkSession) -> DataFrame:
    """What a lost driver takes along, and what checkpointed levels let a new one go on from."""
    rows = [
        ("lineage graph", "lost", False), ("scheduler state", "lost", False), ("task completion", "lost", False), ("shuffle output locations", "lost", False), ("accumulators", "lost", False),
        ("cached partitions", "maybe", False), ("shuffle files", "maybe", False), ("external input", "safe", True), ("checkpointed levels", "safe", True),
    ]
    return spark.createDataFrame(rows, "item string, fate string, resumable boolean")


def tree_reduce(df: DataFrame, col: str, f, depth: int = 2, root: str = "driver"):
    """The reduced value on the driver, None for no rows."""
    return tree_aggregate(df.select(col), ReduceSummary(f, None, ""), depth, root)


def tree_reduce_finalize(df: DataFrame, col: str, f, finish, result_schema: str, depth: int = 2) -> DataFrame:
    """Same-type reduce whose root finishes on its executor; `finish` turns the value into an Arrow table."""
    return tree_aggregate_finalize(df.select(col), ReduceSummary(f, finish, result_schema), depth)


def tagged_tree_aggregate(df: DataFrame, summary: Summary, total_rows: int, depth: int = 2, root: str = "executor") -> pa.Table | None:
    """The workaround without a finishing hook: every merge carries the rows seen and finishes at `total_rows`."""
    done = tree_aggregate(df, TaggedSummary(summary, total_rows), depth, root)
    if done is None:
        return None
    if done[0] != "finished":
        raise ValueError(f"the last merge saw {done[1]} rows of {total_rows}")
    return done[2]


def state_sizes(df: DataFrame, summary: Summary, depth: int = 2) -> DataFrame:
    """slot, rows, state_bytes of the states that reach the root."""
    return partial_states(df, summary, depth).groupBy("slot").agg(F.sum("rows").alias("rows"), F.sum(F.length("state")).cast("long").alias("state_bytes"))


def checkpointed_states(df: DataFrame, summary: Summary, folder: str, depth: int = 2) -> DataFrame:
    """States after the planned levels, each level written under `folder`; complete levels are not run again.

    A restarted driver that calls this with the same folder goes on from the last complete level, and other
    answers may be finished from the same states without another scan.
    """
    spark = df.sparkSession

    def level(i: int, build) -> DataFrame:
        path = f"{folder}/level-{i}"
        if not exists(spark, f"{path}/_SUCCESS"):
            build().write.mode("overwrite").parquet(path)
        return spark.read.schema(STATE_SCHEMA).parquet(path)

    states = level(0, lambda: _fold(df, summary))
    for i, width in enumerate(plan_tree(partition_count(df), depth).levels, 1):
        states = level(i, lambda below=states, width=width: _merge_level(below, width, summary))
    return states


def finish_states(states: DataFrame, summary: Summary) -> DataFrame:
    """The answer from stored states: one merge and the finishing step on an executor."""

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger = _Merger(summary)
        for b in batches:
            merger.add_batch(b)
        yield from summary.finalize(merger.state).combine_chunks().to_batches()

    return states.groupBy(F.pmod("slot", F.lit(1)).alias("node")).applyInArrow(run, summary.result_schema)
