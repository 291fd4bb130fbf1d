"""Structured Streaming around the methods: windowed counts and a running sketch that only a read finishes."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.heavy_hitters import exact_hitters, whole_states
from ..summary import CounterSummary, Summary
from ..tree import CLASS_SCHEMA, STATE_SCHEMA, _Merger, finish_states, partial_states


def event_stream(spark: SparkSession, folder: str, name: str = "events") -> DataFrame:
    """The table as a file stream by its own schema."""
    schema = spark.read.parquet(f"{folder}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(folder)


def _drained(stream: DataFrame, out: str, mode: str, write) -> None:
    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()


def windowed_counts(stream: DataFrame, out: str, ts: str = "ts", width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """window_start, event_type, count of a drained stream; every trigger replaces the written result."""
    timed = stream.withColumn("at", F.col(ts).cast("timestamp")).withWatermark("at", late)
    counts = timed.groupBy(F.window("at", width, slide), "event_type").count().select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "event_type", "count")
    _drained(counts, out, "complete", lambda df, _: df.write.mode("overwrite").parquet(f"{out}/result"))
    return stream.sparkSession.read.schema(counts.schema).parquet(f"{out}/result")


def running_sketch(stream: DataFrame, col: str, summary: Summary, out: str) -> DataFrame:
    """The answer of a drained stream. Each micro-batch stores its partial states once, under its own number, so that
    a batch run again replaces them; the stored states stay open and a read finishes a merged copy."""

    def write(df: DataFrame, batch: int) -> None:
        states = partial_states(df.select(F.col(col).alias("item")).where("item IS NOT NULL"), summary)
        states.write.mode("overwrite").parquet(f"{out}/states/batch={batch}")

    _drained(stream, out, "append", write)
    return finish_states(stream.sparkSession.read.schema(STATE_SCHEMA + ", batch int").parquet(f"{out}/states").drop("batch"), summary)


def running_hitters(stream: DataFrame, col: str, k: int, summary: CounterSummary, out: str) -> DataFrame:
    """The k most frequent of a drained stream, exact however many labels come. Each micro-batch stores states that give up no label; a read
    takes their counters as weighted labels."""

    def write(df: DataFrame, batch: int) -> None:
        whole_states(df.select(F.col(col).alias("item")).where("item IS NOT NULL"), summary, folder=f"{out}/states/batch={batch}")

    def counters(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger = _Merger(summary)
        for b in batches:
            merger.add_batch(b)
        yield from summary.counted(merger.state).to_batches()

    kind = stream.schema[col].dataType
    _drained(stream, out, "append", write)
    stored = stream.sparkSession.read.schema(CLASS_SCHEMA + ", batch int").parquet(f"{out}/states")
    rows = stored.groupBy("batch", "class").applyInArrow(counters, T.StructType([T.StructField("item", kind), T.StructField("count", T.LongType())]))
    return exact_hitters(rows, "item", k, capacity=summary.capacity, weight_col="count")


def windowed_summaries(stream: DataFrame, col: str, summary: Summary, out: str, columns: str, ts: str = "ts", width: str = "day", late: str = "1 hour") -> DataFrame:
    """window_start and the summary's answer for each window that the watermark has closed.

    The open state of a window is the dumped summary, which later rows may still join; it is finished once, when the watermark
    passes the window's end, and dropped. `columns` is the answer's DDL. Rows later than the watermark are left out by Spark.
    """
    span = F.expr(f"INTERVAL 1 {width.upper()}")
    timed = stream.withColumn("at", F.col(ts).cast("timestamp")).withWatermark("at", late)
    timed = timed.select(F.date_trunc(width, "at").alias("w"), (F.unix_millis(F.date_trunc(width, "at") + span)).alias("ends"), F.col(col).alias("x"), "at").where("x IS NOT NULL")

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = summary.load(bytes(state.get[0])) if state.exists else summary.zero()
        if state.hasTimedOut:
            state.remove()
            done = summary.finalize(held).to_pandas()
            done.insert(0, "window_start", key[0])
            yield done
            return
        ends = 0
        for frame in frames:
            batch = pa.RecordBatch.from_pandas(frame[["x"]], preserve_index=False)
            held, ends = summary.fold(held, batch), int(frame["ends"].iloc[0])
        state.update((summary.dump(held),))
        state.setTimeoutTimestamp(max(ends, state.getCurrentWatermarkMs() + 1))

    done = timed.groupBy("w").applyInPandasWithState(step, f"window_start timestamp, {columns}", "state binary", "append", GroupStateTimeout.EventTimeTimeout)
    _drained(done, out, "append", lambda df, i: df.write.mode("overwrite").parquet(f"{out}/result/batch={i}"))
    return stream.sparkSession.read.schema(done.schema).parquet(f"{out}/result").drop("batch").withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


def session_counts(stream: DataFrame, key: str, out: str, ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """key, session_start, count of sessions that the watermark has closed."""
    timed = stream.withColumn("at", F.col(ts).cast("timestamp")).withWatermark("at", late)
    counts = timed.groupBy(key, F.session_window("at", gap).alias("s")).count().select(key, F.col("s.start").cast("timestamp_ntz").alias("session_start"), "count")
    return _appended(counts, out)


def _appended(rows: DataFrame, out: str) -> DataFrame:
    _drained(rows, out, "append", lambda df, i: df.write.mode("overwrite").parquet(f"{out}/result/batch={i}"))
    return rows.sparkSession.read.schema(rows.schema).parquet(f"{out}/result").drop("batch")


def deduplicated(stream: DataFrame, keys: list[str], out: str, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """Rows with keys not met before within the watermark."""
    names = stream.columns
    timed = stream.withColumn("__at", F.col(ts).cast("timestamp")).withWatermark("__at", late)
    return _appended(timed.dropDuplicatesWithinWatermark(keys).select(*names), out)


def joined_static(stream: DataFrame, static: DataFrame, on, out: str, columns: list[str]) -> DataFrame:
    """Each streamed row with its match in a table."""
    return _appended(stream.join(static, on).select(*columns), out)


def joined_streams(left: DataFrame, right: DataFrame, key: str, out: str, ts: str = "ts", within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """left_id, right_id of rows of one key whose right one comes at most `within` after the left one; both sides have watermarks."""
    a = left.select(F.col(key).alias("ka"), F.col("event_id").alias("left_id"), F.col(ts).cast("timestamp").alias("ta")).withWatermark("ta", late)
    b = right.select(F.col(key).alias("kb"), F.col("event_id").alias("right_id"), F.col(ts).cast("timestamp").alias("tb")).withWatermark("tb", late)
    near = (F.col("ka") == F.col("kb")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"INTERVAL {within}"))
    return _appended(a.join(b, near).select("left_id", "right_id"), out)


def late_rows(stream: DataFrame, out: str, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """batch, rows, late: of each micro-batch how many rows lay behind the watermark that the batches before it had set."""

    def write(df: DataFrame, batch: int) -> None:
        seen = f"{out}/seen"
        spark = df.sparkSession
        before = spark.read.schema("most timestamp_ntz").parquet(f"{seen}/*").agg(F.max("most")).first()[0] if batch else None
        bar = F.lit(None).cast("timestamp_ntz") if before is None else F.lit(str(before)).cast("timestamp_ntz") - F.expr(f"INTERVAL {late}")
        df.agg(F.lit(batch).cast("long").alias("batch"), F.count("*").alias("rows"), F.count_if(F.col(ts) < bar).alias("late"), F.max(ts).alias("most")).write.mode("overwrite").parquet(f"{seen}/batch={batch}")

    _drained(stream, out, "append", write)
    return stream.sparkSession.read.schema("batch long, rows long, late long").parquet(f"{out}/seen/*")
