"""The methods over unbounded input, with Structured Streaming.

Event times are cast to time-zoned timestamps before a watermark, as plain
ones are refused. Results go to files through ``foreachBatch``, so nothing
gathers on the driver; offsets, state and results share the folder that the
session names for checkpoints.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from warpspan.functions import kernels
from warpspan.operators import search
from warpspan.sources.store import shared_folder

EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
    ]
)


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 8) -> DataFrame:
    """The events as a stream of files, with ``ts`` fit for a watermark and ``cents`` whole."""
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch)
    # As a pattern, since a stream takes a folder or a pattern but no single file.
    rows = reader.parquet(f"{sf_dir}/event[s].parquet")
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("cents", F.floor(F.col("value") * 100 + 0.5).cast("bigint"))


def rate_stream(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    """A made-up regular series for demonstrations."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rows.select((F.col("value") % 10).alias("user_id"), F.col("timestamp").alias("ts"), "value")


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs over all that is there and returns the result: the last state in complete mode, all rows otherwise."""
    spark = stream.sparkSession
    place = shared_folder(spark)

    def write(batch: DataFrame, number: int) -> None:
        # A repeated batch overwrites its own folder, so restarts leave no doubles.
        batch.write.mode("overwrite").parquet(f"{place}/rows" if mode == "complete" else f"{place}/rows/batch={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{place}/log").foreachBatch(write).trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()
    out = spark.read.schema(stream.schema).parquet(f"{place}/rows")
    return out.select(*stream.columns)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Regular samples: sum and count by user and window."""
    return _windowed(events, F.window("ts", width), late)


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Overlapping segments."""
    return _windowed(events, F.window("ts", width, slide), late)


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Bursts of a user's events that no gap divides."""
    return _windowed(events, F.session_window("ts", gap), late)


def _windowed(events: DataFrame, window: Column, late: str) -> DataFrame:
    sums = events.withWatermark("ts", late).groupBy("user_id", window.alias("w")).agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    return sums.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), "n", "cents")


def once(events: DataFrame, late: str = "1 day") -> DataFrame:
    """Repeated events are dropped while the watermark remembers them."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def late_rows(stream: DataFrame, late: str = "1 hour") -> int:
    """How many rows of all that is there come after the watermark has passed them, from the query's own progress.

    A trigger's rows are held against the watermark that the trigger before it
    began with, as in every stateful operator here; late rows are left out.
    """
    place = shared_folder(stream.sparkSession)
    keyed = stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{place}/rows/batch={number}")

    query = keyed.writeStream.option("checkpointLocation", f"{place}/log").foreachBatch(write).trigger(availableNow=True).start()
    query.awaitTermination()
    return sum(state.numRowsDroppedByWatermark for progress in query.recentProgress for state in progress.stateOperators)


def paired(left: DataFrame, right: DataFrame, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Two streams joined where a user's events are at most ``within`` apart."""
    a = left.select(F.col("user_id"), F.col("ts").alias("left_ts"), F.col("event_id").alias("left_id")).withWatermark("left_ts", late)
    b = right.select(F.col("user_id").alias("other"), F.col("ts").alias("right_ts"), F.col("event_id").alias("right_id")).withWatermark("right_ts", late)
    near = (F.col("user_id") == F.col("other")) & F.expr(f"right_ts between left_ts - interval {within} and left_ts + interval {within}")
    return a.join(b, near).select("user_id", "left_id", "right_id")


_BUFFER = T.StructType([T.StructField("seen", T.LongType()), T.StructField("last", T.ArrayType(T.DoubleType())), T.StructField("ids", T.ArrayType(T.LongType()))])


def _stateful(events: DataFrame, keep: int, schema: str, each: Callable[[int, int, list[float], list[int]], Iterator[tuple]]) -> DataFrame:
    """Runs ``each(user, position, last values, their ids)`` for every event in time order; the state is the last ``keep`` samples."""
    names = [f.split()[0] for f in schema.split(", ")]

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, last, ids = state.get if state.exists else (0, [], [])
        last, ids = list(last), list(ids)
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for event, cents in zip(rows["event_id"], rows["cents"], strict=True):
            seen += 1
            last, ids = [*last, float(cents)][-keep:], [*ids, int(event)][-keep:]
            out += each(key[0], seen, last, ids)
        state.update((seen, last, ids))
        yield pd.DataFrame(out, columns=names)

    rows = events.select("user_id", "ts", "event_id", "cents").groupBy("user_id")
    return rows.applyInPandasWithState(step, schema, _BUFFER, "append", GroupStateTimeout.NoTimeout)


def envelope_stream(events: DataFrame, w: int) -> DataFrame:
    """The envelope with a delay of w: position i - w is ready when sample i has come.

    The last w positions stay open, as a stream has no last sample;
    ``close_envelope`` gives them for a finished series.
    """

    def each(user, seen, last, ids):
        if seen > w:
            at = len(last) - 1 - w
            window = last[max(0, at - w) :]
            yield user, seen - w, ids[at], int(min(window)), int(max(window))

    return _stateful(events, 2 * w + 1, "user_id long, pos long, event_id long, lo long, hi long", each)


def close_envelope(last: list[float], w: int) -> list[tuple[float, float]]:
    """The open positions' ``(lo, hi)``, from the state's last samples."""
    n = len(last)
    return [(min(last[max(0, at - w) :]), max(last[max(0, at - w) :])) for at in range(max(0, n - w), n)]


def watch_patterns(events: DataFrame, patterns: dict[int, list[float]], w: int, eps: float, stride: int = 1) -> DataFrame:
    """Alerts where a user's last samples come within ``eps`` of a pattern.

    Patterns are few and travel with the function; their envelopes are
    computed once, so most windows cost one sweep.
    """
    ready = []
    for number, y in patterns.items():
        lo, hi = kernels.envelope(np.array([y], dtype=float), w)
        ready.append((number, np.array([y], dtype=float), lo, hi))
    n = len(ready[0][1][0])

    def each(user, seen, last, ids):
        if seen < n or seen % stride:
            return
        x = np.array([last[-n:]])
        for number, y, lo, hi in ready:
            if kernels.pass1_pow(x, lo, hi)[0] <= eps and kernels.pass2_pow(x, y, lo, hi, w)[0] <= eps:
                dist = kernels.dtw_pow(x, y, w)[0]
                if dist <= eps:
                    yield user, ids[-1], number, int(dist)

    return _stateful(events, n, "user_id long, event_id long, pattern long, dist long", each)


def nearest_online(segments: DataFrame, index, w: int, path: str, method: str = "box_pass2"):
    """Starts a query that takes each batch's finished segments ``(query_id, y)`` to the index and appends the answers."""

    def answer(batch: DataFrame, number: int) -> None:
        if batch.limit(1).count():
            search.nearest(batch, index, w, method=method).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return segments.writeStream.option("checkpointLocation", f"{path}/_log").foreachBatch(answer).trigger(availableNow=True).start()
