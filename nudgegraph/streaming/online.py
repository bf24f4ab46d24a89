"""Online learning of edge probabilities from a stream of actions.

``stream_actions`` reads action files as they come. The transformations work
on streams and on tables alike, so a batch run over the same rows is the check.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nudgegraph.session import scratch_path
from nudgegraph.sources.networks import SECONDS

LATENESS = "2 hours"
ACTION = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def stream_actions(spark: SparkSession, path: str, lateness: str = LATENESS, files: int = 1) -> DataFrame:
    """A stream of (ts, actor, action) from parquet files at ``path``, with a bound on lateness."""
    rows = spark.readStream.schema(ACTION).option("maxFilesPerTrigger", files).parquet(path)
    return as_actions(rows).withWatermark("ts", lateness)


def as_actions(events: DataFrame) -> DataFrame:
    return events.select("ts", F.col("user_id").alias("actor"), F.concat_ws("|", "event_type", "props").alias("action"))


def tumbling(actions: DataFrame, width: str = "1 day") -> DataFrame:
    return actions.groupBy(F.window("ts", width)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sliding(actions: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    return actions.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(actions: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return actions.groupBy("actor", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("actor", F.col("w.start").alias("start"), "n")


def first_actions(actions: DataFrame) -> DataFrame:
    """The earliest time of each pair of actor and action, as an updating aggregate."""
    return actions.groupBy("actor", "action").agg(F.min("ts").alias("ts"))


def deduplicated(actions: DataFrame) -> DataFrame:
    return actions.dropDuplicatesWithinWatermark(["actor", "action", "ts"]) if actions.isStreaming else actions.dropDuplicates(["actor", "action", "ts"])


def hits(left: DataFrame, right: DataFrame, window: str = "6 hours") -> DataFrame:
    """(src, dst, action, at): dst did after src, within the window, such as ``6 hours``, what src had done.

    The join is an equality on the action and a slice of time as wide as the
    window, so a popular action's rows are held against those of two slices,
    not of all time.
    """
    number, unit = window.split()
    seconds = SECONDS[unit.rstrip("s")]
    # a row meets its own slice of time and the next; days and weeks may be an hour longer than their seconds
    width = int(number) * seconds + (0 if seconds < SECONDS["day"] else SECONDS["day"])
    own = F.floor(F.unix_timestamp("ts") / width)
    a = left.select(F.col("actor").alias("src"), F.col("action").alias("action_u"), F.col("ts").alias("ts_u"), F.explode(F.array(own, own + 1)).alias("slice_u"))
    b = right.select(F.col("actor").alias("dst"), F.col("action").alias("action_v"), F.col("ts").alias("ts_v"), own.alias("slice_v"))
    near = F.expr(f"action_u = action_v and slice_u = slice_v and src <> dst and ts_v > ts_u and ts_v <= ts_u + interval {window}")
    return a.join(b, near).select("src", "dst", F.col("action_u").alias("action"), F.col("ts_v").alias("at"))


def drain(stream: DataFrame, mode: str = "append") -> tuple[DataFrame, list[dict]]:
    """Run a stream over all that is there, to a table; the rows and the progress reports."""
    spark = stream.sparkSession
    out, state = scratch_path(spark, "stream-out"), scratch_path(spark, "stream-state")
    seen: list[int] = []

    def write(rows: DataFrame, epoch: int) -> None:
        # an epoch that comes again replaces what it wrote before
        rows.write.mode("overwrite").parquet(f"{out}/epoch={epoch}")
        seen.append(epoch)

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    reports = [p.jsonValue if hasattr(p, "jsonValue") else p for p in query.recentProgress]
    if not seen:
        return spark.createDataFrame([], stream.schema), reports
    return spark.read.schema(stream.schema).parquet(*[f"{out}/epoch={e}" for e in sorted(set(seen))]), reports


def latest(rows: DataFrame, *keys: str) -> DataFrame:
    """Of an updating stream's output the last state of each key: counts only grow."""
    value = [c for c in rows.columns if c not in keys]
    return rows.groupBy(*keys).agg(*[F.max(c).alias(c) for c in value])


def split_by_time(spark: SparkSession, events: DataFrame, parts: int, late: bool = False) -> str:
    """Write the events as files in the order of time; with ``late`` the earliest hour comes last."""
    bounds = events.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi")).first()
    span = (bounds.hi - bounds.lo) / parts
    path = scratch_path(spark, "replay")
    own = events.select("event_id", "ts", "user_id", "event_type", "value", "props")
    hour = F.lit(bounds.lo) + F.expr("interval 1 hour")
    for i in range(parts):
        lo, hi = bounds.lo + span * i, bounds.lo + span * (i + 1)
        part = own.where((F.col("ts") >= F.lit(lo)) & ((F.col("ts") < F.lit(hi)) | F.lit(i == parts - 1)))
        (part.where(F.col("ts") >= hour) if late else part).coalesce(1).write.mode("append").parquet(path)
    if late:
        own.where(F.col("ts") < hour).coalesce(1).write.mode("append").parquet(path)
    return path


def publish(spark: SparkSession, stream: DataFrame, merge: Callable[[DataFrame, int], None]) -> None:
    """Give each batch of an updating stream to ``merge`` with its epoch, once all that is there is read."""
    state = scratch_path(spark, "publish-state")
    stream.writeStream.outputMode("update").option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(merge).start().awaitTermination()


def probabilities(first: DataFrame, met: DataFrame) -> DataFrame:
    """(src, dst, p) from first actions and hits, as tables."""
    done = first.groupBy(F.col("actor").alias("src")).agg(F.count("*").alias("done"))
    return met.groupBy("src", "dst").agg(F.count("*").alias("hits")).join(done, "src").select("src", "dst", (F.col("hits") / F.col("done")).alias("p"))


def with_known(actions: DataFrame, known: DataFrame, key: str = "actor") -> DataFrame:
    """Actions joined with a table that doesn't stream, on its column ``key``; actions of unknown keys go."""
    return actions.join(known, key)


def _earliest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of a task's rows the earliest of each pair."""
    held: list[pa.RecordBatch] = []

    def least() -> pa.Table:
        return pa.Table.from_batches(held).group_by(["actor", "action"]).aggregate([("ts", "min")]).rename_columns({"ts_min": "ts"}).select(["actor", "action", "ts"])

    rows = 0
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows > 1_000_000:
            held, rows = least().to_batches(), 0
    if held:
        yield from least().to_batches()


def first_seen(actions: DataFrame, keep_seconds: int | None = None) -> DataFrame:
    """First action of each pair as a stateful stream: one row a pair, when it is first met.

    Each trigger's earliest rows of all pairs are found by one pass a task,
    and pairs that were met before go. With ``keep_seconds`` a pair is
    forgotten when the watermark passes its time by that much, so the state
    stays bounded; met again later, the pair counts as new. That form calls
    Python for each pair.
    """
    if keep_seconds is None:
        near = actions.select("actor", "action", "ts").repartition("actor", "action")
        return near.mapInArrow(_earliest, "actor long, action string, ts timestamp").dropDuplicates(["actor", "action"])

    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        least = min((b.ts.min() for b in batches), default=None)
        if not state.exists and least is not None:
            state.update((least.value // 1000,))
            state.setTimeoutTimestamp(max(least.value // 1_000_000 + 1000 * keep_seconds, state.getCurrentWatermarkMs() + 1))
            yield pd.DataFrame({"actor": [key[0]], "action": [key[1]], "ts": [least]})

    return actions.groupBy("actor", "action").applyInPandasWithState(run, "actor long, action string, ts timestamp", "us long", "append", GroupStateTimeout.EventTimeTimeout)
