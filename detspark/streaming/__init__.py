"""Structured Streaming forms: running top-K, incremental unique sets, windowed configurations."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from detspark.functions.schema import ProblemSpec
from detspark.operators import topk
from detspark.operators.dedup import key_names
from detspark.plans.scratch import children, discard
from detspark.sources.tables import from_positions


class RunningTop:
    """Top-K over micro-batches: each one is merged with the set of the batch before, which is kept as files by batch number.

    A restarted query goes on from the last set, and a batch that is run again writes the same set again.
    """

    def __init__(self, k: int, path: str, score: str = "score") -> None:
        self.k, self.path, self.score = k, path.rstrip("/"), score

    def update(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        rows = batch.select(*key_names(batch), self.score)
        earlier = [int(x) for x in children(spark, self.path) if x.isdigit() and int(x) < batch_id]
        if earlier:
            held = spark.read.schema(rows.schema).parquet(f"{self.path}/{max(earlier)}")
            floor = held.agg(F.count("*"), F.min(self.score)).first()
            rows = held.unionByName(rows.where(F.col(self.score) >= floor[1]) if floor[0] >= self.k else rows)
        topk.exact(rows, self.k, self.score).write.mode("overwrite").parquet(f"{self.path}/{batch_id}")
        for old in sorted(earlier)[:-1]:
            discard(spark, f"{self.path}/{old}")

    def frame(self, spark: SparkSession) -> DataFrame:
        """The set after the last batch."""
        return spark.read.parquet(f"{self.path}/{max(int(x) for x in children(spark, self.path) if x.isdigit())}")


def top(stream: DataFrame, k: int, checkpoint: str, score: str = "score") -> tuple[RunningTop, StreamingQuery]:
    """Start a top-K over all files there are (available-now) and return its state, kept beside the checkpoint, and query."""
    state = RunningTop(k, checkpoint.rstrip("/") + "-top", score)
    query = stream.writeStream.foreachBatch(state.update).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    return state, query


def dedup(stream: DataFrame, time_column: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Each key once.  Without a time column the state grows with the unique keys; with one it is bounded by the watermark."""
    names = key_names(stream)
    if time_column is None:
        return stream.select(*names).dropDuplicates(names)
    return stream.select(*names, time_column).withWatermark(time_column, delay).dropDuplicatesWithinWatermark(names)


def window_configurations(events: DataFrame, spec: ProblemSpec, width: str = "1 day", slide: str | None = None, gap: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Per user and window (tumbling, sliding or session) the set of hours with events, as ``window, user_id, hours``."""
    span = F.session_window("ts", gap) if gap else F.window("ts", width, slide)
    timed = events.withWatermark("ts", delay) if events.isStreaming else events
    hours = timed.groupBy(span.alias("window"), "user_id").agg(F.sort_array(F.collect_set(F.hour("ts"))).alias("hours"))
    return hours.where(F.size("hours") >= spec.n)


def configurations(windows: DataFrame, spec: ProblemSpec) -> DataFrame:
    """Configurations of the first ``n`` hours of each window (batch)."""
    return from_positions(windows.select(F.slice("hours", 1, spec.n).alias("at")), "at", spec)


def redundancy_per_batch(stream: DataFrame, sink: Callable[[int, int, int], None], checkpoint: str) -> StreamingQuery:
    """Report rows, and keys that are new, of each micro-batch; seen keys are kept as files beside the checkpoint."""
    names = key_names(stream)
    path = checkpoint.rstrip("/") + "-seen"

    def update(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        keys = batch.select(*names)
        rows = keys.count()
        fresh = keys.distinct()
        if batch_id:
            fresh = fresh.join(spark.read.schema(keys.schema).parquet(*[f"{path}/{i}" for i in range(batch_id)]), names, "left_anti")
        fresh.write.mode("overwrite").parquet(f"{path}/{batch_id}")
        sink(batch_id, rows, spark.read.schema(keys.schema).parquet(f"{path}/{batch_id}").count())

    return stream.select(*names).writeStream.foreachBatch(update).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def nearby_pairs(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Events of one user at most ``within`` apart, left before right; on streams both sides carry watermarks."""
    a = left.select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = right.select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    if left.isStreaming:
        a, b = a.withWatermark("a_ts", within), b.withWatermark("b_ts", within)
    return a.join(b, F.expr(f"a_user = b_user and b_ts > a_ts and b_ts <= a_ts + interval {within}"))
