"""Structured Streaming around the network: windows as inputs, continuous inference and online training.

Files are replayed with availableNow. Sinks are idempotent by batch id, and all checkpoints lie in the session's shared folder.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.listener import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import passes
from ..operators.encode import EVENT_TYPES, event_neuron
from ..operators.topology import Network
from ..session import shared_folder
from ..sources.versions import complete_steps, load_step, save_step

EVENTS = "event_id BIGINT, ts TIMESTAMP, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", files).parquet(folder)


def run_to_table(stream: DataFrame, mode: str) -> DataFrame:
    """Replays what is there into the shared folder, a directory a batch id, and reads it: all batches, or the last one in complete mode."""
    spark, out = stream.sparkSession, new_folder(stream.sparkSession, "sink")
    wrote: list[int] = []

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")
        wrote.append(batch_id)

    q = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", new_folder(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    if not wrote:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{out}/batch={k}" for k in (wrote if mode != "complete" else [max(wrote)])])


def tumbling(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding(events: DataFrame, size: str = "6 hours", slide: str = "3 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, slide)).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def clicks_to_purchases(events: DataFrame, within: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: purchases of the same user within the time after a click, as labels."""
    c = events.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("c_user"), F.col("ts").alias("c_ts")).withWatermark("c_ts", late)
    p = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("p_user"), F.col("ts").alias("p_ts")).withWatermark("p_ts", late)
    return c.join(p, F.expr(f"c_user = p_user AND p_ts >= c_ts AND p_ts <= c_ts + INTERVAL {within}")).select("click_id", "purchase_id")


def user_recency(events: DataFrame) -> DataFrame:
    """(user_id, events, last_ts): state of each user, updated a batch at a time."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, last = state.get if state.exists else (0, 0)
        for b in batches:
            n, last = n + len(b), max(last, int(b["at"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_at": [last]})

    at = events.select("user_id", F.unix_timestamp("ts").alias("at"))
    return at.groupBy("user_id").applyInPandasWithState(update, "user_id long, events long, last_at long", "n long, last long", "update", GroupStateTimeout.NoTimeout)


def idle_users(events: DataFrame, idle: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, events, last_at): emitted once a user has been idle for so long in event time, and the state is then dropped."""
    span = int(pd.Timedelta(idle).total_seconds() * 1000)

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            n, last = state.get
            state.remove()
            yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_at": [last]})
            return
        n, last = state.get if state.exists else (0, 0)
        for b in batches:
            n, last = n + len(b), max(last, int(b["at"].max()))
        state.update((n, last))
        state.setTimeoutTimestamp(max(1000 * last + span, state.getCurrentWatermarkMs() + 1))

    at = events.withWatermark("ts", late).select("user_id", "ts", F.unix_timestamp("ts").alias("at"))
    return at.groupBy("user_id").applyInPandasWithState(update, "user_id long, events long, last_at long", "n long, last long", "append", GroupStateTimeout.EventTimeTimeout)


class Progress(StreamingQueryListener):
    """Keeps rows read, rows dropped as late and batches of every query, by its name or id."""

    def __init__(self):
        self.read: dict[str, int] = {}
        self.late: dict[str, int] = {}
        self.batches: dict[str, int] = {}
        self.ended: set[str] = set()

    def onQueryStarted(self, event) -> None:
        self.read.setdefault(event.name or str(event.id), 0)

    def onQueryProgress(self, event) -> None:
        p = event.progress
        name = p.name or str(p.id)
        self.read[name] = self.read.get(name, 0) + p.numInputRows
        self.batches[name] = self.batches.get(name, 0) + 1
        self.late[name] = self.late.get(name, 0) + sum(s.numRowsDroppedByWatermark for s in p.stateOperators)

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        self.ended.add(str(event.id))


def window_vectors(events: DataFrame) -> DataFrame:
    """Inputs of closed windows of a day: x = 1 where the user did the type in the hour."""
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01")).cast("bigint")
    return events.filter(F.col("event_type").isin(EVENT_TYPES)).select((F.col("user_id") * 1000 + day).alias("vec_id"), event_neuron().alias("neuron")).distinct().withColumn("x", F.lit(1.0))


def stream_inference(events: DataFrame, net: Network, out: str | None = None) -> DataFrame:
    """(batch, vec_id, neuron, x): each micro-batch through all layers, written once per batch id."""
    spark = events.sparkSession
    out = out or new_folder(spark, "scores")

    def score(batch: DataFrame, batch_id: int) -> None:
        passes.last_layer(net, window_vectors(batch)).select("vec_id", "neuron", "x").write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    q = events.writeStream.foreachBatch(score).option("checkpointLocation", new_folder(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema("vec_id BIGINT, neuron BIGINT, x DOUBLE, batch INT").parquet(out)


def online_train(events: DataFrame, net: Network, targets, root: str, eta: float = 0.01) -> Network:
    """One micro-batch is one batch of training. targets(x) -> (vec_id, neuron, y). A replayed batch id finds its step complete and is skipped."""
    spark = events.sparkSession

    def train(batch: DataFrame, batch_id: int) -> None:
        done = complete_steps(spark, root)
        if batch_id + 1 in done:
            return
        at = net.with_weights(load_step(spark, root, done[-1])[1]) if done else net
        x = window_vectors(batch)
        n = x.select("vec_id").distinct().count()
        if n:
            save_step(passes.step(at, x, targets(x), eta, n).weights, root, batch_id + 1)

    q = events.writeStream.foreachBatch(train).option("checkpointLocation", new_folder(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return net.with_weights(load_step(spark, root)[1])
