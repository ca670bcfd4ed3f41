"""The reward log as a stream. Timestamps without a zone are cast, as watermarks need a zoned type."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.io import stage_dir

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of events in a folder, read as they come."""
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def reward_curve(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Mean reward in tumbling windows, or sliding ones; works on streams and on tables."""
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg("value").alias("reward")).select(F.col("w.start").alias("start"), "n", F.round("reward", 6).alias("reward"))


def reward_sessions(events: DataFrame, gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    s = F.session_window("ts", gap)
    return events.groupBy("user_id", s.alias("w")).agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("reward")).select("user_id", F.col("w.start").alias("start"), "n", "reward")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_labels(events: DataFrame, ontology: DataFrame) -> DataFrame:
    """A stream joined to the static ontology (21 rows) by a label number out of the event."""
    numbered = events.withColumn("seq", (F.col("event_id") % 21).cast("int"))
    return numbered.join(F.broadcast(ontology.select("seq", "label")), "seq", "left")


def matched_responses(prompts: DataFrame, answers: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: an answer of the same user no later than ``within`` after the prompt."""
    p = prompts.withWatermark("ts", late).select(F.col("event_id").alias("prompt_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pts"))
    a = answers.withWatermark("ts", late).select(F.col("event_id").alias("answer_id"), F.col("user_id").alias("au"), F.col("ts").alias("ats"))
    return p.join(a, F.expr(f"pu = au and ats >= pts and ats <= pts + interval {within}")).select("prompt_id", "answer_id")


def complete_groups(responses: DataFrame, k: int, timeout_ms: int = 3_600_000) -> DataFrame:
    """Buffers the responses of a question until k are there or event time passes the timeout, then emits their advantages.

    A question's rows are (sample_id, k, reward, ts). State holds at most k rewards a question.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key, frames: Iterator, state: GroupState):
        import numpy as np
        import pandas as pd

        def out(ks, values, full):
            a = np.asarray(values)
            spread = a.std()
            adv = np.zeros(len(a)) if spread <= 1e-12 else (a - a.mean()) / spread
            return pd.DataFrame({"sample_id": key[0], "k": ks, "adv": adv.round(6), "complete": full})

        if state.hasTimedOut:
            ks, values = state.get
            state.remove()
            yield out(list(ks), list(values), False)
            return
        ks, values = (list(x) for x in state.get) if state.exists else ([], [])
        last = state.getCurrentWatermarkMs()
        got = [f for f in frames if len(f)]
        for f in [pd.concat(got).sort_values(["ts", "k"], kind="stable")] if got else []:  # rows come in any order within a batch
            for i, r, t in zip(f["k"], f["reward"], f["ts"], strict=True):
                ks.append(int(i))
                values.append(float(r))
                last = max(last, int(t.timestamp() * 1000))
                if len(ks) == k:
                    yield out(ks, values, True)
                    ks, values = [], []
        if ks:
            state.update((ks, values))
            state.setTimeoutTimestamp(last + timeout_ms)
        elif state.exists:
            state.remove()

    grouped = responses.withWatermark("ts", "1 hour").groupBy("sample_id")
    return grouped.applyInPandasWithState(step, "sample_id long, k long, adv double, complete boolean", "ks array<long>, rewards array<double>", "append", GroupStateTimeout.EventTimeTimeout)


def run_to_end(stream: DataFrame) -> DataFrame:
    """Runs a bounded stream to its end into a table in the shared folder and returns it."""
    folder = f"{stage_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    q = stream.writeStream.format("parquet").option("path", f"{folder}/table").option("checkpointLocation", f"{folder}/state").outputMode("append").trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{folder}/table")


def exactly_once_sink(path: str, key: list[str]):
    """A foreachBatch function: appends the rows whose key the table lacks, so a repeated batch adds nothing."""
    from ..sources.io import append_new

    def write(batch: DataFrame, _: int) -> None:
        append_new(batch.dropDuplicates(key), path, key)

    return write
