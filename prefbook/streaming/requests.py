"""Streams of requests: demand by window, session and user, joint demand, online cost, and redesign."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from prefbook.operators.assign import nearest
from prefbook.operators.refine import means
from prefbook.plans.engine import Layout, SparkEngine
from prefbook.sources.tables import EVENTS_SCHEMA


def read(spark: SparkSession, path: str, pattern: str = "events*.parquet", per_trigger: int = 1000) -> DataFrame:
    """event_id, user_id, item_id, symbol and ts as an instant; a watermark needs the latter."""
    source = spark.readStream.schema(EVENTS_SCHEMA).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", per_trigger).parquet(path)
    return as_requests(source)


def as_requests(events: DataFrame) -> DataFrame:
    return events.select("event_id", "user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id"), F.col("event_type").alias("symbol"), F.col("ts").cast("timestamp").alias("ts"))


def windowed_demand(requests: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """(start, item_id, c) by tumbling or sliding windows; requests later than ``late`` are dropped."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return requests.withWatermark("ts", late).groupBy(window.alias("w"), "item_id").agg(F.count("*").alias("c")).select(F.col("w.start").alias("start"), "item_id", "c")


def sessions(requests: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """(user_id, start, c): bursts of requests of a user."""
    grouped = requests.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("c"))
    return grouped.select("user_id", F.col("s.start").alias("start"), "c")


def deduplicated(requests: DataFrame, late: str = "1 day") -> DataFrame:
    """Each event once, however often it is sent within the watermark."""
    return requests.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def online_cost(requests: DataFrame, spv: DataFrame, q: np.ndarray, length: int = 20) -> DataFrame:
    """(symbol, bits, c): what the requests cost under the current books; a join of the stream with the items' table."""
    priced = nearest(spv.select("item_id", "p"), q).select("item_id", "cost")
    return requests.join(priced, "item_id").groupBy("symbol").agg((length * F.sum("cost")).alias("bits"), F.count("*").alias("c"))


def joint_requests(requests: DataFrame, minutes: int = 10, late: str = "1 hour") -> DataFrame:
    """(i, j, ts): requests of two cohorts within some minutes of each other, stream against stream."""
    width = 60 * minutes
    timed = requests.withWatermark("ts", late).withColumn("bucket", F.floor(F.unix_timestamp("ts") / width))
    near = F.explode(F.array(*(F.col("bucket") + d for d in (-1, 0, 1))))
    left = timed.filter(F.col("user_id") % 2 == 0).select(F.col("item_id").alias("i"), F.col("ts").alias("t0"), near.alias("b0"))
    right = timed.filter(F.col("user_id") % 2 == 1).select(F.col("item_id").alias("j"), F.col("ts").alias("t1"), F.col("bucket").alias("b1"))
    gap = F.expr(f"INTERVAL {minutes} MINUTES")
    return left.join(right, (F.col("b0") == F.col("b1")) & (F.col("t1") >= F.col("t0") - gap) & (F.col("t1") <= F.col("t0") + gap)).select("i", "j", F.col("t0").alias("ts"))


def user_demand(requests: DataFrame, decay: float = 0.5) -> DataFrame:
    """(user_id, requests, top_item, weight): per-user demand whose past fades by ``decay`` with each batch; all items that a user ever asked for are held."""

    def update(key: tuple[Any, ...], frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, items, weights = state.get if state.exists else (0, [], [])
        held = {i: w * decay for i, w in zip(items, weights)}
        for frame in frames:
            seen += len(frame)
            for item, n in frame["item_id"].value_counts().items():
                held[item] = held.get(item, 0.0) + float(n)
        kept = sorted(held.items(), key=lambda x: (-x[1], x[0]))
        state.update((int(seen), [int(i) for i, _ in kept], [float(w) for _, w in kept]))
        yield pd.DataFrame({"user_id": [key[0]], "requests": [int(seen)], "top_item": [int(kept[0][0])], "weight": [float(kept[0][1])]})

    return requests.filter("item_id is not null").groupBy("user_id").applyInPandasWithState(
        update, "user_id long, requests long, top_item long, weight double", "requests long, items array<long>, weights array<double>", "update", GroupStateTimeout.NoTimeout
    )


class Redesign:
    """Books that follow a stream: each batch adds its sums per book, and books become the means of all sums so far.

    Sums add up over batches, so a step reads only the batch; its state is books x (symbols + 1) numbers. A batch that
    comes again after a failure is not counted twice.
    """

    def __init__(self, spv: DataFrame, q: np.ndarray):
        self.spv, self.q = spv.select("item_id", "p"), q
        self.t, self.s = np.zeros(len(q)), np.zeros_like(q)
        self.done: set[int] = set()

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number in self.done:
            return
        counts = batch.groupBy("item_id").agg(F.count("*").cast("double").alias("w0"))
        sums = SparkEngine(counts.join(self.spv, "item_id"), self.q.shape[1]).hard({0: (Layout(len(self.q)), self.q)})[0]
        self.t, self.s = self.t + sums.t, self.s + sums.s
        sums.t, sums.s = self.t, self.s
        self.q = means(sums, self.q)
        self.done.add(number)


def drain(df: DataFrame, mode: str, name: str, checkpoint: str | None = None) -> DataFrame:
    """All that a stream has now, in a memory table; for reports and tests."""
    writer = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    writer.start().awaitTermination()
    return df.sparkSession.table(name)


def each_batch(df: DataFrame, step: Callable[[DataFrame, int], None]) -> None:
    df.writeStream.foreachBatch(step).trigger(availableNow=True).start().awaitTermination()


