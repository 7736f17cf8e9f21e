"""Streams of changes: micro-batches are compacted to one low-rank change and applied to a view once each."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.models import View
from ..sources.updates import compact
from .store import ViewStore


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    """events as a stream; ts becomes a timestamp with a zone, which watermarks need."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # As a pattern, since a stream's plain path must be a folder and the table may be one file.
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/event[s].parquet")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


class Refresher:
    """foreachBatch sink: additive cell changes (i, j, v) of one input. Late changes are only applied later, since additions
    commute.

    With a store a batch's factors and its id are committed before the view changes, and a new Refresher takes the input from
    the store, so that a restart behind the stream's checkpoint loses nothing and a replayed batch changes nothing. Without one
    the ids are kept in memory, for streams that end with the process."""

    def __init__(self, view: View, name: str, store: ViewStore | None = None):
        self.view, self.name, self.store, self.done, self.ranks = view, name, store, -1, []
        if store is not None and store.has(name):
            view.restore({name: store.get(name)})
            self.done = store.batch(name)
        elif store is not None:
            store.put(name, view.backend.coo(view.env[name]))

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        rows, cols = self.view.program.inputs[self.name]
        left, right, rank = compact(batch, rows, cols)
        if rank and self.store is not None:
            self.store.add(self.name, left, right, batch=batch_id)
        if rank:
            self.view.apply(self.name, left, right)
        self.ranks.append(rank)
        self.done = batch_id


def run(stream: DataFrame, refresher: Refresher, checkpoint: str) -> Refresher:
    """Takes all that is there and stops."""
    query = stream.writeStream.foreachBatch(refresher).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return refresher


def to_table(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs the stream over what is there into a Parquet folder and reads it; complete mode keeps the last batch."""
    spark = stream.sparkSession
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start()
    else:
        q = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(f"{path}/out")).option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{path}/out")


def latest_rows(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """Replacing changes (matrix row i, column j, v, event_time): the newest by event time for each cell; duplicates by seq go."""
    fresh = stream.withWatermark("event_time", delay).dropDuplicatesWithinWatermark(["seq"])
    return fresh.groupBy("i", "j").agg(F.max_by("v", "event_time").alias("v"), F.max("event_time").alias("event_time"))


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, within: str, delay: str = "1 day") -> DataFrame:
    """Pairs of two streams with equal keys and the right one's time after the left one's by at most ``within``. Both sides have
    watermarks, so state older than the interval and the delay goes. Columns of the right side end in ``_2``."""
    a = left.withWatermark(time, delay)
    b = right.select(*[F.col(c).alias(f"{c}_2") for c in right.columns]).withWatermark(f"{time}_2", delay)
    return a.join(b, F.expr(f"{key} = {key}_2 AND {time}_2 > {time} AND {time}_2 <= {time} + INTERVAL {within}"))


def transitions(stream: DataFrame, key: str, order: list[str], kind: str) -> DataFrame:
    """(a, b): each row's kind and the next one's of the same key, with the last kind of each key as state. Rows of a micro-batch
    are put in order; a row that comes in a later batch counts as later."""

    def step(_, parts, state: GroupState):
        rows = pd.concat(list(parts)).sort_values(order, kind="stable")
        kinds = ([state.get[0]] if state.exists else []) + rows[kind].tolist()
        state.update((kinds[-1],))
        yield pd.DataFrame({"a": kinds[:-1], "b": kinds[1:]})

    return stream.select(key, *order, kind).groupBy(key).applyInPandasWithState(step, "a string, b string", "last string", "append", GroupStateTimeout.NoTimeout)
