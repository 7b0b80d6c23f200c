"""The stream side: windows, late data, state, and slim runs made batch by batch."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from .. import sorter
from ..session import new_path
from ..sources import stream


def event_stream(spark: SparkSession, events: DataFrame, files: int = 4) -> DataFrame:
    """The events as a stream of several files in time order, ``at`` their timestamp."""
    path = new_path(spark, "events")
    events.repartitionByRange(files, "event_id").sortWithinPartitions("event_id").write.parquet(path)
    return stream(spark, path, spark.read.parquet(path).schema, 2).withColumn("at", F.col("ts").cast("timestamp"))


def with_watermark(df: DataFrame, delay: str = "1 hour") -> DataFrame:
    return df.withWatermark("at", delay)


def collected(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to its end and return what its sink holds: Parquet files in the shared folder, no row on the driver.

    A batch has a folder of its own, so that one that is tried again replaces itself; in ``complete`` mode the last batch is all.
    """
    spark, path, last = df.sparkSession, new_path(df.sparkSession, "sink"), []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{0 if mode == 'complete' else number}")
        last.append(number)

    q = df.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", new_path(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    if not last:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).option("recursiveFileLookup", "true").parquet(path)


def stream_window(df: DataFrame, kind: str, size: str, slide: str | None = None, by: list[str] = ()) -> DataFrame:
    """Counts in tumbling, sliding or session windows."""
    w = F.session_window("at", size) if kind == "session" else F.window("at", size, slide) if kind == "sliding" else F.window("at", size)
    return df.groupBy(w.alias("w"), *by).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


def stream_dedup(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.dropDuplicatesWithinWatermark(keys)


def stream_enrich(df: DataFrame, static: DataFrame, on, how: str = "inner") -> DataFrame:
    return df.join(static, on, how)


def stream_pair(a: DataFrame, b: DataFrame, gap: str) -> DataFrame:
    """Pairs of one user where the second follows within ``gap``; both sides need watermarks."""
    x = a.select(F.col("user_id"), F.col("event_id").alias("first_id"), F.col("at").alias("first_at"))
    y = b.select(F.col("user_id").alias("u2"), F.col("event_id").alias("second_id"), F.col("at").alias("second_at"))
    return x.join(y, F.expr(f"user_id = u2 AND second_at > first_at AND second_at <= first_at + INTERVAL {gap}"))


def late_split(df: DataFrame, delay_s: int) -> tuple[DataFrame, DataFrame]:
    """Rows of a batch that are on time, and those older than ``delay_s`` before the newest."""
    newest = df.agg(F.max("at")).first()[0]
    edge = F.lit(newest).cast("timestamp") - F.make_dt_interval(secs=F.lit(delay_s))
    return df.where(F.col("at") >= edge), df.where(F.col("at") < edge)


def stream_runs(df: DataFrame, path: str, key: Column, checkpoint: str = "", bounds: list[bytes] | None = None) -> None:
    """One sorted slim run a micro-batch, named by the batch: a batch that is tried again writes the same run again.

    With the ``checkpoint`` of an earlier call only files that came since are read, as further runs.  ``bounds`` cut the
    keys into ranges, the same for all runs, of which each is merged by a task of its own.
    """
    cuts = sorted(bounds or [])

    def write(batch: DataFrame, number: int) -> None:
        range_id = sum([(F.col("key") >= F.lit(bytearray(c))).cast("int") for c in cuts], F.lit(0))
        slim = batch.select(key.alias("key"), F.lit(0).alias("file_id"), F.col("event_id").alias("pos"))
        ordered = slim.withColumn("range_id", range_id).repartition("range_id").sortWithinPartitions("range_id", "key", "file_id", "pos")
        ordered.write.mode("overwrite").partitionBy("range_id").parquet(f"{path}/run={number}")

    at = checkpoint or new_path(df.sparkSession, "checkpoint")
    q = df.writeStream.foreachBatch(write).option("checkpointLocation", at).trigger(availableNow=True).start()
    q.awaitTermination()


def merged_runs(spark: SparkSession, path: str) -> DataFrame:
    """All runs so far, ranked."""
    count = spark.read.parquet(path).agg(F.max("run")).first()[0]
    return sorter.merged(spark, path, 1000, 0 if count is None else count + 1)


def stream_topk(df: DataFrame, k: int) -> DataFrame:
    """The k largest values of each event type so far, in state; updates of each batch."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = list(state.get[0]) if state.exists else []
        for f in frames:
            best = sorted(best + [int(round(v * 100)) for v in f["value"]], reverse=True)[:k]
        state.update((best,))
        yield pd.DataFrame({"event_type": [key[0]], "best": [best]})

    out = "event_type string, best array<long>"
    return df.groupBy("event_type").applyInPandasWithState(update, out, "best array<long>", "update", GroupStateTimeout.NoTimeout)
