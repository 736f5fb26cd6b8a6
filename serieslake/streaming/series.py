"""Series from streams: windows of events, ring buffers, exactly-once appends, standing queries."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import search as Q
from ..operators.index import SeriesIndex
from ..sources import store


def stream_events(spark: SparkSession, path: str, glob: str = "*.parquet") -> DataFrame:
    """Files of events as a stream. Event time gets a zone, since watermarks need one."""
    schema = spark.read.parquet(path).schema if glob == "*.parquet" else spark.read.option("pathGlobFilter", glob).parquet(path).schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", glob).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, kind: str, size: str, slide: str | None = None, lateness: str = "1 hour", keys: tuple[str, ...] = ("event_type",)) -> DataFrame:
    """Counts and sums by window: tumbling, sliding or session, with late rows dropped at the watermark."""
    late = events.withWatermark("ts", lateness)
    win = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", size)}[kind]()
    return late.groupBy(win.alias("win"), *keys).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def window_series(events: DataFrame, size: str, bins: int, lateness: str = "1 hour") -> DataFrame:
    """One series a user and full window: sums by bin inside the window, empty bins zero."""
    late = events.withWatermark("ts", lateness).withColumn("win", F.window("ts", size))
    span = F.unix_micros(F.col("win.end")) - F.unix_micros(F.col("win.start"))
    late = late.withColumn("bin", F.floor((F.unix_micros("ts") - F.unix_micros(F.col("win.start"))) * bins / span).cast("int"))
    sums = [F.sum(F.when(F.col("bin") == b, F.col("value")).otherwise(0.0)).alias(f"b{b}") for b in range(bins)]
    got = late.groupBy("win", "user_id").agg(*sums)
    return got.select(F.col("win.start").alias("start"), "user_id", F.array(*(F.col(f"b{b}") for b in range(bins))).alias("values"))


def ring_series(events: DataFrame, n: int) -> DataFrame:
    """For each user the last n values after every batch that brought some, once n were seen."""

    def keep(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(state.get[0]) if state.exists else []
        last = state.get[1] if state.exists else -1
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        held = (held + rows["value"].fillna(0.0).tolist())[-n:]
        last = int(max(last, rows["event_id"].max()))
        state.update((held, last))
        if len(held) == n:
            yield pd.DataFrame({"series_id": [last], "user_id": [key[0]], "values": [held]})

    return events.select("user_id", "ts", "event_id", "value").groupBy("user_id").applyInPandasWithState(keep, "series_id bigint, user_id bigint, values array<double>", "held array<double>, last bigint", "append", GroupStateTimeout.NoTimeout)


def interval_join(first: DataFrame, then: DataFrame, key: str, within: str, lateness: str = "1 hour") -> DataFrame:
    """(key, first_id, then_id, first_ts, then_ts): rows of ``then`` at most ``within`` after a row of ``first`` of the same
    key. Both streams have watermarks and the bound is one of time, so the state of either is let go in time."""
    a = first.select(F.col(key).alias("_key"), F.col("event_id").alias("first_id"), F.col("ts").alias("first_ts")).withWatermark("first_ts", lateness)
    b = then.select(key, F.col("event_id").alias("then_id"), F.col("ts").alias("then_ts")).withWatermark("then_ts", lateness)
    near = (F.col("_key") == F.col(key)) & F.col("then_ts").between(F.col("first_ts"), F.col("first_ts") + F.expr(f"interval {within}"))
    return a.join(b, near).select(key, "first_id", "then_id", "first_ts", "then_ts")


def append_stream(series: DataFrame, path: str, checkpoint: str):
    """Appends each batch of series to a stored index once: the manifest names the batches it holds, so a replayed batch is skipped."""

    def add(batch: DataFrame, batch_id: int) -> None:
        if not batch.isEmpty():
            store.append(batch.sparkSession, path, batch.select("series_id", "values"), batch_id)

    return series.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def standing_queries(series: DataFrame, index: SeriesIndex, answers: list[DataFrame], checkpoint: str, k: int = 1):
    """Each new series against a loaded index; hands every batch's answers to ``answers``."""

    def ask(batch: DataFrame, batch_id: int) -> None:
        if not batch.isEmpty():
            answers.append(Q.knn(index, batch.select(F.col("series_id").alias("query_id"), "values"), k))

    return series.writeStream.foreachBatch(ask).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_to_table(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there now into a memory table and returns it; for tests and small results."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def run_to_folder(df: DataFrame, path: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there now and returns all that its batches, of this run and earlier ones with the same
    checkpoint, gave. A batch has a folder of its own, so a replayed one replaces itself."""

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.read.parquet(path)
