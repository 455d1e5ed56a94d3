"""Edges that arrive as a stream of events. Runs drain the source once (availableNow) into the shared folder and return the table.

Event times are cast to TIMESTAMP before watermarks, which don't take TIMESTAMP_NTZ; the session's zone should be UTC.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from deltahop import graphs
from deltahop.operators.partitioning import bucketed
from deltahop.operators.storage import shared_path

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def edge_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files: int | None = None) -> DataFrame:
    """Streaming events of a folder, with ts as TIMESTAMP and the item of props.k. files: at most so many a micro batch."""
    reader = spark.readStream.schema(SCHEMA).option("pathGlobFilter", pattern)
    raw = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(folder)
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("bigint").alias("item"))


def as_edges(events: DataFrame) -> DataFrame:
    return events.select(graphs.typed("user_id", "customer").alias("src_id"), F.col("event_type").alias("rel"), graphs.typed("item", "item").alias("dst_id"), "ts")


def drain(stream: DataFrame, name: str, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Run a stream to the end of its source and return what it wrote: in update mode the last row of each of `keys`."""
    spark = stream.sparkSession
    path, marks = shared_path(spark, name), shared_path(spark, f"{name}-marks")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", marks).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", marks).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(path)
    if not keys:
        return rows.where(F.col("epoch") == rows.agg(F.max("epoch")).first()[0]).drop("epoch")
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "epoch").alias("r"))
    return last.select("r.*")


def dedupe(events: DataFrame, delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(events: DataFrame, width: str = "1 day", delay: str = "1 day") -> DataFrame:
    return _windowed(events.withWatermark("ts", delay), F.window("ts", width))


def sliding(events: DataFrame, width: str = "1 day", step: str = "6 hours", delay: str = "1 day") -> DataFrame:
    return _windowed(events.withWatermark("ts", delay), F.window("ts", width, step))


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    return _windowed(events.withWatermark("ts", delay), F.session_window("ts", gap), "user_id")


def _windowed(events: DataFrame, window, *keys: str) -> DataFrame:
    rows = events.groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"))
    return rows.select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), *keys, "n")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


def click_to_purchase(events: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Stream-stream interval join of a user's clicks and purchases."""
    click = events.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t0")).withWatermark("t0", delay)
    bought = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("t1")).withWatermark("t1", delay)
    return click.join(bought, F.expr(f"u = v and t1 >= t0 and t1 < t0 + interval {within}")).select("click", "purchase")


def degree_and_sample(events: DataFrame, fanout: int = 5) -> DataFrame:
    """(user_id, degree, sample): edges seen so far and the `fanout` items of smallest hash, kept per user as edges arrive.

    A bottom-f sample merges: the sample of a union is the bottom f of the samples, so state is f entries per user.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        degree, held = state.get if state.exists else (0, [])
        best = dict(zip(held[1::2], held[::2], strict=True)) if held else {}
        for pdf in frames:
            degree += len(pdf)
            for item, p in zip(pdf["item"], pdf["p"], strict=True):
                if not pd.isna(item):  # counts as an edge, but has no end to keep
                    best[int(item)] = int(p)
        kept = sorted(best.items(), key=lambda x: (x[1], x[0]))[:fanout]
        state.update((degree, [v for item, p in kept for v in (p, item)]))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [degree], "sample": [",".join(str(i) for i, _ in kept)]})

    from deltahop import hashing

    keyed = events.select("user_id", "item", hashing.mix(F.col("user_id") * 1000 + F.col("item"), 5).alias("p"))
    return keyed.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, degree bigint, sample string", "degree bigint, held array<bigint>", "update", GroupStateTimeout.NoTimeout)


def append_to_buckets(events: DataFrame, path: str, marks: str, p: int = 4, seed: int = 0) -> None:
    """Append arriving edges to their buckets, exactly once: each micro batch owns a folder that a repeat overwrites."""

    def keep(batch: DataFrame, epoch: int) -> None:
        bucketed(as_edges(batch), p, seed).write.mode("overwrite").partitionBy("src_part").parquet(f"{path}/batch={epoch}")

    events.writeStream.foreachBatch(keep).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
