"""Streams: arriving strings scored against a static index, windows, late rows, duplicates, interval joins.

Nothing here collects a stream: scoring a micro-batch is the batch operator inside `foreachBatch`; everything else is
a declarative streaming plan. `available` runs a stream over what there is and ends, for jobs and tests alike.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import minhash, text
from ..operators import ranking
from ..operators.index import Queries, TokenIndex
from ..operators.storage import shared_dir


def read_files(spark: SparkSession, path: str, schema, fmt: str = "parquet", files_a_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.format(fmt).schema(schema)
    if files_a_trigger:
        reader = reader.option("maxFilesPerTrigger", files_a_trigger)
    return reader.load(path)


def folder(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}"


def available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """The result of a stream over all that is there, as Parquet in the shared folder (its own table otherwise)."""
    spark, at = stream.sparkSession, folder(stream.sparkSession)
    if mode == "append":
        stream.writeStream.format("parquet").option("checkpointLocation", f"{at}/log").outputMode("append").trigger(availableNow=True).start(f"{at}/rows").awaitTermination()
    else:
        # Complete results come whole with every batch: the last one stands.
        def put(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(f"{at}/rows")

        stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{at}/log").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/rows")


def select_stream(index: TokenIndex, arriving: DataFrame, predicate: str = "bm25", threshold: float | None = None, k: int | None = None, **params) -> DataFrame:
    """Arriving (qid, s) against a fixed index: each micro-batch is a set of queries. The index is static."""
    at = folder(arriving.sparkSession)

    def put(batch: DataFrame, number: int) -> None:
        ranking.approx_select(index, Queries(batch), predicate, threshold, k, **params).write.mode("overwrite").parquet(f"{at}/rows/batch={number}")

    arriving.writeStream.foreachBatch(put).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    return arriving.sparkSession.read.schema("qid long, tid long, score double").parquet(f"{at}/rows").drop("batch")


def append_stream(index: TokenIndex, arriving: DataFrame, path: str) -> TokenIndex:
    """Arriving (tid, s) added to an index in micro-batches; statistics are sums, so each batch adds its own. The
    index is saved under `path` after every batch, alternately in two places."""
    index.save(f"{path}/0")

    def put(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        TokenIndex.load(spark, f"{path}/{number}").append(batch.select("tid", "s")).save(f"{path}/{number + 1}")
        last[0] = number + 1

    last = [0]
    arriving.writeStream.foreachBatch(put).option("checkpointLocation", f"{folder(arriving.sparkSession)}/log").trigger(availableNow=True).start().awaitTermination()
    return TokenIndex.load(arriving.sparkSession, f"{path}/{last[0]}")


def in_order(rows: DataFrame, parts: list) -> DataFrame:
    """A stream that gets the rows of each condition as a batch of its own, one after the other."""
    at = f"{folder(rows.sparkSession)}/parts"
    for part in parts:
        rows.where(part).coalesce(1).write.mode("append").parquet(at)
    return read_files(rows.sparkSession, at, rows.schema, files_a_trigger=1)


def minhash_bands(rows: DataFrame, hashes: int = 8, rows_a_band: int = 2, q: int = 2) -> DataFrame:
    """band, tid, ts of (tid, s, ts): min-hash values of the grams, rows_a_band at a time."""
    signature = minhash.minhash_signature(F.array_distinct(text.qgrams(F.col("s"), q)), hashes)
    bands = F.array(*(F.concat_ws("|", F.lit(str(i)), *(F.col("signature")[i + k].cast("string") for k in range(rows_a_band))) for i in range(0, hashes, rows_a_band)))
    return rows.withColumn("signature", signature).where("signature is not null").select(F.explode(bands).alias("band"), "tid", "ts")


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "0 seconds") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "2 hours", slide: str = "1 hour", late: str = "0 seconds") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "0 seconds") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "n")


def without_duplicates(events: DataFrame, keys: list[str], late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def interval_join(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Pairs of a user's events of left (ts) and of right (ts) that follow within a time."""
    a = left.withWatermark("ts", late).select(F.col("user_id").alias("user_a"), F.col("ts").alias("ts_a"), F.col("event_id").alias("event_a"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("user_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("event_b"))
    return a.join(b, F.expr(f"user_a = user_b AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {within}"))


def near_duplicates(arriving: DataFrame, bands: Callable[[DataFrame], DataFrame], ttl_ms: int = 3_600_000, late: str = "0 seconds") -> DataFrame:
    """Stateful near-duplicate marks: `bands` turns arriving (tid, s, ts) into (band, tid, ts); a tuple whose band was
    met before, within the time to live after its last tuple, gets the band's first tid. State is one number per live
    band; it goes when the watermark passes its time (a timeout by the clock would never let a bounded run end)."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        first = state.get[0] if state.exists else None
        # a large group comes in several frames, in no order: the first tuple is known when all are there
        f = pd.concat([*frames]).sort_values(["ts", "tid"])
        last = max([0, *(int(x.timestamp() * 1000) for x in f["ts"].iloc[-1:])])
        if first is None and len(f):
            first = int(f["tid"].iloc[0])
        again = f[f["tid"] != first]
        if len(again):
            yield pd.DataFrame({"tid": again["tid"].to_numpy(), "first": first})
        if first is not None:
            state.update((first,))
            state.setTimeoutTimestamp(max(last + ttl_ms, state.getCurrentWatermarkMs() + 1))

    return bands(arriving).withWatermark("ts", late).groupBy("band").applyInPandasWithState(run, "tid long, first long", "first long", "append", GroupStateTimeout.EventTimeTimeout)
