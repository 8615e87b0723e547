"""Structured Streaming forms over the events table: adaptive code length with keyed state, windows, duplicates.

Each function replays the table to its end (availableNow) into a table in the shared folder and reads that back.
"""

from __future__ import annotations

import math
import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions import alphabet as A
from ..sources.tables import shared_dir


def _source(spark, sf_dir) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))  # event time needs a time zone: the session's


def _run(df: DataFrame, mode: str = "append") -> DataFrame:
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").foreachBatch(sink).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/out/*")


def order1_bits(key, frames: list[pd.DataFrame], counts: dict, last: int | None):
    """Rows in event order: bits under order-1 counts; returns rows, counts and the last code."""
    rows = pd.concat(frames).sort_values(["ts", "event_id"])
    ts, bits = [], []
    for t, code in zip(rows["ts"], rows["code"], strict=True):
        if last is not None:
            hit, seen = counts.get((last, code), 0), sum(counts.get((last, c), 0) for c in range(5))
            ts.append(t)
            bits.append(-math.log2((hit + 1) / (seen + 5)))
            counts[last, code] = hit + 1
        last = code
    return pd.DataFrame({"user_id": [key[0]] * len(ts), "ts": ts, "bits": bits}), counts, last


class OrderOne(StatefulProcessor):
    """State of each key: 25 counts and the last code; rows older than the last one are counted as late, not coded."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("model", "counts string, last int, until timestamp, late long")

    def handleInputRows(self, key, rows, timerValues):
        import json

        counts, last, until, late = {}, None, None, 0
        if self.state.exists():
            c, last, until, late = self.state.get()
            counts = {tuple(map(int, k.split(","))): v for k, v in json.loads(c).items()}
        frames = list(rows)
        every = pd.concat(frames)
        if until is not None:
            fresh = every[every["ts"] >= pd.Timestamp(until)]
            late += len(every) - len(fresh)
            every = fresh
        if len(every):
            out, counts, last = order1_bits(key, [every], counts, last)
            until = max(every["ts"]).to_pydatetime()
            self.state.update((json.dumps({f"{a},{b}": v for (a, b), v in counts.items()}), int(last), until, int(late)))
            yield out

    def close(self) -> None:
        pass


def coded(events: DataFrame) -> DataFrame:
    code = A.code(A.event_base(F.col("event_type")))
    rows = events.select("user_id", "ts", "event_id", code.alias("code")).withWatermark("ts", "1 day")
    return rows.groupBy("user_id").transformWithStateInPandas(
        OrderOne(), outputStructType="user_id long, ts timestamp, bits double", outputMode="Append", timeMode="None"
    )


def _with_rocksdb(spark, fn):
    """Keyed state of this kind needs the RocksDB store; the session's own choice comes back after."""
    key = "spark.sql.streaming.stateStore.providerClass"
    old = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return fn()
    finally:
        spark.conf.set(key, old) if old is not None else spark.conf.unset(key)


def bits_by_day(spark, sf_dir) -> DataFrame:
    rows = _with_rocksdb(spark, lambda: _run(coded(_source(spark, sf_dir))))
    return rows.groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count("*").alias("n"), F.round(F.sum("bits"), 4).alias("bits"))


def sliding(spark, sf_dir) -> DataFrame:
    """Two-day windows every day, complete at the end."""
    e = _source(spark, sf_dir).withWatermark("ts", "1 day")
    w = e.groupBy(F.window("ts", "2 days", "1 day"), "event_type").agg(F.count("*").alias("n"))
    out = _run(w.select(F.col("window.start").alias("start"), "event_type", "n"), "update")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz")).groupBy("start", "event_type").agg(F.max("n").alias("n"))


def sessions(spark, sf_dir) -> DataFrame:
    e = _source(spark, sf_dir).withWatermark("ts", "1 day")
    g = e.groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    out = _run(g.select("user_id", F.col("w.start").alias("start"), "n"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


def dedupe(spark, sf_dir) -> DataFrame:
    """Every event twice in the stream, once in the result."""
    e = _source(spark, sf_dir)
    twice = e.unionByName(e).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return _run(twice.select("event_type")).groupBy("event_type").agg(F.count("*").alias("n"))
