"""Continuous scoring: incremental bin sums, windows, sessions, dedup, running top documents, over a stream of scores."""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from binlens.sources.index import shared_dir

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def score_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet") -> DataFrame:
    """Events as arriving scores: topic = k mod 24 from the JSON payload, format = event type."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).parquet(folder)
    return with_bins(raw)


def with_bins(raw: DataFrame) -> DataFrame:
    k = F.from_json("props", "k int")["k"]
    return raw.withColumn("topic", (k % 24).cast("long")).withColumnRenamed("event_type", "format")


def bin_sums(s: DataFrame) -> DataFrame:
    """Sufficient statistics of each bin; z needs all bins and is taken when the table is read."""
    return s.groupBy("topic", "format").agg(F.count("*").alias("n"), F.sum("value").alias("total"), F.sum(F.col("value") * F.col("value")).alias("squares"))


def tumbling(s: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return s.withWatermark("ts", late).groupBy(w.alias("w"), "format").agg(F.count("*").alias("n"),
        F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "format", "n", "total")


def sessions(s: DataFrame, gap: str = "6 hours") -> DataFrame:
    return s.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id",
        F.col("w.start").alias("start"), "n")


def deduplicated(s: DataFrame) -> DataFrame:
    return s.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def run_once(df: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what is there and return its result table, from the shared folder: each batch overwrites its own
    part there, and state and offsets are kept beside it, so a batch that is run again doesn't count twice and no row
    passes through the driver.  Of "complete" the last batch is the table, of the other modes all batches are."""
    spark = df.sparkSession
    path, done = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", []

    def sink(rows, batch):
        rows.write.mode("overwrite").parquet(f"{path}/out/batch-{batch}")
        done.append(f"{path}/out/batch-{batch}")

    df.writeStream.foreachBatch(sink).option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    parts = done[-1:] if mode == "complete" else done
    return spark.read.schema(df.schema).parquet(*parts) if parts else spark.createDataFrame([], df.schema)


def replayed(first: DataFrame, second: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, format, n): window counts when ``second`` arrives after ``first``; rows behind the watermark are dropped.

    Two runs of one query over one checkpoint, so it also shows that a stream goes on where it stopped.  Each batch
    overwrites its own folder: a batch that is run again after a failure doesn't count twice."""
    spark, path = first.sparkSession, f"{shared_dir(first.sparkSession)}/late-{uuid.uuid4().hex}"

    def sink(df, batch):
        df.write.mode("overwrite").parquet(f"{path}/out/batch={batch}")

    for part in (first, second):
        part.write.mode("append").parquet(f"{path}/in")
        windows = tumbling(with_bins(spark.readStream.schema(EVENTS).parquet(f"{path}/in")), width, late=late)
        windows.writeStream.foreachBatch(sink).option("checkpointLocation", f"{path}/state").outputMode("update").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/out").groupBy("start", "format").agg(F.max("n").alias("n"))


def late_report(kept: DataFrame, events: DataFrame) -> DataFrame:
    """(format, n_kept, n_late): rows that reached a window, and those that came behind the watermark."""
    k = kept.groupBy("format").agg(F.sum("n").alias("n_kept"))
    return events.groupBy("format").agg(F.count("*").alias("n")).join(k, "format", "left").select("format", F.coalesce("n_kept",
        F.lit(0)).alias("n_kept"), (F.col("n") - F.coalesce("n_kept", F.lit(0))).alias("n_late"))


def deduplicated_bloom(s: DataFrame, lanes: int = 16, bits: int = 1 << 23, hashes: int = 7) -> DataFrame:
    """Deliveries whose id a Bloom filter in the state hasn't seen: (event_id), each kept once.

    State is ``lanes`` filters of ``bits`` bits, whatever the stream, so it needs no watermark; the price is a small
    share of first deliveries that is dropped, about (1 - exp(-hashes * n / bits)) ^ hashes at n ids a lane."""

    def step(key, batches, state):
        seen = np.frombuffer(zlib.decompress(state.get[0]), np.uint8).copy() if state.exists else np.zeros(bits // 8, np.uint8)
        for b in batches:
            ids = np.unique(b.event_id.to_numpy()).astype(np.uint64)
            at = np.empty((len(ids), hashes), np.int64)
            for j in range(hashes):
                x = ids * np.uint64(0x9E3779B97F4A7C15) + np.uint64(0xD1B54A32D192ED03 * (j + 1) % (1 << 64))
                x ^= x >> np.uint64(29)
                x *= np.uint64(0xBF58476D1CE4E5B9)
                x ^= x >> np.uint64(32)
                at[:, j] = (x % np.uint64(bits)).astype(np.int64)
            new = ~((seen[at >> 3] >> (at & 7)) & 1).all(axis=1)
            np.bitwise_or.at(seen, at[new].ravel() >> 3, (1 << (at[new].ravel() & 7)).astype(np.uint8))
            yield pd.DataFrame({"event_id": ids[new].astype(np.int64)})
        state.update((zlib.compress(seen.tobytes(), 1),))

    return s.withColumn("lane", F.pmod(F.xxhash64("event_id"), F.lit(lanes))).groupBy("lane").applyInPandasWithState(step, "event_id long",
        "bits binary", "append", GroupStateTimeout.NoTimeout)


def with_owner(s: DataFrame, owners: DataFrame) -> DataFrame:
    """Stream-static join; the static side is read anew for each batch."""
    return s.join(owners, "user_id")


def followed_by(s: DataFrame, first: str, then: str, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join of one user's events; both watermarks let state older than the interval go."""
    a = s.where(F.col("format") == first).select(F.col("user_id"), F.col("event_id").alias("first_id"), F.col("ts").alias("first_ts")).withWatermark("first_ts", "1 hour")
    b = s.where(F.col("format") == then).select(F.col("user_id").alias("u"), F.col("event_id").alias("then_id"),
        F.col("ts").alias("then_ts")).withWatermark("then_ts", "1 hour")
    near = (F.col("user_id") == F.col("u")) & (F.col("then_ts") >= F.col("first_ts")) & (F.col("then_ts") <= F.col("first_ts") + F.expr(f"interval {within}"))
    return a.join(b, near).select("user_id", "first_id", "then_id")


def running_topk(s: DataFrame, k: int = 5) -> DataFrame:
    """The k best events of each (topic, format) so far; ``version`` grows with each batch that touches the group.

    State is k ids and k values, and a batch is reduced Arrow batch by Arrow batch, so no group is held whole.
    Null values take no part; ties go to the smaller id."""

    def step(key, batches, state):
        ids, values, version = state.get if state.exists else ([], [], 0)
        best = pd.DataFrame({"event_id": pd.Series(list(ids), dtype="int64"), "value": pd.Series(list(values), dtype="float64")})
        for b in batches:
            best = pd.concat([best, b[["event_id", "value"]].dropna()]).sort_values(["value", "event_id"], ascending=[False, True]).head(k)
        state.update((best.event_id.astype(int).tolist(), best.value.astype(float).tolist(), version + 1))
        yield pd.DataFrame({"topic": key[0], "format": key[1], "rank": range(1, len(best) + 1), "event_id": best.event_id.to_numpy(),
            "value": best.value.to_numpy(), "version": version + 1})

    out = "topic long, format string, rank int, event_id long, value double, version long"
    return s.groupBy("topic", "format").applyInPandasWithState(step, out, "ids array<long>, vals array<double>, version long", "update", GroupStateTimeout.NoTimeout)


def latest(versions: DataFrame) -> DataFrame:
    """The last emitted list of each group."""
    last = F.max(F.struct("version", "event_id", "value"))
    return versions.groupBy("topic", "format", "rank").agg(last.alias("x")).select("topic", "format", "rank", "x.event_id", "x.value")


def fires_once(s: DataFrame, target: float) -> DataFrame:
    """Convergence monitor: each group's earliest arrival at or above the target, told once and never again."""

    def step(key, batches, state):
        done = state.exists
        first = None
        for b in batches:
            hit = b.loc[b.value >= target, "ts"]
            if len(hit) and (first is None or hit.min() < first):
                first = hit.min()
        if not done and first is not None:
            state.update((True,))
            yield pd.DataFrame({"topic": [key[0]], "format": [key[1]], "ts": [first]})

    return s.groupBy("topic", "format").applyInPandasWithState(step, "topic long, format string, ts timestamp", "fired boolean", "append", GroupStateTimeout.NoTimeout)
