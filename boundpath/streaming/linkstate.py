"""Link state as a stream: load per link over windows, duplicates, late rows, flow timeouts, and affected answers."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundpath.loop import shared_dir

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """link_id, ts, amount, event_id: an event claims ceil(value) of link user_id modulo 97."""
    raw = spark.readStream.schema(SCHEMA).parquet(f"{sf_dir}/events.parquet*")
    return claims(raw)


def claims(raw: DataFrame) -> DataFrame:
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("user_id") % 97).alias("link_id"), F.ceil("value").cast("bigint").alias("amount"))


def run_once(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its rows, collected by batch in the shared folder."""
    import uuid

    spark = df.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch, number):
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    query = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.schema(df.schema).parquet(f"{base}/out/*")
    if mode == "complete":
        last = max(int(r[0]) for r in spark.read.parquet(f"{base}/out").select("batch").distinct().collect())
        out = spark.read.schema(df.schema).parquet(f"{base}/out/batch={last}")
    return out


def tumbling_load(stream: DataFrame, length: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", "10 minutes").groupBy(F.window("ts", length).alias("w"), "link_id").agg(F.sum("amount").alias("load"))
    return w.select(F.col("w.start").alias("start"), "link_id", "load")


def sliding_load(stream: DataFrame, length: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", "10 minutes").groupBy(F.window("ts", length, step).alias("w"), "link_id").agg(F.sum("amount").alias("load"))
    return w.select(F.col("w.start").alias("start"), "link_id", "load")


def session_load(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Idle timeout: a session ends when a link is silent for the gap."""
    w = stream.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", gap).alias("w"), "link_id").agg(F.sum("amount").alias("load"), F.count("*").alias("n"))
    return w.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "link_id", "load", "n")


def distinct_events(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def hard_timeout(stream: DataFrame, seconds: int = 3600) -> DataFrame:
    """Allocations by creation: a link's allocation holds for a fixed time after the event that opened it, whatever
    comes meanwhile.  One row per allocation: link_id, opened, load, n.  State: the open allocation of each link."""

    def step(key, frames, state):
        opened, load, n = state.get if state.exists else (None, 0, 0)
        rows, parts = [], []
        for f in frames:
            # a link's events of one trigger may come in several frames, in no order: the time order holds over all of them
            parts.append(f.groupby("ts")["amount"].agg(["sum", "count"]))
        if parts:
            times = pd.concat(parts).groupby(level=0).sum().sort_index()
            stamps = times.index.to_numpy().astype("datetime64[us]").astype("int64")
            for us, amount, events in zip(stamps.tolist(), times["sum"].tolist(), times["count"].tolist(), strict=True):
                if opened is not None and us - opened >= seconds * 1_000_000:
                    rows.append((key[0], opened, load, n))
                    opened, load, n = None, 0, 0
                if opened is None:
                    opened = us
                load, n = load + int(amount), n + int(events)
        if state.hasTimedOut:
            if opened is not None:
                rows.append((key[0], opened, load, n))
            state.remove()
        elif opened is not None:
            state.update((opened, load, n))
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, opened // 1000 + seconds * 1000))
        yield pd.DataFrame(rows, columns=["link_id", "opened", "load", "n"])

    grouped = stream.withWatermark("ts", "10 minutes").groupBy("link_id")
    return grouped.applyInPandasWithState(step, "link_id bigint, opened bigint, load bigint, n bigint", "opened bigint, load bigint, n bigint", "append", "EventTimeTimeout")


def affected_requests(path_links: DataFrame, changed: DataFrame) -> DataFrame:
    """Requests whose path uses a link that changed: only these have to be solved again."""
    return path_links.join(changed.select("link_id").distinct(), "link_id", "left_semi").select("req_id").distinct()


def expire(ledger: DataFrame, now, kind: str = "hard", seconds: int = 3600) -> DataFrame:
    """Ledger rows still held at ``now`` (a timestamp column or literal): counted from creation, or from the last match."""
    start = F.col("ts_from") if kind == "hard" else F.col("ts_last")
    return ledger.filter(start + F.expr(f"INTERVAL {int(seconds)} SECONDS") > now)
