"""Streams: running means, encoding on arrival, index changes, standing queries."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.functions import quantize
from vecengine.functions.vectors import center
from vecengine.operators.exact import exact_knn
from vecengine.sources import io


def windowed_counts(events: DataFrame, size: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """(start, event_type, n, total) by event-time window; rows later than ``late`` drop out of a stream."""
    e = events.withColumn("at", F.col("ts").cast("timestamp"))
    e = e.withWatermark("at", late) if late else e
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,4)")).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", F.col("total").cast("double").alias("total"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    """(user_id, start, n): runs of a user's events less than ``gap`` apart."""
    e = events.withColumn("at", F.col("ts").cast("timestamp"))
    e = e.withWatermark("at", late) if late else e
    s = e.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), "n")


def latest_state(log: DataFrame, key: str, order: list[str], op: str, gone: str) -> DataFrame:
    """Last operation of every key; deleted keys are left out. Partial sums first, no window."""
    last = log.groupBy(key).agg(F.max_by(F.struct("*"), F.struct(*order)).alias("r")).select("r.*")
    return last.where(F.col(op) != gone)


def running_mean(stream: DataFrame, vec: str = "vec") -> DataFrame:
    """(j, n, s): count and sum of every component so far."""
    return stream.select(F.posexplode(vec).alias("j", "x")).groupBy("j").agg(F.count("*").alias("n"), F.sum("x").alias("s"))


def encode_stream(stream: DataFrame, mean: list[float], bits: int, version: int) -> DataFrame:
    """Codes on arrival; each carries the version of the mean it belongs to."""
    return stream.withColumn("q", quantize.pvq(center("vec", mean), bits)).withColumn("model_version", F.lit(version)).drop("vec")


def deduplicated(stream: DataFrame, keys: list[str], late: str) -> DataFrame:
    """The first row of each key; a repetition drops out if it comes within ``late`` of event time, and state older than that goes."""
    return stream.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late).dropDuplicatesWithinWatermark(keys).drop("at")


def followed(first: DataFrame, then: DataFrame, key: str, within: str, late: str) -> DataFrame:
    """Rows of ``then`` within a time after one of ``first`` with the same key; both are streams or tables of (id, key, ts)."""
    a = first.select(F.col("event_id").alias("first"), F.col(key).alias("k1"), F.col("ts").cast("timestamp").alias("t1")).withWatermark("t1", late)
    b = then.select(F.col("event_id").alias("then"), F.col(key).alias("k2"), F.col("ts").cast("timestamp").alias("t2")).withWatermark("t2", late)
    return a.join(b, (F.col("k1") == F.col("k2")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {within}"))).select("first", "then")


def user_vectors(events: DataFrame, kinds: list[str]) -> DataFrame:
    """Stateful: (user_id, n, total, counts) after each batch in which a user occurs, counts by event type; the state is these sums."""
    state = f"n long, total double, {', '.join(f'c{i} long' for i in range(len(kinds)))}"

    def step(key, frames, held):
        now = list(held.get) if held.exists else [0, 0.0] + [0] * len(kinds)
        for f in frames:
            now[0] += len(f)
            now[1] += float(f["value"].sum())
            for i, kind in enumerate(kinds):
                now[2 + i] += int((f["event_type"] == kind).sum())
        held.update(tuple(now))
        yield pd.DataFrame({"user_id": [key[0]], "n": [now[0]], "total": [now[1]], "counts": [now[2:]]})

    slim = events.select("user_id", "event_type", F.col("value").cast("double"))
    return slim.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double, counts array<long>", state, "update", "NoTimeout")


def merged(base: DataFrame, log: DataFrame, key: str, order: list[str], op: str, gone: str) -> DataFrame:
    """A base table after a log of upserts and deletions: the base without keys that the log names, and each key's last state unless deleted."""
    last = log.groupBy(key).agg(F.max_by(F.struct("*"), F.struct(*order)).alias("r")).select("r.*")
    kept = base.join(last.select(key), key, "left_anti")
    return kept.unionByName(last.where(F.col(op) != gone).select(*base.columns))


def standing_knn(stream: DataFrame, db: DataFrame, sink, k: int = 5):
    """A query whose batches search a static table; ``sink(found, epoch)`` gets the results."""

    def batch(asks: DataFrame, epoch: int) -> None:
        sink(exact_knn(db, asks, k), epoch)

    return stream.writeStream.foreachBatch(batch)


def drain(spark: SparkSession, frame: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run a stream over all that is there, and return its table.

    A complete result is kept by the driver; added or changed rows are as many
    as the stream's, so each batch is written to the shared folder.
    """
    path = io.scratch(spark, name)
    writer = frame.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/progress")
    if mode == "complete":
        writer.format("memory").queryName(name).start().awaitTermination()
        return spark.table(name)
    epochs = set()

    def keep(rows: DataFrame, epoch: int) -> None:
        # A batch that runs again replaces what it wrote.
        rows.write.mode("overwrite").parquet(f"{path}/rows/{epoch}")
        epochs.add(epoch)

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(frame.schema).parquet(*(f"{path}/rows/{e}" for e in sorted(epochs))) if epochs else spark.createDataFrame([], frame.schema)


def drift(fitted: list[float], new: list[float], threshold: float) -> tuple[float, bool]:
    """Distance of the means, and whether codes should be fitted anew."""
    far = sum((a - b) ** 2 for a, b in zip(fitted, new, strict=True)) ** 0.5
    return far, far > threshold
