"""Standing searches over streams of objects, by Structured Streaming."""

from __future__ import annotations

from collections.abc import Iterator, Mapping
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from polymetric.index import MultiMetricIndex
from polymetric.spaces import MultiMetricSchema, mm_distance
from polymetric.store import new_folder
from polymetric.updates import place


def range_alerts(stream: DataFrame, queries: DataFrame, schema: MultiMetricSchema, w: Mapping[str, float], r: float, sigma: Mapping[str, float]) -> DataFrame:
    """Each arriving object within r of a registered query: stateless; the registered queries are a stated, broadcast set."""
    qs = F.broadcast(queries.select(F.col(schema.oid).alias("qid"), *(F.col(n).alias(f"q_{n}") for n in schema.names)))
    return stream.join(qs).withColumn("dist", F.expr(mm_distance(schema, None, w, sigma))).where(F.col("dist") <= r)


def running_topk(scored: DataFrame, k: int, oid: str = "oid", windowed: bool = False, buckets: int = 16) -> DataFrame:
    """(bucket, w_start, nearest): the k nearest so far, as state of k entries a bucket; ``best_of`` merges the buckets.

    scored has dist, the id and, if windowed, w (the window) and a watermark: then a window's rows leave once, when the
    watermark passes its end, and its state goes; late rows are dropped. Else each batch emits the buckets it changed.
    Buckets split a hot window, and the state never holds a window's rows.
    """
    one = scored.select(F.expr(f"pmod(xxhash64({oid}), {buckets})").alias("bucket"), F.col("w.start").alias("w_start") if windowed else F.lit(None).cast("timestamp").alias("w_start"), F.col("w.end").alias("w_end") if windowed else F.lit(None).cast("timestamp").alias("w_end"), F.col("dist"), F.col(oid).cast("long").alias("id"), *(["at"] if windowed else []))
    out = "bucket long, w_start timestamp, nearest array<struct<dist:double,oid:long>>"

    def row(key: tuple, dist: list, ids: list) -> pd.DataFrame:
        return pd.DataFrame({"bucket": [key[0]], "w_start": [key[1]], "nearest": [[{"dist": d, "oid": i} for d, i in zip(dist, ids, strict=True)]]})

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: Any) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            dist, ids = state.get
            state.remove()
            yield row(key, dist, ids)
            return
        best = list(zip(*state.get, strict=True)) if state.exists else []
        for f in frames:
            few = f.nsmallest(k, ["dist", "id"])
            best = sorted(set(best) | {(float(d), int(i)) for d, i in zip(few["dist"], few["id"], strict=True)})[:k]
        dist, ids = [d for d, _ in best], [i for _, i in best]
        state.update((dist, ids))
        if windowed:
            end = int(pd.Timestamp(key[2]).timestamp() * 1000)
            if end > state.getCurrentWatermarkMs():
                state.setTimeoutTimestamp(end)
        else:
            yield row(key, dist, ids)

    keyed = one.groupBy("bucket", "w_start", "w_end")
    return keyed.applyInPandasWithState(step, out, "dist array<double>, ids array<long>", "append" if windowed else "update", "EventTimeTimeout" if windowed else "NoTimeout")


def window_topk(stream: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], k: int, sigma: Mapping[str, float], ts: str = "ts", length: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """The k nearest of tumbling or sliding windows, by ``running_topk``."""
    scored = stream.withColumn("dist", F.expr(mm_distance(schema, q, w, sigma))).withColumn("at", F.col(ts)).withWatermark("at", delay)
    cut = scored.withColumn("w", F.window("at", length, slide) if slide else F.window("at", length))
    return running_topk(cut, k, schema.oid, True)


def best_of(found: DataFrame, k: int) -> DataFrame:
    """(w_start, rank, oid, dist) of what ``running_topk`` wrote: at most k rows a bucket meet."""
    flat = found.select("w_start", F.explode("nearest").alias("n")).select("w_start", "n.dist", "n.oid").distinct()
    return flat.withColumn("rank", F.row_number().over(Window.partitionBy("w_start").orderBy("dist", "oid"))).where(F.col("rank") <= k)


def session_distance(stream: DataFrame, schema: MultiMetricSchema, q: Mapping[str, Any], w: Mapping[str, float], sigma: Mapping[str, float], key: str = "user_id", ts: str = "ts", gap: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """(key, start, n, mean_dist, total) of sessions; total is the sum in billionths, the same in any order of rows."""
    scored = stream.withColumn("dist", F.expr(mm_distance(schema, q, w, sigma))).withWatermark(ts, delay)
    return scored.groupBy(key, F.session_window(ts, gap).alias("s")).agg(F.count("*").alias("n"), F.avg("dist").alias("mean_dist"), F.sum(F.round(F.col("dist") * 1e9).cast("long")).alias("total")).select(key, F.col("s.start").alias("start"), "n", "mean_dist", "total")


def deduplicated(stream: DataFrame, oid: str = "oid", ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark(ts, delay).dropDuplicatesWithinWatermark([oid])


def drain(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over what is there now, into a memory table; for tests and small results."""
    writer = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    writer.start().awaitTermination()
    return df.sparkSession.table(name)


def near_pairs(left: DataFrame, right: DataFrame, key: str, ts: str, within: str, delay: str, condition: str) -> DataFrame:
    """Rows of two streams with the same key, the right one later by ``within`` at most, that meet a condition over l_ and r_
    columns. Both sides have a watermark, so the state is bounded by the interval."""
    a = left.select(*(F.col(c).alias(f"l_{c}") for c in left.columns)).withWatermark(f"l_{ts}", delay)
    b = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns)).withWatermark(f"r_{ts}", delay)
    return a.join(b, F.expr(f"l_{key} = r_{key} AND r_{ts} > l_{ts} AND r_{ts} <= l_{ts} + INTERVAL {within} AND ({condition})"))


def landed(df: DataFrame) -> DataFrame:
    """Runs a stream in append mode over what is there now, into Parquet in the shared folder; restartable from its checkpoint."""
    spark, folder = df.sparkSession, new_folder(df.sparkSession)
    df.writeStream.format("parquet").option("checkpointLocation", f"{folder}/state").option("path", f"{folder}/rows").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows")


def upserted(df: DataFrame, keys: list[str]) -> DataFrame:
    """Runs a stream in update mode; each batch lands as Parquet with its number, and the last row of each key counts.
    A batch that runs again overwrites its own folder."""
    spark, folder = df.sparkSession, new_folder(df.sparkSession)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={number}")

    df.writeStream.foreachBatch(write).option("checkpointLocation", f"{folder}/state").outputMode("update").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.schema(df.schema.add("batch", "long")).parquet(f"{folder}/rows")
    rest = [c for c in df.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last")).select(*keys, "last.*")


def ingest(stream: DataFrame, index: MultiMetricIndex, folder: str) -> DataFrame:
    """Arriving objects, mapped and sent to their leaf, land as a delta beside the index; ``updates.with_delta`` reads them."""
    def write(batch: DataFrame, number: int) -> None:
        place(index, batch).write.mode("overwrite").parquet(f"{folder}/delta/batch={number}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return index.objects.sparkSession.read.parquet(f"{folder}/delta").drop("batch")
