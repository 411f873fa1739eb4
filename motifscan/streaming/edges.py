"""Edges from a stream of events, and triangles that new edges close."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from motifscan.operators import kernels


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table replayed as files."""
    stream = spark.readStream.schema(spark.read.parquet(f"{sf_dir}/events.parquet").schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly_members(events: DataFrame, kind: str = "purchase", delay: str = "2 hours", span: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(hour, members): the users with such an event in each window; late events beyond the delay are dropped."""
    window = F.window("ts", span, slide) if slide else F.window("ts", span)
    return events.where(F.col("event_type") == kind).withWatermark("ts", delay).groupBy(window).agg(F.collect_set("user_id").alias("members")).select(F.col("window.start").alias("hour"), "members")


def pairs_of(members: DataFrame) -> DataFrame:
    """(src, dst) of all pairs of each row's members."""
    a = members.select("members", F.explode("members").alias("src"))
    return a.select("src", F.explode("members").alias("dst")).where("src < dst").distinct()


def user_sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "2 hours") -> DataFrame:
    """(user_id, start, end, n): stretches of a user's events without a longer gap."""
    s = events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def interval_pairs(events: DataFrame, minutes: int = 10, delay: str = "1 hour") -> DataFrame:
    """Stream-stream join: (src, dst, ts) of different users whose purchases are at most so many minutes apart."""
    bought = events.where("event_type = 'purchase'").select("user_id", "ts")
    # a stream-stream join needs an equality: times meet by slots of the interval's length, the other side in three of them
    slot = lambda c: F.floor(F.unix_timestamp(c) / (60 * minutes))
    a = bought.toDF("src", "ts").withWatermark("ts", delay).withColumn("slot", slot("ts"))
    b = bought.toDF("dst", "ts2").withWatermark("ts2", delay).withColumn("slot2", F.explode(F.array(slot("ts2") - 1, slot("ts2"), slot("ts2") + 1)))
    near = F.expr(f"slot = slot2 and ts2 >= ts - interval {minutes} minutes and ts2 <= ts + interval {minutes} minutes and src < dst")
    return a.join(b, near).select("src", "dst", "ts")


def without_repeats(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Events whose id came before, within the delay, are dropped."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def append_edges(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Writes a stream of (hour, members) as edges, batch by batch. A batch that runs again after a failure overwrites its own folder, so that edges are there once."""

    def write(batch: DataFrame, epoch: int) -> None:
        pairs_of(batch).write.mode("overwrite").parquet(f"{path}/batch={epoch}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def run_to_folder(stream: DataFrame, path: str, checkpoint: str, mode: str = "update") -> int:
    """Runs a stream over all that is there now; each batch goes to a folder of its own, which a batch that runs again overwrites. Returns how many rows came too late and were dropped."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={epoch}")

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return late_rows(q)


def late_rows(query: StreamingQuery) -> int:
    """Rows behind the watermark that a query's stateful steps dropped so far."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in json.loads(p.json)["stateOperators"])


def run_to_table(stream: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all that is there now; the result as a table in memory (tests, small results)."""
    writer = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q = writer.start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def new_triangles(keyed_edges: DataFrame, b: int, ttl: str | None = None) -> DataFrame:
    """(rk, x0, x1, x2): triangles as their last edge arrives. Input: a stream of (rk, src, dst[, ts]) from the bucket-list scheme; a key holds its local edges as state, in arrays.

    An edge that comes again changes nothing but its time. ttl, in seconds, with ts and a watermark on it: edges that are
    older than the newest of their key by more are forgotten, and a key without edges for so long gives its state back.
    The caller keeps rows that their key owns.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    seconds = float(ttl) if ttl else None

    def step(key: tuple, pdfs: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        src, dst, at = (np.array(x, t) for x, t in zip(state.get if state.exists else ([], [], []), (np.int64, np.int64, np.float64), strict=True))
        new = pd.concat(list(pdfs))
        stamp = new["ts"].astype("int64").to_numpy() / 1e9 if seconds else np.zeros(len(new))
        a, c = (np.concatenate(x) for x in ((src, new["src"].to_numpy()), (dst, new["dst"].to_numpy())))
        when, fresh = np.concatenate([at, stamp]), np.arange(len(a)) >= len(src)
        if seconds:
            keep = when >= when.max() - seconds
            a, c, when, fresh = a[keep], c[keep], when[keep], fresh[keep]
        # each edge once: known ones first, with their latest time
        order = np.lexsort((fresh, c, a))
        a, c, when, fresh = a[order], c[order], when[order], fresh[order]
        head = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (c[1:] != c[:-1])))
        a, c, when, fresh = a[head], c[head], np.maximum.reduceat(when, head), fresh[head]
        g = kernels.LocalIndex(a, c)
        number = pd.Series(np.arange(g.n), index=g.ids)
        u, v = number[a[fresh]].to_numpy(), number[c[fresh]].to_numpy()
        row, to = g.expand(u)
        found = np.stack([u[row], v[row], to], 1)[g.has(v[row], to)]
        found = np.unique(np.sort(g.ids[found], axis=1), axis=0) if len(found) else np.zeros((0, 3), np.int64)
        state.update((a.tolist(), c.tolist(), when.tolist()))
        if seconds and state.getCurrentWatermarkMs() >= 0:
            state.setTimeoutTimestamp(max(int((when.max() + seconds) * 1000), state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"rk": np.full(len(found), key[0], np.int64), **{f"x{i}": found[:, i] for i in range(3)}})

    timeout = GroupStateTimeout.EventTimeTimeout if seconds else GroupStateTimeout.NoTimeout
    return keyed_edges.groupBy("rk").applyInPandasWithState(step, "rk long, x0 long, x1 long, x2 long", "src array<long>, dst array<long>, at array<double>", "append", timeout)
