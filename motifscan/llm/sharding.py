"""Sharding by sampled splitters.

Records are ordered by a key that starts with the text's hash, so equal texts lie side by side, and goes on with
the document's, so a text of many copies can be cut. A size-weighted sample of keys gives quantile splitters of
many fine ranges; each range's exact bytes and rows are measured; ranges that came out overfull are subdivided
by a second hash; running totals over the ranges then put every record at its exact place in bytes and rows.
What the driver holds is the sample and the range totals, whose sizes are parameters, whatever the input's size.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from motifscan.llm.common import Stage, uniform


def shard_by_bytes(docs: DataFrame, shards: int = 40, fine: int = 32, sample: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard: each document's shard and place in it, shards near equal in bytes.

    size: UTF-8 bytes of the text (null: none) plus 16. A shard is a stretch of the key order, and its bytes differ
    from an even share by one record at most; slots count from 0 without gaps. `fine` ranges are cut for each shard
    from `sample` keys a range. Reruns agree; rows that are equal in doc_id and text are interchangeable. An empty
    table gives an empty result. Other columns aren't read.
    """
    stage, ranges = Stage(docs.sparkSession, "sharding"), shards * fine
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    tie = F.xxhash64(F.col("doc_id"), F.lit(7))
    rows = stage.put(
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.shiftleft(F.shiftright(F.xxhash64(text), 20), 20).alias("high"))
        .withColumn("key", F.col("high") + F.shiftrightunsigned(tie, 44))
        .withColumn("lot", (F.monotonically_increasing_id() % 4096).cast("int"))
        .drop("high")
    )
    total = rows.agg(F.sum("size")).first()[0] or 0
    rate = ranges * sample / max(total, 1)
    # rows that repeat an id and a text are drawn together, as one row of their number
    drawn = rows.where(uniform("key", "doc_id", F.lit("splitters")) < F.col("size") * rate).groupBy("key", "doc_id", "size").agg(F.count("*").alias("n")).toPandas()
    drawn = drawn.sort_values(["key", "doc_id", "size"])
    weight = (np.maximum(drawn["size"].to_numpy(float), 1 / rate) * drawn["n"].to_numpy(float)).cumsum()
    at = np.searchsorted(weight, np.arange(1, ranges) / ranges * (weight[-1] if len(weight) else 0))
    splitters = np.unique(drawn["key"].to_numpy(np.int64)[np.minimum(at, max(len(drawn) - 1, 0))]) if len(drawn) else np.zeros(0, np.int64)

    @F.pandas_udf("int")
    def range_of(keys: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for k in keys:
            yield pd.Series(np.searchsorted(splitters, k.to_numpy(), "right").astype(np.int32))

    dealt = stage.put(rows.withColumn("range", range_of("key")))
    even = max(1, total / ranges)
    measured = dealt.groupBy("range").agg(F.sum("size").alias("bytes")).toPandas()
    over = {int(r): min(math.ceil(b / even), ranges) for r, b in zip(measured["range"], measured["bytes"], strict=True) if b > 4 * even}
    parts = F.lit(1)
    if over:
        parts = F.coalesce(F.create_map(*(F.lit(x) for kv in over.items() for x in kv))[F.col("range")], F.lit(1))
    place = uniform("doc_id", "key", F.lit("parts"))
    if over:
        # rows that repeat an id and a text have one key; where they alone are more than a range, at most `ranges` keys, they are dealt by lot
        heavy = [r["key"] for r in dealt.where(F.col("range").isin(list(over))).groupBy("key", "doc_id").agg(F.sum("size").alias("bytes")).where(F.col("bytes") > even).select("key").distinct().collect()]
        place = F.when(F.col("key").isin(heavy), (place + F.col("lot") / 4096) % 1).otherwise(place) if heavy else place
    dealt = dealt.withColumn("part", F.floor(place * parts).cast("int"))
    totals = dealt.groupBy("range", "part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).toPandas().sort_values(["range", "part"])
    totals["bytes_before"] = totals["bytes"].cumsum() - totals["bytes"]
    totals["rows_before"] = totals["n"].cumsum() - totals["n"]
    before = docs.sparkSession.createDataFrame(totals[["range", "part", "bytes_before", "rows_before"]], "range int, part int, bytes_before long, rows_before long")
    inside = Window.partitionBy("range", "part").orderBy("key", "doc_id", "text_crc32", "size")
    running = F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    placed = stage.put(
        dealt.join(F.broadcast(before), ["range", "part"])
        .withColumn("middle", F.col("bytes_before") + running - F.col("size") / 2)
        .withColumn("at", F.col("rows_before") + F.row_number().over(inside) - 1)
        .select("doc_id", "size", "text_crc32", F.least(F.floor(F.col("middle") * shards / max(total, 1)), F.lit(shards - 1)).cast("int").alias("shard"), "at")
    )
    stage.drop(rows)
    first = placed.groupBy("shard").agg(F.min("at").alias("first"))
    return placed.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("at") - F.col("first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
