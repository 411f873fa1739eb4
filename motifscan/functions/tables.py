"""Python table and aggregate functions over edges, for use from SQL. Local graphs only: a group must fit a task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from motifscan.operators import kernels
from motifscan.plans.patterns import CATALOGUE


class MotifInstances:
    """motif_instances(TABLE(SELECT rk, src, dst ...) PARTITION BY (rk), pattern): (rk, nodes) of each instance in each key's local graph, least mapping first. Rows come and go in Arrow batches."""

    def __init__(self) -> None:
        self.held: list[pa.RecordBatch] = []
        self.pattern = ""

    def eval(self, batch: pa.RecordBatch, pattern: pa.Array) -> Iterator[pa.Table]:
        if batch.num_rows:
            self.held.append(batch)
            self.pattern = pattern[0].as_py()
        return iter(())

    def terminate(self) -> Iterator[pa.Table]:
        if self.held:
            t = pa.Table.from_batches(self.held)
            g = kernels.LocalIndex(*(t.column(c).to_numpy() for c in ("src", "dst")))
            for x in kernels.find_blocks(g, CATALOGUE[self.pattern]):
                if len(x):
                    nodes = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(g.ids[x].reshape(-1)))
                    yield pa.table({"rk": pa.array(np.full(len(x), t.column("rk")[0].as_py())), "nodes": nodes})


def triangle_count_of(src: pd.Series, dst: pd.Series) -> int:
    if not len(src):
        return 0
    return len(kernels.triangles(kernels.LocalIndex(src.to_numpy(), dst.to_numpy())))


def register(spark: SparkSession) -> None:
    """motif_instances and triangle_count for SQL."""
    spark.udtf.register("motif_instances", F.arrow_udtf(MotifInstances, returnType="rk long, nodes array<long>"))

    def count(src: pd.Series, dst: pd.Series) -> int:
        return triangle_count_of(src, dst)

    spark.udf.register("triangle_count", F.pandas_udf(count, "long"))
