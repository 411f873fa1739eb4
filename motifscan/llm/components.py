"""Connected components of a graph of links, by alternating stars. DataFrame operations, and one task for what little is left."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from motifscan.llm.common import Stage, frequent, in_arrow, join_dealt


#: Edges that one task settles by a union-find: a bounded number, a few megabytes.
FEW = 1 << 17


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(u, v): of all edges (u, v) together, each node v and its component's smallest one."""
    held = [np.stack([c.to_numpy() for c in batch.columns], 1) for batch in batches if batch.num_rows]
    if not held:
        return
    nodes, ends = np.unique(np.concatenate(held), return_inverse=True)
    u, v = ends.reshape(-1, 2).T
    up = np.arange(len(nodes))
    while True:
        low = np.minimum(up[u], up[v])
        before = up.copy()
        for x in (up[u], up[v]):
            np.minimum.at(up, x, low)
        while (up[up] != up).any():
            up = up[up]
        if (up == before).all():
            break
    yield pa.RecordBatch.from_arrays([pa.array(nodes[up]), pa.array(nodes)], ["u", "v"])


def _written(edges: DataFrame, stage: Stage) -> tuple[DataFrame, dict]:
    """The edges as a table, with their number and two sums that tell whether they changed."""
    seen = Observation()
    h = F.xxhash64("u", "v")
    out = stage.put(edges.observe(seen, F.count("*").alias("n"), F.bit_xor(h).alias("x"), F.sum(h % 1_000_003).alias("y")))
    return out, seen.get


def connected_components(links: DataFrame, stage: Stage) -> DataFrame:
    """node, component (its smallest node) of every node of links (a, b).

    Each round hangs every node's larger neighbours on the smallest one around it, then its smaller ones too, until
    all hang on their component's smallest node. The rounds are logarithmic in the longest path; a node with very
    many neighbours is only ever met by an aggregate with partial sums or a join that deals its rows to several tasks.
    """
    edges, mark = _written(links.where("a != b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct(), stage)
    while mark["n"]:
        if mark["n"] <= FEW:
            edges = in_arrow(edges.select("u", "v").coalesce(1), _settle, "u long, v long")
            return stage.put(edges.select(F.col("v").alias("node"), F.col("u").alias("component")))
        # in neither join below a node has more rows than edges
        degree = edges.select(F.explode(F.array("u", "v")).alias("node")).groupBy("node").agg(F.count("*").alias("c"))
        hot = frequent(degree, ["node"], "c", mark["n"])
        both = edges.select(F.col("u").alias("at"), F.col("v").alias("to")).unionByName(edges.select(F.col("v").alias("at"), F.col("u").alias("to")))
        least = both.groupBy("at").agg(F.min("to").alias("m")).select("at", F.least("at", "m").alias("m"))
        large = join_dealt(both.where("to > at"), least, ["at"], hot).select(F.col("to").alias("v"), F.col("m").alias("u")).where("u != v").distinct()
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        small = join_dealt(large, low, ["v"], hot).select(F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("m").alias("u")), F.struct("v", F.col("m").alias("u")))).alias("e")).select("e.u", "e.v").where("u != v").distinct()
        old, last = edges, mark
        edges, mark = _written(small, stage)
        stage.drop(old)
        if mark == last:
            break
    root = edges.select("u").distinct()
    return edges.select(F.col("v").alias("node"), F.col("u").alias("component")).unionByName(root.select(F.col("u").alias("node"), F.col("u").alias("component")))
