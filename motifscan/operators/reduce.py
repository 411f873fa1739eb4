"""The reduce side of a mapping scheme: rows (rk, src, dst) meet by key in one exchange, and a serial algorithm runs on the keys' local graphs."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifscan.functions.buckets import bucket_of
from motifscan.llm.common import give_back, in_arrow
from motifscan.operators import kernels
from motifscan.plans.cqs import MotifQuery
from motifscan.plans.patterns import Pattern

#: Edges of the keys that are worked on at once; a larger key goes alone.
EDGES = 1 << 18


@dataclass(frozen=True)
class Lists:
    """Keys are lists of buckets: an instance belongs to the list of its own nodes' buckets."""

    b: int
    kind: str = "xx"
    seed: int = 0

    def counts(self, keys: np.ndarray, p: int) -> np.ndarray:
        """How often each bucket is in each key's list."""
        out, rest, row = np.zeros((len(keys), self.b), np.int8), keys.copy(), np.arange(len(keys))
        for i in range(p - 1, -1, -1):
            table = np.array([math.comb(c + i, i + 1) for c in range(self.b)])
            c = np.searchsorted(table, rest, "right") - 1
            rest -= table[c]
            np.add.at(out, (row, c), 1)
        return out

    def pruner(self, g: kernels.LocalIndex, keys: np.ndarray, bucket: np.ndarray, p: int) -> kernels.Prune:
        room = self.counts(keys, p)

        def prune(old: np.ndarray) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
            left = room[g.key[old[:, 0]]]
            for c in old.T:
                left[np.arange(len(old)), bucket[c]] -= 1
            free = (left > 0).ravel()
            return lambda row, to: free[row * self.b + bucket[to]]

        return prune

    def owned(self, g: kernels.LocalIndex, keys: np.ndarray, bucket: np.ndarray, x: np.ndarray) -> np.ndarray:
        rank = np.zeros(len(x), np.int64)
        for i, c in enumerate(np.sort(bucket[x], axis=1).T):
            rank += np.array([math.comb(v + i, i + 1) for v in range(self.b)])[c]
        return rank == keys[g.key[x[:, 0]]]


@dataclass(frozen=True)
class Subsets:
    """Keys are subsets of groups, as bits: an instance belongs to the least one that holds its nodes' groups."""

    b: int
    kind: str = "xx"
    seed: int = 0

    def pruner(self, g: kernels.LocalIndex, keys: np.ndarray, bucket: np.ndarray, p: int) -> None:
        return None

    def owned(self, g: kernels.LocalIndex, keys: np.ndarray, bucket: np.ndarray, x: np.ndarray) -> np.ndarray:
        least = np.bitwise_or.reduce(np.left_shift(np.int64(1), bucket[x].astype(np.int64)), axis=1)
        for _ in range(x.shape[1] - 1):
            lowest_free = ~least & (least + 1)
            least = np.where(np.bitwise_count(least) < x.shape[1], least | lowest_free, least)
        return least == keys[g.key[x[:, 0]]]


def narrow(x: np.ndarray) -> np.ndarray:
    """x in 32 bits if its values fit."""
    fits = x.dtype == np.int64 and len(x) and x.min() >= -(1 << 31) and x.max() < 1 << 31
    return x.astype(np.int32) if fits else x


def key_runs(batches: Iterator[pa.RecordBatch], together: bool) -> Iterator[tuple[np.ndarray, np.ndarray | None, list[np.ndarray]]]:
    """(keys, the number of each row's key, or None if there is one, the other columns) of whole keys: EDGES or so rows at a time, or key by key; a key of more rows is alone. The input is sorted by key, its first column."""
    held: list[list[np.ndarray]] = []
    rows = 0

    def taken(i: int, j: int) -> list[np.ndarray]:
        """The pieces' columns, which nothing else holds any more."""
        columns = [np.concatenate(c) for c in zip(*(h[1:] for h in held[i:j]), strict=True)]
        large = sum(len(h[1]) for h in held[i:j]) > EDGES
        held[i:j] = [None] * (j - i)
        if large:
            give_back()
        return columns

    def whole() -> Iterator[tuple[np.ndarray, np.ndarray | None, list[np.ndarray]]]:
        key = np.array([h[0] for h in held])
        count = np.array([len(h[1]) for h in held])
        start = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        sizes = np.add.reduceat(count, start)
        cut = [0, start[-1], len(held)] if len(start) > 1 and sizes[-1] > EDGES else [0, len(held)]
        for i, j in zip(cut, cut[1:], strict=False):
            mine = (start >= i) & (start < j)
            yield key[start[mine]], np.repeat(np.arange(mine.sum()), sizes[mine]) if mine.sum() > 1 else None, taken(i, j)

    for batch in batches:
        if not batch.num_rows:
            continue
        rk = batch.column(0).to_numpy()
        columns = [narrow(c.to_numpy(zero_copy_only=False)) for c in batch.columns[1:]]
        edge = np.flatnonzero(rk[1:] != rk[:-1]) + 1
        for i, j in zip([0, *edge.tolist()], [*edge.tolist(), len(rk)], strict=True):
            if held and rk[i] != held[-1][0] and (not together or rows >= EDGES):
                yield from whole()
                held, rows = [], 0
            held.append([rk[i], *(c[i:j] for c in columns)])
            rows += j - i
    if held:
        yield from whole()


def reduce_by_key(shipped: DataFrame, s: Pattern, algorithm: str = "grow", owner: Lists | Subsets | None = None, count_only: bool = False, with_key: bool = False, queries: Sequence[MotifQuery] | None = None) -> DataFrame:
    """(x0..x{p-1}): the canonical mappings in each key's local graph that the key owns (all of them without owner; with_key: and rk); count_only: their number, n. queries: found by these, all at each key, in place of the algorithm.

    Rows are shipped once, by key, and results leave block by block. What a task holds is the local graphs of EDGES rows,
    or one key's; b is chosen so that it fits.
    """
    names = ["rk"] * with_key + [f"x{i}" for i in range(s.p)]
    together = s.connected()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = 0
        for keys, number, columns in key_runs(batches, together):
            src, dst, *ends = columns
            g = kernels.LocalIndex(src, dst, s.directed, number, by_id=bool(queries) or algorithm != "odd", marks=tuple(ends) or None)
            bucket = g.marks
            del src, dst, ends, columns
            prune = owner.pruner(g, keys, bucket, s.p) if owner else None
            for x in kernels.query_blocks(g, s, queries, prune) if queries else kernels.find_blocks(g, s, algorithm, prune):
                if owner:
                    x = x[owner.owned(g, keys, bucket, x)] if len(x) else x
                total += len(x)
                if not count_only:
                    for i in range(0, len(x), 1 << 16):
                        part = x[i : i + (1 << 16)]
                        out = [keys[g.key[part[:, 0]]]] * with_key + [g.ids[part[:, j]] for j in range(s.p)]
                        yield pa.RecordBatch.from_arrays([pa.array(c) for c in out], names)
        if count_only:
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    ends = [bucket_of(c, owner.b, owner.kind, owner.seed).cast("short") for c in ("src", "dst")] if owner else []
    rows = by_key(shipped, *ends)
    if count_only:
        return in_arrow(rows, run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    return in_arrow(rows, run, ", ".join(f"{c} long" for c in names))


def by_key(shipped: DataFrame, *more: Column) -> DataFrame:
    """The rows by key, each key's together; further columns are made where the rows arrive."""
    return shipped.select("rk", "src", "dst").repartition("rk").sortWithinPartitions("rk").select("rk", "src", "dst", *(c.alias(f"more{i}") for i, c in enumerate(more)))


def probe_counts(shipped: DataFrame, s: Pattern, algorithm: str = "grow") -> DataFrame:
    """(rk, edges, found, probes) of each key: what the serial algorithm does there."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, _, (src, dst) in key_runs(batches, False):
            g = kernels.LocalIndex(src, dst, s.directed)
            n = sum(len(x) for x in kernels.find_blocks(g, s, algorithm))
            yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (int(keys[0]), len(src), n, g.probes)], ["rk", "edges", "found", "probes"])

    return by_key(shipped).mapInArrow(run, "rk long, edges long, found long, probes long")
