"""Counts of patterns without listing instances, and their roll-ups."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.functions.buckets import FINE
from motifscan.llm.common import in_arrow
from motifscan.operators.triangles import degree_ordered, triangles_by_degree
from motifscan.sources.graphs import DataGraph
from motifscan.sources.tables import kept

BIG = "decimal(38,0)"


def path_and_star_counts(g: DataGraph) -> DataFrame:
    """(pattern, n): paths of three nodes and stars of four, from degrees alone."""
    d = F.col("degree").cast(BIG)
    two, three = d * (d - 1) / 2, d * (d - 1) * (d - 2) / 6
    sums = g.degrees().agg(F.sum(two.cast("decimal(38,0)")).alias("path3"), F.sum(three.cast("decimal(38,0)")).alias("star4"))
    return sums.select(F.stack(F.lit(2), F.lit("path3"), F.col("path3"), F.lit("star4"), F.col("star4")).alias("pattern", "n")).select("pattern", F.coalesce("n", F.lit(0)).cast(BIG).alias("n"))


def motif_census(g: DataGraph) -> DataFrame:
    """(pattern, n) for all connected patterns of three and four nodes as subgraphs (not induced); n: decimal(38,0), as counts of paths and stars outgrow 64 bits.

    Triangles and complete fours are enumerated along degree order; the others follow from degrees, triangles of an
    edge, and common neighbours of a pair.
    """
    t = triangles_by_degree(g)
    edges_of = t.select(F.explode(F.array(F.struct(F.col("x0").alias("a"), F.col("x1").alias("b")), F.struct(F.col("x0").alias("a"), F.col("x2").alias("b")), F.struct(F.col("x1").alias("a"), F.col("x2").alias("b")))).alias("e")).select("e.a", "e.b")
    per_edge = edges_of.groupBy("a", "b").agg(F.count("*").alias("t"))
    d = g.degrees()
    as_row = lambda name, df: df.select(F.lit(name).alias("pattern"), F.coalesce(F.col("n"), F.lit(0)).cast(BIG).alias("n"))
    tri = t.agg(F.count("*").alias("n"))
    half = lambda c: F.col(c).cast("decimal(19,0)") * (F.col(c) - 1).cast("decimal(18,0)")
    diamond = per_edge.agg((F.sum(half("t")) / 2).alias("n"))
    pendant = t.select(F.explode(F.array("x0", "x1", "x2")).alias("node")).groupBy("node").agg(F.count("*").alias("t")).join(d, "node").agg(F.sum(F.col("t").cast("decimal(19,0)") * (F.col("degree") - 2).cast("decimal(18,0)")).alias("n"))
    o = degree_ordered(g)
    walks = o.agg(F.sum((F.col("lo_degree") - 1).cast("decimal(19,0)") * (F.col("hi_degree") - 1).cast("decimal(18,0)")).alias("w"))
    path4 = walks.join(tri).select((F.col("w") - 3 * F.col("n")).alias("n"))
    # a square's node of the highest (degree, id) sees the opposite one over two lower ones
    rank = F.struct
    both = o.select(F.explode(F.array(F.struct(F.col("lo").alias("v"), F.col("lo_degree").alias("dv"), F.col("hi").alias("u"), F.col("hi_degree").alias("du")), F.struct(F.col("hi").alias("v"), F.col("hi_degree").alias("dv"), F.col("lo").alias("u"), F.col("lo_degree").alias("du")))).alias("e")).select("e.*")
    down = o.select(F.col("lo").alias("v"), F.col("hi").alias("top"), F.col("hi_degree").alias("dtop"))
    seen = down.join(both, "v").where(rank("du", "u") < rank("dtop", "top"))
    square = seen.groupBy("top", "u").agg(F.count("*").alias("c")).agg((F.sum(half("c")) / 2).alias("n"))
    e = g.edges
    k4 = t.join(e.toDF("x0", "x3"), "x0").where("x2 < x3").join(e.toDF("x1", "x3"), ["x1", "x3"], "left_semi").join(e.toDF("x2", "x3"), ["x2", "x3"], "left_semi").agg(F.count("*").alias("n"))
    out = path_and_star_counts(g)
    for name, df in (("triangle", tri), ("diamond", diamond), ("pendant_triangle", pendant), ("path4", path4), ("square", square), ("k4", k4)):
        out = out.unionByName(as_row(name, df))
    return out


def node_triangles(g: DataGraph) -> DataFrame:
    """(node, triangles) of nodes that lie in some."""
    return triangles_by_degree(g).select(F.explode(F.array("x0", "x1", "x2")).alias("node")).groupBy("node").agg(F.count("*").alias("triangles"))


def clustering(g: DataGraph) -> DataFrame:
    """(node, degree, triangles, clustering): the part of a node's pairs of neighbours that are linked."""
    d = g.degrees().join(node_triangles(g), "node", "left").select("node", "degree", F.coalesce("triangles", F.lit(0)).alias("triangles"))
    pairs = F.col("degree") * (F.col("degree") - 1) / 2
    return d.withColumn("clustering", F.when(pairs > 0, F.col("triangles") / pairs).otherwise(0.0))


def census_of(graphs: dict[str, DataGraph]) -> DataFrame:
    """(graph, a column for each pattern): the census of several graphs, pivoted."""
    out = None
    for name, g in graphs.items():
        row = motif_census(g).select(F.lit(name).alias("graph"), "pattern", "n")
        out = row if out is None else out.unionByName(row)
    return out.groupBy("graph").pivot("pattern", ["path3", "star4", "triangle", "diamond", "pendant_triangle", "path4", "square", "k4"]).agg(F.first("n"))


def grouped_census(edges: DataFrame, by: str) -> DataFrame:
    """(by, edges, path3, triangles) of the graphs that edges (by, src, dst) or lists of them (by, src, dsts), each edge once, make for each value of `by`. The edges are read once, and written packed to the shared folder."""
    chunks = kept(edge_chunks(edges, by), "chunks")
    degree = kept(chunk_degrees(chunks, by), "degrees")
    d = F.col("d").cast(BIG)
    sums = degree.groupBy(by).agg((F.sum(d) / 2).cast("long").alias("edges"), (F.sum(d * (d - 1)) / 2).cast("long").alias("path3"))
    return sums.join(chunk_triangles(chunks, degree, by), by, "left").select(by, "edges", "path3", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def grouped_triangles(edges: DataFrame, by: str, load: int = 1 << 21) -> DataFrame:
    """(by, triangles) of the graphs of each value of `by`, counted at the keys of bucket lists: no two-path is shipped."""
    chunks = kept(edge_chunks(edges, by), "chunks")
    return chunk_triangles(chunks, chunk_degrees(chunks, by), by, load)


def edge_chunks(edges: DataFrame, by: str) -> DataFrame:
    """(by, i, j, chunk): the edges packed, by pairs of fine buckets i <= j; a chunk's sources are of bucket i."""
    dsts = F.col("dsts") if "dsts" in edges.columns else F.array("dst")
    lists = edges.where(F.col(by).isNotNull()).select(by, F.col("src").cast("long").alias("src"), dsts.cast("array<long>").alias("dsts"))
    return in_arrow(lists, packed_chunks, f"`{by}` {edges.schema[by].dataType.simpleString()}, i int, j int, chunk binary")


def chunk_degrees(chunks: DataFrame, by: str) -> DataFrame:
    """(by, v, d): degrees."""
    rows = in_arrow(chunks.select(by, "chunk"), degrees_of_chunks, f"`{by}` {chunks.schema[by].dataType.simpleString()}, v long, d long")
    return rows.groupBy(by, "v").agg(F.sum("d").alias("d"))


def chunk_triangles(chunks: DataFrame, degree: DataFrame, by: str, load: int = 1 << 21) -> DataFrame:
    """(by, triangles). Chunks go to the b keys each of their coarse buckets, the fine ones modulo b. b is such that a key of any graph holds some `load` edges, or as bits, in which dense graphs are held, 8 * load words of 64."""
    kind, words = chunks.schema[by].dataType.simpleString(), 8 * load
    sizes = degree.groupBy(by).agg((F.sum("d") / 2 / load).alias("edges"), (F.pow(F.count("*"), F.lit(2)) / 128 / words).alias("bits"))
    largest = sizes.agg(F.max(F.least("edges", "bits"))).first()[0] or 0
    b = min(FINE, max(1, math.ceil(3 * math.sqrt(largest))))
    u, v = F.col("i") % b, F.col("j") % b
    lists = chunks.select(by, F.least(u, v).alias("i"), F.greatest(u, v).alias("j"), (u > v).alias("turned"), "chunk", F.explode(F.sequence(F.lit(0), F.lit(b - 1))).alias("w")).withColumn("k", F.array_sort(F.array("i", "j", "w")))
    keys = [by, "k0", "k1", "k2"]
    rows = lists.select(by, *(F.col("k")[n].alias(f"k{n}") for n in range(3)), "i", "j", "turned", "chunk").repartition(*keys).sortWithinPartitions(*keys)
    found = in_arrow(rows, lambda batches: triangles_at_keys(batches, words), f"`{by}` {kind}, n long")
    return found.groupBy(by).agg(F.sum("n").alias("triangles"))


def ranks(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(x's values in order, the place of each of x among them)."""
    low, span = int(x.min()), int(x.max()) - int(x.min()) + 1
    if span > 8 * len(x):
        return np.unique(x, return_inverse=True)
    seen = np.zeros(span, bool)
    seen[x - low] = True
    return np.flatnonzero(seen) + low, (np.cumsum(seen) - 1)[x - low]


def packed(a: np.ndarray, b: np.ndarray) -> bytes:
    """A chunk: the edges by source; the distinct ids of both sides, how many edges a source has, and the steps from one target to the next among those ids, in as few bytes as the largest takes."""
    (left, a), (right, b) = ranks(a), ranks(b)
    count = np.bincount(a, minlength=len(left))
    code = a * len(right) + b
    if (code[1:] < code[:-1]).any():
        code.sort()
    b = code - np.repeat(np.arange(len(left)) * len(right), count)
    steps, start = np.diff(b, prepend=0), np.cumsum(count) - count
    steps[start] = b[start]
    width = next(w for w in (1, 2, 4, 8) if int(steps.max()) < 1 << min(63, 8 * w))
    body = b"".join(x.tobytes() for x in (np.diff(left, prepend=0).astype("<i8"), np.diff(right, prepend=0).astype("<i8"), count.astype("<i8"), steps.astype(f"<u{width}")))
    return np.array([len(b), len(left), len(right), width], "<i8").tobytes() + pa.compress(body, "zstd", asbytes=True)


def unpacked(chunk: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(ids of sources, ids of targets, each source's number of edges, each edge's target as a place among the ids); edges by source."""
    n, left, right, width = (int(x) for x in np.frombuffer(chunk, "<i8", 4))
    body = pa.decompress(chunk[32:], 8 * (2 * left + right) + width * n, "zstd")
    ids = np.frombuffer(body, "<i8", left), np.frombuffer(body, "<i8", right, 8 * left)
    count = np.frombuffer(body, "<i8", left, 8 * (left + right))
    at = np.cumsum(np.frombuffer(body, f"<u{width}", n, 8 * (2 * left + right)), dtype=np.int64)
    before = np.append(0, at)[np.cumsum(count)[:-1]]
    return np.cumsum(ids[0]), np.cumsum(ids[1]), count, at - np.repeat(np.append(0, before), count)


def packed_chunks(batches: Iterator[pa.RecordBatch], rows: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """(group, i, j, chunk): a task's edges of each group and pair of buckets, `rows` or so at a time."""

    def pack(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held).combine_chunks()
        group, lists = t.column(0).combine_chunks().dictionary_encode(), t.column(2).combine_chunks()
        size = lists.value_lengths().to_numpy()
        code, a = (x.to_numpy().repeat(size) for x in (group.indices, t.column(1)))
        b = lists.flatten().to_numpy()
        i, j = a % FINE, b % FINE
        down = i > j
        a, b = np.where(down, b, a), np.where(down, a, b)
        block = (code.astype(np.int64) * FINE + np.minimum(i, j)) * FINE + np.maximum(i, j)
        order = np.argsort(block.astype(np.uint16) if block.max() < 1 << 16 else block, kind="stable")
        block, a, b = block[order], a[order], b[order]
        cuts = np.flatnonzero(np.diff(block)) + 1
        of = block[np.append(0, cuts)]
        for which, x, y in zip(of, np.split(a, cuts), np.split(b, cuts), strict=True):
            columns = [group.dictionary.take(pa.array([which // FINE**2])), pa.array([which // FINE % FINE], pa.int32()), pa.array([which % FINE], pa.int32()), pa.array([packed(x, y)], pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, [t.column_names[0], "i", "j", "chunk"])

    held, n = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        n += len(batch.column(2).flatten())
        if n >= rows:
            yield from pack(held)
            held, n = [], 0
    if n:
        yield from pack(held)


def degrees_of_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(group, v, d): for each chunk, how many of its edges a node has."""
    for batch in batches:
        for n in range(batch.num_rows):
            left, right, count, to = unpacked(batch.column(1)[n].as_py())
            v, d = np.concatenate([left, right]), np.concatenate([count, np.bincount(to, minlength=len(right))])
            yield pa.RecordBatch.from_arrays([pa.repeat(batch.column(0)[n], len(v)), pa.array(v), pa.array(d)], [batch.schema.names[0], "v", "d"])


#: Of a key's pair of buckets: for each chunk, whether its sources are of the larger bucket, and the chunk.
Blocks = dict[tuple[int, int], list[tuple[bool, bytes]]]


def triangles_at_keys(batches: Iterator[pa.RecordBatch], words: int = 1 << 24) -> Iterator[pa.RecordBatch]:
    """(group, n) of each key (group, three buckets): the triangles of just these buckets. The input is sorted by key."""
    held, last, kind, name = {}, None, None, ""

    def row(key: tuple, blocks: Blocks) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([key[0]], kind), pa.array([triangles_of_list(key[1:], blocks, words)], pa.int64())], [name, "n"])

    for batch in batches:
        kind, name = batch.schema.field(0).type, batch.schema.field(0).name
        for n, r in enumerate(zip(*(batch.column(c).to_pylist() for c in range(7)), strict=True)):
            if last is not None and r[:4] != last:
                yield row(last, held)
                held = {}
            last = r[:4]
            held.setdefault(r[4:6], []).append((r[6], batch.column(7)[n].as_py()))
    if last is not None:
        yield row(last, held)


def triangles_of_list(k: tuple[int, int, int], blocks: Blocks, words: int = 1 << 24) -> int:
    """Triangles with a node in each of three buckets: for each edge between two of them, the neighbours in the third that its ends share."""
    base, third = ((k[1], k[2]), k[0]) if k[1] == k[2] else ((k[0], k[1]), k[2])
    one = k[0] == k[2]  # all in one bucket: an edge's ends see each other's neighbours in both directions
    edges = [c for _, c in blocks.get(base, [])]
    # chunks that tell neighbours in the third bucket, and whether their sources or their targets are the nodes that have them
    near = [(side, c) for x in sorted(set(base)) for turned, c in blocks.get((min(x, third), max(x, third)), []) for side in ((False, True) if one else ((x > third) != turned,))]
    if not edges or not near:
        return 0
    sides = [(unpacked_ids(c)[::-1] if side else unpacked_ids(c)) for side, c in near]
    ids, others = (np.unique(np.concatenate([s[n] for s in sides])) for n in (0, 1))
    m, width = sum(edges_in(c) for _, c in near), 8 * math.ceil(len(others) / 512)
    if len(ids) * width <= words and (width <= 32 * m / len(ids) or m > words // 4):
        total = dense_pairs(edges, near, ids, others, width)
    else:
        listed = lambda c: (lambda left, right, count, to: (left.repeat(count), right[to]))(*unpacked(c))
        a, b = (np.concatenate(x) for x in zip(*map(listed, edges), strict=True))
        node, to = (np.concatenate(x) for x in zip(*(listed(c)[:: -1 if side else 1] for side, c in near), strict=True))
        total = common_neighbours(a, b, node, to)
    return total // (3 if one else 1)


def edges_in(chunk: bytes) -> int:
    return int(np.frombuffer(chunk, "<i8", 1)[0])


def unpacked_ids(chunk: bytes) -> tuple[np.ndarray, np.ndarray]:
    return unpacked(chunk)[:2]


def dense_pairs(edges: list[bytes], near: list[tuple[bool, bytes]], ids: np.ndarray, others: np.ndarray, width: int) -> int:
    """The sum over the edges of how many of the others their ends share: a row of bits for each of ids, in words. Chunks are unpacked one at a time."""
    bits = np.zeros(len(ids) * width * 8, np.uint8)
    for side, c in near:
        left, right, count, to = unpacked(c)
        row, column = (np.searchsorted(ids, right)[to], np.searchsorted(others, left).repeat(count)) if side else (np.searchsorted(ids, left).repeat(count), np.searchsorted(others, right)[to])
        np.add.at(bits, row * (8 * width) + (column >> 3), np.left_shift(np.uint8(1), (column & 7).astype(np.uint8)))  # each edge once: a bit is never added twice
    bits, total = bits.view(np.uint64).reshape(len(ids), width), 0
    for c in edges:
        left, right, count, to = unpacked(c)
        row, column = (np.minimum(np.searchsorted(ids, x), len(ids) - 1) for x in (left, right))
        known, have = ids[row] == left, (ids[column] == right)[to]
        have &= known.repeat(count)
        mine = np.bincount(np.arange(len(left)).repeat(count)[have], minlength=len(left))
        total += shared_bits(bits, row, mine, column[to[have]])
    return total


def shared_bits(bits: np.ndarray, a: np.ndarray, count: np.ndarray, b: np.ndarray, step: int = 1 << 16) -> int:
    """The sum over the pairs of rows of the bits that both have; the pairs are each of a with the next `count` of b. `step` words at a time, in the same room."""
    width = bits.shape[1]
    some, total = max(1, step // width), 0
    x, c = np.empty((some, width), np.uint64), np.empty((some, width), np.uint8)

    def bits_of(n: int) -> int:
        np.bitwise_count(x[:n], out=c[:n])
        flat, third = c[:n].ravel(), n * width // 3
        three = flat[:third] + flat[third : 2 * third]  # at most 64 each, so three fit
        three += flat[2 * third : 3 * third]
        return int(three.sum(dtype=np.int64)) + int(flat[3 * third :].sum(dtype=np.int64))

    if len(b) >= 16 * np.count_nonzero(count):
        end = 0
        for row, n in zip(a[count > 0].tolist(), count[count > 0].tolist(), strict=True):
            end += n
            for i in range(end - n, end, some):
                m = min(some, end - i)
                np.take(bits, b[i : i + m], axis=0, out=x[:m], mode="clip")
                np.bitwise_and(x[:m], bits[row], out=x[:m])
                total += bits_of(m)
        return total
    a, y = a.repeat(count), np.empty((some, width), np.uint64)
    for i in range(0, len(b), some):
        m = min(some, len(b) - i)
        np.take(bits, a[i : i + m], axis=0, out=x[:m], mode="clip")
        np.take(bits, b[i : i + m], axis=0, out=y[:m], mode="clip")
        np.bitwise_and(x[:m], y[:m], out=x[:m])
        total += bits_of(m)
    return total


def common_neighbours(a: np.ndarray, b: np.ndarray, node: np.ndarray, to: np.ndarray, words: int = 1 << 24, step: int = 1 << 20) -> int:
    """The sum over the pairs (a, b) of how many neighbours (node, to) they share: by bits where the lists are dense, else by looking up the shorter list in the longer."""
    if not len(a) or not len(node):
        return 0
    ids, at = np.unique(node, return_inverse=True)
    others, to = np.unique(to, return_inverse=True)
    place = [np.minimum(np.searchsorted(ids, x), len(ids) - 1) for x in (a, b)]
    known = (ids[place[0]] == a) & (ids[place[1]] == b)
    a, b = (p[known] for p in place)
    degree, width = np.bincount(at, minlength=len(ids)), (len(others) + 63) // 64
    if len(ids) * width <= words and len(a) * width <= 32 * int(np.minimum(degree[a], degree[b]).sum()):
        bits = np.zeros((len(ids), width * 8), np.uint8)
        np.bitwise_or.at(bits, (at, to >> 3), np.left_shift(np.uint8(1), (to & 7).astype(np.uint8)))
        bits, some = bits.view(np.uint64), max(1, step // width)
        return sum(int(np.bitwise_count(bits[a[i : i + some]] & bits[b[i : i + some]]).sum(dtype=np.int64)) for i in range(0, len(a), some))
    packed = np.sort(at * len(others) + to)
    first = np.searchsorted(packed, np.arange(len(ids) + 1) * len(others))
    swap = degree[a] > degree[b]
    a, b = np.where(swap, b, a), np.where(swap, a, b)
    ends, total = np.cumsum(degree[a]), 0
    for run in np.split(np.arange(len(a)), np.flatnonzero(np.diff(ends // step)) + 1):
        count = degree[a[run]]
        which = np.repeat(np.arange(len(run)), count)
        far = packed[np.repeat(first[a[run]] - (np.cumsum(count) - count), count) + np.arange(len(which))] % len(others)
        key = b[run][which] * len(others) + far
        total += int((packed[np.minimum(np.searchsorted(packed, key), len(packed) - 1)] == key).sum())
    return total
