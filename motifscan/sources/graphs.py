"""Data graphs: an edge table with each edge once, low id first; and those derived from the given tables."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifscan.functions.buckets import FINE, bucket_of
from motifscan.sources.tables import kept, load


@dataclass(frozen=True)
class DataGraph:
    """edges: src, dst (longs) and label if there is one. Undirected: src < dst. Directed: no loops, both directions may be there."""

    edges: DataFrame
    directed: bool = False

    @staticmethod
    def from_df(df: DataFrame, src: str = "src", dst: str = "dst", label: str | None = None, directed: bool = False) -> DataGraph:
        """Drops loops, nulls and repeated edges; turns edges low id first unless directed."""
        a, b = F.col(src).cast("long"), F.col(dst).cast("long")
        ends = [a.alias("src"), b.alias("dst")] if directed else [F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")]
        columns = ends + ([F.col(label).cast("string").alias("label")] if label else [])
        return DataGraph(df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(*columns).distinct(), directed)

    @staticmethod
    def given(edges: DataFrame, directed: bool = False) -> DataGraph:
        """Edges known to be in form already."""
        return DataGraph(edges, directed)

    def both_ways(self) -> DataFrame:
        """(at, to) of each edge from both ends."""
        e = self.edges
        return e.select(F.explode(F.array(F.struct(F.col("src").alias("at"), F.col("dst").alias("to")), F.struct(F.col("dst").alias("at"), F.col("src").alias("to")))).alias("e")).select("e.at", "e.to")

    def degrees(self) -> DataFrame:
        """(node, degree)."""
        return self.edges.select(F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count("*").alias("degree"))

    def stats(self) -> DataFrame:
        """One row: n, m, max_degree."""
        d = self.degrees()
        return d.agg(F.count("*").alias("n"), (F.sum("degree") / 2).cast("long").alias("m"), F.max("degree").alias("max_degree"))

    def with_min_degree(self, least: int, rounds: int = 3) -> DataGraph:
        """Edges between nodes of at least this degree, trimmed a bounded number of times: what a pattern of this least degree can use."""
        g = self
        for _ in range(rounds):
            keep = g.degrees().where(F.col("degree") >= least).select("node")
            g = DataGraph(g.edges.join(keep.withColumnRenamed("node", "src"), "src", "left_semi").join(keep.withColumnRenamed("node", "dst"), "dst", "left_semi").select(*g.edges.columns), g.directed)
        return g


def co_membership_edges(facts: DataFrame, group: Column | str, member: Column | str, max_group: int | None = 100_000) -> DataFrame:
    """Edges between different members of a group, once whatever the number of common groups.

    The pairs of a group grow with its square: groups over max_group members stop the job, rather than being cut.
    """
    group, member = (F.col(c) if isinstance(c, str) else c for c in (group, member))
    f = facts.select(group.alias("g"), member.cast("long").alias("v")).where("g is not null and v is not null").distinct()
    if max_group is not None:
        sizes = f.groupBy("g").agg(F.count("*").alias("c"))
        f = f.join(sizes, "g").where(F.when(F.col("c") <= max_group, True).otherwise(F.raise_error(F.lit(f"a group has more than {max_group} members")).cast("boolean"))).select("g", "v")
    a, b = f.withColumnRenamed("v", "src"), f.withColumnRenamed("v", "dst")
    return a.join(b, "g").where("src < dst").select("src", "dst").distinct()


def co_membership_lists(facts: DataFrame, by: str, group: str, member: str, pairs: int = 1 << 22) -> DataFrame:
    """(by, src, dsts): edges between different members of a group, as lists of some of a node's neighbours; once for each value of `by`, from one of the two ends, whatever the number of common groups.

    Members are shipped, not pairs: those of two buckets meet at a key, which alone makes their edges and drops the repeats. A key makes some `pairs`.
    """
    f = facts.select(by, F.col(group).alias("g"), F.col(member).cast("long").alias("v")).where(F.col(by).isNotNull() & F.col("g").isNotNull() & F.col("v").isNotNull()).distinct()
    c = F.col("c").cast("double")
    made, b = f.groupBy(by, "g").agg(F.count("*").alias("c")).agg(F.sum(c * (c - 1) / 2)).first()[0] or 0, 4
    while b < FINE and made > pairs * b * b / 2:
        b = min(FINE, 2 * b)
    lists = f.groupBy(by, "g", bucket_of("v", FINE, "mod").alias("fine")).agg(F.collect_list("v").alias("members"))
    own, w = F.col("fine") % b, F.col("w")
    rows = lists.select("*", F.explode(F.sequence(F.lit(0), F.lit(b - 1))).alias("w")).select(by, F.least(own, w).alias("i"), F.greatest(own, w).alias("j"), own.alias("own"), "fine", "g", "members")
    kind = f.schema[by].dataType.simpleString()
    return rows.repartition(by, "i", "j").sortWithinPartitions(by, "i", "j").mapInArrow(edges_at_keys, f"`{by}` {kind}, src long, dsts array<long>")


def edges_at_keys(batches: Iterator[pa.RecordBatch], step: int = 1 << 20, longest: int = 64) -> Iterator[pa.RecordBatch]:
    """(by, src, dsts) of each key (by, two buckets) of rows (by, i, j, own bucket, fine bucket, group, members), sorted by key; made from `step` pairs or so at a time, each edge once. Lists are short, as rows are counted where they're put into batches."""

    def made(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held).combine_chunks()
        i, j = t.column(1)[0].as_py(), t.column(2)[0].as_py()
        members = t.column(6).combine_chunks()
        size = members.value_lengths().to_numpy()
        group = t.column(5).combine_chunks().dictionary_encode().indices.to_numpy().repeat(size)
        own, fine = (t.column(c).to_numpy().repeat(size) for c in (3, 4))
        v = members.flatten().to_numpy()

        def numbered(mine: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            """(ids by fine bucket, each member's place among them, its group)."""
            ids, first, at = np.unique(v[mine], return_index=True, return_inverse=True)
            order = np.lexsort((ids, fine[mine][first]))
            place = np.empty(len(ids), np.int64)
            place[order] = np.arange(len(ids))
            return ids[order], place[at], group[mine]

        (left, a, ga), (right, b, gb) = numbered(own == i), numbered(own == j)
        if not len(left) or not len(right):
            return
        by_group = np.argsort(gb, kind="stable")
        b, start = b[by_group], np.searchsorted(gb[by_group], np.arange(max(ga.max(), gb.max()) + 2))
        order = np.argsort(a, kind="stable")
        a, ga = a[order], ga[order]
        count = start[ga + 1] - start[ga]
        total = np.cumsum(np.bincount(a, count, len(left)).astype(np.int64))
        cuts = np.searchsorted(a, np.flatnonzero(np.diff(total // step)) + 1)
        for part in np.split(np.arange(len(a)), cuts):
            n = count[part]
            to = b[np.repeat(start[ga[part]] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
            code = np.repeat(a[part] * len(right), n) + to
            if i == j:
                code = code[np.repeat(a[part], n) < to]
            code.sort()
            code = code[np.append(True, code[1:] != code[:-1])[: len(code)]]
            x = code // len(right)
            y = right[code - x * len(right)]
            new = np.flatnonzero(np.append(True, x[1:] != x[:-1])[: len(x)])
            run = np.diff(np.append(new, len(x)))
            of = -(-run // longest)  # lists of a node
            first = np.repeat(new - longest * (np.cumsum(of) - of), of) + longest * np.arange(of.sum())
            ends = np.append(first, len(x)).astype(np.int32)
            for k in range(0, len(first), 1 << 14):
                n = min(1 << 14, len(first) - k)
                lists = pa.ListArray.from_arrays(pa.array(ends[k : k + n + 1] - ends[k]), pa.array(y[ends[k] : ends[k + n]]))
                yield pa.RecordBatch.from_arrays([pa.repeat(t.column(0)[0], n), pa.array(left[x[first[k : k + n]]]), lists], [t.column_names[0], "src", "dsts"])

    held, last = [], None
    for batch in batches:
        keys, at = list(zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True)), 0
        for n in range(1, len(keys) + 1):
            if n < len(keys) and keys[n] == keys[at]:
                continue
            if held and keys[at] != last:
                yield from made(held)
                held = []
            held.append(batch.slice(at, n - at))
            last, at = keys[at], n
    if held:
        yield from made(held)


def oversized_groups(facts: DataFrame, group: str, member: str, over: int) -> DataFrame:
    return facts.groupBy(group).agg(F.countDistinct(member).alias("members")).where(F.col("members") > over)


def bipartite_edges(df: DataFrame, left: str, right: str) -> DataFrame:
    """Left ids become even, right ids odd."""
    return DataGraph.from_df(df.select((F.col(left) * 2).alias("src"), (F.col(right) * 2 + 1).alias("dst"))).edges


def sequence_arcs(df: DataFrame, group: str, order: str, member: str) -> DataFrame:
    """Arcs from each member of a group to the next one in order."""
    from pyspark.sql import Window

    follow = F.lead(member).over(Window.partitionBy(group).orderBy(order, member))
    return DataGraph.from_df(df.select(F.col(member).alias("src"), follow.alias("dst")), directed=True).edges


def sign_tables(n: int, tau: float, recall: float = 0.95, rows: int = 500) -> tuple[int, int]:
    """(bits, tables) of random projections for n vectors: so many bits that a bucket has some `rows`, and so many tables that a pair at the threshold agrees on all bits of one with this probability."""
    bits = min(24, max(4, math.ceil(math.log2(max(1, n) / rows)))) if n > rows else 4
    agree = (1 - math.acos(min(1.0, max(-1.0, tau))) / math.pi) ** bits
    return bits, 1 if agree >= recall else math.ceil(math.log(1 - recall) / math.log(1 - agree))


def similarity_edges(vectors: DataFrame, tau: float, recall: float = 0.95, exact: bool = False) -> DataFrame:
    """Edges between vectors whose cosine is at least tau, verified: among pairs that agree on all signs of some table of random projections, of which there are as many as the recall needs; exact: among all pairs, which meet in tiles of blocks.

    Vectors that are null, empty or zero have no edges; vectors of different widths never meet.
    """
    import numpy as np

    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    first = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("v")).where(F.col("v").isNotNull() & (F.size("v") > 0) & F.exists("v", lambda c: c != 0))
    first = first.withColumns({"w": F.size("v"), "norm": F.sqrt(dot(F.col("v"), F.col("v")))})
    n, widths = first.agg(F.count("*"), F.collect_set("w")).first()
    if exact:
        blocks = max(1, math.ceil(n / 2000))
        own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
        tiles = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda o: F.struct(F.least(o, own).alias("i"), F.greatest(o, own).alias("j")))
        keyed = first.select("vec_id", "v", "w", "norm", F.explode(tiles).alias("k"))
    else:
        bits, tables = sign_tables(n, tau, recall)
        sign = lambda plane: F.when(dot(F.col("v"), F.array(*(F.lit(float(x)) for x in plane))) > 0, "1").otherwise("0")
        of_width = F.lit(None).cast("array<string>")
        for w in sorted(widths):
            planes = np.random.default_rng([1, w]).normal(size=(tables, bits, w))
            of_width = F.when(F.col("w") == w, F.array(*(F.concat(*(sign(p) for p in t)) for t in planes))).otherwise(of_width)
        keyed = first.select("vec_id", "v", "w", "norm", F.posexplode(of_width).alias("t", "s")).select("vec_id", "v", "w", "norm", F.struct("t", "s").alias("k"))
    a, b = keyed.toDF("src", "va", "w", "na", "k"), keyed.toDF("dst", "vb", "w", "nb", "k")
    # only pairs over the threshold leave the join
    near = dot(F.col("va"), F.col("vb")) / (F.col("na") * F.col("nb")) >= tau
    return a.join(b, ["k", "w"]).where("src < dst").where(near).select("src", "dst").distinct()


# the graphs of the workloads


def copurchase_returned(spark: SparkSession, sf_dir: str) -> DataGraph:
    items = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    return DataGraph(co_membership_edges(items, "l_orderkey", "l_partkey"))


def copurchase_bulk(spark: SparkSession, sf_dir: str) -> DataGraph:
    """A sparse part of the co-purchase graph that has cycles of odd lengths: returned lines of 30 pieces or more."""
    items = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity >= 30")
    return DataGraph(co_membership_edges(items, "l_orderkey", "l_partkey"))


def cosupply_bulk(spark: SparkSession, sf_dir: str) -> DataGraph:
    items = load(spark, sf_dir, "lineitem").where("l_quantity >= 45")
    return DataGraph(co_membership_edges(items, "l_orderkey", "l_suppkey"))


def coactive_purchase(spark: SparkSession, sf_dir: str) -> DataGraph:
    events = load(spark, sf_dir, "events").where("event_type = 'purchase'")
    return DataGraph(co_membership_edges(events, F.date_trunc("hour", F.col("ts")), "user_id"))


def buyer_part(spark: SparkSession, sf_dir: str) -> DataGraph:
    items = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity >= 40").select("l_orderkey", "l_partkey")
    bought = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(items, F.col("o_orderkey") == F.col("l_orderkey"))
    return DataGraph(bipartite_edges(bought, "o_custkey", "l_partkey"))


def near_docs(documents: DataFrame, min_chars: int = 80) -> DataFrame:
    """Edges between a document and the first one (by doc_id) that has a line of at least min_chars in common with it: a star for each line, never all pairs of those that have it."""
    lines = documents.select(F.col("doc_id").cast("long").alias("v"), F.explode(F.split("text", "\n")).alias("line")).where(F.col("v").isNotNull() & (F.length("line") >= min_chars))
    # one aggregate with partial sums finds each line's first document; the join back is by the line's hash
    keyed = lines.select("v", F.xxhash64("line").alias("a"), F.xxhash64("line", F.lit(3)).alias("b")).distinct()
    first = keyed.groupBy("a", "b").agg(F.min("v").alias("u"), F.count("*").alias("c")).where("c > 1").drop("c")
    return DataGraph.from_df(keyed.join(first, ["a", "b"]).select(F.col("u").alias("src"), F.col("v").alias("dst"))).edges


def group_relations(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    """Five relations of very unequal sizes in a cycle: region-nation, nation-part (bought by its customers), part-supplier, supplier-nation (sold to), nation-region; columns (a, b), distinct."""
    nations = load(spark, sf_dir, "nation").select(F.col("n_regionkey").cast("long").alias("r"), F.col("n_nationkey").cast("long").alias("n")).distinct()
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    buyers = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("c_custkey") == F.col("o_custkey"))
    # two of the relations read it
    sold = kept(items.join(buyers, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("c_nationkey").cast("long").alias("n"), F.col("l_partkey").cast("long").alias("p"), F.col("l_suppkey").cast("long").alias("s")), "sold")
    return [nations.toDF("a", "b"), sold.select("n", "p").toDF("a", "b").distinct(), items.select(F.col("l_partkey").cast("long").alias("a"), F.col("l_suppkey").cast("long").alias("b")).distinct(), sold.select("s", "n").toDF("a", "b").distinct(), nations.select("n", "r").toDF("a", "b")]


def labelled_copart(spark: SparkSession, sf_dir: str) -> DataGraph:
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag", "l_partkey").distinct()
    a, b = items.toDF("o", "label", "src"), items.toDF("o", "label", "dst")
    return DataGraph(a.join(b, ["o", "label"]).where("src < dst").select("src", "dst", "label").distinct())


def buys_from(spark: SparkSession, sf_dir: str) -> DataGraph:
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return DataGraph(orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct(), True)


def part_sequence(spark: SparkSession, sf_dir: str) -> DataGraph:
    return DataGraph(sequence_arcs(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), "l_orderkey", "l_linenumber", "l_partkey"), True)


def five_relations(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    """nation-customer, customer-order, order-part, part-supplier, supplier-nation; columns (a, b), distinct."""
    two = lambda t, a, b: load(spark, sf_dir, t).select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).distinct()
    return [two("customer", "c_nationkey", "c_custkey"), two("orders", "o_custkey", "o_orderkey"), two("lineitem", "l_orderkey", "l_partkey"), two("lineitem", "l_partkey", "l_suppkey"), two("supplier", "s_suppkey", "s_nationkey")]
