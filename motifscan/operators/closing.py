"""Cycles from paths that meet at one node: the last edge closes them, and few open ones are shipped to find it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Neighbours in a list, or so; a node of more has several lists. Words of 64 bits in a sieve: at most so many, and one for so many edges.
LIST, WORDS, EDGES_A_WORD = 1024, 1 << 22, 4


def neighbour_lists(arcs: DataFrame) -> DataFrame:
    """(at, ends): arcs (at, to) as lists; to may be a struct."""
    cut = F.ceil(F.count("*").over(Window.partitionBy("at")) / LIST)
    return arcs.withColumn("part", F.pmod(F.xxhash64("to"), cut)).groupBy("at", "part").agg(F.collect_list("to").alias("ends")).select("at", "ends")


def _shift(name: str, value: Column, by: Column) -> Column:
    return F.call_function(name, value, by.cast("int"))


def _marks(h: Column) -> Column:
    """Four bits of a word."""
    out = F.lit(0).cast("long")
    for i in (40, 46, 52, 58):
        out = out.bitwiseOR(_shift("shiftleft", F.lit(1).cast("long"), _shift("shiftrightunsigned", h, F.lit(i)).bitwiseAND(63)))
    return out


def sieve(edges: DataFrame) -> tuple[DataFrame, int]:
    """(one row: words; their number): bits that every edge (src, dst) has set, and few other pairs. More edges than the words are meant for let more pairs pass; none is lost."""
    n, size = edges.count(), 1
    while size < WORDS and size * EDGES_A_WORD < n:
        size *= 2
    h = edges.select(F.xxhash64("src", "dst").alias("h"))
    bits = h.groupBy(F.col("h").bitwiseAND(size - 1).alias("id")).agg(F.bit_or(_marks(F.col("h"))).alias("bits"))
    full = edges.sparkSession.range(size).join(bits, "id", "left").select("id", F.coalesce("bits", F.lit(0).cast("long")).alias("bits"))
    ordered = lambda by, what: F.transform(F.sort_array(F.collect_list(F.struct(by, what))), lambda s: s[what])
    runs = full.groupBy(F.shiftright("id", 12).alias("run")).agg(ordered("id", "bits").alias("words"))
    return runs.agg(F.flatten(ordered("run", "words")).alias("words")), size


def closed(open_paths: DataFrame, a: str, b: str, edges: DataFrame, sifted: tuple[DataFrame, int]) -> DataFrame:
    """The paths whose ends a < b are an edge (src, dst). Most others are sifted out where they are made, so that they aren't shipped; what passes meets the edges themselves."""
    words, size = sifted
    paths = open_paths.columns
    hashed = open_paths.withColumn("_h", F.xxhash64(a, b)).select(*paths, F.col("_h").bitwiseAND(size - 1).cast("int").alias("_at"), _marks(F.col("_h")).alias("_marks"))
    passed = hashed.join(F.broadcast(words), F.get("words", F.col("_at")).bitwiseAND(F.col("_marks")) == F.col("_marks"), "left_semi").select(*paths)
    return passed.join(edges.select(F.col("src").alias(a), F.col("dst").alias(b)), [a, b], "left_semi").select(*paths)
