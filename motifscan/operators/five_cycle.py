"""The join of five relations in a cycle, R1(a, b) R2(b, c) R3(c, d) R4(d, e) R5(e, a), whose sizes may differ by any factor."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifscan.functions.buckets import bucket_of
from motifscan.operators import schemes
from motifscan.operators.rounds import guarded_cross, one_round
from motifscan.plans import shares as sh
from motifscan.sources.tables import kept

#: Up to so many rows the two relations at case B's first variable are sent to all tasks.
SMALL = 1 << 16

V = ["v1", "v2", "v3", "v4", "v5"]


def five_cycle_case(sizes: Sequence[int]) -> tuple[str, int, float]:
    """('A' or 'B', rotation, bound). A: the root of the product bounds the result. B: for some rotation the product of
    the two relations that meet at its first variable and the one opposite is smaller still, and is both bound and plan."""
    root = math.sqrt(math.prod(float(n) for n in sizes))
    best = min(range(5), key=lambda r: float(sizes[r]) * sizes[(r + 4) % 5] * sizes[(r + 2) % 5])
    three = float(sizes[best]) * sizes[(best + 4) % 5] * sizes[(best + 2) % 5]
    return ("B", best, three) if three < root else ("A", best, root)


def five_cycle_shares(sizes: Sequence[int], k: float) -> list[float]:
    """Shares of the variables for one round over k keys; relation i holds variables i and i + 1."""
    return sh.optimise(5, tuple(sh.Term(i, (i + 1) % 5, float(max(1, n))) for i, n in enumerate(sizes)), k)


def _join_order(sizes: Sequence[float], values: Sequence[tuple[int, int]]) -> tuple[float, list[list[int]]]:
    """(rows of the largest join before the last, the two paths of relations): the cycle as two paths, each joined along itself from the end that grows less, which then meet in both their ends. Sizes are expected ones."""

    def grown(path: list[int]) -> tuple[float, float]:
        rows = most = float(sizes[path[0]])
        for i, j in zip(path, path[1:], strict=False):
            # neighbours share a variable: the later one's first if the path goes on, its second if it goes back
            own, other = (1, 0) if (i + 1) % 5 == j else (0, 1)
            rows = rows * sizes[j] / max(1.0, values[i][own], values[j][other])
            most = max(most, rows)
        return rows, most

    best = (math.inf, [[0]])
    for start in range(5):
        for length in (2, 3, 4):
            one = [(start + i) % 5 for i in range(length)]
            two = [(start + length + i) % 5 for i in range(5 - length)]
            most, paths = 0.0, []
            for path in (one, two):
                path = min((path, path[::-1]), key=lambda p: grown(p)[1])
                most += grown(path)[1]
                paths.append(path)
            best = min(best, (most, paths))
    return best


def _one_round(rels: list[DataFrame], sizes: Sequence[int], values: Sequence[tuple[int, int]], k: int) -> DataFrame:
    ts = tuple(sh.Term(i, (i + 1) % 5, float(max(1, n))) for i, n in enumerate(sizes))
    shares = sh.round_shares(5, ts, sh.optimise(5, ts, k), k)
    shipped = []
    for i, r in enumerate(rels):
        j = (i + 1) % 5
        fixed = sum((bucket_of(c, shares[v], seed=v).cast("long") * math.prod(shares[v + 1 :]) for c, v in (("a", i), ("b", j))), F.lit(0).cast("long"))
        rows = schemes.free_keys(r.select(F.col("a").alias(V[i]), F.col("b").alias(V[j]), fixed.alias("rk")), shares, [v for v in range(5) if v not in (i, j)])
        shipped.append(rows.repartition("rk"))
    joined = []
    for path in _join_order(sizes, values)[1]:
        df = shipped[path[0]]
        for i in path[1:]:
            df = df.join(shipped[i], ["rk", *(c for c in shipped[i].columns if c != "rk" and c in df.columns)])
        joined.append(df)
    left, right = joined
    return one_round(left.join(right, [c for c in left.columns if c in right.columns]).select(*V))


def _packed(df: DataFrame, key: str, value: str) -> DataFrame:
    """(key, word, bits): each key's values as bits of words, 32 values a word; never more rows than df has."""
    word, bit = F.shiftright(value, 5), F.call_function("shiftleft", F.lit(1).cast("long"), F.col(value).bitwiseAND(31).cast("int"))
    return df.groupBy(key, word.alias("word")).agg(F.bit_or(bit).alias("bits"))


def _has(value: str) -> Column:
    return F.call_function("shiftright", F.col("bits"), F.col(value).bitwiseAND(31).cast("int")).bitwiseAND(1) == 1


def _turned(rels: list[DataFrame], r: int, sizes: Sequence[int]) -> tuple[list[str], DataFrame, DataFrame, DataFrame, DataFrame]:
    """(variables from r on, the corner: the relations at r joined; the second and fourth relations, what of them hangs on the corner; the one opposite)."""
    v = [V[(r + i) % 5] for i in range(5)]
    r1, r2, r3, r4, r5 = (rels[(r + i) % 5] for i in range(5))
    corner = r1.toDF(v[0], v[1]).join(r5.toDF(v[4], v[0]), v[0])
    small = F.broadcast if sizes[r] * sizes[(r + 4) % 5] <= SMALL else lambda df: df
    second = r2.toDF(v[1], v[2]).join(small(corner.select(v[1]).distinct()), v[1], "left_semi")
    fourth = r4.toDF(v[3], v[4]).join(small(corner.select(v[4]).distinct()), v[4], "left_semi")
    return v, small(corner), second, fourth, r3.toDF(v[2], v[3])


def _corner_counts(rels: list[DataFrame], r: int, sizes: Sequence[int]) -> DataFrame:
    """(the three variables of the two relations at variable r, n): how many rows of the join each of the corner's rows has.

    The rows aren't made. What the opposite relation's rows reach through the second one goes along as bits, is counted at
    the other end, where nothing is shipped again, and meets the fourth relation as counts.
    """
    v, corner, second, fourth, far = _turned(rels, r, sizes)
    reached = far.join(_packed(second, v[2], v[1]), v[2]).select(v[3], "word", "bits").repartition(v[3])
    bit = F.explode(F.array(*(F.lit(i) for i in range(32)))).alias("bit")
    values = reached.select(v[3], "word", "bits", bit).where(F.call_function("shiftright", F.col("bits"), F.col("bit")).bitwiseAND(1) == 1)
    per = values.groupBy(v[3], (F.col("word") * 32 + F.col("bit")).alias(v[1])).agg(F.count("*").alias("n"))
    pairs = per.join(fourth, v[3]).groupBy(v[1], v[4]).agg(F.sum("n").alias("n"))
    return pairs.join(corner, [v[1], v[4]]).select(v[0], v[1], v[4], "n")


def _opposite(rels: list[DataFrame], r: int, sizes: Sequence[int], most: int = 1 << 40) -> DataFrame:
    """The relations at variable r joined, then all rows of the one opposite, checked in the other two: no step makes more rows than the product of the three.

    The product is only built where going through R2 would make more: how many rows that gives is counted first, from
    the numbers of rows of each value. Of the opposite relation only rows that both checks can accept take part. Going
    through R2, its rows bring along what the fourth relation accepts, as bits, so that the result isn't shipped for that check.
    """
    v, corner, second, fourth, r3 = _turned(rels, r, sizes)
    there = lambda df, c: df.select(c).distinct()
    far = r3.join(there(second, v[2]), v[2], "left_semi").join(there(fourth, v[3]), v[3], "left_semi")
    per = lambda df, c, n: df.groupBy(c).agg(F.count("*").cast("decimal(38,0)").alias(n))
    steps = per(corner, v[1], "n").join(per(second, v[1], "m"), v[1]).agg(F.coalesce(F.sum(F.col("n") * F.col("m")), F.lit(0)).alias("through"))
    sides = corner.agg(F.count("*").alias("corner")).crossJoin(far.agg(F.count("*").alias("far"))).crossJoin(steps).first()
    if sides["through"] <= sides["corner"] * sides["far"]:
        accepted = far.join(_packed(fourth, v[3], v[4]), v[3])
        return second.join(corner, v[1]).withColumn("word", F.shiftright(v[4], 5)).join(accepted, [v[2], "word"]).where(_has(v[4])).select(*V)
    return guarded_cross(corner, far, most).join(second, [v[1], v[2]], "left_semi").join(fourth, [v[3], v[4]], "left_semi").select(*V)


def five_cycle_join(rels: list[DataFrame], strategy: str = "auto", k: int = 64, sizes: Sequence[int] | None = None, count_only: bool = False, by: Sequence[str] | None = None) -> DataFrame:
    """(v1..v5), or their number n. rels: five DataFrames with columns a, b, without repeated rows. strategy: 'A', 'B' or by the sizes; relations are written once and counted unless these are given.

    by: some of the variables; (these, n), the number of rows of each of their values. In case B, those of the two relations
    at its first variable are counted without making the rows.
    """
    values = [(1, 1)] * 5
    if sizes is None:
        rels = [kept(r, "relation") for r in rels]
        counts = None
        for i, r in enumerate(rels):
            c = r.agg(F.count("*").alias("n"), F.approx_count_distinct("a").alias("a"), F.approx_count_distinct("b").alias("b")).select(F.lit(i).alias("i"), "n", "a", "b")
            counts = c if counts is None else counts.unionByName(c)
        rows = sorted(counts.collect(), key=lambda row: row["i"])
        sizes, values = [row["n"] for row in rows], [(row["a"], row["b"]) for row in rows]
    case, r, _ = five_cycle_case(sizes)
    if strategy == "auto":
        strategy = case
    if by and strategy == "B" and set(by) == {V[r], V[(r + 1) % 5], V[(r + 4) % 5]}:
        out = _corner_counts(rels, r, sizes).select(*by, "n")
        return out.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")) if count_only else out
    out = _one_round(rels, sizes, values, k) if strategy == "A" else _opposite(rels, r, sizes)
    if count_only:
        return out.agg(F.count("*").alias("n"))
    return out.groupBy(*by).agg(F.count("*").alias("n")) if by else out


def extremal_five_cycle(spark: SparkSession, sizes: Sequence[int]) -> list[DataFrame]:
    """Relations of about these sizes whose join is as large as the bound allows."""
    case, r, _ = five_cycle_case(sizes)
    n = [float(sizes[(r + i) % 5]) for i in range(5)]
    if case == "A":
        # domain of a variable: the root of (its two relations and the opposite one by the other two)
        dom = [max(1, round(math.sqrt(n[i] * n[i - 1] * n[(i + 2) % 5] / (n[(i + 1) % 5] * n[i - 2])))) for i in range(5)]
        rels = [_product(spark, dom[i], dom[(i + 1) % 5]) for i in range(5)]
    else:
        # one value of the first variable; the others' values are the rows of the relations that hold them
        b, e, (c, d) = int(n[0]), int(n[4]), (1, int(n[2]))
        if n[1] >= n[0] * n[2]:
            c, d = int(n[2]), 1
        rels = [_product(spark, 1, b), _product(spark, b, c), _product(spark, c, d), _product(spark, d, e), _product(spark, e, 1)]
    return rels[5 - r :] + rels[: 5 - r] if r else rels


def _product(spark: SparkSession, left: int, right: int) -> DataFrame:
    return spark.range(left * right).select(F.floor(F.col("id") / right).alias("a"), (F.col("id") % right).alias("b"))
