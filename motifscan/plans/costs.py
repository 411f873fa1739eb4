"""Closed forms of communication costs, keys and bounds; and the report that holds measured values against them."""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession


def multiway_pairs(b: int, dedup: bool = False) -> int:
    """Pairs per edge of the three-role triangle scheme; two of its keys are equal and can be merged."""
    return 3 * b - 2 if dedup else 3 * b


def ordered_pairs(b: int) -> int:
    return b


def nodeset_pairs(b: int, p: int = 3, same: float | None = None) -> float:
    """Pairs per edge of p-subsets of b groups; same: the share of edges inside one group (1/b if nodes are hashed)."""
    same = 1 / b if same is None else same
    return same * math.comb(b - 1, p - 1) + (1 - same) * math.comb(b - 2, p - 2)


def bucket_pairs(b: int, p: int) -> int:
    return math.comb(b + p - 3, p - 2)


def keys(scheme: str, b: int, p: int = 3) -> int:
    return {"multiway": b**p, "ordered": math.comb(b + p - 1, p), "bucket": math.comb(b + p - 1, p), "nodeset": math.comb(b, p)}[scheme]


def useful_keys(b: int, p: int) -> Iterator[tuple[int, ...]]:
    """The keys that can own an instance of one ordered query, of all b^p: lists that never fall. There are C(b+p-1, p)."""
    return itertools.combinations_with_replacement(range(b), p)


def asymptotic(scheme: str, k: float) -> float:
    """Pairs per edge of triangles at k keys, for many keys: k is b^3/6, or b^3 for the multiway scheme."""
    return {"nodeset": 1.5 * (6 * k) ** (1 / 3), "multiway": 3 * k ** (1 / 3), "ordered": (6 * k) ** (1 / 3)}[scheme]


def nodeset_over_bucket(p: int) -> float:
    return 1 + 1 / (p - 1)


def output_bound(p: int, m: float) -> float:
    return m ** (p / 2)


def bounded_degree_bound(p: int, m: float, delta: float) -> float:
    return m * delta ** (p - 2)


def is_convertible(alpha: float, beta: float, p: int) -> bool:
    """Whether a serial algorithm of n^alpha m^beta steps does no more work in all keys together than alone."""
    return alpha + 2 * beta >= p


def excess_factor(alpha: float, beta: float, p: int, b: float) -> float:
    return b ** (p - alpha - 2 * beta)


def degree_ok(delta: float, b: int, n: int) -> bool:
    """Whether buckets of a bounded-degree graph keep its degree bound: delta / b is at least about log n."""
    return delta / b >= math.log(max(n, 2))


@dataclass(frozen=True)
class CostReport:
    """Measured and expected cost of one scheme on one graph."""

    scheme: str
    pattern: str
    b: int
    k: int
    m: int
    pairs: int
    keys_hit: int
    max_load: int
    replication: float
    mean_load: float
    formula: float

    def to_df(self, spark: SparkSession) -> DataFrame:
        return reports_df(spark, [self])


def reports_df(spark: SparkSession, reports: list[CostReport]) -> DataFrame:
    schema = "scheme string, pattern string, b long, k long, m long, pairs long, keys_hit long, max_load long, replication double, mean_load double, formula double"
    return spark.createDataFrame([tuple(asdict(r).values()) for r in reports], schema)
