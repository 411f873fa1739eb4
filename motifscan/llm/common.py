"""What the training-data operators share: input columns, staged tables, seeded hashes, joins that split frequent keys."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word as the text contracts have it: no ASCII white space inside.
WORD = r"[^\x20\x09-\x0D]+"
#: A key counts as frequent from this part of all rows on, so that there are never more frequent keys than its inverse; and from so many rows on.
FREQUENT, MANY = 1 / 1000, 1000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as spark.checkpoint.dir names it. Unset, it is a temporary folder where all runs in one process, as in tests, and an error on a cluster."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return _own_dir()


@lru_cache(maxsize=None)
def _own_dir() -> str:
    named = tempfile.mkdtemp(prefix="motifscan-stage-")
    atexit.register(shutil.rmtree, named, True)
    return named


class Stage:
    """Intermediate tables of one operator run, written as Parquet in the shared folder.

    A written table cuts lineage and survives lost executors; `drop` deletes one that no later plan reads.
    """

    _watchers: list[list[Stage]] = []

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root, self.n = spark, f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}", 0
        for seen in Stage._watchers:
            seen.append(self)

    def put(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/t{self.n}"
        self.n += 1
        df.write.option("compression", "zstd").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._stage_path = path
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        for t in tables:
            if path := getattr(t, "_stage_path", None):
                self._delete(path)

    def _delete(self, path: str) -> None:
        at = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


@contextmanager
def released() -> Iterator[None]:
    """Deletes, when it ends, the tables of all stages that began inside: for callers that have written down the result that read them."""
    seen: list[Stage] = []
    Stage._watchers.append(seen)
    try:
        yield
    finally:
        Stage._watchers.remove(seen)
        for stage in seen:
            stage._delete(stage.root)


def uniform(*key: Column) -> Column:
    """A number in [0, 1) that depends on the key alone, so that reruns agree."""
    return F.pmod(F.xxhash64(*key), F.lit(1 << 53)).cast("double") / F.lit(float(1 << 53))


def fresh(taken: list[str], *names: str) -> list[str]:
    """The names, each with as many underscores behind it as make them all differ from the taken ones."""
    known, tail = {t.lower() for t in taken}, "_"
    while any((n + tail).lower() in known for n in names):
        tail += "_"
    return [n + tail for n in names]


def row_keys(docs: DataFrame) -> dict[str, Column]:
    """What tells documents apart: doc (id; null: below all), and, if any ids are null or repeated, row (a hash of the text)."""
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))
    shared = docs.groupBy(doc.alias("doc")).agg(F.count("*").alias("n"), F.count("doc_id").alias("named")).where("n > 1 or named = 0")
    return {"doc": doc} if shared.isEmpty() else {"doc": doc, "row": F.xxhash64(F.col("text").cast("string"))}


def frequent(keys: DataFrame, on: list[str], count: str, total: int) -> list[tuple]:
    """The frequent values of `on`, each with the number of tasks that its rows are dealt to: at most 1 / FREQUENT, whatever the input."""
    least = max(MANY, total * FREQUENT)
    return [(*r[:-1], int(r[-1] // least) + 1) for r in keys.where(F.col(count) > least).select(*on, count).collect()]


def join_split(rows: DataFrame, keys: DataFrame, on: list[str], count: str, total: int, how: str = "inner") -> DataFrame:
    """rows joined with keys, a written table which has each value of `on` (longs) once and how many of the `total` rows have it; frequent values' rows are dealt to several tasks."""
    return join_dealt(rows, keys.drop(count), on, frequent(keys, on, count, total), how)


def join_dealt(rows: DataFrame, keys: DataFrame, on: list[str], hot: list[tuple], how: str = "inner") -> DataFrame:
    """rows joined with keys, which has each value of `on` once; the rows of the values of `hot` are dealt to several tasks, to each of which the value's row goes."""
    if not hot:
        return rows.join(keys, on, how)
    part, parts, *names = fresh([*rows.columns, *keys.columns], "part", "parts", *(f"key{i}" for i in range(len(on))))
    spread = F.broadcast(rows.sparkSession.createDataFrame(hot, ", ".join(f"{n} long" for n in names) + f", {parts} int"))

    def dealt(df: DataFrame) -> DataFrame:
        same = F.lit(True)
        for c, n in zip(on, names, strict=True):
            same = same & (df[c] == F.col(n))
        return df.join(spread, same, "left").drop(*names)

    others = F.xxhash64(*(F.col(x) for x in rows.columns if x not in on))
    left = dealt(rows).withColumn(part, F.coalesce(F.pmod(others, F.col(parts)), F.lit(0)).cast("int")).drop(parts)
    right = dealt(keys).withColumn(part, F.explode(F.sequence(F.lit(0), F.coalesce(F.col(parts) - 1, F.lit(0))))).drop(parts)
    return left.join(right, [*on, part], how).drop(part)


def give_back() -> None:
    """Returns what the worker's allocators hold but don't use, so that idle workers stay small."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        pass


def in_arrow(df: DataFrame, f: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: object) -> DataFrame:
    """mapInArrow by workers that give their memory back at each task's end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from f(batches)
        finally:
            give_back()

    return df.mapInArrow(run, schema)
