"""Approximate nearest neighbours by cross-polytope hashing.

Each table turns unit vectors by rounds of random signs and a fast Hadamard transform and assigns them to the nearest
signed axis, of the first AXES ones, or to the nearest axes of two turns, so that there are 2 * AXES or (2 * AXES)^2
buckets. A query looks into the buckets nearest to it in every table. How many turns, tables and probes there are is
settled by trial: for a bounded sample of queries the true neighbours are found by meeting all vectors in blocks, and of
the settings that reach the wanted recall on them the one of least work is taken, for so many rows as there are. So
vectors that lie in groups are met by few queries however many rows there are; vectors without structure need half.
Bucket and visiting queries meet in blocks of bounded size, which keep each query's best by the exact cosine; the
tables' bests are merged. A query that found fewer than k meets all vectors of its width, in blocks of the same kind.
Equal vectors are looked up once, by their smallest ids.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from motifscan.llm.common import Stage, in_arrow

#: Rows of one block: vectors of a bucket, and queries that visit it.
BLOCK = 2048
#: Axes of a turn at most, so that the share of vectors that a query meets doesn't fall with the width.
AXES = 64
#: For the trial: queries, rows that stand for all, and how many rows' meetings a shipped probe costs.
TRIAL_QUERIES, TRIAL_ROWS, PROBE_COST = 64, 1024, 64


def hadamard(x: np.ndarray) -> np.ndarray:
    """The orthonormal Hadamard transform of each row; the width is a power of two."""
    n, h = x.shape[1], 1
    while h < n:
        y = x.reshape(len(x), n // (2 * h), 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], 2).reshape(len(x), n)
        h *= 2
    return x / math.sqrt(n)


def rotate(x: np.ndarray, table: int, seed: int) -> np.ndarray:
    """A pseudo-random rotation of each row, filled up with zeros to a power of two."""
    width = 1 << max(0, (x.shape[1] - 1).bit_length())
    x = np.pad(x, ((0, 0), (0, width - x.shape[1])))
    rng = np.random.default_rng([seed, table, width])
    for _ in range(3):
        x = hadamard(x * rng.choice([-1.0, 1.0], width))
    return x


@dataclass(frozen=True)
class Setting:
    """Tables, turns of each (1 or 2), and how many buckets of a table a query looks into."""

    tables: int = 12
    turns: int = 1
    probes: int = 10


def distances(x: np.ndarray, table: int, turns: int, seed: int) -> list[np.ndarray]:
    """For each turn, how far each row is from each signed axis (columns 2 * axis, and 1 more for the negative one), as what the nearest one's component exceeds the axis' by."""
    out = []
    for t in range(turns):
        y = rotate(x, 2 * table + t, seed)[:, :AXES]
        signed = np.stack([y, -y], 2).reshape(len(y), -1)
        out.append(signed.max(1, keepdims=True) - signed)
    return out


def nearest_buckets(x: np.ndarray, table: int, setting: Setting, count: int, seed: int) -> np.ndarray:
    """The `count` nearest buckets of each row, nearest first: of two turns, by the sum of both distances."""
    gaps = distances(x, table, setting.turns, seed)
    if setting.turns == 1:
        return np.argsort(gaps[0], axis=1, kind="stable")[:, :count]
    # of each turn, the nearest `count` axes are enough for the nearest `count` pairs
    near = [np.argsort(g, axis=1, kind="stable")[:, :count] for g in gaps]
    both = [np.take_along_axis(g, n, 1) for g, n in zip(gaps, near, strict=True)]
    total = (both[0][:, :, None] + both[1][:, None, :]).reshape(len(x), -1)
    pick = np.argsort(total, axis=1, kind="stable")[:, :count]
    width = near[1].shape[1]
    return np.take_along_axis(near[0], pick // width, 1) * (2 * AXES) + np.take_along_axis(near[1], pick % width, 1)


def ranks(gaps: list[np.ndarray], *targets: list[np.ndarray]) -> list[np.ndarray]:
    """How many buckets come before each target's own (columns), for each query (rows of gaps)."""
    pick = lambda t: sum(np.take_along_axis(g, x, 1) for g, x in zip(gaps, t, strict=True))
    every = gaps[0] if len(gaps) == 1 else (gaps[0][:, :, None] + gaps[1][:, None, :]).reshape(len(gaps[0]), -1)
    every = np.sort(every, axis=1)
    return [np.stack([np.searchsorted(row, o, "left") for row, o in zip(every, pick(t), strict=True)]) for t in targets]


def settle(queries: np.ndarray, neighbours: np.ndarray, rows: np.ndarray, n: int, recall: float, seed: int) -> Setting:
    """The setting of least work for n rows that finds this part of the neighbours (of each query, rows of its own). rows: a sample of all."""
    tables, k = 16, neighbours.shape[1]
    found: dict[int, np.ndarray] = {}
    met: dict[int, np.ndarray] = {}
    for turns in (1, 2):
        f, m = [], []
        for table in range(tables):
            gaps = distances(queries, table, turns, seed)
            nearest = lambda x: [d.argmin(1) for d in distances(x, table, turns, seed)]  # noqa: B023, E731
            own = [t.reshape(-1, k) for t in nearest(neighbours.reshape(-1, queries.shape[1]))]
            of_rows = [np.tile(t, (len(queries), 1)) for t in nearest(rows)]
            for part, got in zip((f, m), ranks(gaps, own, of_rows), strict=True):
                part.append(got)
        found[turns], met[turns] = np.minimum.accumulate(np.stack(f)), np.stack(m)
    best: tuple[float, Setting] | None = None
    for turns, most in ((1, 2 * AXES), (2, 1024)):
        probes = sorted({int(round(2 ** (i / 4))) for i in range(4 * 11)} & set(range(1, most + 1)))
        for t in range(2, tables + 1, 2):
            for p in probes:
                if (found[turns][t - 1] < p).mean() >= recall:
                    work = n * float((met[turns][:t] < p).mean(0).mean()) * t + PROBE_COST * t * p
                    if best is None or work < best[0]:
                        best = (work, Setting(t, turns, p))
                    break
    return best[1] if best else Setting(probes=probes_at(queries.shape[1], 10))


def probes_at(width: int, probes: int) -> int:
    """Probes at a width: the nearest cosines of wide vectors without structure are smaller, so each doubling beyond AXES adds a quarter."""
    return probes + math.ceil(probes / 4 * max(0.0, math.log2(1 << max(0, (width - 1).bit_length())) - math.log2(AXES)))


def scaled(x: np.ndarray) -> np.ndarray:
    """Each row times the power of two that brings its largest component to between a half and one, so that no square overflows or vanishes. Cosines stay as they are."""
    _, exponent = np.frexp(np.abs(x).max(1, keepdims=True))
    return np.ldexp(x, -exponent)


def cosines(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """The cosine of each pair of scaled rows, with one order of summation, so that equal vectors get equal values."""
    return (q * x).sum(1) / (np.sqrt((q * q).sum(1)) * np.sqrt((x * x).sum(1)))


def _parts(rows: np.ndarray, values: int) -> list[np.ndarray]:
    """Runs of rows of so many values each, a run of some two million values at most."""
    step = max(1, (1 << 21) // values)
    return [rows[at : at + step] for at in range(0, len(rows), step)]


def unit(x: np.ndarray) -> np.ndarray:
    x = scaled(x)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _hash(vectors: DataFrame, id_column: str, settings: dict[int, Setting], asking: bool, seed: int) -> DataFrame:
    """(table, bucket, key, vector) of each row and table; if asking, a row for each bucket that is looked into. settings: by width; other widths have the default."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                rows = batch.column(1).to_pylist()
                widths = np.array([len(r) for r in rows], np.int64)
                for width in np.unique(widths).tolist():
                    setting = settings.get(width) or Setting(probes=probes_at(width, 10))
                    count = setting.probes if asking else 1
                    for of in _parts(np.flatnonzero(widths == width), max(width, (count if setting.turns == 1 else count * min(count, 2 * AXES)))):
                        x = unit(np.array([rows[i] for i in of], np.float64))
                        for table in range(setting.tables):
                            buckets = nearest_buckets(x, table, setting, count, seed)
                            n = buckets.shape[1]
                            picked = pa.array(np.repeat(of, n))
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(of) * n, table, np.int32)), pa.array((width * (4 * AXES * AXES) + buckets.reshape(-1)).astype(np.int64)), batch.column(0).take(picked), batch.column(1).take(picked)], ["table", "bucket", "key", "vector"])

    return in_arrow(vectors.select(F.col(id_column).alias("key"), "vector"), run, "table int, bucket long, key long, vector array<double>")


def search(vectors: DataFrame, every: int = 50, k: int = 5, recall: float = 0.95, seed: int = 3, id_column: str = "vec_id", vector_column: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found by cosine of each row whose id is divisible by `every`, among all other rows.

    Vectors that are null, empty or zero, or hold a null or non-finite component, and rows without an id take no
    part; vectors of different widths never meet. Ties go to the smaller id. Fewer than k candidates of the width give
    fewer rows, all of them; an empty table gives none. Rows that repeat an id and a vector count once. `recall` is what
    the trial settles the most common width's tables and probes for, on TRIAL_QUERIES queries; other widths have 12 tables
    of one turn and 10 probes, more beyond AXES dimensions.
    """
    stage = Stage(vectors.sparkSession, "ann")
    v = F.col(vector_column).cast("array<double>")
    x = vectors.select(F.col(id_column).cast("long").alias("id"), v.alias("vector"))
    fine = F.forall("vector", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("vector", lambda c: c != 0)
    x = x.where(F.col("id").isNotNull() & F.col("vector").isNotNull() & fine).withColumn("vector", F.transform("vector", lambda c: c + 0.0))
    # of equal vectors, only the first ids can be among the k nearest
    same = F.struct(F.xxhash64("vector").alias("a"), F.xxhash64("vector", F.lit(5)).alias("b"))
    first = x.withColumn("same", same).withColumn("n", F.dense_rank().over(Window.partitionBy("same").orderBy("id"))).where(F.col("n") <= 2 * (k + 1))
    points = stage.put(first.groupBy("same").agg(F.min(F.struct("id", "vector")).alias("f"), F.array_sort(F.collect_set("id")).alias("ids")).select(F.col("f.id").alias("key"), "f.vector", "ids"))
    queries = stage.put(x.where(F.col("id") % every == 0).groupBy("id", F.xxhash64("vector")).agg(F.first("vector").alias("vector")).select("id", "vector"))

    def chunks(rows: DataFrame) -> dict[tuple[int, int], int]:
        """Blocks of each bucket that is over one; a width has tables times (2 * AXES)^2 buckets at most, whatever the rows."""
        counts = rows.groupBy("table", "bucket").count().where(F.col("count") > BLOCK).collect()
        return {(r["table"], r["bucket"]): math.ceil(r["count"] / BLOCK) for r in counts}

    def dealt(rows: DataFrame, own: dict, other: dict, mine: str, theirs: str) -> DataFrame:
        """Each row to one block of its own side and to all of the other side's."""
        spread = [(t, b, own.get((t, b), 1), other.get((t, b), 1)) for t, b in {*own, *other}]
        if not spread:
            return rows.withColumn(mine, F.lit(0)).withColumn(theirs, F.lit(0))
        sizes = F.broadcast(vectors.sparkSession.createDataFrame(spread, "table int, bucket long, n_own int, n_other int"))
        rows = rows.join(sizes, ["table", "bucket"], "left")
        rows = rows.withColumn(mine, F.pmod(F.xxhash64("key"), F.coalesce("n_own", F.lit(1))).cast("int"))
        return rows.withColumn(theirs, F.explode(F.sequence(F.lit(0), F.coalesce("n_other", F.lit(1)) - 1))).drop("n_own", "n_other")

    wide = 2 * (k + 1)

    def meet(qs: pa.Table, cs: pa.Table) -> pa.Table:
        out: list[list] = [[], [], [], []]
        if qs.num_rows and cs.num_rows:
            width = len(qs.column("vector")[0])
            a, b = (scaled(t.column("vector").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, width)) for t in (qs, cs))
            ids, keys = qs.column("key").to_numpy(), cs.column("key").to_numpy()
            order = np.argsort(keys, kind="stable")
            b, keys = b[order], keys[order]
            alone = cs.column("alone").take(order) if "alone" in cs.column_names else None
            norm = np.sqrt((b * b).sum(1))
            for at in range(0, len(a), 256):
                part = a[at : at + 256]
                s = part @ b.T / norm
                if alone is not None:  # a vector that only the query's own id has can't be a result
                    s[(ids[at : at + 256, None] == alone.fill_null(0).to_numpy()) & alone.is_valid().to_numpy()] = -np.inf
                n = min(wide, s.shape[1])
                near = np.argpartition(-s, n - 1, axis=1)[:, :n] if n < s.shape[1] else np.tile(np.arange(n), (len(part), 1))
                # rows that come up to the last of them, but for the order of summation, stay in too
                edge = np.take_along_axis(s, near, 1).min(1, keepdims=True)
                r, c = np.nonzero((s >= edge - 1e-9 * np.abs(edge)) & (s > -np.inf))
                score = cosines(part[r], b[c])
                pick = np.lexsort((keys[c], -score, r))
                r, c, score = r[pick], c[pick], score[pick]
                place = np.arange(len(r)) - np.searchsorted(r, r)
                keep = place < wide
                for o, values in zip(out, (ids[at + r[keep]], keys[c[keep]], score[keep], place[keep]), strict=True):
                    o.append(values)
        join = lambda p, t: np.concatenate(p) if p else np.zeros(0, t)
        return pa.table({"query_id": pa.array(join(out[0], np.int64)), "key": pa.array(join(out[1], np.int64)), "score": pa.array(join(out[2], np.float64))})

    def nearest(asked: DataFrame, held: DataFrame) -> DataFrame:
        many, visits = chunks(held), chunks(asked)
        left, right = dealt(asked, visits, many, "q", "c"), dealt(held, many, visits, "c", "q")
        met = left.groupBy("table", "bucket", "q", "c").cogroup(right.groupBy("table", "bucket", "q", "c")).applyInArrow(meet, "query_id long, key long, score double")
        best = met.groupBy("query_id", "key").agg(F.max("score").alias("score"))
        few = best.withColumn("n", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "key"))).where(F.col("n") <= wide).drop("n")
        named = few.join(points.select("key", "ids"), "key").withColumn("vec_id", F.explode("ids")).where(F.col("vec_id") != F.col("query_id"))
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        return named.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")

    # the whole width is one bucket
    bucket = F.size("vector").cast("long").alias("bucket")
    everything = points.select(F.lit(-1).alias("table"), bucket, "key", "vector", F.when(F.size("ids") == 1, F.get("ids", F.lit(0))).alias("alone"))
    asking_all = lambda q: q.select(F.lit(-1).alias("table"), bucket, F.col("id").alias("key"), "vector")

    settings: dict[int, Setting] = {}
    common = points.groupBy(F.size("vector").alias("w")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").first()
    if common:
        width, n = common["w"], common["n"]
        own = F.size("vector") == width
        picked = queries.where(own).orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(TRIAL_QUERIES)
        chosen = stage.put(picked)
        best = nearest(asking_all(chosen), everything.where(F.col("bucket") == width)).where(F.col("rank") <= k)
        named = best.join(points.select("vector", F.explode("ids").alias("vec_id")), "vec_id").select("query_id", "rank", "vector").collect()
        asked_for = {r["id"]: r["vector"] for r in chosen.collect()}
        lists: dict[int, list] = {}
        for r in sorted(named, key=lambda r: (r["query_id"], r["rank"])):
            lists.setdefault(r["query_id"], []).append(r["vector"])
        full = [q for q, v in lists.items() if len(v) >= k]
        if full:
            rows = points.where(own).orderBy(F.xxhash64("key", F.lit(seed + 1))).limit(TRIAL_ROWS).select("vector").collect()
            near = np.stack([unit(np.array(lists[q][:k], np.float64)) for q in full])
            settings[width] = settle(unit(np.array([asked_for[q] for q in full], np.float64)), near, unit(np.array([r["vector"] for r in rows], np.float64)), n, recall, seed)

    held = stage.put(_hash(points, "key", settings, False, seed))
    asked = stage.put(_hash(queries, "id", settings, True, seed))
    found = stage.put(nearest(asked, held))
    stage.drop(held, asked)
    enough = found.groupBy("query_id").count().where(F.col("count") >= k).select(F.col("query_id").alias("id"))
    short = stage.put(queries.join(enough, "id", "left_anti"))
    if short.isEmpty():
        return found
    # a width of few candidates has few queries, so those that can't reach k cost little
    whole = everything.join(short.select(bucket).distinct(), "bucket", "left_semi")
    exact = nearest(asking_all(short), whole)
    return found.join(short.select(F.col("id").alias("query_id")).distinct(), "query_id", "left_anti").unionByName(exact)
