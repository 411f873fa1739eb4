"""MinHash near-duplicates with b-bit signatures.

A document's set holds the hashes of its word 5-grams. Equal sets are one class. Each class has HASHES minima: the
first ones, by bands, give bucket keys; the low BITS bits of all of them, packed, are its signature. In each
bucket the collision-corrected estimate by bit counts says which classes may be similar; classes that hang
together by such estimates are a cluster. Each class' full set then goes to its cluster, where every pair is counted
exactly. The confirmed links' components are the groups.

A large bucket or cluster is dealt to blocks twice, by independent hashes, and pairs meet within blocks. As only
components count, a group of alike classes hangs together after that; its other pairs need no look. What is left
apart from a key's largest component meets that, and itself, in tiles of two blocks, so that no pair is lost.
Nothing lists the pairs of a bucket or cluster: blocks and tiles give one row for each member, its root in a
union-find. There are as many bands as make the chance to miss a pair at the threshold t, (1 - t^4)^bands, at most
MISS: 20 at 0.85, 28 at 0.8. The estimate is held against a bound six standard deviations below the threshold.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import WORD, Stage, fresh, in_arrow, join_split
from motifscan.llm.components import connected_components
from motifscan.llm.hashing import WORDS, U, grouped_column, mix, stretch_hash, stretch_sums, word_hashes, word_spans

ROWS, HASHES, BITS, MISS = 4, 128, 4, 4e-7
#: Classes of one tile's block: of a bucket, and of a cluster; and most shingles of a cluster's block.
BUCKET_BLOCK, CLUSTER_BLOCK, SHINGLES_BLOCK = 1024, 256, 1 << 21
_rng = np.random.default_rng(20)
_A, _B = (_rng.integers(0, 1 << 31, HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1) for _ in range(2))
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_ONES = int("1" * (HASHES * BITS // 4), 16)


def shingle_sets(texts: list[bytes], size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """The texts' sets, sorted, one behind the other, and how many shingles each has. A text of fewer words has one, of all its words."""
    data = np.frombuffer(b"\n".join([b"", *texts, b""]).translate(_FOLD), np.uint8)
    starts, ends = word_spans(data)
    hashes = word_hashes(data, starts, ends)
    text_ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    words = np.diff(np.searchsorted(starts, text_ends + 1), prepend=0)
    first = np.cumsum(words) - words
    count = np.where(words == 0, 0, np.maximum(words - size + 1, 1))
    of = np.repeat(np.arange(len(texts)), count)
    at = np.repeat(first, count) + np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count)
    values = stretch_hash(stretch_sums(hashes, WORDS), at, at + np.repeat(np.minimum(words, size), count), WORDS)
    order = np.lexsort((values, of))
    of, values = of[order], values[order]
    new = np.ones(len(of), bool)
    new[1:] = (of[1:] != of[:-1]) | (values[1:] != values[:-1])
    return values[new], np.bincount(of[new], minlength=len(texts))


def minima(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """HASHES minima (rows) of each non-empty set (columns)."""
    filled = counts[counts > 0]
    first = np.cumsum(filled) - filled
    lo, hi = values.astype(np.uint32), (values >> U(32)).astype(np.uint32)
    out = np.empty((HASHES, len(filled)), np.uint32)
    for i in range(HASHES):
        h = lo * _A[i]
        h += hi * _B[i]
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA6B)
        out[i] = np.minimum.reduceat(h, first) if len(first) else 0
    return out


def pack(low: np.ndarray) -> np.ndarray:
    """Signatures (a row of HASHES * BITS / 8 bytes for each set) of the minima's low bits."""
    n = (low & np.uint32((1 << BITS) - 1)).astype(np.uint8).T
    return (n[:, ::2] << 4) | n[:, 1::2]


def similarity(matches: np.ndarray | int) -> np.ndarray | float:
    """The estimate from the number of equal low bits, corrected for those that are equal by chance."""
    chance = 2.0**-BITS
    return (matches / HASHES - chance) / (1 - chance)


def least_matches(threshold: float) -> int:
    """Equal low bits that a pair at the threshold has but for a chance of about 1e-9."""
    p = threshold + (1 - threshold) * 2.0**-BITS
    return int(HASHES * p - 6 * np.sqrt(HASHES * p * (1 - p)))


def bands_for(threshold: float) -> int:
    return min(HASHES // ROWS, math.ceil(math.log(MISS) / math.log(1 - threshold**ROWS))) if threshold < 1 else 1


def _signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def sign(docs: DataFrame, bands: int) -> DataFrame:
    """doc_id, row (a hash of the text), n, s1, s2 (the set's hash), sig, bands of every row; without a set the last two are null."""
    names = ["doc_id", "row", "n", "s1", "s2", "sig", "bands"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at, group in grouped_column(whole.column(1)):
                values, counts = shingle_sets(group)
                filled, some = counts > 0, np.flatnonzero(counts)
                low = minima(values, counts)
                keys = np.empty((len(some), bands), np.uint64)
                for b in range(bands):
                    h = np.full(len(some), b + 1, np.uint64)
                    for r in range(ROWS):
                        h = mix(h * U(0x9E3779B97F4A7C15) + low[b * ROWS + r])
                    keys[:, b] = h
                first = (np.cumsum(counts) - counts)[some]
                total = [np.zeros(len(group), np.uint64), np.zeros(len(group), np.uint64)]
                if len(some):
                    total[0][some] = np.add.reduceat(mix(values), first)
                    total[1][some] = np.add.reduceat(mix(values ^ U(0xDEADBEEFCAFEF00D)), first)
                place = np.full(len(group), -1)
                place[some] = np.arange(len(some))
                take = pa.array(place, mask=~filled)
                sig = pa.array([s.tobytes() for s in pack(low)], pa.binary()).take(take)
                keyed = pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1) * bands, pa.int32()), pa.array(_signed(keys.reshape(-1)))).take(take)
                yield pa.RecordBatch.from_arrays([whole.column(0).slice(at, len(group)), whole.column(2).slice(at, len(group)), pa.array(counts.astype(np.int64)), pa.array(_signed(total[0])), pa.array(_signed(total[1])), sig, keyed], names)

    return in_arrow(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.xxhash64(F.col("text").cast("string"))), run, "doc_id long, row long, n long, s1 long, s2 long, sig binary, bands array<long>")


class Groups:
    """Union-find over 0..n-1; a root is its group's smallest."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = i = up[up[i]]
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.root(i), self.root(j)
        self.up[max(i, j)] = min(i, j)


def runs(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """The rows of each value of the first `keys` columns, which the input is sorted by."""
    kept: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(keys)]
        change = np.zeros(batch.num_rows, bool)
        for c in cols:
            change[1:] |= c[1:] != c[:-1]
        head = tuple(c[0] for c in cols)
        cuts = np.flatnonzero(change).tolist()
        if kept and head != last:
            yield pa.Table.from_batches(kept)
            kept = []
        for a, b in zip([0, *cuts], cuts, strict=False):
            yield pa.Table.from_batches([*kept, batch.slice(a, b - a)])
            kept = []
        kept.append(batch.slice(cuts[-1] if cuts else 0))
        last = tuple(c[-1] for c in cols)
    if kept:
        yield pa.Table.from_batches(kept)


def _first_look(rows: DataFrame) -> DataFrame:
    """Adds the tiles of each row: the only one of a key of one block, else a block each of two independent dealings."""
    block = lambda seed: F.struct(F.pmod(F.xxhash64("rep", F.lit(seed)), F.col("blocks")).cast("int").alias("i"), F.lit(seed).alias("j"))
    return rows.withColumn("tiles", F.when(F.col("blocks") > 1, F.array(block(0), block(1))).otherwise(F.array(block(0))))


def _second_look(rows: DataFrame, key: str, links: DataFrame, stage: Stage) -> DataFrame | None:
    """Rows and tiles, of keys of many blocks, for those pairs that didn't meet and whose rows don't hang together yet; None if there are none.

    A key's largest component needs no more looks inside: its rows meet the key's other rows only, in blocks, and those meet each other.
    """
    many = stage.put(rows.where("blocks > 1"))
    if many.isEmpty():
        return None
    inner = links.join(many.select(F.col("rep").alias("a")).distinct(), "a", "left_semi")
    found = connected_components(inner, stage).withColumnRenamed("node", "rep")
    placed = stage.put(many.join(found, "rep", "left").withColumn("part", F.coalesce("component", "rep")).drop("component"))
    parts = placed.groupBy(key, "part").agg(F.count("*").alias("c"))
    keys = parts.groupBy(key).agg(F.max_by("part", "c").alias("main"), F.sum("c").alias("all"), F.max("c").alias("most")).where("all > most")
    apart = placed.join(keys, key).withColumn("wide", F.ceil(F.col("blocks") * (F.col("all") - F.col("most")) / F.col("all")).cast("int"))
    tile = lambda i, j: F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"))
    own, place = F.pmod(F.xxhash64("rep", F.lit(9)), F.col("wide")), F.pmod(F.xxhash64("rep", F.lit(9)), F.col("blocks"))
    others, all_main = F.sequence(F.lit(0), F.col("wide") - 1), F.sequence(F.lit(0), F.col("blocks") - 1)
    free = F.concat(F.transform(others, lambda o: tile(F.least(o, own), F.greatest(o, own))), F.transform(all_main, lambda o: tile(own, F.col("wide") + o)))
    tiles = F.when(F.col("part") != F.col("main"), free).otherwise(F.transform(others, lambda o: tile(o, F.col("wide") + place)))
    return stage.put(apart.withColumn("tiles", tiles).drop("part", "main", "all", "most", "wide"))


def _connect(rows: DataFrame, key: str, look: Callable[[DataFrame], DataFrame], stage: Stage) -> DataFrame:
    """Links (a, b) that connect all that `look` links among the rows of a key. rows: rep, key, blocks, and what look needs besides tiles."""
    first = stage.put(look(_first_look(rows)))
    rest = _second_look(rows, key, first, stage)
    return first if rest is None else stage.put(first.unionByName(look(rest)))


def _in_tiles(rows: DataFrame, key: str) -> DataFrame:
    """A row for each tile, each tile's rows together."""
    dealt = rows.withColumn("_tile", F.explode("tiles")).withColumns({"i": F.col("_tile.i"), "j": F.col("_tile.j")}).drop("_tile", "tiles")
    return dealt.repartition(key, "i", "j").sortWithinPartitions(key, "i", "j")


def _likely(batches: Iterator[pa.RecordBatch], threshold: float) -> Iterator[pa.RecordBatch]:
    """Of each tile of a bucket: each class and the root it hangs on by estimates."""
    least, a, b = least_matches(threshold), [], []
    for t in runs(batches, 3):
        n = t.num_rows
        if n < 2:
            continue
        rep, size = t.column("rep").to_pylist(), t.column("n").to_numpy()
        groups = Groups(n)
        if n <= 24:
            sigs = [int.from_bytes(s.as_py()) for s in t.column("sig")]
            for i in range(n):
                for j in range(i):
                    x = sigs[i] ^ sigs[j]
                    x |= x >> 1
                    x |= x >> 2
                    if HASHES - (x & _ONES).bit_count() >= least and min(size[i], size[j]) >= threshold * max(size[i], size[j]):
                        groups.join(i, j)
        else:
            sigs = np.frombuffer(b"".join(t.column("sig").to_pylist()), np.uint64).reshape(n, -1)
            ones = U(0x1111111111111111)
            for i in range(1, n):
                x = sigs[:i] ^ sigs[i]
                x |= x >> U(1)
                x |= x >> U(2)
                near = HASHES - np.bitwise_count(x & ones).sum(1, dtype=np.int64) >= least
                near &= np.minimum(size[:i], size[i]) >= threshold * np.maximum(size[:i], size[i])
                for j in np.flatnonzero(near).tolist():
                    groups.join(i, j)
        for i in range(n):
            if (r := groups.root(i)) != i:
                a.append(rep[i])
                b.append(rep[r])
        if len(a) > 10_000:
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
            a, b = [], []
    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])


def confirm(sets: list[np.ndarray], percent: int) -> Groups:
    """Groups of sets by exact links: 100 * intersection >= percent * union. All pairs count but those that already hang together."""
    n, groups = len(sets), Groups(len(sets))
    size = np.array([len(s) for s in sets], np.int64)
    if n <= 12:
        for i in range(n):
            for j in range(i):
                if 100 * min(size[i], size[j]) >= percent * max(size[i], size[j]) and groups.root(i) != groups.root(j):
                    common = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                    if 100 * common >= percent * (size[i] + size[j] - common):
                        groups.join(i, j)
        return groups
    of = np.repeat(np.arange(n), size)
    _, token, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = times[token] > 1  # what one set alone has can't be common
    number = np.cumsum(times > 1) - 1
    of, token = of[shared], number[token[shared]]
    order = np.argsort(token, kind="stable")
    of, token = of[order], token[order]
    common, wide = np.zeros((n, n), np.float32), 4096
    for lo in range(0, int(token[-1]) + 1 if len(token) else 0, wide):
        a, b = np.searchsorted(token, [lo, lo + wide])
        m = np.zeros((n, wide), np.float32)
        m[of[a:b], token[a:b] - lo] = 1
        common += m @ m.T
    common = np.rint(common).astype(np.int64)
    linked = 100 * common >= percent * (size[:, None] + size[None, :] - common)
    for i, j in zip(*np.nonzero(np.tril(linked, -1)), strict=True):
        groups.join(int(i), int(j))
    return groups


def _number(docs: DataFrame) -> tuple[DataFrame, int | None]:
    """doc_id, text, with numbers above all ids, by a hash of the text, in place of null ids; and the number from which on they are (null: there are none)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    most, some = rows.agg(F.max("doc_id"), F.count_if(F.col("doc_id").isNull())).first()
    if not some:
        return rows, None
    floor = min(-(1 << 63) if most is None else most + 1, (1 << 63) - 1)
    room = min((1 << 63) - floor, (1 << 63) - 1)
    return rows.withColumn("doc_id", F.coalesce("doc_id", F.lit(floor) + F.pmod(F.xxhash64("text"), F.lit(room)))), floor


def near_duplicates(docs: DataFrame, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row.

    Words are lower-cased in A-Z. Two documents are linked if 100 * intersection >= percent * union of their sets
    of word 5-grams; fewer words are one shingle. component_id is the smallest doc_id that links reach; kept says
    that it is the own one. A document without words links with none. Rows that repeat a doc_id are rows of their
    own. Rows without doc_id link others and come after all that have one, by a hash of the text: their component_id is
    null if they reach none, and of those that reach one another alone one text is kept.
    """
    return _verdicts(docs, percent).drop("row", "group")


def _verdicts(docs: DataFrame, percent: int) -> DataFrame:
    """near_duplicates' columns, and row (a hash of the text), and group, which tells components apart (null: no words)."""
    docs, floor = _number(docs)
    stage, threshold = Stage(docs.sparkSession, "neardup"), percent / 100
    signed = stage.put(sign(docs, bands_for(threshold)))
    full = signed.where("n > 0")
    classes = full.groupBy("s1", "s2").agg(F.min("doc_id").alias("doc"), F.count("*").alias("copies"), *(F.first(c).alias(c) for c in ("n", "sig", "bands")))
    # classes are told apart by a hash of their set's; doc_ids won't do, as rows may repeat them
    classes, seed = stage.put(classes), 0
    while not (reps := classes.withColumn("rep", F.xxhash64("s1", "s2", F.lit(seed)))).groupBy("rep").agg(F.count("*").alias("c")).where("c > 1").isEmpty():
        seed += 1  # two classes of one name: other names

    banded = reps.select("rep", F.explode("bands").alias("bucket"))
    buckets = banded.groupBy("bucket").agg(F.count("*").alias("c"), F.sum(F.xxhash64("rep") % (1 << 40)).alias("members"), F.bit_xor(F.xxhash64("rep", F.lit(4))).alias("more")).where("c > 1")
    once = buckets.groupBy("c", "members", "more").agg(F.min("bucket").alias("bucket"))  # buckets of the same members count once
    split = once.select("bucket", F.ceil(F.col("c") / BUCKET_BLOCK).cast("int").alias("blocks"))
    met = stage.put(banded.join(split, "bucket"))
    signatures = reps.select("rep", "n", "sig")

    def alike(rows: DataFrame) -> DataFrame:
        tiled = _in_tiles(rows.join(signatures, "rep").select("bucket", "rep", "n", "sig", "tiles"), "bucket").select("bucket", "i", "j", "rep", "n", "sig")
        return in_arrow(tiled, lambda b: _likely(b, threshold), "a long, b long")

    likely = _connect(met, "bucket", alike, stage)
    stage.drop(met)

    clusters = stage.put(connected_components(likely, stage).withColumnRenamed("node", "rep").withColumnRenamed("component", "cluster"))
    sized = clusters.join(reps.select("rep", "doc", "s1", "s2", "n"), "rep")
    most = sized.groupBy("cluster").agg(F.greatest(F.ceil(F.count("*") / CLUSTER_BLOCK), F.ceil(F.sum("n") / SHINGLES_BLOCK)).cast("int").alias("blocks"))
    members = sized.join(most, "cluster").select("doc", "s1", "s2", "rep", "cluster", "blocks")
    texts = docs.select(F.col("doc_id").alias("doc"), "text")

    def to_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            want = [c.to_numpy(zero_copy_only=False) for c in (whole.column("s1"), whole.column("s2"))]
            for at, group in grouped_column(whole.column("text")):
                values, counts = shingle_sets(group)
                ends = np.cumsum(counts)
                some = np.flatnonzero(counts)
                ok = np.zeros(len(group), bool)
                if len(some):
                    first = (ends - counts)[some]
                    ok[some] = (_signed(np.add.reduceat(mix(values), first)) == want[0][at + some]) & (_signed(np.add.reduceat(mix(values ^ U(0xDEADBEEFCAFEF00D)), first)) == want[1][at + some])
                part = whole.slice(at, len(group))
                sets = pa.ListArray.from_arrays(pa.array(np.append(0, ends), pa.int32()), pa.array(_signed(values)))
                keep = pa.array(ok)
                yield pa.RecordBatch.from_arrays([part.column("cluster"), part.column("rep"), part.column("tiles"), sets], ["cluster", "rep", "tiles", "set"]).filter(keep)

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in runs(batches, 3):
            rep = t.column("rep").to_pylist()
            seen = {r: i for i, r in enumerate(rep)}  # a row may be there twice
            at = sorted(seen.values())
            values = [t.column("set")[i].values.to_numpy().view(np.uint64) for i in at]
            groups = confirm(values, percent)
            pairs = [(rep[at[i]], rep[at[groups.root(i)]]) for i in range(len(at)) if groups.root(i) != i]
            if pairs:
                yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], ["a", "b"])

    def look(rows: DataFrame) -> DataFrame:
        sets = texts.join(rows, "doc").select("text", "s1", "s2", "cluster", "rep", "tiles")
        sets = in_arrow(sets, to_sets, "cluster long, rep long, tiles array<struct<i int, j int>>, set array<long>")
        return in_arrow(_in_tiles(sets, "cluster").select("cluster", "i", "j", "rep", "set"), links, "a long, b long")

    linked = _connect(members, "cluster", look, stage)
    groups = connected_components(linked, stage)
    named = groups.join(reps.select(F.col("rep").alias("node"), "doc", "s1", "s2"), "node")
    least = named.groupBy("component").agg(F.min("doc").alias("component_id"))
    of_class = named.join(least, "component").select("s1", "s2", "component", "component_id")
    whole = stage.put(reps.select("s1", "s2", "doc", "rep", "copies").join(of_class, ["s1", "s2"], "left").select("s1", "s2", "copies", F.coalesce("component", "rep").alias("group"), F.coalesce("component_id", "doc").alias("component_id")))
    signed = signed.select("doc_id", "row", "n", "s1", "s2")
    out = join_split(signed.where("n > 0"), whole, ["s1", "s2"], "copies", signed.count()).select("doc_id", "row", "group", "n", "component_id")
    out = out.unionByName(signed.where("n = 0").select("doc_id", "row", F.lit(None).cast("long").alias("group"), "n", F.col("doc_id").alias("component_id")))
    out = out.select("doc_id", "row", "group", F.col("n").alias("n_shingles"), "component_id").withColumn("kept", F.col("doc_id") == F.col("component_id"))
    if floor is None:
        return out
    return out.withColumns({c: F.when(F.col(c) < floor, F.col(c)) for c in ("doc_id", "component_id")})


def keep_one(docs: DataFrame, percent: int = 85) -> DataFrame:
    """docs, with its columns, less the documents that reach one of a smaller doc_id; of those that share a group's smallest doc_id, or have none, one text stays, once.

    Verdicts go by doc_id and text: different texts of one doc_id fare each by its own. Columns may have any names.
    """
    own, row, gone_id, gone_row = fresh(docs.columns, "id", "row", "gone", "gone_row")
    verdicts = _verdicts(docs, percent)
    marked = docs.withColumns({own: F.col("doc_id").cast("long"), row: F.xxhash64(F.col("text").cast("string"))})
    odd = docs.select(F.col("doc_id").cast("long").alias("doc_id")).groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null")
    if odd.isEmpty():
        gone = verdicts.where(~F.col("kept")).select(F.col("doc_id").alias(gone_id), F.col("row").alias(gone_row))
        return marked.join(gone, (F.col(own) == F.col(gone_id)) & (F.col(row) == F.col(gone_row)), "left_anti").select(*docs.columns)
    # of texts that share their group's smallest doc_id, the one of the smallest hash stays
    first = verdicts.where(F.col("kept") & F.col("group").isNotNull()).groupBy("group").agg(F.min("row").alias("first"))
    gone = verdicts.join(first, "group").where(~F.col("kept") | (F.col("row") != F.col("first"))).select(F.col("doc_id").alias(gone_id), F.col("row").alias(gone_row)).distinct()
    left = marked.join(gone, F.col(own).eqNullSafe(F.col(gone_id)) & (F.col(row) == F.col(gone_row)), "left_anti")
    worded = F.coalesce(F.col("text").cast("string").rlike(WORD), F.lit(False))
    return left.where(~worded).unionByName(left.where(worded).dropDuplicates([own, row])).select(*docs.columns)
