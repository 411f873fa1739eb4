"""Mixing sources to target weights by pivotal dependent rounding. DataFrame operations only.

A source's target over its size is the number of copies each of its documents should have on average. The whole
part is given to all; the fractional parts are rounded by pairs: words are moved at random from one document of a
pair to the other, with both expectations kept, until one of the two is at 0 or 1. The pair's words stay the same,
so a source's words stay at its target but for what the last document of all is rounded by. Groups of at most
GROUP documents each leave one document that is still fractional; these meet in groups again, level by level, in
a reduction tree whose depth is the logarithm of the largest source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifscan.llm.common import WORD, Stage, fresh, uniform

GROUP = 64
_EPS = 1e-9

#: One step: the document in hand (acc) meets the next one (x). up: acc gains what x loses.
_STEP = f"""
aggregate(items, named_struct('k', -1, 'p', 0D, 'w', 0D, 'ones', cast(array() as array<int>)), (acc, x) -> CASE
  WHEN acc.k < 0 THEN named_struct('k', x.k, 'p', x.p, 'w', x.w, 'ones', acc.ones)
  WHEN x.u * (least((1 - acc.p) * acc.w, x.p * x.w) + least(acc.p * acc.w, (1 - x.p) * x.w)) < least(acc.p * acc.w, (1 - x.p) * x.w) THEN
    CASE WHEN abs((1 - acc.p) * acc.w - x.p * x.w) <= {_EPS} THEN named_struct('k', -1, 'p', 0D, 'w', 0D, 'ones', concat(acc.ones, array(acc.k)))
         WHEN (1 - acc.p) * acc.w < x.p * x.w THEN named_struct('k', x.k, 'p', x.p - (1 - acc.p) * acc.w / x.w, 'w', x.w, 'ones', concat(acc.ones, array(acc.k)))
         ELSE named_struct('k', acc.k, 'p', acc.p + x.p * x.w / acc.w, 'w', acc.w, 'ones', acc.ones) END
  ELSE
    CASE WHEN abs(acc.p * acc.w - (1 - x.p) * x.w) <= {_EPS} THEN named_struct('k', -1, 'p', 0D, 'w', 0D, 'ones', concat(acc.ones, array(x.k)))
         WHEN acc.p * acc.w < (1 - x.p) * x.w THEN named_struct('k', x.k, 'p', x.p + acc.p * acc.w / x.w, 'w', x.w, 'ones', acc.ones)
         ELSE named_struct('k', acc.k, 'p', acc.p - (1 - x.p) * x.w / acc.w, 'w', acc.w, 'ones', concat(acc.ones, array(x.k))) END
  END)
"""


def words(text: str | Column = "text") -> Column:
    """The number of words. Each becomes one character and the rest goes, so that no array of a text's words is made."""
    text = F.col(text).cast("string") if isinstance(text, str) else text
    marks = F.translate(F.regexp_replace(text, WORD, "x"), " \t\n\x0b\f\r", "")
    return F.coalesce(F.length(marks), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """source, s (its place by code point, null last), n, source_size, target; from rows (source, size).

    `share` of all sizes is shared by the weights, which repeat along the sources; a target stops at `cap` times its
    source's size, and what is over goes to the others by weight until none is above. In closed form: sources in
    order of cap by weight are full until the level of those that remain is below the next one's.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n"))
    # windows over rows as many as there are sources
    placed = per.withColumn("s", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    placed = placed.withColumn("weight", F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.col("s") % len(weights) + 1).cast("int"))).withColumn("most", F.col("source_size") * cap)
    order = Window.orderBy(F.col("most") / F.col("weight"), "s")
    before, whole = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.sum("source_size").over(whole) * share - F.coalesce(F.sum("most").over(before), F.lit(0.0))
    level = left / (F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    full = placed.withColumn("level", level).withColumn("open", F.col("level") * F.col("weight") <= F.col("most"))
    at = F.min(F.when(F.col("open"), F.struct(F.col("most") / F.col("weight"), F.col("s"), F.col("level")))).over(whole).getItem("level")
    return full.withColumn("target", F.least(F.coalesce(at * F.col("weight"), F.col("most")), F.col("most"))).select("source", "s", "n", "source_size", "target")


def _round_groups(rows: DataFrame, level: int, seed: int) -> DataFrame:
    """Rows (s, g, parent, k, p, w): g, k names a document, parent its group on this level. Returns s, g, k, p: 0 or 1, but for at most one document of a group."""
    item = F.struct((-F.col("w")).alias("order"), "g", F.col("k").alias("place"), "p", "w")
    grouped = rows.groupBy("s", "parent").agg(F.array_sort(F.collect_list(item)).alias("raw"))
    numbered = F.transform("raw", lambda x, i: F.struct(i.alias("k"), x["p"].alias("p"), x["w"].alias("w"), uniform(F.lit(seed), F.lit(level), F.col("s"), x["g"], x["place"], i).alias("u"), x["g"].alias("g"), x["place"].alias("place")))
    done = grouped.withColumn("items", numbered).withColumn("end", F.expr(_STEP))
    return done.select("s", F.explode(F.transform("items", lambda x: F.struct(x["g"].alias("g"), x["place"].alias("k"), F.when(x["k"] == F.col("end.k"), F.col("end.p")).when(F.array_contains("end.ones", x["k"]), 1.0).otherwise(0.0).alias("p"), x["w"].alias("w")))).alias("o")).select("s", "o.g", "o.k", "o.p", "o.w")


def plan_mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, cap: float = 2.0, seed: int = 11, keep: tuple[Column, ...] = ()) -> DataFrame:
    """doc_id, size, source_size, target, taken: how many words of each document the mix takes, repeats counted.

    size counts the words of the text (null: none). taken is a whole number of copies times size; a document of no
    words has 0. No document has more than the next whole number above its source's copies, so `cap` whole copies at
    most. A source's words differ from its target by less than one document. Reruns agree, as all chance comes from
    hashes of the places; rows equal in all columns are interchangeable. `keep` adds columns to the result, under names of the caller's that the columns above and s, n, g, k, p, mark, bucket, row, whole, extra don't have.
    """
    stage = Stage(docs.sparkSession, "mixing")
    sized = stage.put(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words().alias("size"), F.xxhash64(F.col("text").cast("string")).alias("mark"), *keep))
    kept = sized.columns[4:]
    targets = stage.put(source_targets(sized, weights, share, cap))
    rows = sized.withColumnRenamed("source", "_own").join(targets, F.col("_own").eqNullSafe(F.col("source"))).drop("_own", "source")
    rows = rows.withColumn("copies", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)).withColumn("whole", F.floor(F.col("copies") + _EPS)).withColumn("p", F.col("copies") - F.col("whole"))
    settled = (F.col("p") <= _EPS) | (F.col("size") == 0)
    wide = F.greatest(F.ceil(F.col("n") / GROUP), F.lit(1))
    bucket = F.floor(uniform("doc_id", "mark", F.lit(seed)) * wide)
    inside = Window.partitionBy("s", "bucket").orderBy(F.desc("size"), "doc_id", "mark", *kept)
    split = rows.where(~settled).withColumn("bucket", bucket).withColumn("row", F.row_number().over(inside) - 1)
    # a bucket of more than twice the mean, as of rows that repeat an id and a text, is split on
    split = stage.put(split.withColumn("g", F.col("bucket") + F.floor(F.col("row") / (2 * GROUP)) * wide).withColumn("k", (F.col("row") % (2 * GROUP)).cast("int")).drop("bucket", "row", "copies"))
    now = stage.put(_round_groups(split.select("s", "g", F.col("g").alias("parent"), "k", "p", F.col("size").cast("double").alias("w")), 0, seed))
    parts, level = [now.where((F.col("p") <= 0) | (F.col("p") >= 1))], 1
    last = now.agg(F.max("g")).first()[0]
    open_rows = now.where((F.col("p") > 0) & (F.col("p") < 1))
    reach = GROUP
    while last:
        merged = stage.put(_round_groups(open_rows.withColumn("parent", F.floor(F.col("g") / reach)).select("s", "g", "parent", "k", "p", "w"), level, seed))
        parts.append(merged.where((F.col("p") <= 0) | (F.col("p") >= 1)))
        open_rows = merged.where((F.col("p") > 0) & (F.col("p") < 1))
        last, reach, level = last // GROUP, reach * GROUP, level + 1
    parts.append(open_rows.withColumn("p", F.when(uniform(F.lit(seed), F.lit(-1), "s", "g", "k") < F.col("p"), 1.0).otherwise(0.0)))
    extra = parts[0]
    for p in parts[1:]:
        extra = extra.unionByName(p)
    chosen = split.join(extra.select("s", "g", "k", F.col("p").alias("extra")), ["s", "g", "k"])
    out = ["doc_id", "size", "source_size", "target"]
    one = chosen.select(*out, ((F.col("whole") + F.col("extra")) * F.col("size")).cast("long").alias("taken"), (F.col("whole") + F.col("extra")).cast("long").alias("copies"), *kept)
    other = rows.where(settled).select(*out, (F.col("whole") * F.col("size")).cast("long").alias("taken"), F.when(F.col("size") > 0, F.col("whole")).otherwise(0).cast("long").alias("copies"), *kept)
    return one.unionByName(other)


def mix_documents(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, cap: float = 2.0, seed: int = 11) -> DataFrame:
    """The mix itself: each document as many times as it is taken, with the columns of docs; documents of no words go.

    Rows equal in all columns get their copies together. Columns may have any names.
    """
    columns = [F.col(f"`{c}`") for c in docs.columns]
    a, b, times, n, copy = fresh(docs.columns, "a", "b", "copies", "n", "copy")
    marked = docs.withColumns({a: F.xxhash64(*columns), b: F.xxhash64(F.lit(5), *columns)})
    plan = plan_mix(docs, weights, share, cap, seed, keep=(F.xxhash64(*columns).alias("_a"), F.xxhash64(F.lit(5), *columns).alias("_b")))
    per = plan.groupBy(F.col("_a").alias(a), F.col("_b").alias(b)).agg(F.sum("copies").alias(times), F.count("*").alias(n))
    copies = Stage(docs.sparkSession, "mixed").put(per.where(F.col(times) > 0))
    if not copies.where(F.col(n) > 1).isEmpty():
        marked = marked.dropDuplicates([a, b])
    taken = marked.join(copies.drop(n), [a, b])
    return taken.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times).cast("int")))).select(*docs.columns)
