"""Line dedup by a deletion-neighbourhood join. DataFrame operations only.

Two lines are within one edit (a character replaced, added or left out) exactly if deleting one character from
the longer, or from each of two of a length at the same place, makes them equal. So every variant with one
character deleted is hashed as a key, equal keys meet, and the earliest line of a key is kept. A line has as many
variants as characters, so the places worth deleting are narrowed first: with one edit, all before or all behind
the middle is equal; then one of FANOUT blocks has all before and all behind it equal; and so on. Only spans
whose outside another line shares go on, which loses no pair. No step lists pairs: every step is an aggregate by key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import Stage, fresh, join_split, row_keys

FANOUT = 16
#: Spans of at most so many characters get all their deletion variants.
NARROW = 40
#: Lines may differ by one edit from so many characters on; shorter ones go only if they are equal, as one edit makes another word of them.
NEAR_CHARS = 8


def _hash(*parts: Column | str) -> Column:
    return F.xxhash64(*parts)


def _lines(docs: DataFrame, keys: dict[str, Column]) -> DataFrame:
    """The keys, at, line, of lines that aren't empty or of spaces alone."""
    lines = docs.select(*(c.alias(k) for k, c in keys.items()), F.posexplode(F.split(F.col("text").cast("string"), "\n")).alias("at", "line"))
    return lines.where(F.trim("line") != "")


def _spread(span: DataFrame) -> DataFrame:
    """Rows (h, m, lo, hi): within a pair whose shorter line has m characters, the edit lies in [lo, hi). Adds a row for each of FANOUT blocks of a wide span."""
    width = F.greatest(F.ceil((F.col("hi") - F.col("lo")) / FANOUT), F.lit(1)).cast("int")
    blocks = F.transform(F.sequence(F.col("lo"), F.greatest(F.col("hi") - 1, F.col("lo")), width), lambda a: F.struct(a.alias("lo"), F.least(a + width, F.col("hi")).alias("hi")))
    return span.withColumn("b", F.explode(blocks)).drop("lo", "hi").select("*", "b.lo", "b.hi").drop("b")


def find_near_lines(docs: DataFrame, keys: dict[str, Column], near_chars: int = NEAR_CHARS) -> DataFrame:
    """The keys, at of each line to remove, and first_doc, first_at of an earlier line that it repeats (edits: 0 or 1).

    Order is by doc_id (null first), among texts of one id or of none by their hash, and by place in the text. A line goes if an earlier line, kept or not, is equal
    or, where both have near_chars characters at least, within one edit; that bound is fixed. Empty lines and lines of
    spaces alone always stay. Rows of equal doc_id and text count as one document: their lines at equal places aren't
    earlier than each other.
    """
    stage = Stage(docs.sparkSession, "lines")
    lines = _lines(docs, keys).withColumn("h", F.struct(_hash("line").alias("a"), _hash("line", F.lit(17)).alias("b")))
    ref = F.struct(*keys, "at").alias("ref")
    first = stage.put(lines.select("h", ref).groupBy("h").agg(F.min("ref").alias("ref"), F.count("*").alias("n")))

    # halves: a line shares all before the cut or all behind it; lines of m and m + 1 characters use the same cut
    size = F.length("line")
    klass = F.floor(F.col("l") / 16).cast("int")
    cut = F.col("class") * 8
    keyed = lines.where(size >= near_chars).withColumn("size", size).withColumn("l", F.explode(F.when(F.col("size") % 16 == 0, F.array(F.col("size"), F.col("size") - 1)).otherwise(F.array("size")))).withColumn("class", klass)
    # what is before and behind the cut of lines of the lowest class is empty: all of these go on, on one side
    halves = keyed.withColumn("side", F.explode(F.when(F.col("class") > 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))))
    part = F.when(F.col("side") == 0, F.expr("substring(line, 1, class * 8)")).otherwise(F.expr("right(line, class * 8)"))
    key = F.when(F.col("class") > 0, _hash("class", "side", part))
    # of equal lines the first one speaks for all, so that frequent lines are few rows from here on
    halves = stage.put(halves.select("h", ref, "side", "class", key.alias("key")).groupBy("h", "side", "class", "key").agg(F.min("ref").alias("ref")))
    shared = stage.put(halves.where("key is not null").groupBy("key").agg(F.count("*").alias("c")).where("c > 1"))
    alive = stage.put(join_split(halves.where("key is not null"), shared, ["key"], "c", halves.count(), "left_semi").unionByName(halves.where("key is null")).drop("key"))
    stage.drop(halves, shared)

    # the text of those lines, at their first places
    places = alive.select("h", "ref").groupBy("h").agg(F.min("ref").alias("ref")).groupBy(*(F.col(f"ref.{k}").alias(k) for k in keys)).agg(F.collect_list(F.struct(F.col("ref.at").alias("at"), "h")).alias("wanted"))
    texts = docs.select(*(c.alias(k) for k, c in keys.items()), F.col("text").cast("string").alias("text")).join(places, list(keys))
    found = texts.select(*keys, F.split("text", "\n").alias("all"), F.explode("wanted").alias("w")).select(*keys, "w.at", "w.h", F.get("all", F.col("w.at")).alias("line"))
    found = found.where(F.struct(_hash("line").alias("a"), _hash("line", F.lit(17)).alias("b")) == F.col("h"))
    text = stage.put(found.groupBy("h").agg(F.min(F.struct(*keys, "at", "line")).alias("f")).select("h", F.struct(*(f"f.{k}" for k in keys), "f.at").alias("ref"), "f.line").withColumn("size", F.length("line")))

    # spans in which the edit can lie, for the pair's shorter length m
    roles = F.explode(F.array(F.col("size"), F.col("size") - 1)).alias("m")
    span = alive.select("h", "side", "class").join(text.select("h", "size"), "h").select("h", "side", "class", "size", roles).where(F.floor(F.col("m") / 16) == F.col("class"))
    span = span.select("h", "size", "m", F.when(F.col("side") == 0, cut).otherwise(0).cast("int").alias("lo"), F.when(F.col("side") == 0, F.col("m")).otherwise(F.col("m") - cut).cast("int").alias("hi"))
    span = stage.put(span)
    wide = F.col("hi") - F.col("lo") > NARROW
    most = span.agg(F.max(F.col("hi") - F.col("lo"))).first()[0] or 0
    while most > NARROW:
        old, blocks = span, _spread(span.where(wide))
        tried = blocks.join(text.select("h", "line"), "h").select("h", "size", "m", "lo", "hi", _hash("m", "lo", "hi", F.expr("substring(line, 1, lo)"), F.expr("right(line, m - hi)")).alias("key"))
        tried = stage.put(tried)
        shared = stage.put(tried.groupBy("key").agg(F.min("h").alias("x"), F.max("h").alias("y"), F.max(F.col("size") == F.col("m")).alias("short"), F.count("*").alias("c")).where("x != y and short").select("key", "c"))
        span = stage.put(span.where(~wide).unionByName(join_split(tried, shared, ["key"], "c", tried.count(), "left_semi").drop("key")))
        stage.drop(tried, shared, old)
        most = -(-most // FANOUT)

    # every deletion variant of what is left: of both lines at one place, or of the longer one only
    ready = span.join(text, ["h", "size"])
    swap = ready.where("size = m and hi > lo").select("h", "ref", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("i"), "line", "size", "m").select("h", "ref", F.lit(True).alias("short"), F.lit("swap").alias("kind"), _hash("i", F.expr("substring(line, 1, i)"), F.expr("right(line, size - i - 1)")).alias("a"), _hash(F.lit(3), "i", F.expr("substring(line, 1, i)"), F.expr("right(line, size - i - 1)")).alias("b"))
    drop = ready.where("size = m + 1").select("h", "ref", F.explode(F.sequence("lo", "hi")).alias("i"), "line", "size").select("h", "ref", F.lit(False).alias("short"), F.lit("drop").alias("kind"), F.concat(F.expr("substring(line, 1, i)"), F.expr("right(line, size - i - 1)")).alias("v")).select("h", "ref", "short", "kind", _hash("v").alias("a"), _hash(F.lit(3), "v").alias("b"))
    plain = ready.where("size = m").select("h", "ref", F.lit(True).alias("short"), F.lit("drop").alias("kind"), _hash("line").alias("a"), _hash(F.lit(3), "line").alias("b")).distinct()
    variants = stage.put(swap.unionByName(drop).unionByName(plain))
    stage.drop(alive, span)
    best = variants.groupBy("kind", "a", "b").agg(F.min("ref").alias("any"), F.min(F.when(F.col("short"), F.col("ref"))).alias("of_short"), F.min(F.when(~F.col("short"), F.col("ref"))).alias("of_long"), F.count("*").alias("c")).where("c > 1")
    partner = F.when(F.col("kind") == "swap", F.col("any")).when(F.col("short"), F.col("of_long")).otherwise(F.col("of_short"))
    linked = variants.join(best, ["kind", "a", "b"]).withColumn("partner", partner).where(F.col("partner") < F.col("ref")).groupBy("h", "ref").agg(F.min("partner").alias("partner"))
    checked = linked.join(text.select("h", "line"), "h").join(text.select(F.col("ref").alias("partner"), F.col("line").alias("other")), "partner").where(F.levenshtein("line", "other", 1) >= 0).select("h", "partner")
    near = stage.put(checked)
    stage.drop(text, variants)

    # first places go by their partner, later ones by the first
    verdict = first.join(near, "h", "left").where("n > 1 or partner is not null")
    verdict = stage.put(verdict.select(F.col("h.a").alias("a"), F.col("h.b").alias("b"), "n", F.col("ref").alias("first"), "partner"))
    gone = join_split(lines.select("h.a", "h.b", *keys, "at", ref), verdict, ["a", "b"], "n", first.agg(F.sum("n")).first()[0] or 0)
    stage.drop(first, near)
    gone = gone.withColumn("to", F.when(F.col("ref") != F.col("first"), F.col("first")).otherwise(F.col("partner"))).where(F.col("to").isNotNull())
    return gone.select(*keys, "at", F.col("to.doc").alias("first_doc"), F.col("to.at").alias("first_at"), (F.col("ref") == F.col("first")).cast("int").alias("edits"))


def _removed(docs: DataFrame, keys: dict[str, Column], near_chars: int) -> DataFrame:
    return find_near_lines(docs, keys, near_chars).groupBy(*keys).agg(F.sort_array(F.collect_set("at")).alias("removed"), F.count_if(F.col("edits") == 1).alias("near"))


def dedup_report(docs: DataFrame, near_chars: int = NEAR_CHARS) -> DataFrame:
    """doc_id, n_lines, n_removed, n_near, removed (places of the removed lines, comma-joined). A null text has no lines; an empty one has one."""
    keys = row_keys(docs)
    count = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(c.alias(k) for k, c in keys.items()), F.coalesce(F.size(F.split(F.col("text").cast("string"), "\n")), F.lit(0)).cast("long").alias("n_lines"))
    count = count.withColumn("n_lines", F.greatest("n_lines", F.lit(0)))
    out = count.join(_removed(docs, keys, near_chars), list(keys), "left")
    return out.select("doc_id", "n_lines", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce("near", F.lit(0)).alias("n_near"), F.coalesce(F.array_join("removed", ","), F.lit("")).alias("removed"))


def dedup_lines(docs: DataFrame, near_chars: int = NEAR_CHARS, size_column: str | None = None) -> DataFrame:
    """docs, with its columns, less the repeated lines of each text; a null text stays null. size_column, if there, is set to the new text's length. Columns may have any names."""
    keys = row_keys(docs)
    own, (removed, *theirs) = fresh(docs.columns, *(f"of_{k}" for k in keys)), fresh(docs.columns, "removed", *keys)
    gone = _removed(docs, keys, near_chars).select(*(F.col(k).alias(t) for k, t in zip(keys, theirs, strict=True)), F.col("removed").alias(removed))
    kept = F.array_join(F.filter(F.split(F.col("text").cast("string"), "\n"), lambda _, i: ~F.array_contains(removed, i)), "\n")
    out = docs.withColumns(dict(zip(own, keys.values(), strict=True))).join(gone, [F.col(o) == F.col(t) for o, t in zip(own, theirs, strict=True)], "left")
    out = out.withColumn("text", F.when(F.col(removed).isNull(), F.col("text")).otherwise(kept))
    if size_column in docs.columns:
        out = out.withColumn(size_column, F.when(F.col(removed).isNull(), F.col(size_column)).otherwise(F.length("text").cast("long")))
    return out.select(*docs.columns)
