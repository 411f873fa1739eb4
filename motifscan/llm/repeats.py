"""Substring dedup by recompression: removes what windows of WIDTH words that stand elsewhere too cover.

Rounds of recompression shorten each text: neighbouring symbols merge where they are equal (runs) or the left one
falls into the round's left half of all names and the right one into its right half (pairs). Names are 64-bit
hashes of what a symbol stands for, so they agree in all texts without a table that tasks would have to share. Whether
the edge between two symbols survives a round depends on those two alone, so for every edge the stretch of words is
known that decides it. An edge whose stretch lies inside a window is there in all the window's copies.

A window is represented by its edge of the least key, the hash of the deciding stretch; a window without such an edge
by itself. Equal windows have equal representatives at equal offsets, so only representatives, one for some ten
words, are grouped over the corpus. Where a key occurs twice, its windows are verified: by the hash of the whole
span of windows it represents, or window by window where spans of one key differ. Keys and spans are hashed by two
independent families, so that windows are taken for equal on some 120 bits.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import WORD, Stage, in_arrow, join_split, row_keys
from motifscan.llm.hashing import MORE, WORDS, U, grouped_column, mix, stretch_hash, stretch_sums, word_hashes, word_spans

WIDTH, ROUNDS = 35, 4
_WORD = re.compile(WORD)


def compress(hashes: np.ndarray, of: np.ndarray, sums: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The edges that are left after some rounds: the word each stands before, and the stretch [left, right) that decides it.

    of: the text of each word. An edge that a text's start or end had a part in has a stretch that reaches out of it.
    """
    n = len(hashes)
    at = np.arange(n)
    first = np.ones(n, bool)
    first[1:] = of[1:] != of[:-1]
    left, right = at, at  # to begin with, every word has an edge before it, whatever stands around
    end = np.append(at[1:], n)
    for t in range(rounds):
        last = np.append(first[1:], True)
        names = stretch_hash(sums, at, end, WORDS) if t else hashes
        side = (mix(names ^ U(0x5851F42D4C957F2D * (t + 1) % (1 << 64))) >> U(63)).astype(bool)
        stays = np.ones(len(at), bool)
        stays[1:] = first[1:] | ~((names[1:] == names[:-1]) | (~side[:-1] & side[1:]))
        wide_left = np.where(first, at - 1, np.append(-1, left[:-1]))
        wide_right = np.where(last, end + (t > 0), np.append(right[1:], n + 1))
        at, left, right, first = at[stays], wide_left[stays], wide_right[stays], first[stays]
        end = np.append(at[1:], n)
    return at, left, right


def representatives(hashes: np.ndarray, of: np.ndarray, width: int = WIDTH, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(key, span, s1, s2) of each run of windows, from s1 to s2, with the same representative; span: the hash of all their words."""
    n = len(hashes)
    if n < width:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    sums = stretch_sums(hashes, WORDS)
    start = np.flatnonzero(of[: n - width + 1] == of[width - 1 :])
    at, left, right = compress(hashes, of, sums, rounds)
    inside = (left >= 0) & (right <= n)
    at, left, right = at[inside], left[inside], right[inside]
    key = stretch_hash(sums, left, right, WORDS) ^ mix((at - left).astype(np.uint64) + U(1))
    low, high = np.searchsorted(left, start, "left"), np.searchsorted(right, start + width, "right")
    some = high > low
    chosen = np.full(len(start), -1, np.int64)
    table = np.arange(len(at))
    for k in range(width.bit_length()):
        if k:  # places of the least keys of 2^k edges from each on, the leftmost of equal ones
            half = 1 << (k - 1)
            if len(table) <= half:
                break
            a, b = table[:-half], table[half:]
            table = np.where(key[b] < key[a], b, a)
        w = np.flatnonzero(some & ((high - low) >> k == 1))
        a, b = table[low[w]], table[high[w] - (1 << k)]
        chosen[w] = np.where(key[b] < key[a], b, a)
    alone = chosen < 0
    new = np.ones(len(start), bool)
    new[1:] = alone[1:] | (chosen[1:] != chosen[:-1]) | (start[1:] != start[:-1] + 1)
    begin = np.flatnonzero(new)
    s1, s2, c = start[begin], start[np.append(begin[1:], len(start)) - 1], chosen[begin]
    span = stretch_hash(stretch_sums(hashes, MORE), s1, s2 + width, MORE)
    by_edge = c >= 0
    keys = mix(stretch_hash(sums, s1, s2 + width, WORDS) ^ U(0x2545F4914F6CDD1D))
    keys[by_edge] = key[c[by_edge]]
    span[by_edge] ^= mix((at[c[by_edge]] - s1[by_edge]).astype(np.uint64) + U(77))
    return keys, span, s1, s2


def _words(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all words, the text of each, and where each text's words begin."""
    data = np.frombuffer(b"\n".join([b"", *texts, b""]), np.uint8)
    starts, ends = word_spans(data)
    text_ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    bounds = np.append(0, np.searchsorted(starts, text_ends + 1))
    return word_hashes(data, starts, ends), np.repeat(np.arange(len(texts)), np.diff(bounds)), bounds[:-1]


def _i64(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def removed_ranges(docs: DataFrame, keys: dict[str, Column], width: int = WIDTH, rounds: int = ROUNDS) -> DataFrame:
    """The keys, ranges: the stretches [a, b) of words, as array<struct<a, b>>, that windows which also start elsewhere cover. keys: what tells rows apart, as row_keys has it."""
    stage, ids = Stage(docs.sparkSession, "repeats"), list(keys)
    named = docs.select(*(c.alias(k) for k, c in keys.items()), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    id_types = ", ".join(f"{k} long" for k in ids)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at, group in grouped_column(whole.column("text")):
                hashes, of, begins = _words(group)
                key, span, s1, s2 = representatives(hashes, of, width, rounds)
                text = of[s1] if len(s1) else np.zeros(0, np.int64)
                base, taken = begins[text] if len(s1) else s1, pa.array(at + text)
                yield pa.RecordBatch.from_arrays([_i64(key), _i64(span), *(whole.column(k).take(taken) for k in ids), pa.array((s1 - base).astype(np.int32)), pa.array((s2 - base).astype(np.int32))], ["key", "span", *ids, "s1", "s2"])

    # a row that repeats an id with the same text is a document of its own, but has the same answer
    rows = stage.put(in_arrow(named, find, f"key long, span long, {id_types}, s1 int, s2 int"))
    twice = rows.groupBy("key").agg(F.count("*").alias("c"), F.min("span").alias("x"), F.max("span").alias("y")).where("c > 1")
    twice = stage.put(twice.select("key", "c", (F.col("x") == F.col("y")).alias("same")))
    live = stage.put(join_split(rows, twice, ["key"], "c", rows.count()))
    stage.drop(rows, twice)

    # keys of one span: all its windows are elsewhere too. Other keys: each different span's windows, by one copy of it
    mixed = live.where("not same").groupBy("key", "span").agg(F.count("*").alias("c"), F.min(F.struct(*ids, "s1", "s2")).alias("at"))
    mixed = stage.put(mixed.select("key", "span", "c", *(f"at.{k}" for k in ids), "at.s1", "at.s2"))
    wanted = mixed.groupBy(*ids).agg(F.collect_list(F.struct("key", "span", F.least("c", F.lit(2)).cast("int").alias("c"), "s1", "s2")).alias("spans"))

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            lists = whole.column(1)
            for at, group in grouped_column(whole.column(0)):
                hashes, _, begins = _words(group)
                part = lists.slice(at, len(group))
                flat = part.flatten()
                key, span, c, s1, s2 = (flat.field(i).to_numpy(zero_copy_only=False) for i in range(5))
                base = np.repeat(begins, np.diff(part.offsets.to_numpy()))
                n = (s2 - s1 + 1).astype(np.int64)
                off = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                s = np.repeat(base + s1, n) + off
                one, two = (_i64(stretch_hash(stretch_sums(hashes, p), s, s + width, p)) for p in (WORDS, MORE))
                yield pa.RecordBatch.from_arrays([one, two, *(pa.array(np.repeat(x, n)) for x in (key, span, c)), pa.array(off.astype(np.int32))], ["one", "two", "key", "span", "c", "off"])

    texts = named.join(wanted, ids).select("text", "spans")
    each = stage.put(in_arrow(texts, windows, "one long, two long, key long, span long, c int, off int"))
    often = stage.put(each.groupBy("one", "two").agg(F.sum("c").alias("times"), F.count("*").alias("n")).where("times > 1").drop("times"))
    hits = join_split(each.where("c = 1"), often, ["one", "two"], "n", each.count(), "left_semi").groupBy("key", "span").agg(F.collect_set("off").alias("offs"))
    verdict = stage.put(mixed.select("key", "span", "c").join(hits, ["key", "span"], "left").where("c > 1 or offs is not null").select("key", "span", "c", (F.col("c") > 1).alias("whole"), "offs"))
    stage.drop(mixed, each, often)
    full = F.array(F.struct(F.col("s1").alias("a"), (F.col("s2") + width).alias("b")))
    some = F.transform("offs", lambda o: F.struct((F.col("s1") + o).alias("a"), (F.col("s1") + o + width).alias("b")))
    sure = live.where("same").select(*ids, full.alias("r"))
    other = join_split(live.where("not same"), verdict, ["key", "span"], "c", live.count()).select(*ids, F.when(F.col("whole"), full).otherwise(some).alias("r"))
    return sure.unionByName(other).groupBy(*ids).agg(F.flatten(F.collect_list("r")).alias("ranges"))


def dedup_substrings(docs: DataFrame, width: int = WIDTH, rounds: int = ROUNDS, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row; with_text adds kept, the words that are left, joined by spaces.

    Words stay as they are. A word goes if a window of `width` consecutive words that covers it starts anywhere else
    too, in the same text or another; all is judged on the input. A null or empty text has no words. Rows that repeat
    or lack a doc_id are documents of their own, each cut by its own text.
    """
    keys = row_keys(docs)
    ranges = removed_ranges(docs, keys, width, rounds)
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(c.alias(k) for k, c in keys.items()), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    names = ["doc_id", "n_words", "n_removed", "kept_sha256"] + ["kept"] * with_text

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                out: list[list] = [[], [], [], []]
                for text, spans in zip(batch.column(1), batch.column(2), strict=True):
                    words = _WORD.findall(text.as_py())
                    n, gone = len(words), 0
                    if spans.is_valid and n:
                        depth = np.zeros(n + 1, np.int32)
                        v = spans.values
                        a, b = (np.minimum(v.field(i).to_numpy(), n) for i in (0, 1))
                        np.add.at(depth, a, 1)
                        np.subtract.at(depth, b, 1)
                        stay = np.cumsum(depth[:-1]) == 0
                        words = [words[i] for i in np.flatnonzero(stay).tolist()]
                        gone = n - len(words)
                    kept = " ".join(words)
                    for o, x in zip(out, (n, gone, hashlib.sha256(kept.encode()).hexdigest(), kept), strict=True):
                        o.append(x)
                cols = [batch.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.string())] + ([pa.array(out[3], pa.string())] if with_text else [])
                yield pa.RecordBatch.from_arrays(cols, names)

    joined = named.join(ranges, list(keys), "left").select("doc_id", "text", "ranges")
    return in_arrow(joined, cut, "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept string" * with_text)
