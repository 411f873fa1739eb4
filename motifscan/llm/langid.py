"""Language ID with a linear-chain conditional random field over words.

A word's emission score for a language sums learned weights of its letter trigrams (which reach over its edges),
its first and last letters, and, for the frequent words of the lexicon, the word itself. Learned transitions say
how likely the language changes from a word to the next. Forward-backward gives each word's marginals; a
document's language is the one with the largest mean marginal. All of it is array work over a batch of texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifscan.llm.common import in_arrow, uniform
from motifscan.llm.hashing import BLOCK, grouped, word_hashes, word_spans

TABLE = 1 << 16
#: Words of one chain; longer texts are chains one behind the other, each run with OVERLAP words of its neighbours.
CHAIN = 64
OVERLAP = 16
_LETTER = regex.compile(r"\p{L}")
#: All but letters, by ASCII; bytes of 128 and more count as letters.
_GAP = np.array([not (b >= 128 or 65 <= b <= 90 or 97 <= b <= 122) for b in range(256)])


@dataclass
class Crf:
    """languages; weights of trigrams and affixes (rows TABLE: nothing); the lexicon's sorted hashes and weights; transitions; first word."""

    languages: list[str]
    weights: np.ndarray
    lexicon: np.ndarray
    lexical: np.ndarray
    moves: np.ndarray
    begin: np.ndarray


def _slot(a: np.ndarray, b: np.ndarray, c: np.ndarray, salt: int) -> np.ndarray:
    x = (a.astype(np.uint32) << np.uint32(16)) | (b.astype(np.uint32) << np.uint32(8)) | c
    x = (x + np.uint32(salt)) * np.uint32(0x9E3779B1)
    return (x ^ (x >> np.uint32(15))) & np.uint32(TABLE - 1)


def features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of the words of some texts: the text of each, its trigram slots (all of them, and where each word's begin), its affix slots (2 a word) and its hash."""
    data = np.frombuffer(b"\n".join([b"", *texts, b""]) + b"\n\n", np.uint8)
    starts, ends = word_spans(data, _GAP)
    text_ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    of = np.searchsorted(text_ends, starts - 1, "right")
    clean = np.where(_GAP[data], np.uint8(32), data)
    tri = _slot(clean[:-2], clean[1:-1], clean[2:], 1)
    inside = np.zeros(len(tri), np.int32)  # a word's trigrams begin from the gap before it to its last letter but one
    inside[starts - 1] += 1
    np.subtract.at(inside, np.minimum(ends - 1, len(tri) - 1), 1)
    keep = np.cumsum(inside) > 0
    slots = tri[keep]
    counts = ends - starts
    first = np.cumsum(counts) - counts
    at = np.maximum(ends - 3, starts - 1)
    affix = np.stack([_slot(clean[starts], clean[starts + 1], clean[np.minimum(starts + 2, ends)], 77), _slot(clean[at], clean[at + 1], clean[at + 2], 191)], 1)
    return of, slots, first, affix, word_hashes(clean, starts, ends)


def _emissions(model: Crf, slots: np.ndarray, first: np.ndarray, affix: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    out = np.add.reduceat(model.weights[slots], first, axis=0) if len(first) else np.zeros((0, len(model.languages)), np.float32)
    out += model.weights[affix[:, 0]] + model.weights[affix[:, 1]]
    if len(model.lexicon):
        at = np.minimum(np.searchsorted(model.lexicon, hashes), len(model.lexicon) - 1)
        known = model.lexicon[at] == hashes
        out[known] += model.lexical[at[known]]
    return out


def _chains(of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chain and place in it of each word: a text's words, CHAIN at a time."""
    n = len(of)
    begins = np.flatnonzero(np.diff(of, prepend=-1))
    place = np.arange(n) - np.repeat(begins, np.diff(np.append(begins, n)))
    return np.cumsum(place % CHAIN == 0) - 1, place % CHAIN


def marginals(model: Crf, emissions: np.ndarray, chain: np.ndarray, place: np.ndarray, pairs: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Forward-backward, all chains in step: each word's marginals; if asked, the expected transitions and first labels too."""
    n, k = int(chain[-1]) + 1 if len(chain) else 0, emissions.shape[1]
    length = np.bincount(chain, minlength=n)
    order = np.argsort(-length, kind="stable")  # so that the chains that go on are the first ones
    row = np.empty(n, np.int64)
    row[order] = np.arange(n)
    length, row = length[order], row[chain]
    steps = int(length[0]) if n else 0
    # live[t]: how many chains have more than t words
    live = np.searchsorted(-length, -np.arange(steps + 1), "left")
    e = np.zeros((steps, n, k), np.float32)
    e[place, row] = np.exp(emissions - emissions.max(1, keepdims=True))
    move, begin = np.exp(model.moves).astype(np.float32), np.exp(model.begin).astype(np.float32)
    ahead, back = np.empty_like(e), np.ones_like(e)
    for t in range(steps):
        m = live[t]
        a = (begin if t == 0 else ahead[t - 1, :m] @ move) * e[t, :m]
        ahead[t, :m] = a / a.sum(1, keepdims=True)
    for t in range(steps - 2, -1, -1):
        m = live[t + 1]
        b = (back[t + 1, :m] * e[t + 1, :m]) @ move.T
        back[t, :m] = b / b.sum(1, keepdims=True)
    p = ahead[place, row] * back[place, row]
    p /= p.sum(1, keepdims=True)
    moved, begun = np.zeros((k, k)), np.zeros(k)
    if pairs:
        begun = p[place == 0].sum(0)
        for t in range(steps - 1):
            m = live[t + 1]
            x = ahead[t, :m, :, None] * move * (e[t + 1, :m] * back[t + 1, :m])[:, None, :]
            moved += (x / x.sum((1, 2), keepdims=True)).sum(0)
    return p, moved, begun


def word_marginals(model: Crf, emissions: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Each word's marginals, with the words of its text around its chain taken into account."""
    chain, _ = _chains(of)
    if not len(of):
        return marginals(model, emissions, chain, chain)[0]
    begins = np.flatnonzero(np.diff(chain, prepend=-1))
    ends = np.append(begins[1:], len(of))
    lo = np.maximum(begins - OVERLAP, np.searchsorted(of, of[begins], "left"))
    hi = np.minimum(ends + OVERLAP, np.searchsorted(of, of[begins], "right"))
    n = hi - lo
    which = np.repeat(np.arange(len(n)), n)
    place = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
    word = lo[which] + place
    p, _, _ = marginals(model, emissions[word], which, place)
    return p[(word >= begins[which]) & (word < ends[which])]


def fit(texts: list[str], labels: list[str], rounds: int = 25, lexicon: int = 2000, seed: int = 5) -> Crf:
    """Learns from texts of one language each, cut into spans that are shuffled together so that the language switches inside chains.

    Gradient steps (Adam) on the conditional log-likelihood with a small penalty on the weights.
    """
    languages = sorted(set(labels))
    k, rng = len(languages), np.random.default_rng(seed)
    of, slots, first, affix, hashes = features([t.lower().encode() for t in texts])
    y = np.array([languages.index(x) for x in labels], np.int64)[of] if len(of) else np.zeros(0, np.int64)
    # spans of 6 to 40 words, in random order
    cuts = np.cumsum(rng.integers(6, 41, max(1, len(y) // 6 + 1)))
    begins = np.unique(np.concatenate([[0], cuts[cuts < len(y)], np.flatnonzero(np.diff(of)) + 1])) if len(y) else np.zeros(0, np.int64)
    spans = rng.permutation(len(begins))
    counts = np.diff(np.append(begins, len(y)))
    perm = np.concatenate([np.arange(begins[s], begins[s] + counts[s]) for s in spans]) if len(spans) else np.zeros(0, np.int64)
    words, freq = np.unique(hashes, return_counts=True)
    lex = np.sort(words[np.argsort(-freq, kind="stable")[:lexicon]])
    model = Crf(languages, np.zeros((TABLE + 1, k), np.float32), lex, np.zeros((len(lex), k), np.float32), np.zeros((k, k)), np.zeros(k))
    if k < 2:
        return model
    chain, place = _chains(np.zeros(len(y), np.int64))
    yy = y[perm]
    per_word = np.diff(np.append(first, len(slots)))
    word_of_slot = np.repeat(np.arange(len(y)), per_word)
    at = np.minimum(np.searchsorted(lex, hashes), len(lex) - 1)
    known = np.flatnonzero(lex[at] == hashes)
    seen_moves, inner = np.zeros((k, k)), place[1:] > 0
    np.add.at(seen_moves, (yy[:-1][inner], yy[1:][inner]), 1)
    seen_begin = np.bincount(yy[place == 0], minlength=k)
    params = [model.weights, model.lexical, model.moves, model.begin]
    m1, m2 = [np.zeros_like(p, np.float64) for p in params], [np.zeros_like(p, np.float64) for p in params]
    for step in range(1, rounds + 1):
        emissions = _emissions(model, slots, first, affix, hashes)
        p, moved, begun = marginals(model, emissions[perm], chain, place, True)
        off = np.empty((len(y), k))
        off[perm] = np.eye(k)[yy] - p
        flat = np.concatenate([slots, affix[:, 0], affix[:, 1]]).astype(np.int64)
        from_word = np.concatenate([word_of_slot, np.arange(len(y)), np.arange(len(y))])
        gradients = [
            np.stack([np.bincount(flat, off[from_word, c], TABLE + 1) for c in range(k)], 1),
            np.stack([np.bincount(at[known], off[known, c], len(lex)) for c in range(k)], 1),
            seen_moves - moved,
            seen_begin - begun,
        ]
        for i, (w, g) in enumerate(zip(params, gradients, strict=True)):
            g = g / len(y) - 1e-6 * w
            m1[i] = 0.9 * m1[i] + 0.1 * g
            m2[i] = 0.99 * m2[i] + 0.01 * g * g
            w += (0.3 * (m1[i] / (1 - 0.9**step)) / (np.sqrt(m2[i] / (1 - 0.99**step)) + 1e-8)).astype(w.dtype)
        model.weights[TABLE] = 0
    return model


def label_words(model: Crf, text: str) -> list[tuple[str, str, float]]:
    """(word, language, marginal) of each word of a text."""
    raw = text.lower().encode()
    of, slots, first, affix, hashes = features([raw])
    p = word_marginals(model, _emissions(model, slots, first, affix, hashes), of)
    data = np.frombuffer(raw + b"\n", np.uint8)
    words = [raw[a:b].decode("utf-8", "replace") for a, b in zip(*word_spans(data, _GAP), strict=True)]
    return [(w, model.languages[i], float(x)) for w, i, x in zip(words, p.argmax(1), p.max(1), strict=True)]


def predict(model: Crf, texts: list[str | None]) -> list[tuple[str, float]]:
    """The language and its mean marginal, of each whole text; ("und", 0.0) without a text, a letter or a learned language."""
    k = len(model.languages)
    total, n, pieces, of_piece = np.zeros((len(texts), max(k, 1))), np.zeros(len(texts)), [], []
    wanted = [bool(t) and k > 0 and _LETTER.search(t) is not None for t in texts]
    for i, t in enumerate(texts):
        if not wanted[i]:
            continue
        raw, a = t.lower().encode(), 0
        while a < len(raw):  # a very long text goes piece by piece, cut between words where there are any
            b = a + BLOCK
            b = len(raw) if b >= len(raw) else max(raw.rfind(b" ", a, b), raw.rfind(b"\n", a, b)) + 1 or b
            b = b if b > a else a + BLOCK
            pieces.append(raw[a:b])
            of_piece.append(i)
            a = b
    owner = np.array(of_piece, np.int64)
    for at, group in grouped(pieces):
        of, slots, first, affix, hashes = features(group)
        if not len(of):
            continue
        p = word_marginals(model, _emissions(model, slots, first, affix, hashes), of)
        begins = np.flatnonzero(np.diff(of, prepend=-1))
        doc = owner[at + of[begins]]
        np.add.at(total, doc, np.add.reduceat(p, begins, axis=0))
        np.add.at(n, doc, np.diff(np.append(begins, len(of))))
    out = []
    for i in range(len(texts)):
        if not wanted[i] or not n[i]:
            out.append(("und", 0.0))
        else:
            out.append((model.languages[int(total[i].argmax())], float(min(1.0, total[i].max() / n[i]))))
    return out


def held_out(doc_id: Column) -> Column:
    """Documents that are never learned from: crc32 of the id's decimal digits, modulo 3, is 1."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def learn(docs: DataFrame, sample: int = 150, longest: int = 50_000, languages: int = 1000) -> Crf:
    """Fits on about `sample` different texts of each language, of documents that aren't held out and have a letter, drawn by the text's hash.

    A text gives up to `longest` characters from its first letter on, so the driver gets `languages` * 2 * `sample` such
    pieces at most. More than `languages` different values of lang aren't labels, and an error.
    """
    known = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")) & F.col("text").rlike(r"\p{L}"))
    known = known.select("lang", "text", F.xxhash64("text").alias("mark"))
    counts = known.groupBy("lang").agg(F.approx_count_distinct("mark").alias("n")).limit(languages + 1).collect()
    if not counts:
        return fit([], [])
    if len(counts) > languages:
        raise ValueError(f"lang has more than {languages} different values")
    rate = F.create_map(*(F.lit(x) for r in sorted(counts) for x in (r["lang"], min(1.0, sample / max(1, r["n"])))))
    chance = uniform(F.col("mark"), F.lit("language sample"))
    drawn = known.where(chance < rate[F.col("lang")]).select("lang", "mark", F.substring("text", F.regexp_instr("text", F.lit(r"\p{L}")), F.lit(longest)).alias("text")).dropDuplicates(["lang", "mark"])
    place = F.row_number().over(Window.partitionBy("lang").orderBy(uniform(F.col("mark"), F.lit("language sample")), "mark"))
    rows = drawn.withColumn("place", place).where(F.col("place") <= 2 * sample).select("lang", "text").collect()
    rows.sort(key=lambda r: (r["lang"], r["text"]))
    return fit([r["text"] for r in rows], [r["lang"] for r in rows])


def identify(docs: DataFrame, model: Crf) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every whole text; the prediction sees the text alone.

    `und` with score 0: the text is null, has no letter, or nothing was learned. Repeated rows give repeated rows.
    No shuffle; the model is a few hundred kilobytes whatever the input.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                got = predict(shared.value, batch.column(2).to_pylist())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return in_arrow(docs.select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("string")), run, "doc_id long, held_out boolean, lang_pred string, score double")


def drop_unidentified(docs: DataFrame, model: Crf, least: float = 0.0) -> DataFrame:
    """docs, with its columns, less those without a language: null or letterless texts, and scores under `least`. No shuffle.

    A text that switches evenly among many languages has a low score, so by default none is too low. Where no language
    could be learned, all texts with a letter stay.
    """
    shared, names = docs.sparkSession.sparkContext.broadcast(model), docs.columns
    at = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 512):
                batch = whole.slice(start, 512)
                texts = batch.column(at).to_pylist()
                if shared.value.languages:
                    keep = [lang != "und" and score >= least for lang, score in predict(shared.value, texts)]
                else:
                    keep = [bool(t) and _LETTER.search(t) is not None for t in texts]
                yield batch.filter(pa.array(keep, pa.bool_()))

    return in_arrow(docs, run, docs.schema)
