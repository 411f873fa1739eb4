"""BPE encoding and decoding with a contiguous rank array.

A word's parts lie in one list of boundaries with the rank of each adjacent pair beside it. The loop scans
the ranks for the least, deletes that boundary and refreshes the two neighbouring ranks. That is quadratic in
the word, which is the fastest way for the short words that texts are made of; words of more than LONG parts
go by a heap over a linked list with the same result.

Texts are cut as the tokenizer file says (special tokens first, then NFC, lower case, and the pattern). A
piece never spans white space, so whole space-separated chunks are looked up in a bounded two-generation cache.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import in_arrow

LONG = 48
NONE = 1 << 60
CACHE = 400_000
#: The code points with the Unicode property White_Space.
SPACES = "\t\n\x0b\x0c\r \x85\xa0  -     　"


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte: itself where it is printable Latin-1, else one from 256 on, in order."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class WordBpe:
    """The encoder of one tokenizer file (word-end BPE over bytes)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = [""] * (1 + max([*self.vocab.values(), *self.special.values()]))
        for text, i in [*self.vocab.items(), *self.special.items()]:
            self.tokens[i] = text
        self.numbers = [str(i) for i in range(len(self.tokens))]
        #: left id << 20 | right id -> rank; and for each rank the id of the two joined
        self.pairs: dict[int, int] = {}
        self.made: list[int] = []
        for rank, merge in enumerate(model["merges"]):
            a, b = merge if isinstance(merge, list) else merge.split(" ")
            self.pairs.setdefault(self.vocab[a] << 20 | self.vocab[b], rank)
            self.made.append(self.vocab[a + b])
        alphabet = byte_alphabet()
        self.first = [self.vocab[c] for c in alphabet]
        self.last = [self.vocab[c + self.suffix] for c in alphabet]
        pattern = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")["pattern"]["Regex"]
        self.piece = regex.compile(pattern.replace(r"\s", SPACES))
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.young: dict[str, tuple[int, ...]] = {}
        self.old: dict[str, tuple[int, ...]] = {}

    def word(self, piece: str) -> list[int]:
        data = piece.encode()
        ids = [self.first[b] for b in data]
        ids[-1] = self.last[data[-1]]
        return self._heap(ids) if len(ids) > LONG else self._scan(ids)

    def _scan(self, ids: list[int]) -> list[int]:
        get, made = self.pairs.get, self.made
        ranks = [get(a << 20 | b, NONE) for a, b in zip(ids, ids[1:], strict=False)]
        while ranks and (least := min(ranks)) != NONE:
            at = ranks.index(least)
            ids[at] = new = made[least]
            del ids[at + 1], ranks[at]
            if at < len(ranks):
                ranks[at] = get(new << 20 | ids[at + 1], NONE)
            if at:
                ranks[at - 1] = get(ids[at - 1] << 20 | new, NONE)
        return ids

    def _heap(self, ids: list[int]) -> list[int]:
        n, get, made = len(ids), self.pairs.get, self.made
        after, before = [*range(1, n), -1], [*range(-1, n - 1)]
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := get(ids[i] << 20 | ids[i + 1], NONE)) != NONE]
        heapq.heapify(heap)
        while heap:
            rank, i, a, b = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j < 0 or ids[j] != b:
                continue
            ids[i], ids[j] = new, _ = made[rank], -1
            after[i] = k = after[j]
            if k >= 0:
                before[k] = i
                if (r := get(new << 20 | ids[k], NONE)) != NONE:
                    heapq.heappush(heap, (r, i, new, ids[k]))
            if (h := before[i]) >= 0 and (r := get(ids[h] << 20 | new, NONE)) != NONE:
                heapq.heappush(heap, (r, h, ids[h], new))
        return [i for i in ids if i >= 0]

    def chunk(self, chunk: str) -> tuple[int, ...]:
        """The ids of a stretch of text; a stretch without white space is kept in the cache."""
        text = chunk if unicodedata.is_normalized("NFC", chunk) else unicodedata.normalize("NFC", chunk)
        text = text.replace("Σ", "σ").lower()  # each character by itself: no final sigma
        if text.isalpha():
            return tuple(self.word(text))
        out: list[int] = []
        for piece in self.piece.findall(text):
            ids = self.young.get(piece)
            if ids is None:
                ids = tuple(self.word(piece))
                if len(piece) <= 64:
                    self.young[piece] = ids
            out += ids
        return tuple(out)

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for part in self.cut.split(text) if self.cut and any(s in text for s in self.special) else (text,):
            if part in self.special:
                out.append(self.special[part])
                continue
            if any(c in part for c in "\x1c\x1d\x1e\x1f"):  # split() takes these for spaces, the tokenizer doesn't
                out += self.chunk(part)
                continue
            young, old = self.young, self.old
            for c in part.split():
                ids = young.get(c)
                if ids is None:
                    ids = old.get(c)
                    if ids is None:
                        ids = self.chunk(c)
                    if len(c) <= 64:
                        young[c] = ids
                        if len(young) >= CACHE:
                            self.old, self.young = young, {}
                            young, old = self.young, self.old
                out += ids
        return out

    def decode(self, ids: list[int]) -> str:
        return " ".join(map(self.tokens.__getitem__, ids))


_LOADED: dict[str, WordBpe] = {}


def tokenizer(path: str) -> WordBpe:
    """One encoder for each file and Python worker."""
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


def encode_documents(docs: DataFrame, tokenizer_path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text; with_ids adds ids (array<int>) and decoded (string).

    A null or empty text has no tokens, and the hashes of the empty string. Repeated rows give repeated rows;
    other columns of the input are not read. Runs where the rows are: no shuffle.
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if with_ids else "")
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string()] + ([pa.list_(pa.int32()), pa.string()] if with_ids else [])
    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] + (["ids", "decoded"] if with_ids else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(tokenizer_path)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                columns: list[list] = [[] for _ in names[1:]]
                for text in batch.column(1):
                    ids = bpe.encode(text.as_py() or "")
                    line, decoded = " ".join(map(bpe.numbers.__getitem__, ids)), bpe.decode(ids)
                    row = [len(ids), hashlib.sha256(line.encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest(), ids, decoded]
                    for c, v in zip(columns, row, strict=False):
                        c.append(v)
                yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, columns, kinds[1:])], names)

    return in_arrow(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, schema)


def decode_column(encoded: DataFrame, tokenizer_path: str) -> DataFrame:
    """doc_id, decoded of a table with doc_id and ids (null: the empty string)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(tokenizer_path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bpe.decode(x.as_py() or []) for x in batch.column(1)], pa.string())], ["doc_id", "decoded"])

    return in_arrow(encoded.select(F.col("doc_id").cast("long"), "ids"), run, "doc_id long, decoded string")
