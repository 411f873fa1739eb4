"""Licence scans: Aho-Corasick over words finds notice phrases and identifier tags, a shunting-yard parser evaluates the tags' expressions."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import in_arrow

#: The base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Phrases of the method's own and their labels.
NOTICES = {
    "apache license": "apache",
    "apache software license": "apache",
    "mit license": "mit",
    "permission is hereby granted free of charge": "mit",
    "bsd license": "bsd",
    "redistribution and use in source and binary forms": "bsd",
    "mozilla public license": "mpl",
    "lesser general public license": "lgpl",
    "affero general public license": "agpl",
    "gnu general public license": "gnu-gpl",
    "cc by nc": "cc-by-nc",
    "cc by sa": "cc-by-sa",
    "cc by nd": "cc-by-nd",
    "cc0": "cc0",
    "creative commons attribution": "cc-by",
    "public domain": "public-domain",
    "isc license": "isc",
    "eclipse public license": "epl",
    "boost software license": "bsl",
    "proprietary and confidential": "proprietary",
}
TAG = "spdx license identifier"
#: Identifiers of licences that allow reuse without sharing alike.
PERMISSIVE = frozenset("0bsd apache-1.0 apache-1.1 apache-2.0 bsd-1-clause bsd-2-clause bsd-2-clause-patent bsd-3-clause bsd-3-clause-clear bsd-4-clause bsl-1.0 cc-by-1.0 cc-by-2.0 cc-by-2.5 cc-by-3.0 cc-by-4.0 cc0-1.0 isc mit mit-0 ncsa postgresql psf-2.0 python-2.0 unlicense wtfpl x11 zlib".split())
#: Identifiers of other licences, without the endings -only and -or-later.
RECIPROCAL = frozenset("agpl-1.0 agpl-3.0 cc-by-nc-4.0 cc-by-nc-sa-4.0 cc-by-nd-4.0 cc-by-sa-3.0 cc-by-sa-4.0 cddl-1.0 cddl-1.1 epl-1.0 epl-2.0 eupl-1.1 eupl-1.2 gfdl-1.2 gfdl-1.3 gpl-1.0 gpl-2.0 gpl-3.0 lgpl-2.0 lgpl-2.1 lgpl-3.0 mpl-1.0 mpl-1.1 mpl-2.0 osl-3.0".split())
_BINDS = {"or": 1, "and": 2, "with": 3}
_EXPRESSION = re.compile(rb"spdx-license-identifier[ \t]*:[ \t]*([^\r\n]*)", re.IGNORECASE)
_TOKEN = re.compile(r"\s*([()]|[A-Za-z0-9][A-Za-z0-9.+:\-]*)")
#: Upper-case letters to lower case; bytes that stand in no word to a space.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def known(name: str) -> bool:
    """Whether a lower-case identifier, with an exception behind a + or not, is one of the lists or of the licenceref- kind."""
    base = name.split("+")[0]
    base = base.removesuffix("-only").removesuffix("-or-later")
    return base in PERMISSIVE or base in RECIPROCAL or base.startswith("licenseref-")


@dataclass(frozen=True)
class Expression:
    """A parsed expression: its identifiers (an exception stands behind its licence with +), whether it allows permissive reuse, and whether all of it parsed."""

    licences: tuple[str, ...]
    permissive: bool
    whole: bool


def parse_expression(text: str) -> Expression:
    """Shunting-yard over `or` < `and` < `with` and parentheses. A trailing remark or a broken tail is left out, and whole is False."""
    output: list[tuple[frozenset[str], bool]] = []
    marks: list[str] = []
    whole, operand_next, at = True, True, 0

    def reduce() -> None:
        op = marks.pop()
        (a, pa_), (b, pb) = output[-2:]
        del output[-2:]
        if op == "with":
            output.append((frozenset(f"{x}+{y}" for x in a for y in b), pa_))
        else:
            output.append((a | b, pa_ and pb if op == "and" else pa_ or pb))

    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            whole = whole and not text[at:].strip()
            break
        token, name, end = m[1], m[1].lower(), m.end()
        if name in _BINDS:
            if operand_next:
                whole = False
                break
            while marks and marks[-1] != "(" and _BINDS[marks[-1]] >= _BINDS[name]:
                reduce()
            marks.append(name)
            operand_next = True
        elif token == "(":
            if not operand_next:
                whole = False
                break
            marks.append("(")
        elif token == ")":
            if operand_next or "(" not in marks:
                whole = False
                break
            while marks[-1] != "(":
                reduce()
            marks.pop()
        else:
            if not operand_next:
                whole = False
                break
            output.append((frozenset([name]), name.rstrip("+") in PERMISSIVE))
            operand_next = False
        at = end
    if operand_next and marks:  # an operator or bracket at the end has nothing to join
        whole = False
        while marks and (marks[-1] == "(" or operand_next):
            operand_next = operand_next and marks.pop() == "("
    while marks:
        if marks[-1] == "(":
            whole = False
            marks.pop()
        else:
            reduce()
    licences: frozenset[str] = frozenset().union(*(o[0] for o in output)) if output else frozenset()
    return Expression(tuple(sorted(licences)), bool(output) and all(o[1] for o in output), whole and bool(output))


def automaton(phrases: dict[str, tuple[str, bool]]) -> ahocorasick.Automaton:
    """Finds phrases as whole words in text whose words stand between single spaces; a value has the label, whether it is a base one, and the length."""
    a = ahocorasick.Automaton()
    for phrase, (label, base) in phrases.items():
        a.add_word(f" {phrase} ", (label, base, len(phrase) + 1))
    a.make_automaton()
    return a


def scan(text: str, machine: ahocorasick.Automaton) -> tuple[int, int, int | None, int | None, list[str], list[str], float, list[tuple[int, str]], list[Expression]]:
    """n_words, n_base, first_word, last_word, base labels, all labels, score, places (word, label), expressions."""
    raw = text.encode()
    words = raw.translate(_FOLD).split()
    line = f" {b' '.join(words).decode('latin-1')} "  # a character for each byte: bytes of 128 and more are all word characters
    places, base_starts, base, labels, tagged = [], [], set(), set(), False
    for end, (label, is_base, length) in machine.iter(line):
        at = line.count(" ", 0, end - length + 1) - 1
        if label == TAG:
            tagged = True
            continue
        places.append((at, label))
        labels.add(label)
        if is_base:
            base_starts.append(at)
            base.add(label)
    found = []
    if tagged:
        for m in _EXPRESSION.finditer(raw):
            e = parse_expression(m[1].decode("utf-8", "replace"))
            found.append(e)
            labels.update(f"id:{x}" if known(x) else f"unknown-id:{x}" for x in e.licences)
            labels.update(["permissive"] if e.permissive else [])
    # each kind of sign leaves less doubt; a tag that parses, of known licences, leaves least
    sure = lambda e: e.whole and all(map(known, e.licences))
    doubt = 0.4 ** len(base) * 0.3 ** len({x for _, x in places} - base) * 0.05 ** sum(map(sure, found)) * 0.5 ** sum(not sure(e) and bool(e.licences) for e in found)
    return len(words), len(base_starts), min(base_starts, default=None), max(base_starts, default=None), sorted(base), sorted(labels), 1 - doubt, sorted(places), found


def scan_licences(docs: DataFrame, base: dict[str, str] | None = None, notices: dict[str, str] | None = None, with_places: bool = False) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every whole text.

    Words are stretches of letters, digits and characters beyond ASCII, A-Z in lower case. All places count,
    overlapping ones too. labels joins base ones, the method's notices and, as id:..., the identifiers of tag
    expressions (unknown-id:... if in no list); `permissive` stands for an expression that some choice of its licences makes so. A null or
    empty text has no words, no labels and score 0. with_places adds places (word, label). No shuffle.
    """
    phrases = {p: (x, False) for p, x in (NOTICES if notices is None else notices).items()} | {TAG: (TAG, False)} | {p: (x, True) for p, x in (BASE if base is None else base).items()}
    names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"]
    kinds = [pa.int64()] * 5 + [pa.string(), pa.string(), pa.float64()]
    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"
    if with_places:
        names, kinds = [*names, "places"], [*kinds, pa.list_(pa.struct([("word", pa.int64()), ("label", pa.string())]))]
        schema += ", places array<struct<word: long, label: string>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = automaton(phrases)
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                columns: list[list] = [[] for _ in names[1:]]
                for text in batch.column(1):
                    n, n_base, first, last, own, labels, score, places, _ = scan(text.as_py() or "", machine)
                    row = [n, n_base, first, last, ",".join(own), ",".join(labels), score, [{"word": w, "label": x} for w, x in places]]
                    for c, v in zip(columns, row, strict=False):
                        c.append(v)
                yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, columns, kinds[1:])], names)

    return in_arrow(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, schema)
