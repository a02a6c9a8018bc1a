"""Licence scans: identifier tags, notice phrases, and licence expressions.

One Aho-Corasick automaton holds every phrase as its words with a blank on either side, and runs over a text's words joined by
single blanks, so a hit is always whole words in a row and hits may overlap. Where the words of an identifier tag occur, the text
itself is read for the expression behind the tag; a shunting-yard parser turns it into postfix order and evaluates `and`, `or`
and `with`. What the expressions allow is returned and decides the score: several expressions of one text hold together, so
the worst of them counts; without any, the worst of the licences that notices name.

Words are runs of a-z, 0-9 and non-ASCII characters after A-Z is lower-cased. Null and empty texts have no words: counts 0,
places null, labels empty strings, score 0. A malformed expression yields its identifiers as labels and no verdict. Ties of place
don't matter, since labels are sets; rows are mapped one by one, so repeated rows and extra columns need no care.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import arrow_map

#: The phrases whose places are counted, with their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: Further notice phrases and their labels.
NOTICES = {
    "mit license": "mit",
    "apache license": "apache",
    "bsd license": "bsd",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "lesser general public license": "lgpl",
    "affero general public license": "agpl",
    "gnu general public license": "gnu",
    "boost software license": "bsl",
    "isc license": "isc",
    "creative commons": "cc",
    "cc by nc": "cc-by-nc",
    "cc by sa": "cc-by-sa",
    "cc by nd": "cc-by-nd",
    "cc by nc sa": "cc-by-nc-sa",
    "cc by nc nd": "cc-by-nc-nd",
    "cc0": "cc0",
    "public domain": "public-domain",
    "permission is hereby granted free of charge": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "without warranty of any kind": "no-warranty",
    "licensed under the": "licensed",
}
TAG = "spdx license identifier"

#: What an identifier lets a reader do: 2 reuse freely, 1 reuse on like terms, 0 no reuse for every purpose. By prefix.
TERMS = {
    **dict.fromkeys("mit apache bsd 0bsd isc cc0 unlicense bsl zlib x11 ncsa wtfpl postgresql python psf unicode artistic ecl upl afl ruby php w3c zpl cc-by pddl odc-by openssl vim curl libpng mulanpsl blueoak".split(), 2),
    **dict.fromkeys("gpl lgpl agpl mpl epl cddl eupl osl ms-pl ms-rl gfdl cecill ofl odbl cc-by-sa cpl ipl qpl sleepycat rpl apsl nposl".split(), 1),
    **dict.fromkeys("cc-by-nc cc-by-nd cc-by-nc-sa cc-by-nc-nd sspl busl elastic polyform proprietary commons-clause reserved".split(), 0),
}
#: By what an expression allows, how far that opens the text to reuse; None: nothing known.
OPEN = {2: 1.0, 1: 0.75, 0: 0.25, None: 0.5}

_SPLIT = bytes(c if 0x61 <= c <= 0x7A or 0x30 <= c <= 0x39 or c >= 0x80 else 32 for c in range(256))
_BEHIND_TAG = re.compile(r"spdx-license-identifier\s*:\s*([^\r\n]*)", re.IGNORECASE | re.ASCII)
_TOKEN = re.compile(r"\s*([()]|[A-Za-z0-9.+:\-]+)")
_RANK = {"or": 1, "and": 2, "with": 3}


def terms(identifier: str) -> int | None:
    best = max((k for k in TERMS if identifier == k or identifier.startswith(k + "-")), key=len, default=None)
    return None if best is None else TERMS[best]


@dataclass
class Expression:
    identifiers: list[str]
    #: The postfix order, or None if it is malformed.
    postfix: list[str] | None
    #: The reuse that the whole expression allows; None if unknown.
    allows: int | None


def parse_expression(written: str) -> Expression:
    """`with` binds closest, then `and`, then `or`. `or` leaves the reader the better terms, `and` binds to the worse ones, and
    an exception behind `with` never makes terms worse. What follows a complete expression on the line is left alone."""
    output: list[str] = []
    stack: list[str] = []
    names: list[str] = []
    operand_next, good, at = True, True, 0
    while m := _TOKEN.match(written, at):
        token = m[1].lower()
        if token == "(":
            if not operand_next:
                break
            stack.append(token)
        elif token == ")":
            if operand_next or "(" not in stack:
                good = good and "(" not in stack and not operand_next
                break
            while stack[-1] != "(":
                output.append(stack.pop())
            stack.pop()
        elif token in _RANK:
            if operand_next:
                good = False
                break
            while stack and stack[-1] != "(" and _RANK[stack[-1]] >= _RANK[token]:
                output.append(stack.pop())
            stack.append(token)
            operand_next = True
        else:
            token = token.rstrip(".:-")
            if not operand_next or not token:
                break
            output.append(token)
            names.append(token)
            operand_next = False
        at = m.end()
    if operand_next or "(" in stack or not good:
        return Expression(names, None, None)
    output += reversed(stack)
    values: list[int | None] = []
    for token in output:
        if token not in _RANK:
            values.append(terms(token))
            continue
        b, a = values.pop(), values.pop()
        if token == "with":
            values.append(a)
        elif a is None or b is None:
            values.append((a if a is not None else b) if token == "or" else None)
        else:
            values.append(max(a, b) if token == "or" else min(a, b))
    return Expression(names, output, values[0])


class Scanner:
    def __init__(self):
        self.automaton = ahocorasick.Automaton()
        for phrase, label in [*NOTICES.items(), (TAG, "")]:
            self.automaton.add_word(self._key(phrase), (label, len(phrase) + 2, False))
        for phrase, label in BASE.items():
            self.automaton.add_word(self._key(phrase), (label, len(phrase) + 2, True))
        self.automaton.make_automaton()

    @staticmethod
    def _key(phrase: str) -> str:
        return f" {phrase} "

    def scan(self, text: str) -> tuple[int, int, int | None, int | None, list[str], list[str], float, int | None, list[str], list[tuple[int, str]]]:
        """n_words, n_base, first_word, last_word, base labels, all labels, score, what is allowed, the expressions in postfix order, and
        the places with their labels."""
        words = text.encode("utf-8", "surrogatepass").lower().translate(_SPLIT).split(b" ")
        words = [w for w in words if w]
        line = f" {b' '.join(words).decode('utf-8', 'surrogatepass')} "
        hits = [(end - size + 1, label, base) for end, (label, size, base) in self.automaton.iter(line)]
        if not hits:
            return len(words), 0, None, None, [], [], 0.0, None, [], []
        hits.sort()
        places, seen, at = [], 0, 0
        for start, label, base in hits:  # a place's number is the number of blanks before it
            seen += line.count(" ", at, start)
            at = start
            places.append((seen, label, base))
        own = [p for p, _, base in places if base]
        labels = {label for _, label, _ in places if label}
        named = [v for v in map(terms, labels) if v is not None]
        verdicts, postfix = [], []
        if any(not label for _, label, _ in places):
            for written in _BEHIND_TAG.findall(text):
                found = parse_expression(written)
                labels |= set(found.identifiers)
                if found.postfix is not None:
                    verdicts.append(found.allows)
                    postfix.append(" ".join(found.postfix))
        known = [v for v in verdicts if v is not None]
        allows = min(known) if known else min(named, default=None) if not postfix else None
        # evidence: an expression that is understood is certain, each notice halves what doubt is left
        doubt = 0.0 if known else 0.5 ** len(places)
        score = (1.0 - doubt) * OPEN[allows] if labels else 0.0
        return len(words), len(own), min(own, default=None), max(own, default=None), sorted({x for _, x, base in places if base}), sorted(labels), score, allows, postfix, [(p, x) for p, x, _ in places]


def scan(docs: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document. allows: 2 reuse freely, 1 on like terms, 0 not for every purpose, null unknown; `expressions` are in postfix order; `places` lists (word, label) of every hit, identifier tags with an empty label."""
    kind = dict(docs.dtypes)[id_column]
    at = pa.list_(pa.struct([("word", pa.int64()), ("label", pa.string())]))

    def make():
        scanner = Scanner()

        def run(batch):
            rows = [scanner.scan(t or "") for t in batch.column(1).to_pylist()]
            n, base, first, last, own, labels, score, allows, postfix, places = zip(*rows, strict=True)
            return pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    *(pa.array(x, pa.int64()) for x in (n, base, first, last)),
                    pa.array([",".join(x) for x in own], pa.string()),
                    pa.array([",".join(x) for x in labels], pa.string()),
                    pa.array(score, pa.float64()),
                    pa.array(allows, pa.int64()),
                    pa.array(postfix, pa.list_(pa.string())),
                    pa.array([[{"word": w, "label": x} for w, x in p] for p in places], at),
                ],
                [id_column, "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "allows", "expressions", "places"],
            )

        return run

    return arrow_map(docs.select(id_column, text), f"{id_column} {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, allows long, expressions array<string>, places array<struct<word:long,label:string>>", make)
