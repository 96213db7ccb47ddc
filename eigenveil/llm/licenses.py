"""Licence scan: an Aho-Corasick automaton over normalised words and an expression parser.

Texts are lower-cased (A-Z only) and cut into words of digits, letters and any
non-ASCII characters; one automaton then finds all phrases as runs of whole words.
Where the tag phrase occurs, the identifier expressions are read from the text itself,
parsed by shunting-yard (``with`` binds before ``and``, ``and`` before ``or``) and
evaluated to the identifiers named and an openness between 0 and 1: the least of an
``and``, the greatest of an ``or``.  Malformed expressions count as the identifiers in
them that are known; a tag line without any known identifier (prose, a broken tag) gets
the label ``spdx:unknown`` alone.  Null and empty texts have no words and no labels; each row is scanned on its
own, so repeated rows and further columns change nothing.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_texts, per_worker

# Base phrases and their labels.
BASE_PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

# Further notice phrases (normalised words) and their labels.
NOTICE_PHRASES = {
    "permission is hereby granted free of charge to any person obtaining a copy": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "bsd license": "bsd",
    "licensed under the apache license version 2 0": "apache-2.0",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "isc license": "isc",
    "boost software license": "bsl",
    "cc by": "cc-by",
    "cc by sa": "cc-by-sa",
    "cc by nc": "cc-by-nc",
    "cc by nd": "cc-by-nd",
    "cc by nc sa": "cc-by-nc",
    "cc by nc nd": "cc-by-nc",
    "cc0": "cc0",
    "creative commons attribution": "cc-by",
    "creative commons zero": "cc0",
    "public domain": "public-domain",
    "all rights reserved": "reserved",
}
TAG_PHRASE = "spdx license identifier"

# Openness of identifier prefixes; the longest prefix counts, unknown ones are 0.5.
OPENNESS = {
    "mit": 1.0, "bsd": 1.0, "isc": 1.0, "apache": 1.0, "zlib": 1.0, "bsl-1": 1.0, "unlicense": 1.0, "0bsd": 1.0, "cc0": 1.0, "cc-by-4": 0.9, "cc-by-3": 0.9,
    "mpl": 0.7, "epl": 0.7, "lgpl": 0.6, "cc-by-sa": 0.6, "gpl": 0.3, "agpl": 0.2, "cc-by-nc": 0.1, "cc-by-nd": 0.1, "proprietary": 0.0,
}

# Identifiers that are known (public SPDX names), as families with their versions and suffixes.
KNOWN = re.compile(
    r"(mit(-0|-modern-variant)?|isc|0bsd|bsd-[1-4]-clause(-[a-z-]+)?|apache-[12]\.[01]|(a|l)?gpl-[1-3]\.[01](\+|-only|-or-later)?|mpl-[12]\.[01](-no-copyleft-exception)?"
    r"|epl-[12]\.0|eupl-1\.[0-2]|cddl-1\.[01]|cc0-1\.0|cc-by(-nc)?(-nd|-sa)?-[1-4]\.[05]|cc-pddc|zlib|unlicense|wtfpl|bsl-1\.0|python-2\.0(\.1)?|psf-2\.0|postgresql"
    r"|artistic-[12]\.0|ofl-1\.[01]|ms-(pl|rl)|ncsa|x11|openssl|ruby|php-3\.0[1]?|vim|curl|libpng(-2\.0)?|ijg|icu|unicode-(3\.0|dfs-201[56])|odbl-1\.0|pddl-1\.0|odc-by-1\.0"
    r"|blueoak-1\.0\.0|sspl-1\.0|busl-1\.1|afl-[1-3]\.[012]|ecl-[12]\.0|upl-1\.0|w3c|hpnd|proprietary|licenseref-[a-z0-9.-]+)"
)
UNKNOWN = "unknown"

#: Weight of evidence of one tag, one notice phrase, one base phrase; the score is 1 - the product of what they leave.
TAG_WEIGHT, NOTICE_WEIGHT, BASE_WEIGHT = 0.9, 0.6, 0.5

_TAG = re.compile(rb"SPDX-License-Identifier:[ \t]*([^\r\n]*)", re.IGNORECASE)
_TOKEN = re.compile(r"[()]|[A-Za-z0-9][A-Za-z0-9.+:-]*")
_BINDS = {"or": 1, "and": 2, "with": 3}


def _words_table() -> bytes:
    kept = {*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)}
    return bytes(b + 32 if 0x41 <= b <= 0x5A else b if b in kept else 0x20 for b in range(256))


def postfix(text: str) -> list[str]:
    """The expression in postfix order, operators in lower case; ValueError if it is malformed.

    What follows the expression (closing comment marks, prose) ends it.
    """
    out: list[str] = []
    held: list[str] = []
    want_operand = True
    for token in _TOKEN.findall(text):
        low = token.lower()
        if low in _BINDS:
            if want_operand:
                raise ValueError("an operator without its left side")
            while held and held[-1] != "(" and _BINDS[held[-1]] >= _BINDS[low]:
                out.append(held.pop())
            held.append(low)
            want_operand = True
        elif token == "(":
            if not want_operand:
                break
            held.append(token)
        elif token == ")":
            if want_operand:
                raise ValueError("an empty group")
            while held and held[-1] != "(":
                out.append(held.pop())
            if not held:
                break
            held.pop()
        else:
            if not want_operand:
                break
            out.append(token)
            want_operand = False
    if want_operand or "(" in held:
        raise ValueError("the expression breaks off")
    return out + held[::-1]


def _licences(order: list[str]) -> list[str]:
    """Operands of a postfix expression that are no exceptions (the right sides of ``with``)."""
    stack: list[list[str]] = []
    for token in order:
        if token in _BINDS:
            right, left = stack.pop(), stack.pop()
            stack.append(left if token == "with" else left + right)
        else:
            stack.append([token])
    return stack[0] if stack else []


def openness(identifier: str) -> float:
    low = identifier.lower()
    return OPENNESS[max(found, key=len)] if (found := [x for x in OPENNESS if low.startswith(x)]) else 0.5


def evaluate(text: str) -> tuple[set[str], float]:
    """Known identifiers (lower case, exceptions left out) and openness of an expression; none known: ``unknown``."""
    try:
        order = postfix(text)
    except ValueError:
        order = []
    if not order or not all(KNOWN.fullmatch(x.lower()) for x in _licences(order)):
        names = {x.lower() for x in _TOKEN.findall(text) if KNOWN.fullmatch(x.lower())} or ({UNKNOWN} if text.split() else set())
        return names, min(map(openness, names), default=0.0)
    stack: list[tuple[set[str], float]] = []
    for token in order:
        if token in _BINDS:
            (right, r), (left, n) = stack.pop(), stack.pop()
            # an exception loosens its licence by a step, it is no licence itself
            stack.append((left, min(1.0, n + 0.1)) if token == "with" else (left | right, min(n, r) if token == "and" else max(n, r)))
        else:
            stack.append(({token.lower()}, openness(token)))
    return stack[0]


class LicenseScanner:
    def __init__(self):
        self.table = _words_table()
        self.finder = ahocorasick.Automaton()
        kinds: dict[str, list[tuple[str, str]]] = {}
        for kind, phrases in (("base", BASE_PHRASES), ("notice", NOTICE_PHRASES), ("tag", {TAG_PHRASE: ""})):
            for phrase, label in phrases.items():
                kinds.setdefault(phrase, []).append((kind, label))
        for phrase, found in kinds.items():
            self.finder.add_word(f" {phrase} ", (len(phrase) + 2, found))
        self.finder.make_automaton()

    def scan(self, text: bytes | None) -> tuple:
        """n_words, n_base, first_word, last_word, base_labels, labels, score, expressions, openness."""
        words = (text or b"").translate(self.table).split()
        line = (b" " + b" ".join(words) + b" ").decode("latin-1")
        starts: list[int] = []
        base: set[str] = set()
        more: set[str] = set()
        left, tagged = 1.0, False
        at = number = 0  # a place in the line and the spaces before it
        for last, (width, found) in self.finder.iter(line):
            for kind, label in found:
                if kind == "base":
                    begin = last - width + 1
                    number += line.count(" ", at, begin) if begin >= at else -line.count(" ", begin, at)
                    at = begin
                    starts.append(number)
                    base.add(label)
                    left *= 1 - BASE_WEIGHT
                elif kind == "notice":
                    more.add(label)
                    left *= 1 - NOTICE_WEIGHT
                else:
                    tagged = True
        expressions: list[str] = []
        least: float | None = None
        for got in _TAG.findall(text) if tagged else ():
            said = got.decode("utf-8", "replace").strip()
            names, value = evaluate(said)
            if names:
                expressions.append(said)
                more |= {f"spdx:{x}" for x in names}
                least = value if least is None else min(least, value)
                left *= 1 - TAG_WEIGHT
        return len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(base | more)), 1.0 - left, expressions, least


SCANNED = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, expressions array<string>, openness double"


def scan_licenses(docs: DataFrame) -> DataFrame:
    """One row per document with its licence labels, places, expressions and score."""
    types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.float64(), pa.list_(pa.string()), pa.float64()]
    names = [x.split()[0] for x in SCANNED.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = per_worker("licenses", LicenseScanner)
        for batch in batches:
            rows = [scanner.scan(x) for x in byte_texts(batch.column("text"))]
            columns = list(zip(*rows)) or [()] * len(types)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(list(x), t) for x, t in zip(columns, types))], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, SCANNED)
