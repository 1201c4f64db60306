"""License scans: Aho-Corasick over normalised words, shunting-yard over licence expressions.

Defined results: null or empty text has no words, no labels, score 0 and null first and last words. Rows are
handled one by one, so repeated ids give repeated rows, an empty table gives an empty table and extra columns are ignored.
"""

from __future__ import annotations

import re
from functools import cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_columns

#: The phrases of the contract and their labels.
BASE_PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Further notice phrases.
MORE_PHRASES = {
    "bsd license": "bsd", "bsd 2 clause": "bsd", "bsd 3 clause": "bsd", "isc license": "isc", "mozilla public license": "mpl",
    "eclipse public license": "epl", "creative commons": "cc", "cc by": "cc", "boost software license": "bsl", "zlib license": "zlib",
    "lesser general public license": "lgpl", "affero general public license": "agpl", "permission is hereby granted free of charge": "mit",
    "redistribution and use in source and binary forms": "bsd", "all rights reserved": "reserved", "public domain": "public-domain",
    "unlicense": "unlicense", "spdx license identifier": "spdx",
}
#: Families of identifiers, and those that allow use in closed work.
FAMILIES = ("agpl", "lgpl", "gpl", "mit", "apache", "bsd", "mpl", "epl", "isc", "zlib", "cc0", "cc", "bsl", "unlicense", "artistic", "wtfpl")
PERMISSIVE = {"mit", "apache", "bsd", "isc", "zlib", "cc0", "bsl", "unlicense", "wtfpl"}

_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
_TAG = re.compile(rb"spdx-license-identifier[ \t]*:[ \t]*([^\r\n]*)", re.I)
_FIELD = re.compile(rb"\blicen[cs]es?[\"']?[ \t]*[:=][ \t]*[\[{]?[ \t]*(?:text[ \t]*[=:][ \t]*)?[\"']?([A-Za-z0-9(][A-Za-z0-9.+() -]*)", re.I)
_LEXEME = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+:-]*")
_BINDS = {"or": 1, "and": 2, "with": 3}


def normalise(raw: bytes) -> list[bytes]:
    """Words of the contract's class, on UTF-8 bytes; non-ASCII bytes always belong to words."""
    return raw.translate(_FOLD).split()


@cache
def automaton() -> ahocorasick.Automaton:
    made = ahocorasick.Automaton()
    for phrase, label in (BASE_PHRASES | MORE_PHRASES).items():
        made.add_word(f" {phrase} ", (phrase, label, len(phrase)))
    made.make_automaton()
    return made


def family(identifier: str) -> str:
    low = identifier.lower()
    return next((f for f in FAMILIES if low == f or low.startswith((f"{f}-", f"{f}+", f"{f}."))), low)


def to_postfix(expression: str) -> list[str]:
    """Shunting-yard; operators are and, or, with in any case. Reading stops at the first lexeme that cannot continue; open parentheses close at the end."""
    out: list[str] = []
    held: list[str] = []
    operand_next = True
    depth = 0
    for lexeme in _LEXEME.findall(expression):
        low = lexeme.lower()
        if operand_next:
            if lexeme == "(":
                held.append(lexeme)
                depth += 1
                continue
            if lexeme == ")" or low in _BINDS:
                raise ValueError(f"operand expected at {lexeme!r}")
            out.append(lexeme)
            operand_next = False
        elif lexeme == ")" and depth:
            while held[-1] != "(":
                out.append(held.pop())
            held.pop()
            depth -= 1
        elif low in _BINDS:
            while held and held[-1] != "(" and _BINDS[held[-1]] >= _BINDS[low]:
                out.append(held.pop())
            held.append(low)
            operand_next = True
        else:
            break
    while operand_next and held and held.pop() not in _BINDS:  # an operator or parenthesis that nothing follows says nothing
        pass
    if not out:
        raise ValueError("no identifier")
    return out + [x for x in held[::-1] if x != "("]


def evaluate(expression: str) -> tuple[set[str], bool]:
    """Families named by an expression, and whether some choice that it offers is permissive."""
    stack: list[tuple[set[str], bool]] = []
    for lexeme in to_postfix(expression):
        if lexeme not in _BINDS:
            name = family(lexeme)
            stack.append(({name}, name in PERMISSIVE))
            continue
        (right, r_ok), (left, l_ok) = stack.pop(), stack.pop()
        if lexeme == "with":  # an exception only widens what its licence allows
            stack.append((left, l_ok))
        else:
            stack.append((left | right, (l_ok or r_ok) if lexeme == "or" else (l_ok and r_ok)))
    return stack[0]


def scan(raw: bytes | None) -> tuple:
    words = normalise(raw or b"")
    line = (b" " + b" ".join(words) + b" ").decode("latin-1") if words else ""
    base, starts, labels, marks = 0, [], set(), 0
    base_labels: set[str] = set()
    tagged = False
    word = seen = 0
    for end, (phrase, label, length) in automaton().iter(line):
        if phrase in BASE_PHRASES:
            base += 1
            word, seen = word + line.count(" ", seen, end), end  # spaces before the one that ends the phrase
            starts.append(word - 1 - phrase.count(" "))
            base_labels.add(label)
        elif label == "spdx":
            tagged = True
        else:
            labels.add(label)
        marks += 1
    permissive = None
    if tagged:
        for m in _TAG.finditer(raw):
            try:
                named, ok = evaluate(m[1].decode("ascii", "replace"))
            except ValueError:
                continue
            labels |= named
            permissive = ok if permissive is None else permissive and ok
    if raw and (b"icense" in raw or b"ICENSE" in raw or b"icence" in raw):
        for m in _FIELD.finditer(raw):  # a declared field counts only if all that it names are known families
            try:
                named, ok = evaluate(m[1].decode("ascii"))
            except ValueError:
                continue
            if named <= set(FAMILIES):
                labels |= named
                permissive = ok if permissive is None else permissive and ok
    labels |= base_labels
    return (len(words), base, min(starts, default=None), max(starts, default=None), ",".join(sorted(base_labels)), ",".join(sorted(labels)), marks / (marks + 1.0), permissive)


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: words, base places, labels, score (m places give m/(m+1)) and what tagged expressions allow."""
    fields = [(id_col, pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("permissive", pa.bool_())]
    schema = f"`{id_col}` long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, permissive boolean"

    def kernel(ids: list, texts: list) -> list:
        return [ids, *zip(*map(scan, texts))] if ids else [[] for _ in fields]

    return map_columns(docs, kernel, schema, pa.schema(fields), id_col, text_col, binary=True)
