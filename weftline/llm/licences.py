"""Licence scan: one Aho-Corasick pass for notice phrases and identifier tags.

Texts are brought to small letters, digits and single blanks; the automaton
reports every place of every phrase, overlaps included.  Behind an identifier
tag the original text has an expression of identifiers with AND, OR, WITH and
brackets; a shunting-yard parser brings it to postfix form, from which come the
identifiers and whether a set of accepted licences satisfies it.

Defined cases.  A null or empty text has no words, places or labels and score 0.
A malformed expression is reported as it stands and satisfies nothing; WITH
binds one licence and one exception, so anything else beside it is malformed.
Scanning and parsing are linear in the text.  Rows that repeat are scanned
alike; extra columns pass through whatever their names, those named like the
results are replaced.
"""

from __future__ import annotations

import re
from functools import cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import LOWER_ALNUM, struct_of, text_bytes, with_results

#: Phrases whose places are counted, and their labels.
BASE = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}

#: Further notices, their labels and how surely each one grants a licence.
NOTICES = {
    "gnu general public license version 3": ("gpl-3", 0.9),
    "gnu general public license version 2": ("gpl-2", 0.9),
    "gnu general public license": ("gpl", 0.6),
    "gnu lesser general public license": ("lgpl", 0.8),
    "gnu affero general public license": ("agpl", 0.8),
    "mozilla public license": ("mpl", 0.7),
    "eclipse public license": ("epl", 0.7),
    "permission is hereby granted free of charge to any person": ("mit", 0.9),
    "redistribution and use in source and binary forms": ("bsd", 0.8),
    "the mit license": ("mit", 0.6),
    "apache license": ("apache", 0.6),
    "bsd license": ("bsd", 0.6),
    "isc license": ("isc", 0.6),
    "cc by sa": ("cc-by-sa", 0.7),
    "cc by nd": ("cc-by-nd", 0.7),
    "cc by": ("cc-by", 0.5),
    "cc0 1 0": ("cc0", 0.8),
    "creative commons attribution": ("cc-by", 0.6),
    "public domain dedication": ("public-domain", 0.6),
}
BASE_SURETY, TAG_SURETY = 0.8, 0.95

TAG = "spdx license identifier"
EXPRESSION = re.compile(r"spdx-license-identifier\s*:[^\S\n]*([^\n]*)", re.IGNORECASE)
SYMBOL = re.compile(r"[()]|[A-Za-z0-9.+\-:]+")
BINDING = {"or": 1, "and": 2, "with": 3}


def postfix(expression: str) -> list[str] | None:
    """The expression in postfix form, by a shunting yard; None if malformed."""
    out, waiting, operand_next = [], [], True
    before = before_that = ""
    for symbol in SYMBOL.findall(expression):
        word = symbol.lower()
        if word == "with" and (before == ")" or before_that == "with") or symbol == "(" and before == "with":
            return None
        before_that, before = before, word
        if symbol == "(":
            if not operand_next:
                return None
            waiting.append(symbol)
        elif symbol == ")":
            if operand_next:
                return None
            while waiting and waiting[-1] != "(":
                out.append(waiting.pop())
            if not waiting:
                return None
            waiting.pop()
        elif word in BINDING:
            if operand_next:
                return None
            while waiting and waiting[-1] != "(" and BINDING[waiting[-1]] >= BINDING[word]:
                out.append(waiting.pop())
            waiting.append(word)
            operand_next = True
        else:
            if not operand_next:
                return None
            out.append(symbol)
            operand_next = False
    if operand_next or "(" in waiting:
        return None
    return out + waiting[::-1]


def identifiers(form: list[str]) -> set[str]:
    """The licences in a postfix form, in small letters, each with its exception."""
    names: list[str] = []
    for symbol in form:
        if symbol == "with":
            exception, licence = names.pop(), names.pop()
            names.append(f"{licence} with {exception}")
        elif symbol not in BINDING:
            names.append(symbol.lower())
    return set(names)


def satisfied(form: list[str], accepted: frozenset[str]) -> bool:
    """Whether the accepted licences (small letters) are enough; an exception widens its licence."""
    stack: list[bool] = []
    names: list[str] = []
    for symbol in form:
        if symbol == "with":
            exception, licence = names.pop(), names.pop()
            b, a = stack.pop(), stack.pop()
            names.append(licence)
            stack.append(a or f"{licence} with {exception}" in accepted)
        elif symbol in BINDING:
            b, a = stack.pop(), stack.pop()
            names.pop()
            stack.append(a and b if symbol == "and" else a or b)
        else:
            names.append(symbol.lower())
            stack.append(symbol.lower() in accepted)
    return stack[0]


@cache
def automaton(base: tuple[tuple[str, str], ...]) -> ahocorasick.Automaton:
    """Keys with a blank on either side; bytes beyond ASCII appear as Latin-1 characters."""
    found: dict[str, list] = {}
    for phrase, label in base:
        found.setdefault(phrase, []).append(("base", label, BASE_SURETY))
    for phrase, (label, surety) in NOTICES.items():
        found.setdefault(phrase, []).append(("notice", label, surety))
    found.setdefault(TAG, []).append(("tag", "", 0.0))
    out = ahocorasick.Automaton()
    for phrase, uses in found.items():
        key = f" {phrase.encode().translate(LOWER_ALNUM).decode('latin-1')} "
        out.add_word(key, (len(key), uses))
    out.make_automaton()
    return out


def scan(raw: bytes, base: tuple[tuple[str, str], ...], accepted: frozenset[str]) -> tuple:
    words = raw.translate(LOWER_ALNUM).split()
    text = f" {b' '.join(words).decode('latin-1')} "
    starts, n_base, base_labels, labels, doubt, tagged = [], 0, set(), set(), 1.0, False
    at = words_before = 0
    for end, (length, uses) in automaton(base).iter(text):
        for kind, label, surety in uses:
            if kind == "base":
                begin = end - length + 1
                if begin >= at:
                    words_before += text.count(" ", at, begin)
                    at = begin
                    word = words_before
                else:
                    word = words_before - text.count(" ", begin, at)
                starts.append(word)
                base_labels.add(label)
            if kind == "tag":
                tagged = True
            else:
                labels.add(label)
                doubt *= 1 - surety
    expressions, allowed = [], None
    if tagged:
        for m in EXPRESSION.finditer(raw.decode("utf-8", "replace")):
            told = m[1].strip().removesuffix("*/").removesuffix("-->").strip()
            form = postfix(told)
            expressions.append(told)
            good = form is not None and satisfied(form, accepted)
            allowed = good if allowed is None else allowed and good
            if form is not None:
                labels |= {x.replace(",", "") for x in identifiers(form)}
                doubt *= 1 - TAG_SURETY
    first, last = (min(starts), max(starts)) if starts else (None, None)
    return (len(words), len(starts), first, last, ",".join(sorted(base_labels)), ",".join(sorted(labels)), 1 - doubt, expressions, allowed)


FIELDS = {
    "n_words": ("bigint", pa.int64()), "n_base": ("bigint", pa.int64()), "first_word": ("bigint", pa.int64()),
    "last_word": ("bigint", pa.int64()), "base_labels": ("string", pa.string()), "labels": ("string", pa.string()),
    "score": ("double", pa.float64()), "expressions": ("array<string>", pa.list_(pa.string())), "allowed": ("boolean", pa.bool_()),
}
ACCEPTED = frozenset({"mit", "apache-2.0", "bsd-2-clause", "bsd-3-clause", "isc", "cc0-1.0", "unlicense", "zlib"})


def scan_licences(docs: DataFrame, base: dict[str, str] = BASE, accepted: frozenset[str] = ACCEPTED, *, text: str = "text") -> DataFrame:
    """``docs`` without the text, with the places, labels, score, expressions and verdict of each."""
    told = tuple(base.items())

    def each(raws: list[bytes]) -> list[list]:
        rows = [scan(raw, told, accepted) for raw in raws]
        return [[r[k] for r in rows] for k in range(len(FIELDS))]

    return with_results(docs, struct_of(FIELDS, each)(text_bytes(text)), list(FIELDS), without=(text,))
