"""Line-first quality rules.

Every line is judged alone (symbols, shouting, navigation, boilerplate, missing
end of sentence, repetition of an earlier line); failing lines are taken out, and
a document that loses too large a share of its words is rejected.  Document
measures (words, symbols, repeated lines and five-word windows) come with it.

Defined cases.  A null or empty text has no words and fails.  Lines without a
word are neither kept nor lost.  Rows that repeat are judged alike, each on its
own; there is no state between rows, so neither hot sources nor lost executors
matter.  A line or a word may be of any length: every rule is linear in it.
Extra columns pass through whatever their names; those named like the results
asked for are replaced.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import column, free_name, struct_of, text_bytes, with_results

SYMBOLS = b"#*$%&|<>"

#: Phrases of web furniture, lower case.
BOILERPLATE = (
    b"all rights reserved", b"cookie policy", b"use of cookies", b"privacy policy",
    b"terms of use", b"terms of service", b"enable javascript", b"click here",
    b"read more", b"subscribe to our", b"sign in to", b"lorem ipsum",
)
SEPARATOR = re.compile("[|>/»·•]")
END = re.compile(r"[.!?:;…。！？»”\"')\]]$")


@dataclass(frozen=True)
class Rules:
    min_words: int = 10
    max_repeat_percent: int = 20
    symbols_per_word: float = 0.25
    shouting_share: float = 0.5
    shouting_words: int = 3
    open_line_words: int = 6
    max_lost_share: float = 0.3


def repeated_words(words: list[bytes]) -> int:
    """Words inside five-word windows that the text has twice or more."""
    if len(words) < 6:
        return 0
    first: dict[tuple, int] = {}
    again: list[int] = []
    for at, gram in enumerate(zip(words, *[islice(words, k, None) for k in range(1, 5)])):
        before = first.setdefault(gram, at)
        if before != at:
            again.append(at)
            if before >= 0:
                again.append(before)
                first[gram] = -1
    covered, end = 0, 0
    for at in sorted(again):
        covered += at + 5 - max(at, end)
        end = at + 5
    return covered


def navigation(text: str) -> bool:
    """Whether a line is three or more single words between separators, the last of which may be missing."""
    *items, last = SEPARATOR.split(text)
    return len(items) >= 2 and all(len(item.split(None, 2)) == 1 for item in items) and len(last.split(None, 2)) < 2


def failed_rule(line: bytes, words: list[bytes], rules: Rules) -> str | None:
    """The first rule that the line fails."""
    n = len(words)
    text = line.decode("utf-8", "replace")
    if len(line) - len(line.translate(None, SYMBOLS)) > rules.symbols_per_word * n:
        return "symbols"
    if n >= rules.shouting_words:
        letters = sum(map(str.isalpha, text))
        if letters and sum(map(str.isupper, text)) > rules.shouting_share * letters:
            return "shouting"
        if text.count("!") > rules.shouting_share * n:
            return "shouting"
    small = line.lower()
    if navigation(text):
        return "navigation"
    if n <= 25 and any(p in small for p in BOILERPLATE):
        return "boilerplate"
    if n >= rules.open_line_words and not END.search(text.rstrip()):
        return "open"
    return None


def judge(raw: bytes, rules: Rules) -> tuple:
    words = raw.split()
    n = len(words)
    blanks = sum(raw.count(c) for c in (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r"))
    chars = len(raw.decode("utf-8", "replace"))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    seen, dup, lost, kept_lines, removed = set(), 0, 0, [], 0
    for line in raw.split(b"\n"):
        mine = line.split()
        if not mine:
            continue
        again = line in seen
        dup += again
        seen.add(line)
        if again or failed_rule(line, mine, rules):
            lost += len(mine)
            removed += 1
        else:
            kept_lines.append(line)
    repeat = repeated_words(words)
    base = n < rules.min_words or 100 * repeat > rules.max_repeat_percent * n
    kept = not base and lost <= rules.max_lost_share * n
    return n, chars - blanks, symbols, dup, repeat, base, kept, removed, lost, b"\n".join(kept_lines)


FIELDS = {
    "n_words": ("bigint", pa.int64()), "word_chars": ("bigint", pa.int64()), "n_symbols": ("bigint", pa.int64()),
    "n_dup_lines": ("bigint", pa.int64()), "n_repeat_words": ("bigint", pa.int64()), "base_failed": ("boolean", pa.bool_()),
    "kept": ("boolean", pa.bool_()), "n_lines_removed": ("bigint", pa.int64()), "n_words_lost": ("bigint", pa.int64()),
    "clean_text": ("string", pa.string()),
}


def judgement(text: str, rules: Rules, results: tuple[str, ...]):
    """The struct of ``results`` for the column ``text``."""
    at = [list(FIELDS).index(c) for c in results]

    def each(raws: list[bytes]) -> list[list]:
        rows = [judge(raw, rules) for raw in raws]
        return [[r[k].decode("utf-8", "replace") if c == "clean_text" else r[k] for r in rows] for c, k in zip(results, at)]

    return struct_of({c: FIELDS[c] for c in results}, each)(text_bytes(text))


def quality(docs: DataFrame, rules: Rules = Rules(), *, text: str = "text", results: tuple[str, ...] = tuple(FIELDS)) -> DataFrame:
    """``docs`` with the measures, the verdict ``kept`` and ``clean_text``, the lines left.

    ``results`` names the result columns wanted; ``clean_text`` is costly to move.
    """
    return with_results(docs, judgement(text, rules, results), list(results))


def good_documents(docs: DataFrame, rules: Rules = Rules(), *, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that the rules keep, as they are."""
    verdict = free_name(docs, "verdict")
    judged = docs.withColumn(verdict, judgement(text, rules, ("kept",)))
    return judged.filter(column(verdict)["kept"]).drop(column(verdict))
