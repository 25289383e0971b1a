"""Licence scans: Aho-Corasick over words, then licence expressions by a shunting yard.

One automaton holds every notice phrase and the words of the tag that stands before an
expression. It runs over the text's words joined by blanks, so an occurrence is one of
whole words that follow each other. Where the tag ends, the expression is read from the
raw text, up to the end of the line: it is put into postfix order with operators and
precedence WITH over AND over OR, and evaluated to its licences and to a permissiveness:
OR gives the better side, AND the worse, WITH lifts its licence half way.

An expression goes on as long as it reads as one. Operands are known licences, references
(``LicenseRef-...``) and names with a version (``Name-1.0``); behind WITH, names of
exceptions. A sentence mark ends it, as does any other word; an operator without a side
behind it is left out, and open brackets close at the end.

score: 0 without evidence; else the mean of how sure the strongest evidence is (tag 1,
licence phrase 0.8, mere reservation 0.4) and how permissive the found licences are.

Edge cases: null and word-less texts have no words, no labels and score 0; a tag without
a licence behind it adds the label ``spdx-invalid``, but for the values that declare none
(``NONE``, ``NOASSERTION``); repeated rows and null ids are scanned like others.
"""

from __future__ import annotations

import re

import ahocorasick
from pyspark.sql import DataFrame, types as T

from .common import ALNUM, annotate, words

#: Phrase and label, fixed by the contract.
BASE_PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Phrases of well-known notices.
MORE_PHRASES = {
    "mit license": "mit",
    "permission is hereby granted free of charge": "mit",
    "apache license": "apache-2.0",
    "lesser general public license": "lgpl",
    "affero general public license": "agpl",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "bsd license": "bsd",
    "redistribution and use in source and binary forms": "bsd",
    "isc license": "isc",
    "boost software license": "bsl-1.0",
    "creative commons attribution": "cc-by",
    "creative commons zero": "cc0",
    "cc by sa": "cc-by-sa",
    "cc by nc": "cc-by-nc",
    "cc by nd": "cc-by-nd",
    "cc0": "cc0",
    "public domain": "public-domain",
    "the unlicense": "unlicense",
}
TAG = "spdx license identifier"
#: Share of freedom that a label leaves; 0.5 for others.
PERMISSIVE = {
    "mit": 1.0, "apache-2.0": 1.0, "bsd": 1.0, "isc": 1.0, "bsl-1.0": 1.0, "cc0": 1.0, "public-domain": 1.0, "unlicense": 1.0,
    "cc-by": 0.9, "cc-by-sa": 0.6, "cc-by-nd": 0.3, "cc-by-nc": 0.3, "mpl": 0.6, "epl": 0.6, "lgpl": 0.5, "gpl": 0.4, "agpl": 0.3, "reserved": 0.0, "spdx-invalid": 0.0,
}
#: Families of licences: an identifier is one of these, alone or with a version behind a hyphen.
FAMILIES = ("agpl", "lgpl", "gpl", "apache-2.0", "bsd", "mit", "isc", "mpl", "epl", "cc0", "cc-by-nc", "cc-by-nd", "cc-by-sa", "cc-by", "bsl-1.0", "unlicense")
#: Identifiers without a version that are not families.
PLAIN = frozenset("0bsd afmparse beerware curl fair ftl hpnd ijg intel json libpng libtiff naist-2003 ncsa netcdf newsletr openssl php postgresql psf python ruby sendmail sleepycat vim w3c wtfpl x11 xnet zlib".split())
NOTHING = frozenset({"none", "noassertion"})
_REFERENCE = re.compile(r"(?:documentref-[a-z0-9.-]+:)?licenseref-[a-z0-9.-]+")
_VERSIONED = re.compile(r"[a-z0-9]+(?:[.-][a-z0-9]+)*-v?[0-9]+(?:\.[0-9]+)*[a-z]?(?:-[a-z0-9.]+)*\+?")
_EXCEPTION = re.compile(r"additionref-[a-z0-9.-]+|[a-z0-9.+-]*-exception(?:-[a-z0-9.]+)*|[a-z0-9.-]+-(?:note|permission|exemption)")
_TOKEN = re.compile(r"[()]|[^\s()]+")
_MARKS = ".,;:!?'\"`*/>]}"
_RANK = {"or": 1, "and": 2, "with": 3}
_WORD = re.compile(rb"[^ ]+")
_LEAD = re.compile(rb"[\x20\t\"'`]*[:=]?[\x20\t\"'`]*")


def family(identifier: str) -> str | None:
    return next((p for p in FAMILIES if identifier == p or identifier.startswith((p + "-", p + "+"))), None)


def label_of(identifier: str) -> str:
    low = identifier.lower()
    return family(low) or low.rstrip("+")


def is_licence(token: str) -> bool:
    low = token.lower()
    return family(low) is not None or low.rstrip("+") in PLAIN or bool(_REFERENCE.fullmatch(low) or _VERSIONED.fullmatch(low))


def is_exception(token: str) -> bool:
    return bool(_EXCEPTION.fullmatch(token.lower()))


def postfix(expression: str) -> list[str]:
    """Tokens in postfix order, as far as the text reads as an expression; empty if it doesn't begin as one."""
    out: list[str] = []
    held: list[str] = []
    operand, deep, ended = True, 0, False  # an operand comes next; open brackets; a sentence mark was read

    def pop_ranked(least: int) -> None:
        while held and _RANK.get(held[-1], 0) >= least:
            out.append(held.pop())

    for raw in _TOKEN.findall(expression):
        if ended:
            break
        if raw == "(":
            if not operand or (held and held[-1] == "with"):
                break
            held.append(raw)
            deep += 1
        elif raw == ")":
            if operand or not deep:
                break
            pop_ranked(1)
            held.pop()
            deep -= 1
        else:
            token = raw.rstrip(_MARKS)
            ended = token != raw
            low = token.lower()
            if low in _RANK:
                if operand or ended:
                    break
                pop_ranked(_RANK[low])
                held.append(low)
                operand = True
            elif operand and (is_exception(token) if held and held[-1] == "with" else is_licence(token)):
                out.append(token)
                operand = False
            else:
                break
    # what waits for a side that never came is left out; open brackets close
    while operand and held:
        held.pop()
        operand = bool(held) and held[-1] == "("
    pop_all = [x for x in reversed(held) if x != "("]
    return out + pop_all if out else []


def evaluate(expression: str) -> tuple[set[str], float]:
    """Labels of the licences in an expression, and its permissiveness; ValueError if there is none."""
    stack: list[tuple[set[str], float]] = []
    for token in postfix(expression):
        if token in _RANK:
            (right, r), (left, p) = stack.pop(), stack.pop()
            if token == "with":
                stack.append((left, p + (1 - p) / 2))
            else:
                stack.append((left | right, max(p, r) if token == "or" else min(p, r)))
        else:
            name = label_of(token)
            stack.append(({name}, PERMISSIVE.get(name, 0.5)))
    if not stack:
        raise ValueError(expression)
    return stack[-1]


def expression_at(text: bytes, end: int) -> str:
    """What stands on the line behind a tag that ends at byte ``end``."""
    start = _LEAD.match(text, end).end()
    stop = min((x for x in (text.find(b"\n", start), text.find(b"\r", start)) if x >= 0), default=len(text))
    return text[start:stop].decode("utf-8", "replace")


def automaton() -> ahocorasick.Automaton:
    out = ahocorasick.Automaton()
    for phrase in dict.fromkeys([*BASE_PHRASES, *MORE_PHRASES, TAG]):
        out.add_word(f" {phrase} ", phrase)
    out.make_automaton()
    return out


def scan(text: bytes | None, machine: ahocorasick.Automaton) -> tuple:
    """(n_words, n_base, first_word, last_word, base labels, all labels, score) of one text."""
    w = words(text, ALNUM)
    if not w:
        return 0, 0, None, None, [], [], 0.0
    line = " " + b" ".join(w).decode("utf-8", "replace") + " "
    base, labels, starts, sure, free, tags = set(), set(), [], 0.0, [], []
    for end, phrase in machine.iter(line):
        if phrase in BASE_PHRASES:
            base.add(BASE_PHRASES[phrase])
            starts.append(end - len(phrase) - 1)
        if phrase == TAG:
            tags.append(end)
        else:
            name = BASE_PHRASES.get(phrase) or MORE_PHRASES[phrase]
            labels.add(name)
            free.append(PERMISSIVE.get(name, 0.5))
            sure = max(sure, 0.4 if name == "reserved" else 0.8)
    if tags:
        # number of the tag's last word, then that word's end in the raw text: translation keeps places
        numbers, at, seen = [], 0, -1
        for end in tags:
            seen += line.count(" ", at, end)
            at = end
            numbers.append(seen)
        wanted = set(numbers)
        for k, m in enumerate(_WORD.finditer(text.translate(ALNUM))):
            if k not in wanted:
                continue
            expression = expression_at(text, m.end())
            try:
                names, p = evaluate(expression)
            except ValueError:
                if (_TOKEN.match(expression) or [""])[0].rstrip(_MARKS).lower() in NOTHING:
                    continue
                names, p = {"spdx-invalid"}, 0.0
            sure = 1.0
            labels |= names
            free.append(p)
    first, last = (line.count(" ", 0, x + 1) - 1 for x in (min(starts), max(starts))) if starts else (None, None)
    score = (sure + (min(free) if free else 0.0)) / 2 if sure else 0.0
    return len(w), len(starts), first, last, sorted(base), sorted(labels), score


def scan_licences(docs: DataFrame, text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with the fields of ``scan``; labels comma-joined."""

    def start():
        machine = automaton()

        def work(texts):
            n, places, first, last, base, labels, score = zip(*[scan(t, machine) for t in texts])
            return n, places, first, last, [",".join(x) for x in base], [",".join(x) for x in labels], score

        return work

    long, string = T.LongType(), T.StringType()
    fields = [("n_words", long), ("n_base", long), ("first_word", long), ("last_word", long), ("base_labels", string), ("labels", string), ("score", T.DoubleType())]
    return annotate(docs, [text], fields, start, keep)


def op7_licences(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return scan_licences(docs, keep=["doc_id"])
