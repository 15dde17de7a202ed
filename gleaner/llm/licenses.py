"""Licence scan: Aho-Corasick over phrases and identifier tags, and a shunting-yard parser of licence expressions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from gleaner.llm.common import binary_column

#: Fixed values of the contract: base phrases and their labels.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Further notice phrases (words as normalised below), their labels and weights.
NOTICES = {
    "permission is hereby granted free of charge": ("mit-notice", 0.9),
    "licensed under the apache license version 2 0": ("apache-2.0", 0.95),
    "redistribution and use in source and binary forms": ("bsd-notice", 0.9),
    "gnu lesser general public license": ("lgpl", 0.9),
    "gnu affero general public license": ("agpl", 0.9),
    "mozilla public license": ("mpl", 0.9),
    "eclipse public license": ("epl", 0.9),
    "creative commons attribution": ("cc-by", 0.7),
    "bsd license": ("bsd", 0.7),
    "isc license": ("isc", 0.7),
    "boost software license": ("bsl", 0.8),
    "this is free and unencumbered software released into the public domain": ("unlicense", 0.95),
    "all rights reserved": ("proprietary-notice", 0.3),
    "without warranties or conditions of any kind": ("warranty-disclaimer", 0.4),
}
TAG = "spdx license identifier"
#: Every byte that parts words becomes a blank; A-Z become a-z.
_WORDS = bytes(b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))
_TAG_LINE = re.compile(rb"spdx-license-identifier:[ \t]*([^\r\n]*)", re.IGNORECASE)
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9.+-]+")
#: Operators of licence expressions and how tightly they bind.
BINDS = {"or": 1, "and": 2, "with": 3}


def postfix(expression: str) -> list[str]:
    """Postfix form of a licence expression; reading stops where the expression ends. Empty if there is none."""
    out: list[str] = []
    held: list[str] = []
    operand = True  # is one wanted next?
    for token in _TOKEN.findall(expression):
        word = token.lower()
        if operand:
            if token == "(":
                held.append(token)
            elif word in BINDS or token == ")":
                break
            else:
                out.append(word)
                operand = False
        elif word in BINDS:
            while held and held[-1] != "(" and BINDS[held[-1]] >= BINDS[word]:
                out.append(held.pop())
            held.append(word)
            operand = True
        elif token == ")" and "(" in held:
            while held[-1] != "(":
                out.append(held.pop())
            held.pop()
        else:
            break
    if operand:  # an operator without its right side falls away
        while held and held[-1] in BINDS:
            held.pop()
            break
    out += [op for op in reversed(held) if op != "("]
    return out


def alternatives(expression: str) -> list[frozenset[str]]:
    """Sets of licences, each of which satisfies the expression: ``or`` adds sets, ``and`` joins them, ``with`` binds an exception.

    All of them, which are as many as the product of the sizes joined by ``and``; ``licences`` needs no such product.
    """
    stack: list[list[frozenset[str]]] = []
    for token in postfix(expression):
        if token not in BINDS:
            stack.append([frozenset([token])])
            continue
        if len(stack) < 2:
            continue
        right, left = stack.pop(), stack.pop()
        if token == "or":
            stack.append(list(dict.fromkeys(left + right)))
        elif token == "and":
            stack.append(list(dict.fromkeys(x | y for x in left for y in right)))
        else:
            stack.append([frozenset(f"{a} with {b}" for a in x for b in y) for x in left for y in right])
    return stack[-1] if stack else []


def licences(expression: str) -> set[str]:
    """Every licence named by an expression: its operands, ``x with y`` as one."""
    stack: list[set[str]] = []
    for token in postfix(expression):
        if token not in BINDS:
            stack.append({token})
        elif len(stack) > 1:
            right = stack.pop()
            if token == "with":
                stack[-1] = {f"{a} with {b}" for a in stack[-1] for b in right}
            elif len(right) > len(stack[-1]):
                right |= stack[-1]
                stack[-1] = right
            else:
                stack[-1] |= right
    return stack[-1] if stack else set()


def automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for phrase in (*BASE, *NOTICES, TAG):
        found.add_word(f" {phrase} ", phrase)
    found.make_automaton()
    return found


def scan(text: bytes, phrases) -> dict:
    """What one document says of licences. Words are numbered from 0; every place of a base phrase counts."""
    words = text.translate(_WORDS).split()
    line = (b" " + b" ".join(words) + b" ").decode("utf-8")
    starts: list[int] = []
    base: set[str] = set()
    extra: set[str] = set()
    score = 0.0
    word, seen = 0, 0
    for end, phrase in phrases.iter(line):
        if phrase in BASE:
            begin = end - len(phrase) - 1
            word, seen = word + line.count(" ", seen, begin), max(seen, begin)  # ends come in order, starts nearly so
            starts.append(word if begin == seen else line.count(" ", 0, begin))
            base.add(BASE[phrase])
            score = max(score, 0.8)
        elif phrase in NOTICES:
            label, weight = NOTICES[phrase]
            extra.add(label)
            score = max(score, weight)
        else:
            for said in _TAG_LINE.findall(text):
                named = licences(said.decode("utf-8", "ignore"))
                extra |= named
                score = 1.0 if named else score
    return {
        "n_words": len(words), "n_base": len(starts), "first_word": min(starts, default=None), "last_word": max(starts, default=None),
        "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(base | extra)), "score": score,
    }


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def license_scan(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text), whole texts; SCHEMA gives the columns.

    Null text is empty: no words, empty labels, score 0. Repeated rows each get a row, a null doc_id stays null,
    other columns are not read, an empty table gives an empty one.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        phrases = automaton()
        kinds = {"score": pa.float64(), "base_labels": pa.string(), "labels": pa.string()}
        for batch in batches:
            rows = [scan(t, phrases) for t in binary_column(batch, "text")]
            names = [c.split()[0] for c in SCHEMA.split(", ")][1:]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array([r[n] for r in rows], kinds.get(n, pa.int64())) for n in names)], ["doc_id", *names])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, SCHEMA)
