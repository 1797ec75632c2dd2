"""Licence scan: one Aho-Corasick pass over each text's word sequence, and licence expressions.

Texts become words ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` after lower-casing A-Z; the automaton runs over
the words joined by single spaces, so a hit is a place where a phrase's words stand consecutively.
Where identifier tags stand, the expression after each is read from the raw text and put through a
shunting-yard parser (with > and > or), which gives its identifiers and whether some choice of
licences that it allows is permissive. A text with several tags is under all of them: it is permissive
if each allows a permissive choice.

Defined results: a null or empty text has no words, no places, empty labels, score 0 and null
first_word and last_word; repeated rows are scanned alike; a malformed expression keeps its
identifiers, makes the text not permissive and has no place among its expressions (one postfix form for
each well-formed tag, in order; null without any tag); extra columns are ignored.
"""

from __future__ import annotations

import re

import ahocorasick
import pandas as pd
from pyspark.sql import DataFrame

from .shared import map_texts, pick

# Phrases and their labels.
BASE_PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}
NOTICES = {
    "permission is hereby granted free of charge": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "boost software license": "bsl",
    "bsd license": "bsd",
    "isc license": "isc",
    "cc by nc": "cc-by-nc",
    "cc by nd": "cc-by-nd",
    "cc by sa": "cc-by-sa",
    "cc0 1 0": "cc0",
    "all rights reserved": "all-rights-reserved",
}
PERMISSIVE = ("0bsd", "apache-2.0", "bsd-2-clause", "bsd-3-clause", "bsl-1.0", "cc0-1.0", "isc", "mit", "unlicense", "zlib")
TAG = "spdx license identifier"

WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
_TAG_LINE = re.compile(r"spdx-license-identifier:[ \t]*([^\r\n]*)", re.IGNORECASE)
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9.+:-]+")
_BINDS = {"or": 1, "and": 2, "with": 3}


def parse_expression(text: str) -> tuple[list[str], list[str] | None]:
    """(identifiers, postfix form or None if malformed) of a licence expression; stops at other text."""
    out, held, names, operand = [], [], [], False
    for token in _TOKEN.findall(text):
        low = token.lower()
        if low in _BINDS:
            if not operand:
                return names, None
            while held and held[-1] != "(" and _BINDS[held[-1]] >= _BINDS[low]:
                out.append(held.pop())
            held.append(low)
            operand = False
        elif token == "(":
            if operand:
                break
            held.append(token)
        elif token == ")":
            if not operand or "(" not in held:
                return names, None
            while held[-1] != "(":
                out.append(held.pop())
            held.pop()
        else:
            if operand:
                break
            low = low.rstrip(".:")
            if not (held and held[-1] == "with"):
                names.append(low)
            out.append(low)
            operand = True
    if not operand or "(" in held:
        return names, None
    return names, out + held[::-1]


def permits(postfix: list[str], allowed=PERMISSIVE) -> bool:
    """Whether the postfix expression can be met with allowed licences; an exception leaves its licence as it is."""
    values: list[bool] = []
    for token in postfix:
        if token in _BINDS:
            right, left = values.pop(), values.pop()
            values.append(left if token == "with" else left and right if token == "and" else left or right)
        else:
            values.append(token.rstrip("+") in allowed)
    return values[-1]


def scanner(base: dict[str, str], notices: dict[str, str]):
    def run(batches):
        found = ahocorasick.Automaton()
        for own, phrases in ((0, base), (1, notices), (2, {TAG: ""})):
            for phrase, label in phrases.items():
                as_bytes = f" {phrase} ".encode()
                found.add_word(as_bytes.decode("latin-1"), (own, label, len(as_bytes) - 1, phrase.count(" ") + 1))
        found.make_automaton()
        for pdf in batches:
            rows = []
            for doc_id, text in zip(pdf["doc_id"], pdf["text"]):
                words = text.encode("utf-8", "surrogatepass").translate(WORD_BYTES).split() if text else []
                line = b" " + b" ".join(words) + b" "
                spans, tagged, at, counted = [], False, 0, 0
                for end, (own, label, back, n) in found.iter(line.decode("latin-1")) if words else ():
                    start = end - back
                    counted += line.count(b" ", at, start) if start >= at else -line.count(b" ", start, at)
                    at = start
                    if own == 2:
                        tagged = True
                    else:
                        spans.append((label, counted, n, own == 0))
                names, expressions, permissive = [], None, None
                for m in _TAG_LINE.finditer(text) if tagged else ():
                    more, postfix = parse_expression(m[1])
                    names += more
                    expressions = (expressions or []) + ([" ".join(postfix)] if postfix else [])
                    permissive = permissive is not False and postfix is not None and permits(postfix)
                starts = [s[1] for s in spans if s[3]]
                n_other = len(spans) - len(starts)
                rows.append((
                    doc_id, len(words), len(starts), min(starts, default=None), max(starts, default=None),
                    ",".join(sorted({s[0] for s in spans if s[3]})), ",".join(sorted({s[0] for s in spans} | set(names))),
                    1.0 - 0.5 ** min(50, len(starts) + n_other + 2 * len(names)), expressions, permissive,
                    [{"label": s[0], "first_word": s[1], "n_words": s[2]} for s in spans],
                ))
            out = pd.DataFrame(rows, columns=["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "expressions", "permissive", "spans"])
            yield out.astype({"doc_id": "Int64", "first_word": "Int64", "last_word": "Int64", "permissive": "boolean"})

    return run


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", base: dict[str, str] = BASE_PHRASES, notices: dict[str, str] = NOTICES) -> DataFrame:
    """One row per document: word count, base places, labels, score, expressions and all spans."""
    return map_texts(
        pick(docs, doc_id=id_col, text=text_col),
        scanner(base, notices),
        "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, "
        "expressions array<string>, permissive boolean, spans array<struct<label:string,first_word:long,n_words:long>>",
    )
