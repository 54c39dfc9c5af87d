"""License scan: an Aho-Corasick automaton over words finds identifier tags and notice phrases in one pass
over each text; the expression behind a tag is parsed by a shunting-yard parser and evaluated.

Words are runs of letters, digits and non-ASCII characters, A-Z in lower case; a phrase matches where
its words stand consecutively.  Labels: one per phrase, and the families named in a valid expression.
An expression goes to the end of its line; what follows it there is prose.  The score is one minus the product of ``1 - weight`` over the distinct kinds of evidence.

Null and empty texts have no words, places or labels (score 0).  Rows are judged one by one.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, binary_column

#: Phrases whose places are counted.
BASE_PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Further notices that give a label: phrase -> (label, weight).
NOTICES = {
    "permission is hereby granted free of charge": ("mit", 0.9),
    "redistribution and use in source and binary forms": ("bsd", 0.9),
    "bsd license": ("bsd", 0.7),
    "isc license": ("isc", 0.7),
    "mozilla public license": ("mpl", 0.8),
    "lesser general public license": ("lgpl", 0.8),
    "affero general public license": ("agpl", 0.8),
    "gnu general public license": ("gpl", 0.8),
    "cc by nc": ("cc-by-nc", 0.8),
    "cc by sa": ("cc-by-sa", 0.8),
    "cc by nd": ("cc-by-nd", 0.8),
    "cc by 4 0": ("cc-by", 0.8),
    "creative commons attribution": ("cc-by", 0.7),
    "eclipse public license": ("epl", 0.8),
    "boost software license": ("bsl", 0.8),
    "public domain": ("public-domain", 0.3),
    "all rights reserved": ("proprietary", 0.5),
}
BASE_WEIGHT = 0.7
TAG = "spdx license identifier"
TAG_WEIGHT = 0.95
#: Family by the beginning of an identifier; the first that fits.
FAMILIES = (
    ("agpl", "agpl"), ("lgpl", "lgpl"), ("gpl", "gpl"), ("mit", "mit"), ("apache", "apache"), ("bsd", "bsd"), ("0bsd", "bsd"),
    ("mpl", "mpl"), ("isc", "isc"), ("epl", "epl"), ("bsl", "bsl"), ("cc-by-nc", "cc-by-nc"), ("cc-by-sa", "cc-by-sa"),
    ("cc-by-nd", "cc-by-nd"), ("cc-by", "cc-by"), ("cc0", "public-domain"), ("unlicense", "public-domain"), ("zlib", "zlib"),
)
PERMISSIVE = frozenset({"mit", "apache", "bsd", "isc", "bsl", "zlib", "cc-by", "public-domain"})

_PRECEDENCE = {"or": 1, "and": 2, "with": 3}
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9.+:-]+")
_COLON = re.compile(rb"\s*:\s*")
_LINE_END = re.compile(rb"[\n\r*]|\Z")
#: Names of no known family that may still be licenses: with a digit, a hyphen or capitals only.
_NAME = re.compile(r"(?=.*[0-9-])[A-Za-z0-9.+:-]+|[A-Z.+]{2,}")
_WORD_BYTES = bytes((c + 32 if 65 <= c <= 90 else c) if (48 <= c <= 57 or 65 <= c <= 90 or 97 <= c <= 122 or c > 127) else 32 for c in range(256))


def family(identifier: str) -> str:
    low = identifier.lower()
    return next((f for start, f in FAMILIES if low.startswith(start)), "other")


def is_name(token: str) -> bool:
    return family(token) != "other" or _NAME.fullmatch(token) is not None


def to_postfix(text: str, start: int = 0, end: int | None = None) -> list[str] | None:
    """Postfix form of the license expression in text[start:end] (``with`` binds most, then ``and``, then ``or``), None if it is malformed.

    Words that can't be names of licenses end the expression, with the operator before them.
    """
    out: list[str] = []
    waiting: list[str] = []
    operand_next = True
    depth = 0
    tokens = _TOKEN.finditer(text, start, len(text) if end is None else end)
    ahead = next(tokens, None)
    while ahead is not None:
        token, ahead = ahead[0], next(tokens, None)
        op = token.lower()
        if token == "(":
            if not operand_next:
                return None
            waiting.append(token)
            depth += 1
        elif token == ")":
            if operand_next or not depth:
                return None
            depth -= 1
            while waiting and waiting[-1] != "(":
                out.append(waiting.pop())
            if not waiting:
                return None
            waiting.pop()
        elif op in _PRECEDENCE:
            if operand_next:
                return None
            if not depth and ahead is not None and ahead[0] != "(" and ahead[0].lower() not in _PRECEDENCE and not is_name(ahead[0]):
                break  # prose after the expression
            while waiting and waiting[-1] != "(" and _PRECEDENCE[waiting[-1]] >= _PRECEDENCE[op]:
                out.append(waiting.pop())
            waiting.append(op)
            operand_next = True
        else:
            if operand_next and not is_name(token):
                return None
            if not operand_next:
                break  # prose after the expression
            out.append(token)
            operand_next = False
    if operand_next or "(" in waiting:
        return None
    return out + waiting[::-1]


def evaluate(text: str, start: int = 0, end: int | None = None) -> tuple[frozenset, bool] | None:
    """(families named, may it be used under permissive terms) of the expression in text[start:end]; None if malformed.

    ``or`` needs one permissive side, ``and`` both; ``with`` keeps the terms of its license.
    """
    postfix = to_postfix(text, start, end)
    if not postfix:
        return None
    stack: list[tuple[frozenset, bool]] = []
    for token in postfix:
        if token not in _PRECEDENCE:
            f = family(token)
            stack.append((frozenset({f}), f in PERMISSIVE))
            continue
        if len(stack) < 2:
            return None
        right, left = stack.pop(), stack.pop()
        if token == "with":
            stack.append(left)
        else:
            stack.append((left[0] | right[0], (left[1] or right[1]) if token == "or" else (left[1] and right[1])))
    return stack[0] if len(stack) == 1 else None


class PhraseAutomaton:
    """Aho-Corasick over words: all places of all phrases, in one pass."""

    def __init__(self, phrases):
        self.goto: list[dict[bytes, int]] = [{}]
        self.found: list[list[tuple[str, int]]] = [[]]
        for phrase in sorted(phrases):
            at = 0
            words = phrase.encode().split()
            for w in words:
                to = self.goto[at].get(w)
                if to is None:
                    to = self.goto[at][w] = len(self.goto)
                    self.goto.append({})
                    self.found.append([])
                at = to
            self.found[at].append((phrase, len(words)))
        self.fail = [0] * len(self.goto)
        level = list(self.goto[0].values())
        while level:
            for v in level:
                for w, to in self.goto[v].items():
                    z = self.fail[v]
                    while z and w not in self.goto[z]:
                        z = self.fail[z]
                    self.fail[to] = self.goto[z].get(w, 0)
                    self.found[to] = self.found[to] + self.found[self.fail[to]]
            level = [to for v in level for to in self.goto[v].values()]

    def places(self, words: list[bytes]) -> Iterator[tuple[str, int]]:
        """(phrase, number of its first word)."""
        goto, fail, found = self.goto, self.fail, self.found
        first, state = goto[0].get, 0
        for i, w in enumerate(words):
            if state:
                while state and w not in goto[state]:
                    state = fail[state]
                state = goto[state].get(w, 0)
            else:
                state = first(w, 0)
            for phrase, size in found[state] if state else ():
                yield phrase, i - size + 1


def build_automaton() -> PhraseAutomaton:
    return PhraseAutomaton({*BASE_PHRASES, *NOTICES, TAG})


def tag_values(text: bytes, plain: bytes, tags: list[int]) -> Iterator[tuple[frozenset, bool]]:
    """What the expression behind each tag says; ``tags`` are the numbers of their first words, in order."""
    letters = np.frombuffer(plain, np.uint8) != 32
    letters[1:] &= ~letters[:-1].copy()
    starts = np.flatnonzero(letters)
    size = len(TAG.split()[-1])
    line_end = -1
    for tag in tags:
        colon = _COLON.match(text, int(starts[tag + 2]) + size)
        if colon is None:
            continue
        if colon.end() > line_end:
            line_end = _LINE_END.search(text, colon.end()).start()
        value = evaluate(text[colon.end() : _expression_end(text, colon.end(), line_end)].decode("utf-8", "replace"))
        if value is not None:
            yield value


_NEXT_TAG = re.compile(rb"(?i)spdx\W*license\W*identifier")


def _expression_end(text: bytes, start: int, line_end: int) -> int:
    """A line's next tag ends an expression."""
    other = _NEXT_TAG.search(text, start, line_end)
    return other.start() if other else line_end


def scan_text(text: bytes, automaton: PhraseAutomaton) -> tuple:
    plain = text.translate(_WORD_BYTES)
    words = plain.split()
    places, base, labels, weights, permissive, tags = [], set(), set(), {}, None, []
    for phrase, at in automaton.places(words):
        if phrase in BASE_PHRASES:
            places.append(at)
            base.add(BASE_PHRASES[phrase])
            weights[phrase] = BASE_WEIGHT
        elif phrase == TAG:
            tags.append(at)
        if phrase in NOTICES:
            label, weight = NOTICES[phrase]
            labels.add(label)
            weights[phrase] = weight
    for named, may in tag_values(text, plain, tags) if tags else ():
        labels |= named
        weights[TAG] = TAG_WEIGHT
        permissive = may if permissive is None else permissive and may
    rest = 1.0
    for phrase in sorted(weights):
        rest *= 1 - weights[phrase]
    if permissive is None and base | labels:
        permissive = (base | labels) <= PERMISSIVE
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)), ",".join(sorted(base | labels)), 1 - rest, permissive


_COLUMNS = {"n_words": pa.int64(), "n_base": pa.int64(), "first_word": pa.int64(), "last_word": pa.int64(), "base_labels": pa.string(), "labels": pa.string(), "score": pa.float64(), "permissive": pa.bool_()}


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    automaton = build_automaton()
    for batch in batches:
        rows = [scan_text(x, automaton) for x in binary_column(batch, "body")]
        columns = list(zip(*rows, strict=True)) or [()] * len(_COLUMNS)
        yield pa.RecordBatch.from_arrays([batch.column("id"), *(pa.array(c, t) for c, t in zip(columns, _COLUMNS.values(), strict=True))], names=["id", *_COLUMNS])


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_words, n_base, first_word, last_word, base_labels, labels, score, permissive."""
    body = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("body"))
    out = arrow_map(body, _scan, "id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, permissive boolean")
    return out.withColumnRenamed("id", id_col)
