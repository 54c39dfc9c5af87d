"""Greedy longest-match word-piece counts by a linear automaton.

The vocabulary is a trie with failure links.  The link of a node leads to the node that the rest of
its string reaches after the greedy pieces at its front are cut off; the number of those pieces is
stored with it.  Reading a word is then one step per byte, and the count is a sum of stored numbers:
no piece is ever built.

A vocabulary entry is a byte string.  Entries with the file's end-of-word mark match at the end of a word
only, the others before it only: the last byte of a word is a symbol of its own (the byte plus 256), so
both kinds share the trie.  Without marked entries every piece may stand anywhere.  Words are runs of letters, digits and non-ASCII bytes, or single other ASCII
signs, in lower case (A-Z).  A word with a part that no piece begins is one unknown token.

Null and empty texts have no words.  Rows are counted one by one.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, binary_column

_UNIT = re.compile(rb"[0-9a-z\x80-\xff]+|[^\s]")
#: Words whose counts a task keeps; the memory bound of the cache, which is then started anew.
CACHE = 400_000
#: What the last byte of a word has on top.
_LAST = 256


def _printable_bytes() -> dict[str, int]:
    """The printable stand-ins of bytes in byte-level vocabularies, back to the bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def read_vocabulary(path: str, end_mark: str = "</w>") -> tuple[list[bytes], list[bytes]]:
    """(pieces inside words, pieces at the end of words) of a tokenizer file."""
    with open(path, encoding="utf-8") as f:
        entries = json.load(f)["model"]["vocab"]
    back = _printable_bytes()
    inside, last = set(), set()
    for entry in entries:
        body = entry.removesuffix(end_mark)
        if body and all(c in back for c in body):
            (last if body != entry else inside).add(bytes(back[c] for c in body))
    return sorted(inside), sorted(last)


class PieceCounter:
    """The automaton of a vocabulary; ``last`` are the pieces that end a word (None: all pieces)."""

    def __init__(self, pieces: Iterable[bytes], last: Iterable[bytes] | None = None):
        pieces = list(pieces)
        self.next: list[dict[int, int]] = [{}]
        final = [False]
        parent = [(0, 0)]
        ending = [[*p[:-1], p[-1] + _LAST] for p in (pieces if last is None else last) if p]
        for piece in [*map(list, pieces), *ending]:
            at = 0
            for c in piece:
                to = self.next[at].get(c)
                if to is None:
                    to = self.next[at][c] = len(self.next)
                    self.next.append({})
                    final.append(False)
                    parent.append((at, c))
                at = to
            final[at] = at > 0
        self.link = [-1] * len(self.next)
        self.popped = [0] * len(self.next)
        level = list(self.next[0].values())
        while level:
            for v in level:
                if final[v]:
                    self.link[v], self.popped[v] = 0, 1
                    continue
                u, c = parent[v]
                cut, z = self.popped[u], self.link[u]
                while z >= 0 and c not in self.next[z]:
                    cut, z = cut + self.popped[z], self.link[z]
                if z >= 0:
                    self.link[v], self.popped[v] = self.next[z][c], cut
            level = [w for v in level for w in self.next[v].values()]

    def count(self, word: bytes) -> int:
        """Pieces of a word; 0 if it can't be cut into pieces."""
        nexts, link, popped = self.next, self.link, self.popped
        at = n = 0
        for c in (*word[:-1], word[-1] + _LAST) if word else ():
            while (to := nexts[at].get(c)) is None:
                if link[at] < 0:
                    return 0
                n += popped[at]
                at = link[at]
            at = to
        while at:
            if link[at] < 0:
                return 0
            n += popped[at]
            at = link[at]
        return n


def _count(pieces: list[bytes], last: list[bytes] | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter, kept = PieceCounter(pieces, last), {}

        def of(word: bytes) -> tuple[int, int, int]:
            units = _UNIT.findall(word)
            counts = [counter.count(u) for u in units]
            unknown = counts.count(0)
            return len(units), sum(counts) + unknown, unknown

        for batch in batches:
            columns: list[list[int]] = [[], [], []]
            for text in binary_column(batch, "body"):
                units = total = unknown = 0
                for word in text.lower().split():
                    found = kept.get(word)
                    if found is None:
                        if len(kept) >= CACHE:
                            kept.clear()
                        found = kept[word] = of(word)
                    units += found[0]
                    total += found[1]
                    unknown += found[2]
                for c, v in zip(columns, (units, total, unknown), strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([batch.column("id"), *(pa.array(c, pa.int64()) for c in columns)], names=["id", "n_units", "n_tokens", "n_unknown"])

    return run


def count_pieces(docs: DataFrame, vocabulary: str | Iterable[bytes], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_units (words and signs), n_tokens, n_unknown.

    ``vocabulary`` is the path of a tokenizer file or a list of pieces.  A vocabulary file is read by the driver; its pieces (about a megabyte) go out with the tasks.
    """
    pieces, last = read_vocabulary(vocabulary) if isinstance(vocabulary, str) else (sorted(set(vocabulary)), None)
    body = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("body"))
    return arrow_map(body, _count(pieces, last), "id long, n_units long, n_tokens long, n_unknown long").withColumnRenamed("id", id_col)
