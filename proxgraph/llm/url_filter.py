"""URL rules by a bit-parallel wildcard automaton.

All globs are laid out one after the other in a row of bits cut into 64-bit words.  One Shift-And
step per character moves every active place of every glob at once, for a whole batch of URLs:
``D = (shift(D) & step[c]) | (D & stay[c])`` where ``stay`` holds the places after a ``*`` (they
loop on any character).  Places after a run of stars are entered together with the place before.

Globs are matched against the canonical URL: host in lower case (A-Z), then path, then ``?query``
if there is one; scheme and fragment are dropped.  ``*`` is any string, ``?`` any one byte, and a
backslash takes the next sign as it is.
Host rules win over globs; among the globs, any allow glob wins over block globs; else ``default``.

Null URLs and URLs without ``://`` have an empty host and path and match only globs of stars.  Rows are
judged one by one, so repeated rows have the same verdict.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_map

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: (verdict, host, path): a rule fits its host and all subdomains if the path starts with its path.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
#: (verdict, glob) for the rest.
GLOBS = (
    ("allow", "*/robots.txt"),
    ("block", r"*\?*utm_source=*"),
    ("block", r"*\?*sessionid=*"),
    ("block", "*/login*"),
    ("block", "*/cart/*"),
    ("block", "ads.*"),
    ("block", "*.ads.*"),
    ("block", "*/wp-admin/*"),
    ("block", "*.zip"),
    ("block", "*.exe"),
    ("block", "*/tag/*/page/*"),
)


class GlobAutomaton:
    """Simultaneous matching of globs over byte strings."""

    def __init__(self, globs: Sequence[str]):
        self.globs = tuple(globs)
        places: list[tuple[int | None, bool]] = []  # per place: byte it is entered by, does it loop
        begin, self.final = [], []
        for g in self.globs:
            begin.append(len(places))
            places.append((-1, False))  # the start of a glob is never entered by a shift
            signs = iter(g.encode())
            for b in signs:
                if b == 92 and (taken := next(signs, None)) is not None:
                    places.append((taken, False))
                elif b == 42:
                    places[-1] = (places[-1][0], True)
                else:
                    places.append((None if b == 63 else b, False))
            self.final.append(len(places) - 1)
        self.words = max(1, -(-len(places) // 64))
        self.step = np.zeros((256, self.words), np.uint64)
        self.stay = np.zeros(self.words, np.uint64)
        self.start = np.zeros(self.words, np.uint64)
        for i, (b, loops) in enumerate(places):
            at, bit = i // 64, np.uint64(1) << np.uint64(i % 64)
            if b is None:
                self.step[:, at] |= bit
            elif b >= 0:
                self.step[b, at] |= bit
            if loops:
                self.stay[at] |= bit
        for i in begin:
            self.start[i // 64] |= np.uint64(1) << np.uint64(i % 64)

    def match(self, raw: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """(texts, globs) booleans for the byte strings of a block."""
        n = len(offs) - 1
        state = np.repeat(self.start[None, :], n, axis=0)
        size = offs[1:] - offs[:-1]
        order = np.argsort(-size, kind="stable")  # the longest first: the live ones are a prefix
        live = np.searchsorted(-size[order], -np.arange(1, (size.max() if n else 0) + 1), "right")
        head = offs[:-1][order]
        for t, k in enumerate(live):
            now = state[:k]
            moved = now << np.uint64(1)
            moved[:, 1:] |= now[:, :-1] >> np.uint64(63)
            state[:k] = (moved & self.step[raw[head[:k] + t]]) | (now & self.stay)
        out = np.zeros((n, len(self.globs)), bool)
        for j, f in enumerate(self.final):
            out[order, j] = (state[:, f // 64] >> np.uint64(f % 64)) & np.uint64(1) > 0
        return out


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end; A-Z in lower case."""
    rest = F.substring_index(_rest(url), "/", 1)
    return F.translate(F.substring_index(F.substring_index(rest, "?", 1), "#", 1), _UPPER, _LOWER)


def _rest(url: Column) -> Column:
    at = F.locate("://", url)
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def path_of(url: Column) -> Column:
    """After the host up to ``?``, ``#`` or the end."""
    plain = F.substring_index(F.substring_index(_rest(url), "?", 1), "#", 1)
    slash = F.locate("/", plain)
    return F.when(slash > 0, F.substring(plain, slash, F.length(plain))).otherwise("")


def canonical_url(url: Column) -> Column:
    """host + path + ?query; scheme and fragment are dropped."""
    plain = F.substring_index(_rest(url), "#", 1)
    mark = F.locate("?", plain)
    query = F.when(mark > 0, F.substring(plain, mark, F.length(plain))).otherwise("")
    return F.concat(host_of(url), path_of(url), query)


def _rule(host: Column, path: Column, rules) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits; nulls without one.  Longer hosts come first, then longer paths."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for v, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r[1], r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, h + p).otherwise(rule), F.when(fits, v).otherwise(verdict)
    return rule, verdict


def _glob_hits(globs: tuple[str, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from .common import blocks

        automaton = GlobAutomaton(globs)
        for batch in batches:
            hits = [automaton.match(raw, offs) for _, _, raw, offs in blocks(batch.column("canonical"), 1 << 20)]
            hits = np.concatenate(hits) if hits else np.zeros((0, len(globs)), bool)
            sizes = np.concatenate(([0], np.cumsum(hits.sum(1))))
            lists = pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(np.nonzero(hits)[1].astype(np.int32)))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in batch.schema.names if c != "canonical"), lists], names=[*(c for c in batch.schema.names if c != "canonical"), "globs"])

    return run


def filter_urls(pages: DataFrame, rules=RULES, globs=GLOBS, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row per input row: id, host, path, rule, verdict, globs (numbers of the globs that match)."""
    url = F.coalesce(F.col(url_col).cast("string"), F.lit(""))
    base = pages.select(F.col(id_col).cast("long").alias("id"), host_of(url).alias("host"), path_of(url).alias("path"), canonical_url(url).cast("binary").alias("canonical"))
    out = arrow_map(base, _glob_hits(tuple(g for _, g in globs)), "id long, host string, path string, globs array<int>")
    rule, verdict = _rule(F.col("host"), F.col("path"), rules)
    hit = lambda v: F.exists("globs", lambda i: i.isin([k for k, (w, _) in enumerate(globs) if w == v])) if any(w == v for w, _ in globs) else F.lit(False)
    other = F.when(hit("allow"), "allow").when(hit("block"), "block").otherwise(default)
    return out.select(F.col("id").alias(id_col), "host", "path", rule.alias("rule"), F.coalesce(verdict, other).alias("verdict"), "globs")
