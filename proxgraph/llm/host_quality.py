"""Host-level quality rules.

Every document is judged by rules; failures are counted per host, each host's rate of each rule is
shrunk towards all hosts by a beta prior fitted to the hosts themselves (method of moments), and
the host verdicts are joined back:

* a host is ``blocked`` if the shrunk rate of documents that fail a hard rule exceeds ``block_rate``:
  none of its documents is kept;
* a host is ``strict`` if the shrunk rate of any soft rule exceeds ``strict_rate``: its documents
  must pass the soft rules too;
* elsewhere a document is kept unless it fails a hard rule.

Null hosts form one host of their own.  Null and empty texts have no words (and fail the word
minimum).  Repeated rows count as often as they occur.  An empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WHITE, arrow_map, binary_column, drop_rows, saved

SYMBOLS = b"#*$%&|<>"
_NO_LETTER = bytes(range(0x80, 0xC0)) + WHITE
HARD = ("short", "repetitive")
SOFT = ("symbol_heavy", "duplicate_lines", "odd_word_length")

_COUNTS = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def count_document(text: bytes) -> tuple[int, ...]:
    """The counts of one text, in the order of ``_COUNTS``."""
    words = text.split()
    n = len(words)
    repeat = 0
    if n > 3:
        grams = list(zip(words, words[1:], words[2:], strict=False))
        held = Counter(grams)
        if len(held) < len(grams):
            end = 0
            for i, g in enumerate(grams):
                if held[g] > 1:
                    repeat += i + 3 - max(end, i)
                    end = i + 3
    lines = [x for x in text.split(b"\n") if x.strip()]
    return n, len(text.translate(None, _NO_LETTER)), len(text) - len(text.translate(None, SYMBOLS)), len(lines), len(lines) - len(set(lines)), repeat


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [count_document(x) for x in binary_column(batch, "body")]
        columns = list(zip(*found, strict=True)) or [()] * len(_COUNTS)
        yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("text_hash"), batch.column("host"), *(pa.array(c, pa.int64()) for c in columns)], names=["id", "text_hash", "host", *_COUNTS])


def rules(min_words: int = 50, max_repeat: int = 50) -> dict[str, Column]:
    """Rule name -> failure, over the counts."""
    n = F.col("n_words")
    return {
        "short": n < min_words,
        "repetitive": 100 * F.col("n_repeat_words") > max_repeat * n,
        "symbol_heavy": 10 * F.col("n_symbols") > n,
        "duplicate_lines": 10 * F.col("n_dup_lines") > 3 * F.col("n_lines"),
        "odd_word_length": (F.col("word_chars") < 3 * n) | (F.col("word_chars") > 10 * n),
    }


def beta_prior(mean: float | None, var: float | None, most: float) -> tuple[float, float]:
    """(a, b) of a beta with the hosts' mean and variance; ``most`` bounds a + b from above."""
    mean = min(max(mean or 0.0, 1e-4), 1 - 1e-4)
    size = min(max(mean * (1 - mean) / var - 1, 1.0), most) if var else most
    return mean * size, (1 - mean) * size


def host_rates(judged: DataFrame, names: tuple[str, ...], max_prior: float = 1000.0) -> DataFrame:
    """One row per host: n_docs and the shrunk failure rate of each rule."""
    hosts = saved(judged.groupBy("host").agg(F.count("*").alias("n_docs"), *(F.sum(F.col(x).cast("long")).alias(f"{x}_fails") for x in names)))
    moments = hosts.agg(*(y for x in names for y in (F.avg(F.col(f"{x}_fails") / F.col("n_docs")).alias(f"{x}_mean"), F.var_pop(F.col(f"{x}_fails") / F.col("n_docs")).alias(f"{x}_var"))))
    m, out = moments.first(), hosts
    for x in names:
        a, b = beta_prior(m[f"{x}_mean"], m[f"{x}_var"], max_prior)
        out = out.withColumn(f"{x}_rate", (F.col(f"{x}_fails") + F.lit(a)) / (F.col("n_docs") + F.lit(a + b)))
    return out.select("host", "n_docs", *(f"{x}_rate" for x in names))


def judge(docs: DataFrame, block_rate: float = 0.9, strict_rate: float = 0.5, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """One row per input row: id, counts, ``base_failed``, ``host_verdict`` (open, strict or blocked), ``kept``."""
    body = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(F.col(text_col).cast("string")).alias("text_hash"), F.col(host_col).cast("string").alias("host"), F.col(text_col).cast("string").cast("binary").alias("body"))
    counts = arrow_map(body, _count, "id long, text_hash long, host string, " + ", ".join(f"{c} long" for c in _COUNTS))
    failed = rules()
    judged = saved(counts.select("*", *(failed[x].alias(x) for x in HARD + SOFT)).withColumn("base_failed", F.col("short") | F.col("repetitive")))
    rates = host_rates(judged, ("base_failed", *SOFT))
    soft_rate = F.greatest(*(F.col(f"{x}_rate") for x in SOFT))
    verdict = F.when(F.col("base_failed_rate") > block_rate, "blocked").when(soft_rate > strict_rate, "strict").otherwise("open")
    hosts = rates.select(F.col("host").alias("of_host"), verdict.alias("host_verdict"))
    out = judged.join(hosts, F.col("host").eqNullSafe(F.col("of_host")), "left")
    soft = F.lit(False)
    for x in SOFT:
        soft = soft | F.col(x)
    kept = ~F.col("base_failed") & (F.col("host_verdict") != "blocked") & ~((F.col("host_verdict") == "strict") & soft)
    return out.select(F.col("id").alias(id_col), "text_hash", F.col("host").alias(host_col), *_COUNTS, "base_failed", "host_verdict", kept.alias("kept"))


def filter_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows that are kept, with all their columns."""
    bad = judge(docs, id_col=id_col, text_col=text_col, **options).where("not kept")
    return drop_rows(docs, bad.select(F.col(id_col).alias("id"), "text_hash"), id_col, text_col)
