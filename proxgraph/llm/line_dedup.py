"""Removal of repeated runs of lines.

The lines with a word of each document are a sequence of line ids.  Suffixes of all sequences are
ranked by prefix doubling: ranks of length-L prefixes at a place and L places on give the ranks of
length 2L.  Ranks are positions in the sorted order of the distinct keys, found by a range-partitioned
sort with partition offsets, so a key that a third of all suffixes share is one row of that sort.  A
suffix whose prefix is unique leaves: it is in no interval of the LCP table at this or a longer length.

An LCP interval of length ``min_lines`` is a set of suffixes with equal first ``min_lines`` lines.
All but the earliest of an interval, by (id, place), are later copies; the lines they cover are
deleted.  Overlapping copies merge into maximal runs.  With ``min_words``, a line of at least that
many words is an interval of its own.

Null ids: the row is left alone and is no source.  Rows that are equal in id and text are one
document; rows that share an id but differ in text are ordered by a text hash.  Null texts stay
null.  Blank lines are never part of a run and stay.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, join_bounded, saved

#: A line with a character that is no white space.
_HAS_WORD = r"[^\x20\x09-\x0D]"


#: Words from which the query and the pipeline take a single line as a passage.
PASSAGE_WORDS = 50


def line_sequences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text_hash, place, line, h1, h2): lines with a word; ``place`` counts them, ``line`` counts all lines."""
    text = F.col(text_col).cast("string")
    base = docs.where(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text).alias("text_hash"), F.filter(F.transform(F.split(text, "\n"), lambda x, i: F.struct(i.alias("line"), F.xxhash64(x).alias("h1"), F.hash(x).alias("h2"), x.rlike(_HAS_WORD).alias("full"))), lambda x: x["full"]).alias("lines"))
    out = base.select("id", "text_hash", F.posexplode("lines").alias("place", "l"))
    return out.select("id", "text_hash", "place", "l.line", "l.h1", "l.h2")


def _local_ranks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows before each key, within this partition of the sorted keys."""
    part, run = TaskContext.get().partitionId(), 0
    for batch in batches:
        before = []
        for n in batch.column("n").to_pylist():
            before.append(run)
            run += n
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([part] * len(before), pa.int32()), pa.array(before, pa.int64())], names=[*batch.schema.names, "part", "before"])


def ranks(keys: DataFrame, names: list[str]) -> DataFrame:
    """(names, new_rank): 1 + the number of rows with a smaller key; ``keys`` has a row per key, ``n`` its rows."""
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in keys.schema if f.name in (*names, "n"))
    ordered = keys.select(*names, "n").repartitionByRange(*names).sortWithinPartitions(*names)
    local = saved(arrow_map(ordered, _local_ranks, f"{kinds}, part int, before long"))
    offset, starts = 1, []
    for r in local.groupBy("part").agg(F.sum("n").alias("n")).orderBy("part").collect():  # a row per partition
        starts.append((r["part"], offset))
        offset += r["n"]
    offsets = keys.sparkSession.createDataFrame(starts, "part int, offset long")
    return local.join(F.broadcast(offsets), "part").select(*names, (F.col("offset") + F.col("before")).alias("new_rank"))


def _regroup(rows: DataFrame, names: list[str]) -> DataFrame:
    """Suffixes whose key occurs at least twice, with its rank in place of the key."""
    keys = rows.groupBy(*names).agg(F.count("*").alias("n")).where("n > 1")
    return saved(rows.join(ranks(keys, names), names).select("id", "text_hash", "place", "line", F.col("new_rank").alias("rank")))


def _double(now: DataFrame, step: int) -> DataFrame:
    """From ranks at one length to ranks at ``step`` lines more (at most twice the length)."""
    ahead = now.select("id", "text_hash", (F.col("place") - step).alias("place"), F.col("rank").alias("rank_ahead"))
    return _regroup(now.join(ahead, ["id", "text_hash", "place"]), ["rank", "rank_ahead"])


def lcp_intervals(docs: DataFrame, length: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text_hash, place, line, rank): suffixes that share their first ``length`` lines with another; equal rank, equal lines."""
    if length < 1:
        raise ValueError("length must be positive")
    lines = saved(line_sequences(docs, id_col, text_col).distinct())
    now, have = _regroup(lines, ["h1", "h2"]), 1
    while have < length:
        step = min(have, length - have)
        now, have = _double(now, step), have + step
    return now


def long_lines(docs: DataFrame, min_words: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text_hash, line, h1, h2): the lines of ``min_words`` words or more."""
    if min_words < 1:
        raise ValueError("min_words must be positive")
    text = F.col(text_col).cast("string")
    enough = rf"\A[\x20\x09-\x0D]*+(?:[^\x20\x09-\x0D]++[\x20\x09-\x0D]++){{{min_words - 1}}}+[^\x20\x09-\x0D]"
    lines = F.transform(F.split(text, "\n"), lambda x, i: F.struct(i.alias("line"), x.alias("x")))
    long = F.filter(lines, lambda l: (F.length(l["x"]) >= 2 * min_words - 1) & l["x"].rlike(enough))
    base = docs.where(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text).alias("text_hash"), F.explode(long).alias("l"))
    return base.select("id", "text_hash", "l.line", F.xxhash64("l.x").alias("h1"), F.hash("l.x").alias("h2")).distinct()


def longest_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text_hash, place, lines): for each suffix with a repeated line, the greatest power of two that its repeat reaches."""
    lines = saved(line_sequences(docs, id_col, text_col).distinct())
    now, have = _regroup(lines, ["h1", "h2"]), 1
    out = now.select("id", "text_hash", "place", F.lit(have).alias("lines"))
    while now.limit(1).count():
        now, have = _double(now, have), 2 * have
        out = out.unionByName(now.select("id", "text_hash", "place", F.lit(have).alias("lines")))
    return out.groupBy("id", "text_hash", "place").agg(F.max("lines").alias("lines"))


def removed_lines(docs: DataFrame, min_lines: int = 2, id_col: str = "doc_id", text_col: str = "text", min_words: int | None = None) -> DataFrame:
    """(id, text_hash, gone): the line numbers (from 0) to delete."""
    held = lcp_intervals(docs, min_lines, id_col, text_col)
    first = held.groupBy("rank").agg(F.min(F.struct("id", "text_hash", "place")).alias("first"))
    later = held.join(first, "rank").where(F.struct("id", "text_hash", "place") != F.col("first")).select("id", "text_hash", "place")
    covered = later.select("id", "text_hash", F.explode(F.sequence("place", F.col("place") + min_lines - 1)).alias("place")).distinct()
    lines = line_sequences(docs, id_col, text_col).select("id", "text_hash", "place", "line").distinct()
    gone = covered.join(lines, ["id", "text_hash", "place"]).select("id", "text_hash", "line")
    if min_words is not None:
        long = saved(long_lines(docs, min_words, id_col, text_col))
        source = long.groupBy("h1", "h2").agg(F.min(F.struct("id", "text_hash", "line")).alias("first"), F.count("*").alias("n")).where("n > 1")
        again = long.join(source, ["h1", "h2"]).where(F.struct("id", "text_hash", "line") != F.col("first"))
        gone = gone.unionByName(again.select("id", "text_hash", "line")).distinct()
    return gone.groupBy("id", "text_hash").agg(F.sort_array(F.collect_list("line")).alias("gone"))


def dedup_lines(docs: DataFrame, min_lines: int = 2, id_col: str = "doc_id", text_col: str = "text", min_words: int | None = None) -> DataFrame:
    """The input with later copies of repeated runs deleted from ``text_col``, and n_lines, n_removed_lines."""
    gone = saved(removed_lines(docs, min_lines, id_col, text_col, min_words).select(F.col("id").alias("_px_gone_id"), F.col("text_hash").alias("_px_gone_hash"), F.col("gone").alias("_px_gone")))
    size = gone.agg(F.count("*"), F.coalesce(F.sum(F.size("_px_gone")), F.lit(0))).first()
    text = F.col(text_col).cast("string")
    base = docs.withColumn("_px_id", F.col(id_col).cast("long")).withColumn("_px_hash", F.xxhash64(text))
    on = (F.col("_px_id") == F.col("_px_gone_id")) & (F.col("_px_hash") == F.col("_px_gone_hash"))
    out = join_bounded(base, gone, on, "left", size[0], 48 + 4 * int(size[1] / max(1, size[0])))
    lines = F.split(text, "\n")
    kept = F.when(F.col("_px_gone").isNull(), text).otherwise(F.array_join(F.filter(lines, lambda x, i: ~F.array_contains("_px_gone", i)), "\n"))
    n_lines = F.coalesce(F.size(F.filter(lines, lambda x: x.rlike(_HAS_WORD))), F.lit(0)).cast("long")
    extra = [n_lines.alias("n_lines"), F.coalesce(F.size("_px_gone"), F.lit(0)).cast("long").alias("n_removed_lines")]
    return out.select(*(kept.alias(c) if c == text_col else F.col(c) for c in docs.columns if c not in ("n_lines", "n_removed_lines")), *extra)
