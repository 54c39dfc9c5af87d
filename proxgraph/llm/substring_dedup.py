"""Removal of token windows that already occur in an earlier document.

Every window of ``width`` words has a Rabin-Karp hash, taken from running sums over the word
hashes.  Windows are counted in Spark and covered words are removed.

1. One scan gives, per document, a fingerprint of its word sequence and its *anchors*: in each
   window, the half-width gram with the smallest hash.  Equal windows have equal anchors, so a
   window whose anchor no other document has cannot repeat.  This filter loses nothing and cuts
   the shuffled rows to about two in ``width / 2`` words.
2. A document whose whole word sequence occurs under a smaller id is removed as a whole (it has
   at least ``width`` words) and takes no further part: the first copy has all its windows.
3. Windows under shared anchors are counted exactly, with 128-bit hashes: each learns the smallest
   id that has it, and windows with a smaller one become removal intervals.

Null ids: nothing is removed and the row is never a source.  Repeated ids never remove from each
other (an id must be strictly smaller); a null or empty text has no words.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import arrow_map, binary_column, blocks, mix, powers, saved, signed, word_hashes

_SECOND = np.uint64(0xA0761D6478BD642F)


def _grams(w: np.ndarray, k: int) -> np.ndarray:
    """Rabin-Karp values of all k-word grams of one block's words."""
    if len(w) < k:
        return np.zeros(0, np.uint64)
    up, down = powers(len(w) + 1)
    run = np.zeros(len(w) + 1, np.uint64)
    np.cumsum(w * up[:-1], out=run[1:])
    return (run[k:] - run[:-k]) * down[: len(w) - k + 1]


def _sliding_min(a: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while span * 2 <= width:
        a = np.minimum(a[:-span], a[span:])
        span *= 2
    rest = width - span
    return np.minimum(a[: len(a) - rest], a[rest:]) if rest else a


def _anchors(w: np.ndarray, width: int) -> np.ndarray:
    """The anchor of each window of a document (none when it is shorter than a window)."""
    k = width // 2
    return _sliding_min(mix(_grams(w, k)), width - k + 1) if len(w) >= width else np.zeros(0, np.uint64)


def _fingerprint(w: np.ndarray) -> tuple[int, int]:
    up, _ = powers(len(w) + 1)
    one = int((w * up[: len(w)]).sum(dtype=np.uint64)) if len(w) else 0
    two = int((mix(w ^ _SECOND) * up[: len(w)]).sum(dtype=np.uint64)) if len(w) else 0
    return one - (1 << 64) if one >> 63 else one, two - (1 << 64) if two >> 63 else two


def _scan(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp1, fp2, count, lists, sizes = [], [], [], [], [0]
            for lo, hi, raw, offs in blocks(batch.column("body")):
                w, at = word_hashes(raw, offs, False)
                for i in range(hi - lo):
                    own = w[at[i] : at[i + 1]]
                    a, b = _fingerprint(own)
                    found = np.unique(_anchors(own, width))
                    fp1.append(a)
                    fp2.append(b)
                    count.append(len(own))
                    lists.append(found)
                    sizes.append(sizes[-1] + len(found))
            values = signed(np.concatenate(lists)) if lists else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.array(fp1, pa.int64()), pa.array(fp2, pa.int64()), pa.array(count, pa.int64()), pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(values))],
                names=["id", "fp1", "fp2", "n_words", "anchors"],
            )

    return run


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts in packed form, for the shuffle."""
    for batch in batches:
        packed = [zlib.compress(x, 1) for x in binary_column(batch, "body")]
        yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(packed, pa.binary())], names=["id", "body"])


def _windows(width: int):
    """Rows of the windows under shared anchors, for documents that have any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, shared = batch.column("id").to_numpy(zero_copy_only=False), batch.column("shared")
            cols: list[list[np.ndarray]] = [[], [], [], [], [], []]
            for i, packed in enumerate(batch.column("body").to_pylist()):
                w, _ = _words(zlib.decompress(packed))
                if len(w) < width:
                    continue
                hot = np.asarray(shared[i].values.to_numpy(zero_copy_only=False))
                at = np.flatnonzero(np.isin(signed(_anchors(w, width)), hot))
                if not len(at):
                    continue
                h1, h2 = mix(_grams(w, width))[at], mix(_grams(mix(w ^ _SECOND), width))[at]
                # a window that stands several times in the document is one row
                order = np.lexsort((h2, h1))
                h1, h2, at = h1[order], h2[order], at[order]
                head = np.flatnonzero(np.concatenate(([True], (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1]))))
                sizes = np.diff(np.concatenate((head, [len(at)])))
                for c, v in zip(cols, (signed(h1[head]), signed(h2[head]), np.full(len(head), ids[i], np.int64), np.full(len(head), _fingerprint(w)[0], np.int64), sizes, at.astype(np.int32)), strict=True):
                    c.append(v)
            if cols[0]:
                *keys, sizes, starts = (np.concatenate(c) for c in cols)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(starts))
                yield pa.RecordBatch.from_arrays([*(pa.array(k) for k in keys), lists], names=["h1", "h2", "id", "fp1", "starts"])

    return run


def _words(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    raw = np.frombuffer(text, np.uint8)
    return word_hashes(raw, np.array([0, len(raw)]), False)


def _remove(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, n, gone = [], [], []
            for packed, cut in zip(batch.column("body").to_pylist(), batch.column("cuts").to_pylist(), strict=True):
                text = zlib.decompress(packed)
                words = text.split()
                n.append(len(words))
                gone.append(0)
                for c in cut or ():
                    if c["fp1"] == _fingerprint(_words(text)[0])[0]:
                        edge = np.zeros(len(words) + 1, np.int64)
                        if c["whole"]:
                            edge[0] += 1
                        else:
                            starts = np.asarray(c["starts"], np.int64)
                            np.add.at(edge, starts, 1)
                            np.add.at(edge, starts + width, -1)
                        mask = np.cumsum(edge[:-1]) > 0
                        gone[-1] = int(mask.sum())
                        words = [x for x, m in zip(words, mask.tolist(), strict=True) if not m]
                        break
                kept.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary())], names=["id", "n_words", "n_removed", "kept"])

    return run


def removal_intervals(docs: DataFrame, width: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, cuts): per document, what is to be removed from each word sequence it stands for."""
    body = _bodies(docs, id_col, text_col)
    seen = saved(arrow_map(body.where("id is not null"), _scan(width), "id long, fp1 long, fp2 long, n_words long, anchors array<long>").where(F.col("n_words") >= width))
    first = seen.groupBy("fp1", "fp2", "n_words").agg(F.min("id").alias("first_id"), F.max("id").alias("last_id"))
    copies = saved(seen.drop("anchors").join(first.where("first_id < last_id"), ["fp1", "fp2", "n_words"]).where("id > first_id").select("id", "fp1", "fp2").distinct())
    alone = seen.join(copies, ["id", "fp1", "fp2"], "left_anti").select("id", F.explode("anchors").alias("anchor"))
    hot = alone.groupBy("anchor").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo < hi").select("anchor")
    shared = saved(alone.join(hot, "anchor").groupBy("id").agg(F.collect_set("anchor").alias("shared")))
    # both joins with the texts are shuffles at any size: neither side has a proven bound
    texts = arrow_map(body.where("id is not null"), _pack, "id long, body binary")
    windows = arrow_map(texts.join(shared.hint("merge"), "id"), _windows(width), "h1 long, h2 long, id long, fp1 long, starts array<int>")
    own = Window.partitionBy("h1", "h2")
    later = windows.withColumn("owner", F.min("id").over(own)).where("id > owner")
    parts = later.groupBy("id", "fp1").agg(F.flatten(F.collect_list("starts")).alias("starts")).withColumn("whole", F.lit(False))
    whole = copies.select("id", "fp1", F.array().cast("array<int>").alias("starts"), F.lit(True).alias("whole")).distinct()
    return parts.unionByName(whole).groupBy("id").agg(F.collect_list(F.struct("fp1", "starts", "whole")).alias("cuts"))


def _bodies(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("body"))


def dedup_substrings(docs: DataFrame, width: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: ``id_col``, n_words, n_removed and ``kept`` (the kept words, one space between)."""
    cuts = saved(removal_intervals(docs, width, id_col, text_col))
    texts = arrow_map(_bodies(docs, id_col, text_col), _pack, "id long, body binary")
    joined = texts.join(cuts.hint("merge"), "id", "left")
    out = arrow_map(joined.select("id", "body", "cuts"), _remove(width), "id long, n_words long, n_removed long, kept binary")
    return out.select(F.col("id").alias(id_col), "n_words", "n_removed", F.col("kept").cast("string").alias("kept"))
