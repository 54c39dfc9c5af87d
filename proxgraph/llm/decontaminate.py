"""Benchmark decontamination with DataFrame functions only.

Item windows (ten words, or the whole item if it is shorter) are hashed and broadcast as a literal
hash set behind a check of their number; beyond the bound they are joined by shuffle.  A training
text is scanned once: hashes of its normalised words, then every window is looked up in the set.
Hits are verified word by word against the item windows, so hash collisions have no effect.

Null and wordless texts have no words and are never hit; null items and items without words are
ignored; items may repeat.  Rows are judged one by one, so repeated ids do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_rows

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Every ASCII character that is no letter and no digit.
_BREAKS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Item windows up to which the set is broadcast.
MAX_BROADCAST_WINDOWS = 50_000


def normal_words(text: Column) -> Column:
    """Words of letters, digits and non-ASCII characters, A-Z in lower case; null gives none."""
    plain = F.translate(F.coalesce(text.cast("string"), F.lit("")), _UPPER, _LOWER)
    return F.filter(F.split(plain, _BREAKS), lambda w: w != "")


def benchmark_windows(items: DataFrame, width: int = 10, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(item_id, len, gram, key, first): every window of every item; key hashes the gram, first its first words."""
    words = items.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("item_id"), normal_words(F.col(text_col)).alias("w")).where(F.size("w") > 0)
    span = F.least(F.size("w"), F.lit(width))
    gram = words.select("item_id", span.alias("len"), F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - span + 1), lambda i: F.slice("w", i, span))).alias("gram"))
    return gram.distinct().withColumn("key", _key(F.transform("gram", lambda x: F.xxhash64(x)), F.lit(0), F.col("len"), width))


def _key(h: Column, i: Column, size: Column, width: int) -> Column:
    """Hash of the ``size`` word hashes from place ``i`` (from 0), by one expression for each size."""
    out = F.lit(None).cast("long")
    for k in range(width, 0, -1):
        out = F.when(size == k, F.xxhash64(*(F.get(h, i + j) for j in range(k)))).otherwise(out)
    return out


def _places_of(h: Column, k: int, keys: list[int] | None) -> Column:
    """[(at, len, key)] of the windows of ``k`` words whose hash is in the set (of all, without a set)."""

    def window(i: Column) -> Column:
        return F.xxhash64(*(F.get(h, i + j) for j in range(k)))

    last = F.size(h) - k
    at = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
    if keys is not None:
        at = F.filter(at, lambda i: window(i).isin(keys))
    return F.transform(at, lambda i: F.struct(i.alias("at"), F.lit(k).alias("len"), window(i).alias("key")))


def _places(h: Column, sizes: list[int], keys: dict[int, list[int]] | None) -> Column:
    parts = [_places_of(h, k, None if keys is None else keys[k]) for k in sizes]
    return F.concat(*parts) if parts else F.array().cast("array<struct<at:int,len:int,key:bigint>>")


def _covered(spans: Column) -> Column:
    """Number of words under the spans."""
    return F.aggregate(
        F.array_sort(spans),
        F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")),
        lambda acc, x: F.struct(F.greatest(acc["end"], x["at"] + x["len"]).alias("end"), (acc["n"] + F.greatest(F.lit(0), x["at"] + x["len"] - F.greatest(acc["end"], x["at"]))).alias("n")),
        lambda acc: acc["n"],
    )


def decontaminate(docs: DataFrame, items: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """One row per input row: id, text_hash, n_words, n_hit, spans [(at, len)], items (sorted strings), contaminated.

    ``at`` counts normalised words from 0.
    """
    bench = benchmark_windows(items, width, item_col, item_text_col).groupBy("len", "key", "gram").agg(F.collect_set(F.col("item_id").cast("string")).alias("item_ids"))
    held = bench.groupBy("len").agg(F.count("*").alias("n")).collect()  # at most ``width`` rows
    sizes, n = sorted(r["len"] for r in held), sum(r["n"] for r in held)
    keys = {k: [r[0] for r in bench.where(F.col("len") == k).select("key").distinct().collect()] for k in sizes} if n <= MAX_BROADCAST_WINDOWS else None
    base = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col).cast("string")).alias("text_hash"), normal_words(F.col(text_col)).alias("w"))
    base = base.withColumn("h", F.transform("w", lambda x: F.xxhash64(x)))
    base = base.select("id", "text_hash", F.size("w").cast("long").alias("n_words"), "w", _places(F.col("h"), sizes, keys).alias("places"))
    rows = base.select("id", "text_hash", "n_words", "w", F.posexplode_outer("places").alias("pos", "place"))
    rows = rows.select("id", "text_hash", "n_words", "pos", F.col("place.at").alias("at"), F.col("place.len").alias("len"), F.col("place.key").alias("key"), F.slice("w", F.coalesce(F.col("place.at"), F.lit(0)) + 1, F.coalesce(F.col("place.len"), F.lit(0))).alias("gram"))
    found = rows.join(F.broadcast(bench) if keys is not None else bench, ["len", "key", "gram"], "left")
    # rows that are equal in all respects are one group here; ``copies`` brings them back
    per = found.groupBy("id", "text_hash", "n_words").agg(
        F.sum((F.col("pos").isNull() | (F.col("pos") == 0)).cast("int")).alias("copies"),
        F.collect_set(F.when(F.col("item_ids").isNotNull(), F.struct("at", "len"))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("item_ids")))).alias("items"),
    )
    per = per.select(F.col("id").alias(id_col), "text_hash", "n_words", _covered(F.col("spans")).cast("long").alias("n_hit"), F.array_sort("spans").alias("spans"), "items", (F.size("items") > 0).alias("contaminated"), F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    return per.drop("copy")


def drop_contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows without a hit, with all their columns."""
    bad = decontaminate(docs, items, id_col=id_col, text_col=text_col, **options).where("contaminated")
    return drop_rows(docs, bad.select(F.col(id_col).alias("id"), "text_hash"), id_col, text_col)


def cut_spans(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows with the hit words cut out: ``clean_words`` holds the normalised words that stay."""
    found = decontaminate(docs, items, id_col=id_col, text_col=text_col, **options).where("contaminated").select(F.col(id_col).alias("_px_id"), F.col("text_hash").alias("_px_hash"), F.col("spans").alias("_px_spans")).distinct()
    out = docs.join(found, (docs[id_col].eqNullSafe(F.col("_px_id"))) & (F.xxhash64(docs[text_col].cast("string")) == F.col("_px_hash")), "left")
    spans = F.coalesce("_px_spans", F.array().cast("array<struct<at:int,len:int>>"))
    clean = F.filter(normal_words(F.col(text_col)), lambda w, i: ~F.exists(spans, lambda s: (i >= s["at"]) & (i < s["at"] + s["len"])))
    return out.withColumn("clean_words", clean).drop("_px_id", "_px_hash", "_px_spans")
