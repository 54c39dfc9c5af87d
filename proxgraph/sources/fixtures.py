"""Graphs of the given tables; each has a DataFrame builder and the same edges in SQL.

Ids of mixed graphs are ``4 * key + tag`` with a tag per kind of node.  String keys are numbered by
rank here, for equal ids in both engines; ``string_ids`` numbers them by hash at scale.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators.graph import Graph
from ..session import ship
from ..storage import column, local_path, saved, shared_folder


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def string_ids(values: DataFrame, column: str, how: str = "rank") -> DataFrame:
    """(column, num): numbers from 1 by rank, or 62-bit hashes whose clashes raise."""
    distinct = values.select(column).distinct()
    if how == "rank":
        return distinct.withColumn("num", F.row_number().over(Window.orderBy(column)).cast("long"))
    out = distinct.withColumn("num", F.shiftrightunsigned(F.xxhash64(column), 3))
    if out.groupBy("num").count().where("count > 1").limit(1).count():
        raise ValueError("two strings have the same hash")
    return out


def next_in_group(df: DataFrame, group: str, order: list[str], value: str) -> DataFrame:
    """Arcs from each row's value to the next one's in its group; the last goes back to the first."""
    w = Window.partitionBy(group).orderBy(*order)
    return df.select(F.col(value).alias("src"), F.coalesce(F.lead(value).over(w), F.first(value).over(w)).alias("dst"))


def next_overall(df: DataFrame, bucket, order: list[str], value: str) -> DataFrame:
    """As ``next_in_group`` over the whole table, without one task for all rows: neighbours inside
    buckets, and a small table of bucket ends for the arcs between them."""
    d = df.withColumn("_bucket", bucket)
    w = Window.partitionBy("_bucket").orderBy(*order)
    inner = d.select(F.col(value).alias("src"), F.lead(value).over(w).alias("dst")).where("dst is not null")
    ends = d.groupBy("_bucket").agg(F.min_by(value, F.struct(*order)).alias("head"), F.max_by(value, F.struct(*order)).alias("tail"))
    b = Window.orderBy("_bucket")
    first = F.first("head").over(b)
    outer = ends.select(F.col("tail").alias("src"), F.coalesce(F.lead("head").over(b), first).alias("dst"))
    return inner.unionByName(outer)


def _part_next(spark, d):
    return next_in_group(table(spark, d, "lineitem"), "l_orderkey", ["l_linenumber", "l_partkey"], "l_partkey")


def _user_next(spark, d):
    return next_overall(table(spark, d, "events"), F.to_date("ts"), ["ts", "event_id"], "user_id")


def _nation_trade(spark, d):
    li = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    c, s = table(spark, d, "customer").select("c_custkey", "c_nationkey"), table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    return li.join(o, "l_orderkey").join(c, "c_custkey").join(s, "l_suppkey").select(F.col("c_nationkey").alias("src"), F.col("s_nationkey").alias("dst")).distinct()


def _role_turn(spark, d):
    c = table(spark, d, "conversations")
    e = next_in_group(c, "conv_id", ["turn"], "role")
    ids = string_ids(c, "role")
    return e.join(ids.select(F.col("role").alias("src"), F.col("num").alias("a")), "src").join(ids.select(F.col("role").alias("dst"), F.col("num").alias("b")), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))


def _cust_part(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return table(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(o, "l_orderkey").select((4 * F.col("o_custkey")).alias("src"), (4 * F.col("l_partkey") + 1).alias("dst"))


def _part_supp(spark, d):
    return table(spark, d, "lineitem").select((4 * F.col("l_partkey") + 1).alias("src"), (4 * F.col("l_suppkey") + 2).alias("dst"))


def _page_link(spark, d):
    e = table(spark, d, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("link"))
    return e.join(string_ids(e, "link"), "link").select((4 * F.col("page_id")).alias("src"), (4 * F.col("num") + 1).alias("dst")).distinct()


def _geo_tree(spark, d):
    t = lambda n: table(spark, d, n)
    a = t("nation").select((4 * F.col("n_regionkey").cast("long")).alias("src"), (4 * F.col("n_nationkey").cast("long") + 1).alias("dst"))
    b = t("customer").select((4 * F.col("c_nationkey").cast("long") + 1).alias("src"), (4 * F.col("c_custkey") + 2).alias("dst"))
    c = t("orders").select((4 * F.col("o_custkey") + 2).alias("src"), (4 * F.col("o_orderkey") + 3).alias("dst"))
    return a.unionByName(b).unionByName(c)


#: Words of a vocabulary up to which tasks map their hashes and numbers from array files; a larger one is joined by shuffle.
STORE_WORDS = 24_000_000
#: Different words that a task holds before it gives them on; bytes of texts that are hashed at once; texts of a batch.
HELD_WORDS, HASHED_BYTES, TEXT_ROWS = 1 << 17, 1 << 19, 2000


def _word_hashes(raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each word between blanks, and its text's place, for the texts that lie between ``offs``."""
    blank = raw == 32
    begins = ~blank
    begins[1:] &= blank[:-1]
    heads = offs[:-1][offs[:-1] < offs[1:]]
    begins[heads] = ~blank[heads]
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, np.uint64), starts
    values = np.random.default_rng(20_23).integers(1, 1 << 63, 256, np.uint64)
    values[32] = 0
    base, back = np.full(len(raw), 0x9E3779B97F4A7C15, np.uint64), np.full(len(raw), pow(0x9E3779B97F4A7C15, -1, 1 << 64), np.uint64)
    base[0] = back[0] = 1
    h = np.add.reduceat(values[raw] * np.multiply.accumulate(base), starts) * np.multiply.accumulate(back)[starts]
    return (h ^ h >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9), np.searchsorted(offs, starts, "right") - 1


def _task_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Different words of a task's texts, with their hashes."""
    held: set = set()

    def give() -> pa.RecordBatch:
        held.discard(b"")
        words = list(held)
        held.clear()
        raw = np.frombuffer(b"".join(words), np.uint8)
        return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(_word_hashes(raw, np.cumsum([0, *map(len, words)]))[0].view(np.int64))], names=["word", "h"])

    for batch in batches:
        for text in batch.column(0).drop_null():
            held.update(text.as_buffer().to_pybytes().split(b" "))
            if len(held) >= HELD_WORDS:
                yield give()
    yield give()


def _numbered_words(folder: str):
    """(4 * doc_id, 4 * number + 1) of each different word of a text; ``folder`` has the words' sorted hashes and their numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, numbers = (np.load(f"{folder}/{name}.npy", mmap_mode="r") for name in ("hashes", "numbers"))

        def arcs(docs: pa.Array, texts: list[bytes]) -> pa.RecordBatch:
            h, of = _word_hashes(np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)]))
            own, at = np.unique(h, return_inverse=True)
            found = np.searchsorted(hashes, own)
            if len(own) and np.any(hashes[np.minimum(found, len(hashes) - 1)] != own):
                raise RuntimeError("a word is not in the vocabulary")
            pairs = np.unique(of * np.int64(max(1, len(own))) + at)
            return pa.RecordBatch.from_arrays([pc.multiply(docs.take(pa.array(pairs // max(1, len(own)))), 4), pa.array(4 * numbers[found].astype(np.int64)[pairs % max(1, len(own))] + 1)], names=["src", "dst"])

        for batch in batches:
            texts, docs, lo, size = [x.as_buffer().to_pybytes() if x.is_valid else b"" for x in batch.column(1)], batch.column(0), 0, 0
            for i, text in enumerate(texts, 1):
                size += len(text)
                if size >= HASHED_BYTES or i == len(texts):
                    yield arcs(docs[lo:i], texts[lo:i])
                    lo, size = i, 0

    return run


def _stored_words(words: DataFrame) -> str | None:
    """The folder of array files of the hashes of ``words``, whose files are in order, and their numbers; none if two words share a hash or files can't be shared."""
    if (path := local_path(shared_folder(words.sparkSession))) is None or words.count() > STORE_WORDS:
        return None
    h = column(words, "h").view(np.uint64)
    order = np.argsort(h)
    h = h[order]
    if np.any(h[1:] == h[:-1]):
        return None
    folder = f"{path}/words/{uuid.uuid4().hex}"
    os.makedirs(folder)
    np.save(f"{folder}/hashes.npy", h)
    np.save(f"{folder}/numbers.npy", (order + 1).astype(np.int32))
    return folder


def _doc_word(spark, d):
    ship(spark)
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > TEXT_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(TEXT_ROWS))
    texts = table(spark, d, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").cast("binary").alias("text"))
    words = texts.select("text").mapInArrow(_task_words, "word binary, h long").groupBy("word").agg(F.first("h").alias("h"))
    # ranges of words, one file after the other: a word's place is its number
    words = saved(words.select(F.col("word").cast("string").alias("word"), "h").repartitionByRange("word").sortWithinPartitions("word"))
    if (folder := _stored_words(words)) is not None:
        return texts.mapInArrow(_numbered_words(folder), "src long, dst long")
    e = texts.select("doc_id", F.explode(F.array_distinct(F.split(F.col("text").cast("string"), " "))).alias("word")).where("word <> ''")
    return e.join(string_ids(words, "word"), "word").select((4 * F.col("doc_id")).alias("src"), (4 * F.col("num") + 1).alias("dst"))


#: Vectors of a block that is held by a task at once.
KNN_BLOCK = 8_000


def nearest(vectors: DataFrame, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", block: int = KNN_BLOCK) -> DataFrame:
    """(src, dst, sim): the k nearest other vectors by cosine, rounded to nine digits, ties by id.

    Vectors are dealt over blocks of about ``block``; a group holds a pair of blocks, in which each vector of
    the first gets its k nearest of the second, and the best k of all blocks stay.
    """
    spark = vectors.sparkSession
    ship(spark)
    t = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    blocks = max(1, -(-t.count() // block))
    own = t.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asks, held = own.select(F.col("own").alias("a"), every.alias("b"), "id", "v"), own.select(every.alias("a"), F.col("own").alias("b"), F.col("id").alias("held_id"), F.col("v").alias("held_v"))

    def unit(part: pa.Table, ids: str, vs: str):
        v = np.array(part.column(vs).to_pylist())
        return part.column(ids).to_numpy(), v / np.linalg.norm(v, axis=1, keepdims=True)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if left.num_rows and right.num_rows:
            (mine, q), (other, m) = unit(left, "id", "v"), unit(right, "held_id", "held_v")
            for lo in range(0, len(mine), 256):
                ids = mine[lo : lo + 256]
                sim = np.round(q[lo : lo + 256] @ m.T, 9)
                same = ids[:, None] == other[None, :]
                sim[same] = -np.inf
                near = np.lexsort((np.broadcast_to(other, sim.shape), -sim), axis=1)[:, :k]
                best = np.take_along_axis(sim, near, 1)
                real = ~np.take_along_axis(same, near, 1).ravel()
                out.append(pa.table({"src": np.repeat(ids, near.shape[1])[real], "dst": other[near].ravel()[real], "sim": best.ravel()[real]}))
        kinds = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("sim", pa.float64())])
        return pa.concat_tables(out).cast(kinds) if out else kinds.empty_table()

    best = asks.groupBy("a", "b").cogroup(held.groupBy("a", "b")).applyInArrow(run, "src long, dst long, sim double")
    if blocks == 1:
        return best
    place = F.row_number().over(Window.partitionBy("src").orderBy(F.isnan("sim"), F.desc("sim"), "dst"))
    return best.withColumn("place", place).where(F.col("place") <= k).drop("place")


def _knn10(spark, d):
    return nearest(table(spark, d, "embeddings")).select("src", "dst")


_NEXT = "SELECT {v} AS src, coalesce(lead({v}) OVER w, first_value({v}) OVER w) AS dst FROM {t} WINDOW w AS ({p} ORDER BY {o})"

_SQL = {
    "part_next": _NEXT.format(v="l_partkey", t="lineitem", p="PARTITION BY l_orderkey", o="l_linenumber, l_partkey"),
    "user_next": _NEXT.format(v="user_id", t="events", p="", o="ts, event_id"),
    "nation_trade": "SELECT c_nationkey AS src, s_nationkey AS dst FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey",
    "role_turn": "SELECT a.num AS src, b.num AS dst FROM (" + _NEXT.format(v="role", t="conversations", p="PARTITION BY conv_id", o="turn") + ") e JOIN (SELECT role, row_number() OVER (ORDER BY role) AS num FROM (SELECT DISTINCT role FROM conversations)) a ON a.role = e.src JOIN (SELECT role, row_number() OVER (ORDER BY role) AS num FROM (SELECT DISTINCT role FROM conversations)) b ON b.role = e.dst",
    "cust_part": "SELECT 4 * o_custkey AS src, 4 * l_partkey + 1 AS dst FROM lineitem JOIN orders ON o_orderkey = l_orderkey",
    "part_supp": "SELECT 4 * l_partkey + 1 AS src, 4 * l_suppkey + 2 AS dst FROM lineitem",
    "page_link": "SELECT 4 * page_id AS src, 4 * dense_rank() OVER (ORDER BY link) + 1 AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS link FROM pages)",
    "geo_tree": "SELECT 4 * n_regionkey::BIGINT AS src, 4 * n_nationkey::BIGINT + 1 AS dst FROM nation UNION ALL SELECT 4 * c_nationkey::BIGINT + 1, 4 * c_custkey + 2 FROM customer UNION ALL SELECT 4 * o_custkey + 2, 4 * o_orderkey + 3 FROM orders",
    "doc_word": "SELECT 4 * doc_id AS src, 4 * dense_rank() OVER (ORDER BY word) + 1 AS dst FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS word FROM documents) WHERE word <> ''",
    "knn10": "SELECT a AS src, b AS dst FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 9) DESC, y.vec_id) AS k FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE k <= 10",
}


@dataclass(frozen=True)
class Fixture:
    name: str
    directed: bool
    build: Callable[[SparkSession, str], DataFrame]

    def graph(self, spark: SparkSession, sf_dir: str) -> Graph:
        return Graph.from_edges(self.build(spark, sf_dir), self.directed)

    @property
    def sql(self) -> str:
        return _SQL[self.name]


FIXTURES = {
    f.name: f
    for f in (
        Fixture("part_next", True, _part_next),
        Fixture("user_next", True, _user_next),
        Fixture("nation_trade", True, _nation_trade),
        Fixture("role_turn", True, _role_turn),
        Fixture("knn10", True, _knn10),
        Fixture("cust_part", False, _cust_part),
        Fixture("part_supp", False, _part_supp),
        Fixture("page_link", False, _page_link),
        Fixture("geo_tree", False, _geo_tree),
        Fixture("doc_word", False, _doc_word),
    )
}
