"""Exact join of documents whose word-shingle sets have a Jaccard similarity of 0.8 or more.

The token-group matrix: similar sets are put into groups, a group keeps the union of its members'
tokens, and a group is opened for a query set only if the bound on the query's overlap with that
union can reach the threshold.

1. A scan reduces each document to (id, set size, set fingerprint).  Equal sets are one *text* from
   here on, so exact copies are never paired.  A text is named by 64 bits; fingerprints that two
   different sets share (told apart by 64 more bits) are replaced by those.
2. All tokens are put into one order, the rarest first: tokens of one text only come before all
   others, frequent ones last.  The order comes from the number of texts of each token's key (its first
   bits), so one shuffle is needed, of sorted packed runs; copies are left out before.  The most frequent
   tokens (found per block of texts, a bounded list) are known to be shared and stand last, so a text's
   own task knows their places; they are not shuffled with the others.
3. Two linked sets of ``n`` and ``m`` tokens share at least ``t (n + m) / (1 + t)`` tokens.  If their first
   shared token stands at place ``i`` of the one (from 0), the overlap is ``n - i`` at most.  So the first
   shared token is among the first ``(1 - t) n`` tokens of the larger set (its probe rows) and the first
   ``(1 - t) / (1 + t) m`` of the smaller (its matrix rows).
4. Grouping: among the texts with a probe row of a token the one that shares most is the centre; each text
   is compared with its most frequent centre.  Components of these links are the groups.
5. The matrix has, for each group, set size and token, the most tokens that any member of that size has
   from there on in its matrix rows: the token union of the group, split by size, with its bound.  A text
   asks with its probe rows; the smaller of what the two sides can still share bounds the overlap with
   every member.  Where the token is frequent, all that is shared is frequent and is bounded class by
   class of tokens as well.  A group that can't reach the threshold stays closed.
6. The members of open groups that meet the bound themselves are compared by their whole sets.  Every
   linked pair is in one group by step 4 or is compared here, so no link is lost.
7. Components of all links give the result, as the smallest id of each.

Null ids take no part (component null); null or blank texts have no tokens and link with nothing.
Repeated ids are handled row by row; ties do not matter (the result does not depend on centres).
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BROADCAST_ROWS, arrow_map, blocks, drop_rows, join_bounded, mix, saved, signed, word_hashes

SHINGLE = 5
_ODD = mix(np.arange(11, 11 + SHINGLE, dtype=np.uint64)) | np.uint64(1)
_SEEDS = (np.uint64(0x51ED270B35A7C3D9), np.uint64(0xB492B66FBE98F273))
#: A token that more than this share of the texts has is frequent; a token is found if a block of texts has
#: it as often.  No more than ``average set size / FREQUENT_SHARE`` tokens can be, and no more than
#: ``MOST_FREQUENT`` are kept: the others are dealt like rare ones, with the same result.
FREQUENT_SHARE = 0.01
MOST_FREQUENT = 1 << 20
#: Fingerprints that different sets share, at most: among 10**11 texts some hundreds are expected.
MOST_COLLISIONS = 1 << 18
#: Parts of a text's rows when components are joined back by shuffle.
SALTS = 16
#: Tokens that are not frequent are counted by their first bits; tokens and bits of texts that a task sorts at once.
KEY_BITS, HELD_TOKENS, TEXT_BITS = 40, 1 << 22, 22
#: Tokens of a range of keys, ranges at least, rows of a batch.
PIECE_TOKENS, LEAST_PIECES, BATCH_ROWS = 1 << 20, 32, 1 << 17
#: Classes by which the frequent tokens of a text are counted.
CLASSES = 16


def shingle_sets(raw: np.ndarray, offs: np.ndarray, shingle: int = SHINGLE) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each document of a block."""
    w, at = word_hashes(raw, offs, True)
    out = []
    if len(w) >= shingle:
        m = len(w) - shingle + 1
        rolled = np.zeros(m, np.uint64)
        for j in range(shingle):
            rolled += w[j : j + m] * _ODD[j]
        rolled = mix(rolled)
    for a, b in zip(at[:-1], at[1:], strict=True):
        if b - a >= shingle:
            out.append(np.unique(rolled[a : b - shingle + 1]))
        elif b > a:
            own = w[a:b]
            out.append(mix((own * _ODD[: b - a]).sum(dtype=np.uint64, keepdims=True) + np.uint64(b - a)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def fingerprint(s: np.ndarray, which: int = 0) -> int:
    v = int(mix(s ^ _SEEDS[which]).sum(dtype=np.uint64))
    return v - (1 << 64) if v >> 63 else v


def text_key(s: np.ndarray, collided: frozenset) -> int:
    own = fingerprint(s)
    return fingerprint(s, 1) if own in collided else own


def _profile(shingle: int):
    """Size and fingerprints of each document; the first row of a block also has the block's frequent tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, fp, fp2, tokens, counts = [], [], [], [], []
            for _, _, raw, offs in blocks(batch.column("body")):
                sets = shingle_sets(raw, offs, shingle)
                u, c = np.unique(np.concatenate(sets), return_counts=True)
                often = c >= max(4, FREQUENT_SHARE * len(sets))
                for i, s in enumerate(sets):
                    n.append(len(s))
                    fp.append(fingerprint(s) if len(s) else None)
                    fp2.append(fingerprint(s, 1) if len(s) else None)
                    tokens.append(None if i else signed(u[often]))
                    counts.append(None if i else c[often])
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("text_hash"), pa.array(n, pa.int64()), pa.array(fp, pa.int64()), pa.array(fp2, pa.int64()), pa.array(tokens, pa.list_(pa.int64())), pa.array(counts, pa.list_(pa.int64()))], names=["id", "text_hash", "n", "fp", "fp2", "often", "times"])

    return run


def _planes(x: np.ndarray) -> bytes:
    """Numbers in the fewest bytes, byte by byte, compressed."""
    wide = next(w for w in range(1, 9) if w == 8 or int(x.max(initial=0)) >> 8 * w == 0)
    held = pa.compress(np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :wide].T).tobytes(), "zstd", asbytes=True)
    return bytes([wide]) + len(held).to_bytes(8, "little") + held


def _pack(base: int, v: np.ndarray) -> bytes:
    """A run of sorted numbers (key, text): differences of keys, and texts counted from ``base``."""
    key, text = v >> np.uint64(TEXT_BITS), v & np.uint64((1 << TEXT_BITS) - 1)
    return len(v).to_bytes(8, "little") + base.to_bytes(8, "little") + _planes(np.diff(key, prepend=np.uint64(0))) + _planes(text)


def _unpack(run: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Keys and names of texts of a run."""
    n, base, at, out = int.from_bytes(run[:8], "little"), int.from_bytes(run[8:16], "little"), 16, []
    for _ in range(2):
        wide, size = run[at], int.from_bytes(run[at + 1 : at + 9], "little")
        raw = pa.decompress(run[at + 9 : at + 9 + size], n * wide, "zstd", asbytes=True)
        x = np.zeros((n, 8), np.uint8)
        x[:, :wide] = np.frombuffer(raw, np.uint8).reshape(wide, n).T
        out.append(x.view("<u8").ravel().astype(np.int64))
        at += 9 + size
    return np.cumsum(out[0]), out[1] + base


_ROWS = {"piece": pa.int64(), "run": pa.binary(), "token": pa.int64(), "name": pa.int64(), "fp": pa.int64(), "n": pa.int64(), "lead": pa.int64(), "pos": pa.int64(), "sig": pa.list_(pa.int32())}


def _batch(rows: int, leave: tuple = (), **given) -> pa.RecordBatch:
    """A batch of the columns of ``_ROWS`` but those to leave; nulls for those not given."""
    names = [k for k in _ROWS if k not in leave]
    return pa.RecordBatch.from_arrays([pa.array(given[k], _ROWS[k]) if k in given else pa.nulls(rows, _ROWS[k]) for k in names], names=names)


def _emit(shingle: int, collided: frozenset, frequent, pieces: int, threshold: int):
    """Runs of the tokens that are not frequent, by ranges of keys; a row of each text; the probe rows of frequent tokens.

    A text's name is its place in the task's rows.  Its frequent tokens come last in the order, so their places are known
    here.  ``lead`` is the number of its other keys; ``sig`` counts the frequent tokens from a row's on by class.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often, order = frequent.value
        base = TaskContext.get().partitionId() << 40
        held: list[np.ndarray] = []
        fps: list[int] = []
        sizes: list[int] = []
        leads: list[int] = []
        probes: list[tuple[np.ndarray, ...]] = []
        count = 0

        def rest() -> Iterator[pa.RecordBatch]:
            v = np.sort(np.concatenate(held))
            again = np.append(False, v[1:] == v[:-1])
            lead = np.array(leads) - np.bincount((v[again] & np.uint64((1 << TEXT_BITS) - 1)).astype(np.int64), minlength=len(leads))
            v = v[~again]
            bounds = [(i << KEY_BITS) // pieces << TEXT_BITS for i in range(1, pieces)]
            at = np.concatenate(([0], np.searchsorted(v, np.array(bounds, np.uint64)), [len(v)]))
            for i in np.flatnonzero(np.diff(at)):
                yield _batch(1, piece=[i], run=[_pack(base, v[at[i] : at[i + 1]])])
            names = base + np.arange(len(fps))
            yield _batch(len(fps), piece=-1 - names % pieces, name=names, fp=fps, n=sizes, lead=lead)
            if probes:
                token, text, pos, sig = (np.concatenate(x) for x in zip(*probes))
                sig = pa.ListArray.from_arrays(np.arange(0, sig.size + 1, CLASSES, np.int32), pa.array(sig.ravel()))
                yield _batch(len(token), piece=-1 - names[text] % pieces, token=token, name=names[text], pos=pos, sig=sig)

        for batch in batches:
            for _, _, raw, offs in blocks(batch.column("body")):
                for s in shingle_sets(raw, offs, shingle):
                    if not len(s):
                        continue
                    f = 0
                    if len(often):
                        place = np.minimum(np.searchsorted(often, s), len(often) - 1)
                        hot = often[place] == s
                        f = int(hot.sum())
                    if f and 100 * f >= threshold * len(s):
                        token = np.sort(order[place[hot]])
                        rows = 1 + (100 * f - threshold * len(s)) // 100
                        own = (mix(token.view(np.uint64)) % np.uint64(CLASSES)).astype(np.int64)
                        later = np.cumsum((own[:, None] == np.arange(CLASSES))[::-1], 0, np.int32)[::-1]
                        probes.append((token[:rows], np.full(rows, len(fps)), len(s) - f + np.arange(rows), later[:rows]))
                    held.append(((s[~hot] if f else s) >> np.uint64(64 - KEY_BITS)) << np.uint64(TEXT_BITS) | np.uint64(len(fps)))
                    fps.append(text_key(s, collided))
                    sizes.append(len(s))
                    leads.append(len(s) - f)
                    count += len(s)
                    if len(fps) == 1 << TEXT_BITS or count >= HELD_TOKENS:
                        yield from rest()
                        base, count = base + len(fps), 0
                        for x in (held, fps, sizes, leads, probes):
                            x.clear()
        if fps:
            yield from rest()

    return run


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row of each text of each key that several have, piece by piece; other rows as they are.

    ``token`` names a key and is its place in the order: 15 bits of how often, 48 of the key.
    """
    parts, now = [], None

    def rest() -> Iterator[pa.RecordBatch]:
        key, name = (np.concatenate(x) for x in zip(*parts))
        by = np.argsort(key)
        key, name = key[by], name[by]
        begin = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        df = np.diff(np.append(begin, len(key)))
        shared = np.repeat(df > 1, df)
        token = (np.repeat(np.minimum(df, (1 << 14) - 1), df) << 48 | key)[shared]
        name = name[shared]
        for lo in range(0, len(token), BATCH_ROWS):
            yield _batch(len(token[lo : lo + BATCH_ROWS]), ("piece", "run"), token=token[lo : lo + BATCH_ROWS], name=name[lo : lo + BATCH_ROWS])

    for batch in batches:
        packed = pc.is_valid(batch.column("run"))
        yield batch.filter(pc.invert(packed)).select([k for k in _ROWS if k not in ("piece", "run")])
        batch = batch.select(["piece", "run"]).filter(packed)
        for piece, held in zip(batch.column(0).to_pylist(), batch.column(1)):
            if parts and piece != now:
                yield from rest()
                parts = []
            now = piece
            parts.append(_unpack(held.as_py()))
    if parts:
        yield from rest()


def _sets(shingle: int, collided: frozenset):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            want = batch.column("fp").to_pylist()
            for lo, _, raw, offs in blocks(batch.column("body")):
                found = [(want[lo + i], s) for i, s in enumerate(shingle_sets(raw, offs, shingle)) if len(s) and text_key(s, collided) == want[lo + i]]
                if found:
                    sizes = np.concatenate(([0], np.cumsum([len(s) for _, s in found])))
                    yield pa.RecordBatch.from_arrays([pa.array([f for f, _ in found], pa.int64()), pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(signed(np.concatenate([s for _, s in found]))))], names=["fp", "toks"])

    return run


def _linked(threshold: int, a: str, b: str):
    """100 * |a & b| >= threshold * |a | b|, from two token arrays."""
    both = F.size(F.array_intersect(a, b)).cast("long")
    return 100 * both >= threshold * (F.size(a) + F.size(b) - both)


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of an undirected edge table (a, b): smallest label along links, with pointer jumping."""
    both = saved(edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).distinct())
    label = saved(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("a"), F.min("b")).alias("root")))
    while True:
        near = both.join(label, F.col("b") == F.col("node")).groupBy("a").agg(F.min("root").alias("near"))
        step = label.join(near, F.col("node") == F.col("a"), "left").select("node", F.col("root").alias("was"), F.least("root", F.coalesce("near", "root")).alias("root"))
        jump = label.select(F.col("node").alias("via"), F.col("root").alias("further"))
        step = saved(step.join(jump, F.col("root") == F.col("via"), "left").select("node", "was", F.least("root", F.coalesce("further", "root")).alias("root")))
        if not step.where("was <> root").limit(1).count():
            return step.select("node", "root")
        label = step.select("node", "root")


def prefix_rows(body: DataFrame, seen: DataFrame, texts: DataFrame, collided: frozenset, threshold: int, shingle: int) -> DataFrame:
    """(token, fp, n, pos, sig): the probe rows; ``pos`` is the token's place in its text, the rarest first, or less.

    Two tokens that share a key count as one; ``pos`` is then less than the place, which can only add candidates.
    """
    spark = body.sparkSession
    least = F.lit(FREQUENT_SHARE) * F.lit(seen.count())
    often = seen.where("often is not null").select(F.explode(F.arrays_zip("often", "times")).alias("x")).groupBy(F.col("x.often").alias("token")).agg(F.sum("x.times").alias("times")).where(F.col("times") >= least)
    held = often.orderBy(F.desc("times"), "token").limit(MOST_FREQUENT).toArrow()
    token, times = (held.column(k).to_numpy() for k in ("token", "times"))
    order = (1 << 14) + np.minimum(np.log2(times) * 256, (1 << 14) - 1).astype(np.int64) << 48 | token & ((1 << 48) - 1)
    by = np.argsort(token.view(np.uint64))
    frequent = spark.sparkContext.broadcast((token.view(np.uint64)[by], order[by]))
    # a text is read from one row, or from rows that are equal in id and text
    rows, tokens, first = texts.agg(F.sum("rows"), F.sum("n"), F.count("*")).first()
    several = saved(texts.where("rows > 1").select("fp", "first"))
    copies = saved(join_bounded(seen.where("id is not null").select("id", "text_hash", "fp"), several, "fp", "inner", several.count()).where(F.struct("id", "text_hash") != F.col("first")).select("id", "text_hash"))
    count = copies.count()
    once = join_bounded(body.where("id is not null"), copies, ["id", "text_hash"], "left_anti", count)
    if count > BROADCAST_ROWS:  # names of texts are their places: tasks that run again must see them in one order
        once = once.sortWithinPartitions("id", "text_hash")
    pieces = max(LEAST_PIECES, -(-(tokens or 0) // PIECE_TOKENS))
    kinds = "token long, name long, fp long, n long, lead long, pos long, sig array<int>"
    runs = arrow_map(once.select("body"), _emit(shingle, collided, frequent, pieces, threshold), f"piece long, run binary, {kinds}")
    runs = runs.repartition(max(1, pieces // 2), "piece").sortWithinPartitions("piece")
    found = arrow_map(runs, _counted, kinds)
    # keys of no other text come first and need no row: they only count
    per = Window.partitionBy("name")
    found = found.withColumn("shared", F.count(F.when(F.col("pos").isNull(), F.col("token"))).over(per))
    for k in ("fp", "n", "lead"):
        found = found.withColumn(k, F.max(k).over(per))
    found = found.withColumn("rank", F.row_number().over(per.orderBy(F.asc_nulls_last("token"))))
    found = found.where("token is not null").withColumn("pos", F.coalesce("pos", F.col("lead") - F.col("shared") + F.col("rank") - 1))
    found = found.where(100 * (F.col("n") - F.col("pos")) >= threshold * F.col("n")).select("token", "fp", "n", "pos", "sig")
    return saved(found if rows == first + count else found.dropDuplicates(["token", "fp"]))


def linked_texts(docs: DataFrame, threshold: int, shingle: int, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(id, text_hash, n, fp) of every row, and (fp, first, rows, root) of every text: its least (id, text_hash), its rows, its component."""
    if not 0 < threshold <= 100:
        raise ValueError("the threshold is a per cent")
    text = F.col(text_col).cast("string")
    body = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text).alias("text_hash"), text.cast("binary").alias("body"))
    seen = saved(arrow_map(body, _profile(shingle), "id long, text_hash long, n long, fp long, fp2 long, often array<long>, times array<long>"))
    twice = seen.where("fp is not null").groupBy("fp").agg(F.min("fp2").alias("lo"), F.max("fp2").alias("hi")).where("lo < hi").select("fp")
    collided = frozenset(r["fp"] for r in twice.limit(MOST_COLLISIONS + 1).collect())
    if len(collided) > MOST_COLLISIONS:
        raise RuntimeError("too many different sets share their fingerprints")
    if collided:
        wide = body.sparkSession.createDataFrame([(x,) for x in collided], "of long")
        seen = saved(seen.join(F.broadcast(wide), F.col("fp") == F.col("of"), "left").withColumn("fp", F.when(F.col("of").isNull(), F.col("fp")).otherwise(F.col("fp2"))).drop("of"))
    texts = saved(seen.where("id is not null and n > 0").groupBy("fp").agg(F.min(F.struct("id", "text_hash")).alias("first"), F.first("n").alias("n"), F.count("*").alias("rows")))
    rows = prefix_rows(body, seen, texts, collided, threshold, shingle)

    def links(pairs: DataFrame) -> DataFrame:
        """Pairs that are linked, by their whole sets; only the texts of these pairs are read again."""
        texts_in = pairs.select(F.col("a").alias("fp")).union(pairs.select("b")).distinct()
        wanted = saved(texts.select("fp", "first.id").join(texts_in, "fp", "left_semi"))
        count = wanted.count()
        sets = saved(arrow_map(join_bounded(body, wanted, "id", "inner", count).select("fp", "body"), _sets(shingle, collided), "fp long, toks array<long>"))
        if sets.count() > count:  # repeated rows
            sets = saved(sets.dropDuplicates(["fp"]))
        both = pairs.join(sets.withColumnsRenamed({"fp": "a"}), "a").join(sets.withColumnsRenamed({"fp": "b", "toks": "core"}), "b")
        return saved(both.where(_linked(threshold, "toks", "core")).select("a", "b"))

    # groups of similar texts
    held = rows.groupBy("token").agg(F.count("*").alias("held")).where("held > 1")
    rows = saved(rows.join(held, "token"))
    weight = rows.groupBy("fp").agg(F.sum("held").alias("weight"))
    centre = rows.join(weight, "fp").groupBy("token").agg(F.max_by("fp", F.struct("weight", "fp")).alias("centre"))
    star = rows.join(centre, "token").where("fp <> centre").groupBy("fp", "centre").agg(F.count("*").alias("shared"))
    star = star.groupBy("fp").agg(F.max_by("centre", F.struct("shared", "centre")).alias("centre"))
    first = links(saved(star.select(F.col("fp").alias("a"), F.col("centre").alias("b"))))
    rows = rows.join(components(first), F.col("fp") == F.col("node"), "left").select("token", "fp", "n", "pos", "sig", F.coalesce("root", "fp").alias("grp"))
    several = rows.groupBy("token").agg(F.min("grp").alias("lo"), F.max("grp").alias("hi")).where("lo < hi").select("token")
    rows = saved(rows.join(several, "token"))

    # the matrix: a row for each token of the union of a group's members of one size, with what bounds the overlap
    inside = rows.where((100 + threshold) * (F.col("n") - F.col("pos")) >= 2 * threshold * F.col("n"))
    inside = inside.select("token", F.col("grp").alias("other"), F.col("n").alias("m"), F.col("fp").alias("b"), (F.col("n") - F.col("pos")).alias("rest"), F.col("sig").alias("own"))
    matrix = inside.groupBy("token", "other", "m").agg(F.max("rest").alias("reach"), F.array(*(F.max(F.col("own")[i]) for i in range(CLASSES))).alias("most"))
    in_size = (F.col("n") >= F.col("m")) & (100 * F.col("m") >= threshold * F.col("n"))

    def enough(can: str) -> Column:
        return (100 + threshold) * F.least(F.col("n") - F.col("pos"), F.col(can)) >= threshold * (F.col("n") + F.col("m"))

    def alike(can: str) -> Column:
        """If the first token they share is frequent, so are all: no class has more of them in both than in either."""
        both = reduce(Column.__add__, (F.least(F.col("sig")[i], F.col(can)[i]) for i in range(CLASSES)))
        return F.coalesce((100 + threshold) * both.cast("long") >= threshold * (F.col("n") + F.col("m")), F.lit(True))

    asks = rows.join(matrix, "token").where("grp <> other").where(in_size).where(enough("reach")).where(alike("most"))
    asks = saved(asks.select("token", F.col("fp").alias("a"), "n", "pos", "sig", "other", "m"))

    # open groups: their members under the same bound on the pair itself; the larger set asks
    pairs = asks.join(inside, ["token", "other", "m"]).where("n > m or a > b").where(enough("rest")).where(alike("own"))
    final = components(saved(first.union(links(saved(pairs.select("a", "b").distinct())))))
    return seen.select("id", "text_hash", "n", "fp"), texts.join(final, F.col("fp") == F.col("node"), "left").select("fp", "first", "rows", F.coalesce("root", "fp").alias("root"))


def _named(docs: DataFrame, threshold: int, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """(id, text_hash, n, first): ``first`` is the least (id, text_hash) of the row's component, null if the row is alone.

    Components are put together by text, so copies meet in no task; only texts of components with two or
    more rows are joined back, by broadcast under the bound, else with salted keys.
    """
    seen, texts = linked_texts(docs, threshold, shingle, id_col, text_col)
    texts = saved(texts)
    several = saved(texts.groupBy("root").agg(F.min("first").alias("least"), F.sum("rows").alias("rows")).where("rows > 1").select("root", "least"))
    of_text = saved(join_bounded(texts.select("fp", "root"), several, "root", "inner", several.count()).select("fp", F.col("least").alias("first")))
    count = of_text.count()
    if count <= BROADCAST_ROWS:
        return join_bounded(seen, of_text, "fp", "left", count).select("id", "text_hash", "n", "first")
    salt = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
    return seen.withColumn("salt", F.pmod(F.xxhash64("id", "text_hash"), F.lit(SALTS)).cast("int")).join(of_text.withColumn("salt", salt), ["fp", "salt"], "left").select("id", "text_hash", "n", "first")


def near_duplicates(docs: DataFrame, threshold: int = 80, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: ``id_col``, n_shingles, component_id (smallest id reachable by links)."""
    named = _named(docs, threshold, shingle, id_col, text_col)
    return named.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), F.coalesce("first.id", "id")).alias("component_id"))


def keep_first(docs: DataFrame, threshold: int = 80, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component, with all its columns: that of the smallest id, then of the smallest text hash.

    Rows with a null id and rows without a word stay.  Of rows that are equal in id and text one stays
    (any, if other columns differ).
    """
    named = saved(_named(docs, threshold, shingle, id_col, text_col).where("id is not null and first is not null"))
    out = drop_rows(docs, named.where(F.struct("id", "text_hash") != F.col("first")).select("id", "text_hash"), id_col, text_col)
    again = saved(named.groupBy("id", "text_hash").agg(F.count("*").alias("rows")).where("rows > 1").select(F.col("id").alias("_px_id"), F.col("text_hash").alias("_px_hash")))
    if not (n := again.count()):
        return out
    on = (out[id_col].cast("long") == F.col("_px_id")) & (F.xxhash64(out[text_col].cast("string")) == F.col("_px_hash"))
    return join_bounded(out, again, on, "left_anti", n).unionByName(join_bounded(out, again, on, "left_semi", n).dropDuplicates([id_col, text_col]))
