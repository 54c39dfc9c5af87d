"""Mixing sources to target weights by hierarchical budgeting.

Leaves of the tree domain > language > source hold the documents.  A token budget is dealt from the
root: each node splits what it got among its children by weight, a child can take no more than
``max_epochs`` times the tokens under it, and what it can't take goes to its siblings by weight
before anything is left for the ancestors' other children.  A leaf's amount is met by whole epochs
and a prefix of the next one: documents in an order seeded by (seed, epoch), while their running
token sum stays within the rest.

The prefix needs no sort of a whole leaf: the order hash is cut into ranges, range sums find the
range in which the prefix ends, and only that range is ordered.

Null domain, language or source values are leaves of their own (``none``).  Null and empty texts
have no tokens: they are never selected.  Null ids are documents like others.  Rows are told apart by id
and text; rows that are equal in both are interchangeable and are taken one by one, so a budget is kept
whatever repeats.  The driver handles the leaf table (a row per leaf, ``MAX_LEAVES`` at most).
"""

from __future__ import annotations

import math
from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import saved

MAX_LEAVES = 200_000
LEVELS = ("domain", "lang", "source")
_RANGE_DOCS, _MOST_RANGES = 500, 100_000


def default_domain(source: str = "source") -> Column:
    """The name of the source without a number at its end: documents have no domain of their own."""
    return F.regexp_replace(F.col(source).cast("string"), r"[0-9]+\z", "")


def fill(amount: float, children: list[tuple[str, float, float]]) -> dict[str, float]:
    """Deal ``amount`` to (name, weight, capacity) by weight; what a full child can't take goes to the others."""
    out = {name: 0.0 for name, _, _ in children}
    # those that are full first, by what they can take for their weight, come first
    open_ = sorted((c for c in children if c[1] > 0 and c[2] > 0), key=lambda c: c[2] / c[1])
    left = min(amount, sum(c[2] for c in open_))
    total = sum(c[1] for c in open_)
    for i, (name, w, cap) in enumerate(open_):
        if cap > left * w / total:
            for other, v, _ in open_[i:]:
                out[other] = left * v / total
            break
        out[name] = cap
        left, total = left - cap, total - w
    return out


def budgets(leaves: list[tuple[str, str, str, int]], budget: float, weights: Mapping[tuple, float], max_epochs: float) -> dict[tuple[str, str, str], int]:
    """Tokens to take of each leaf; ``weights`` maps a path (a tuple of 1 to 3 names) to its weight among siblings, 1 by default."""
    cap: dict[tuple, float] = {}
    kids: dict[tuple, set] = {}
    for *path, tokens in sorted(leaves):
        path = tuple(path)
        for k in range(len(path) + 1):
            cap[path[:k]] = cap.get(path[:k], 0.0) + tokens * max_epochs
            if k:
                kids.setdefault(path[: k - 1], set()).add(path[:k])
    got = {(): min(budget, cap.get((), 0.0))}
    for depth in range(3):
        for node in sorted(p for p in kids if len(p) == depth):
            got |= fill(got.get(node, 0.0), [(c, weights.get(c, 1.0), cap[c]) for c in sorted(kids[node])])
    return {p: int(math.floor(v + 1e-6)) for p, v in got.items() if len(p) == 3}


def _order(seed: int, epoch: Column) -> Column:
    """Order hash in [0, 2**53) of the row's id and text."""
    return F.pmod(F.xxhash64(F.lit(seed), epoch, F.col("id"), F.col("text_hash")), F.lit(1 << 53))


_KEYS = ("id", "text_hash", *LEVELS)


def _described(docs: DataFrame, domain: Column | None, id_col: str, text_col: str, lang_col: str, source_col: str) -> list[Column]:
    name = lambda c: F.coalesce(c.cast("string"), F.lit("none"))
    text = F.col(text_col).cast("string")
    values = (F.col(id_col).cast("long"), F.xxhash64(text), name(default_domain(source_col) if domain is None else domain), name(F.col(lang_col)), name(F.col(source_col)))
    n_tokens = F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")
    return [*(v.alias(c) for v, c in zip(values, _KEYS, strict=True)), n_tokens.alias("n_tokens")]


def plan(docs: DataFrame, budget_share: float, weights: Mapping[tuple, float] | None, max_epochs: float, seed: int, columns: list[Column]) -> DataFrame:
    """(id, text_hash, levels, n_tokens, rows, leaf_tokens, leaf_take, epochs, more): ``more`` of the equal rows are taken once more than ``epochs`` times."""
    rows = saved(docs.select(*columns).groupBy(*_KEYS, "n_tokens").agg(F.count("*").alias("rows")))
    tokens = F.col("n_tokens") * F.col("rows")
    table = rows.groupBy(*LEVELS).agg(F.sum("rows").alias("leaf_docs"), F.sum(tokens).alias("leaf_tokens"))
    held = table.limit(MAX_LEAVES + 1).collect()
    if len(held) > MAX_LEAVES:
        raise ValueError(f"more than {MAX_LEAVES} leaves")
    total = sum(r["leaf_tokens"] for r in held)
    take = budgets([(r["domain"], r["lang"], r["source"], r["leaf_tokens"]) for r in held], budget_share * total, weights or {}, max_epochs)
    leaf_rows = []
    for r in held:
        t = take.get((r["domain"], r["lang"], r["source"]), 0)
        epochs = t // r["leaf_tokens"] if r["leaf_tokens"] else 0
        leaf_rows.append((r["domain"], r["lang"], r["source"], r["leaf_tokens"], t, epochs, t - epochs * r["leaf_tokens"], min(_MOST_RANGES, 1 + r["leaf_docs"] // _RANGE_DOCS)))
    schema = "domain string, lang string, source string, leaf_tokens long, leaf_take long, epochs long, rest long, ranges long"
    leaves = F.broadcast(rows.sparkSession.createDataFrame(leaf_rows, schema))
    placed = rows.join(leaves, list(LEVELS)).withColumn("place", _order(seed, F.col("epochs"))).withColumn("range", F.floor(F.col("place").cast("double") / float(1 << 53) * F.col("ranges")).cast("long"))
    sums = placed.groupBy(*LEVELS, "rest", "range").agg(F.sum(tokens).alias("held"))
    run = Window.partitionBy(*LEVELS).orderBy("range")
    ends = sums.withColumn("upto", F.sum("held").over(run)).where(F.col("upto") > F.col("rest")).groupBy(*LEVELS).agg(F.min(F.struct("range", (F.col("upto") - F.col("held")).alias("before"))).alias("end"))
    ends = F.broadcast(saved(ends.select(*(F.col(c).alias(f"of_{c}") for c in LEVELS), F.col("end.range").alias("end_range"), F.col("end.before").alias("before"))))  # a row per leaf at most
    on = [F.col(c) == F.col(f"of_{c}") for c in LEVELS]
    placed = placed.join(ends, on, "left").drop(*(f"of_{c}" for c in LEVELS))
    before_end = F.col("end_range").isNull() | (F.col("range") < F.col("end_range"))
    whole = placed.where("end_range is null or range <> end_range").withColumn("more", F.when(before_end, F.col("rows")).otherwise(F.lit(0)))
    order = Window.partitionBy(*LEVELS).orderBy("place", "id", "text_hash").rowsBetween(Window.unboundedPreceding, -1)
    room = F.col("rest") - F.col("before") - F.coalesce(F.sum(tokens).over(order), F.lit(0))
    fits = F.floor(room / F.greatest(F.col("n_tokens"), F.lit(1))).cast("long")
    last = placed.where("range = end_range").withColumn("more", F.least(F.col("rows"), F.greatest(F.lit(0).cast("long"), fits)))
    some = (F.col("n_tokens") > 0) & (F.col("rest") > 0)
    return whole.unionByName(last).select(*_KEYS, "n_tokens", "rows", "leaf_tokens", "leaf_take", F.when(F.col("n_tokens") > 0, F.col("epochs")).otherwise(0).alias("epochs"), F.when(some, F.col("more")).otherwise(0).cast("long").alias("more"))


def mix(docs: DataFrame, budget_share: float = 0.5, weights: Mapping[tuple, float] | None = None, max_epochs: float = 4.0, seed: int = 17, domain: Column | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """One row per input row: id, domain, lang, source, n_tokens, leaf_tokens, leaf_take, copies."""
    out = plan(docs, budget_share, weights, max_epochs, seed, _described(docs, domain, id_col, text_col, lang_col, source_col))
    out = out.select("*", F.explode(F.sequence(F.lit(1).cast("long"), F.col("rows"))).alias("number"))
    copies = F.col("epochs") + (F.col("number") <= F.col("more")).cast("long")
    return out.select(F.col("id").alias(id_col), "domain", "lang", "source", "n_tokens", "leaf_tokens", "leaf_take", copies.alias("copies"))


def select_documents(docs: DataFrame, budget_share: float = 0.5, weights: Mapping[tuple, float] | None = None, max_epochs: float = 4.0, seed: int = 17, domain: Column | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The rows that are taken at least once, with all their columns and ``copies``.

    Of rows that are equal in id, text and leaf any may be the one that is taken more often.
    """
    columns = _described(docs, domain, id_col, text_col, lang_col, source_col)
    taken = plan(docs, budget_share, weights, max_epochs, seed, columns).where("epochs > 0 or more > 0")
    taken = taken.select(*(F.col(c).alias(f"_px_of_{c}") for c in _KEYS), F.col("rows").alias("_px_rows"), F.col("epochs").alias("_px_epochs"), F.col("more").alias("_px_more"))
    base = docs.drop("copies") if "copies" in docs.columns else docs
    names = base.columns
    base = base.select("*", *(c.alias(f"_px_{k}") for c, k in zip(columns, _KEYS, strict=False)))
    on = [F.col(f"_px_{c}").eqNullSafe(F.col(f"_px_of_{c}")) for c in _KEYS]
    both = base.join(taken, on)
    one = both.where("_px_rows = 1").withColumn("_px_number", F.lit(1))
    several = both.where("_px_rows > 1").withColumn("_px_number", F.row_number().over(Window.partitionBy(*(f"_px_{c}" for c in _KEYS)).orderBy("_px_id")))
    copies = F.col("_px_epochs") + (F.col("_px_number") <= F.col("_px_more")).cast("long")
    return one.unionByName(several).select(*names, copies.alias("copies")).where("copies > 0")
