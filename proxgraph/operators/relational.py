"""Relational operators around the graphs: as-of, interval and range joins, prefix sums, per-group top-k."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, by: str, time: str, values: list[str]) -> DataFrame:
    """Each left row with ``values`` of the latest right row of the same ``by`` at or before its ``time``.

    One union and one window over (by, time); right rows come first at equal times.
    """
    marked = left.withColumn("_side", F.lit(1))
    for v in values:
        marked = marked.withColumn(f"_{v}", F.lit(None).cast(right.schema[v].dataType))
    other = right.select(by, time, *(F.col(v).alias(f"_{v}") for v in values)).withColumn("_side", F.lit(0))
    both = marked.unionByName(other, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    for v in values:
        both = both.withColumn(f"asof_{v}", F.last(f"_{v}", ignorenulls=True).over(w))
    return both.where("_side = 1").drop("_side", *(f"_{v}" for v in values))


def interval_join(left: DataFrame, right: DataFrame, by: str, lt: str, rt: str, before: int, bucket: int) -> DataFrame:
    """Pairs with ``0 <= left.lt - right.rt <= before`` (seconds) and equal ``by``.

    Right rows go to every bucket of ``bucket`` seconds that they can serve, so the join is an equi-join
    on (by, bucket) with a residual range test, never a nested loop.
    """
    lo = F.floor(F.col(rt) / bucket)
    hi = F.floor((F.col(rt) + before) / bucket)
    r = right.withColumn("_bucket", F.explode(F.sequence(lo, hi)))
    left = left.withColumn("_bucket", F.floor(F.col(lt) / bucket))
    out = left.join(r, [by, "_bucket"])
    return out.where((F.col(lt) >= F.col(rt)) & (F.col(lt) - F.col(rt) <= before)).drop("_bucket")


def range_lookup(points: DataFrame, ranges: DataFrame, x: str, lo: str, hi: str, cells: int) -> DataFrame:
    """Points of [0, 1) with the row of ``ranges`` that has lo <= x < hi, by an equi-join on cells of the unit interval."""
    first, last = F.floor(F.col(lo) * cells), F.floor(F.col(hi) * cells)
    r = ranges.withColumn("_cell", F.explode(F.sequence(first, last)))
    return points.withColumn("_cell", F.floor(F.col(x) * cells)).join(r, "_cell").where((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("_cell")


def common_neighbours(edges: DataFrame, by: str, item: str, other: str, least: int = 2, block: int = 256) -> DataFrame:
    """(item, other, shared): all pairs ``item < other`` that share ``least`` values of ``by`` or more.

    The items of a value are dealt over blocks of about ``block`` and joined by pair of blocks, so a hot
    value is spread over tasks.
    """
    e = edges.select(by, item).where(F.col(by).isNotNull() & F.col(item).isNotNull()).distinct()
    sizes = e.groupBy(by).agg(F.ceil(F.count("*") / block).cast("int").alias("_blocks"))
    own = e.join(sizes, by).withColumn("_own", F.pmod(F.hash(item), F.col("_blocks")))
    dealt = own.withColumn("_with", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    a = dealt.select(by, F.least("_own", "_with").alias("_lo"), F.greatest("_own", "_with").alias("_hi"), "_own", item)
    b = a.select(by, "_lo", "_hi", F.col("_own").alias("_own_b"), F.col(item).alias(other))
    met = a.join(b, [by, "_lo", "_hi"]).where((F.col(item) < F.col(other)) & ((F.col("_lo") == F.col("_hi")) | (F.col("_own") != F.col("_own_b"))))
    return met.groupBy(item, other).agg(F.count("*").alias("shared")).where(F.col("shared") >= least)


def cumulative(df: DataFrame, value: str, order: list[Column | str], bucket: Column) -> DataFrame:
    """Running sum of ``value`` over the whole table as ``running``, by ordered buckets.

    Sums inside buckets run in parallel; one small window over bucket totals gives their offsets.  The
    order must sort by bucket first.
    """
    d = df.withColumn("_bucket", bucket)
    totals = d.groupBy("_bucket").agg(F.sum(value).alias("_total"))
    offsets = totals.withColumn("_before", F.coalesce(F.sum("_total").over(Window.orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_total")
    run = Window.partitionBy("_bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return d.withColumn("_in", F.sum(value).over(run)).join(offsets, "_bucket").withColumn("running", F.col("_in") + F.col("_before")).drop("_bucket", "_in", "_before")


def top_per_group(df: DataFrame, group: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group, with ``pos`` from 1."""
    return df.withColumn("pos", F.row_number().over(Window.partitionBy(*group).orderBy(*order)).cast("long")).where(F.col("pos") <= k)
