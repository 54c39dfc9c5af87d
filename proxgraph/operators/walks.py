"""Stopping random walks: each step first stops with probability alpha, else moves to a uniform out-neighbour."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import prng
from ..params import PprParams
from ..storage import saved
from . import kernels
from .graph import Graph
from .relational import cumulative

CHUNK = 1 << 17
MAX_ALIAS = 2_000_000


def alias_arrays(weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(accept, alias) so that slot i, kept with probability accept[i] and else replaced by alias[i], follows the weights."""
    n = len(weights)
    share = weights * (n / weights.sum())
    accept, alias = np.ones(n), np.arange(n)
    small, large = [i for i in range(n) if share[i] < 1], [i for i in range(n) if share[i] >= 1]
    while small and large:
        s, b = small.pop(), large.pop()
        accept[s], alias[s] = share[s], b
        share[b] -= 1 - share[s]
        (small if share[b] < 1 else large).append(b)
    return accept, alias


def alias_table(sources: DataFrame) -> DataFrame:
    """(slot, node, accept, alias) of a (node, weight) table, slots by node; weights of zero or less are left out.

    Equal weights need no alias: their slots are numbered where they lie, for any number of sources.  Other
    tables are built on the driver, up to ``MAX_ALIAS`` sources.
    """
    held = saved(sources.where("weight > 0").groupBy("node").agg(F.sum("weight").alias("weight")))
    count, least, most = held.agg(F.count("*"), F.min("weight"), F.max("weight")).first()
    if not count:
        raise ValueError("no source has a positive weight")
    if least == most:
        return _numbered(held.select("node"))
    if count > MAX_ALIAS:
        raise ValueError(f"more than {MAX_ALIAS} sources of different weights")
    rows = held.orderBy("node").toArrow()
    node, weight = rows.column("node").to_numpy(), rows.column("weight").to_numpy().astype(float)
    accept, alias = alias_arrays(weight)
    table = pa.table({"slot": np.arange(len(node)), "node": node, "accept": accept, "alias": node[alias]})
    return sources.sparkSession.createDataFrame(table)


def _numbered(nodes: DataFrame) -> DataFrame:
    """The alias table of equal weights: slots from 0 in order of node, counted inside ranges of nodes."""
    ranges = saved(nodes.repartitionByRange("node").withColumn("range", F.spark_partition_id()))
    placed = cumulative(ranges.withColumn("one", F.lit(1).cast("long")), "one", ["node"], F.col("range"))
    return saved(placed.select((F.col("running") - 1).alias("slot"), "node", F.lit(1.0).alias("accept"), F.col("node").alias("alias")))


def simulate(graph: Graph, start, trials: int, walks: int, p: PprParams, with_steps: bool = False) -> DataFrame:
    """(trial, node, cnt) of ``trials`` times ``walks`` walks.

    ``start`` is a node, or a (node, weight) table.  With ``with_steps`` a row with a null node holds
    the moves made by a task.
    """
    if graph.use_kernel(p.engine):
        return _simulate_kernel(graph, start, trials, walks, p, with_steps)
    return _simulate_frame(graph, start, trials, walks, p)


def _simulate_kernel(graph: Graph, start, trials: int, walks: int, p: PprParams, with_steps: bool) -> DataFrame:
    adjacency, total = graph.csr, trials * walks
    rng = p.generator(total)
    if isinstance(start, DataFrame):
        t = alias_table(start).orderBy("slot").toArrow()
        place = adjacency.value.place
        nodes, accept, alias = place(t.column("node").to_numpy()), t.column("accept").to_numpy(), t.column("alias").to_numpy()
        # slots of the table are looked up after the draw
        starts = (accept, np.searchsorted(nodes, place(alias)), nodes)
    else:
        starts = int(adjacency.value.place(np.array([start]))[0])

    def run(row):
        csr = adjacency.value
        g = np.arange(row["id"] * CHUNK, min((row["id"] + 1) * CHUNK, total))
        trial, walk = g // walks, g % walks
        if isinstance(starts, tuple):
            at = starts[2][kernels.pick_starts(starts[:2], trial, walk, p.seed, rng)]
        else:
            at = np.full(len(g), starts)
        ends, moves = kernels.run_walks(csr, at, trial, walk, p.seed, p.alpha, rng)
        pair, cnt = np.unique(trial * len(csr.ids) + ends, return_counts=True)
        yield kernels.sparse_rows(["trial", "node", "cnt"], [pa.int32(), pa.int64(), pa.int64()], [pair // len(csr.ids), csr.ids[pair % len(csr.ids)], cnt])
        if with_steps:
            yield kernels.sparse_rows(["trial", "node", "cnt"], [pa.int32(), pa.int64(), pa.int64()], [[-1], [None], [moves]])

    tasks = graph.spark.range(0, -(-total // CHUNK), 1, max(1, min(-(-total // CHUNK), 4096)))
    counts = tasks.mapInArrow(kernels.each_row(run), "trial int, node long, cnt long")
    return counts.groupBy("trial", "node").agg(F.sum("cnt").alias("cnt"))


def _simulate_frame(graph: Graph, start, trials: int, walks: int, p: PprParams) -> DataFrame:
    spark, limit, rng = graph.spark, prng.stop_limit(p.alpha), p.generator(trials * walks)
    base = spark.range(trials * walks).select(F.floor(F.col("id") / walks).cast("int").alias("trial"), (F.col("id") % walks).alias("walk"))

    def drawn(step, lane: int):
        if rng == "wide":
            return prng.wide_draw_col(p.seed, F.col("trial"), F.col("walk"), step, lane)
        return prng.draw_col(prng.walk_key_col(p.seed, F.col("trial"), F.col("walk")), step, lane)

    if isinstance(start, DataFrame):
        table = alias_table(start)
        size = table.count()
        base = base.withColumn("slot", drawn(F.lit(1_000_003), 0) % size).join(table, "slot")
        base = base.select("trial", "walk", F.when(drawn(F.lit(1_000_003), 1) < F.col("accept") * prng.P, F.col("node")).otherwise(F.col("alias")).alias("node"))
    else:
        graph.require(start)
        base = base.withColumn("node", F.lit(start).cast("long"))
    live = base.join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node").select("trial", "walk", "node", "deg")
    arcs = graph.arcs.select(F.col("src").alias("node"), "idx", "dst", "dst_deg")
    parts, step = [], 0
    while True:
        ended, held = [], []
        for _ in range(p.table_every):
            live = live.withColumn("stops", drawn(F.lit(step), 0) < limit).persist()
            held.append(live)
            ended.append(live.where("stops").groupBy("trial", "node").agg(F.count("*").alias("cnt")))
            live = live.where("not stops").withColumn("idx", drawn(F.lit(step), 1) % F.col("deg")).join(arcs, ["node", "idx"]).select("trial", "walk", F.col("dst").alias("node"), F.col("dst_deg").alias("deg"))
            step += 1
        done = ended[0]
        for e in ended[1:]:
            done = done.unionByName(e)
        parts.append(saved(done))
        live = saved(live)
        for x in held:
            x.unpersist()
        if not live.limit(1).count():
            break
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out.groupBy("trial", "node").agg(F.sum("cnt").alias("cnt"))
