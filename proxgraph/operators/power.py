"""Exact scores by truncated series: the ground truth and the fallback."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import PprParams
from ..storage import saved
from . import kernels
from .graph import Graph
from .push import start_table, start_vector


def single_source(graph: Graph, source, p: PprParams, tail: float = 1e-12) -> DataFrame:
    """(node, est) from a node or a (node, weight) table; the missing mass is at most ``tail``."""
    starts, rounds = start_table(graph, source), p.rounds_for(tail)
    if graph.use_kernel(p.engine):
        adjacency = graph.csr
        v = start_vector(adjacency.value, starts)

        def run(_):
            csr = adjacency.value
            est = kernels.power(csr, v, p.alpha, rounds)
            on = np.flatnonzero(est > 0)
            yield kernels.sparse_rows(["node", "est"], [pa.int64(), pa.float64()], [csr.ids[on], est[on]])

        return graph.spark.range(0, 1, 1, 1).mapInArrow(kernels.each_row(run), "node long, est double")
    return _frame_rounds(graph, starts.select(F.lit(0).cast("long").alias("query"), "node", F.col("weight").alias("mass")), p, rounds, forward=True).select("node", "est")


def multi_source(graph: Graph, sources: DataFrame, p: PprParams, tail: float = 1e-9) -> DataFrame:
    """(query, node, est) for every node of ``sources`` (node)."""
    rounds = p.rounds_for(tail)
    if graph.use_kernel(p.engine):
        adjacency = graph.csr

        def run(row):
            csr = adjacency.value
            v = np.zeros(len(csr.ids))
            v[csr.place(np.array([row["node"]]))] = 1.0
            est = kernels.power(csr, v, p.alpha, rounds)
            on = np.flatnonzero(est > 0)
            yield kernels.sparse_rows(["query", "node", "est"], [pa.int64(), pa.int64(), pa.float64()], [np.full(len(on), row["node"]), csr.ids[on], est[on]])

        tasks = sources.select("node").distinct().repartition(graph.spark.sparkContext.defaultParallelism, "node")
        return tasks.mapInArrow(kernels.each_row(run), "query long, node long, est double")
    start = sources.select(F.col("node").alias("query"), "node", F.lit(1.0).alias("mass")).distinct()
    return _frame_rounds(graph, start, p, rounds, forward=True)


def summed(graph: Graph, weights: DataFrame, p: PprParams, tail: float = 1e-12) -> DataFrame:
    """(node, est): scores summed over all sources of ``weights`` (node, weight), each times its weight.

    Scores are linear in the source, so one run from all of them gives what all pairs would, for any number of nodes.
    """
    total = weights.where("weight > 0").agg(F.sum("weight")).first()[0]
    return single_source(graph, weights, p, tail).select("node", (F.col("est") * F.lit(float(total))).alias("est"))


def single_target(graph: Graph, target: int, p: PprParams, tail: float = 1e-12) -> DataFrame:
    """(node, est): exact scores of every node toward ``target``."""
    graph.require(target)
    rounds = p.rounds_for(tail)
    if graph.use_kernel(p.engine):
        adjacency = graph.csr

        def run(_):
            csr = adjacency.value
            est = kernels.reverse_power(csr, int(csr.place(np.array([target]))[0]), p.alpha, rounds)
            on = np.flatnonzero(est > 0)
            yield kernels.sparse_rows(["node", "est"], [pa.int64(), pa.float64()], [csr.ids[on], est[on]])

        return graph.spark.range(0, 1, 1, 1).mapInArrow(kernels.each_row(run), "node long, est double")
    start = graph.spark.createDataFrame([(0, target, 1.0)], "query long, node long, mass double")
    return _frame_rounds(graph, start, p, rounds, forward=False).select("node", "est")


def all_pairs(graph: Graph, p: PprParams, tail: float = 1e-12, max_nodes: int = 5000) -> DataFrame:
    """(query, node, est) for all pairs of a small graph."""
    if graph.n > max_nodes:
        raise ValueError(f"all pairs of more than {max_nodes} nodes")
    return multi_source(graph, graph.nodes.select(F.col("id").alias("node")), p, tail)


def _frame_rounds(graph: Graph, start: DataFrame, p: PprParams, rounds: int, forward: bool) -> DataFrame:
    """The series by one join and one sum per round; ``start`` is (query, node, mass)."""
    if forward:
        arcs = graph.arcs.select(F.col("src").alias("node"), F.col("dst").alias("to"), "out_deg")
    else:
        arcs = graph.arcs.select(F.col("dst").alias("node"), F.col("src").alias("to"), "out_deg")
    state = start.select("query", "node", "mass", (p.alpha * F.col("mass")).alias("est"))
    for k in range(1, rounds + 1):
        moved = state.where("mass > 0").join(arcs, "node").select("query", F.col("to").alias("node"), ((1 - p.alpha) * F.col("mass") / F.col("out_deg")).alias("mass"), F.lit(0.0).alias("est"))
        state = state.select("query", "node", F.lit(0.0).alias("mass"), "est").unionByName(moved).groupBy("query", "node").agg(F.sum("mass").alias("mass"), F.sum("est").alias("est")).withColumn("est", F.col("est") + p.alpha * F.col("mass"))
        if k % p.table_every == 0:
            state = saved(state)
    return state.where("est > 0").select("query", "node", "est")
