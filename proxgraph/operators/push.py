"""Local pushes in synchronous rounds: all nodes over the threshold settle and spread at once.

Any order of pushes keeps the invariants, so the guarantees are those of one push at a time.  In
the shuffle engine a round is one join of the hot nodes with their arcs and one sum, for all targets
together; the cost of a round is known before it runs, so a budget is never overshot.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import PprParams
from ..storage import join_bounded, saved
from . import kernels
from .graph import Graph

#: Arc touches that one task may do alone.
SMALL_BUDGET = 5_000_000
#: Targets that one task may take for a ladder of budgets.
LADDER_TARGETS = 10_000
STATE = "target long, node long, reserve double, residue double"


@dataclass
class PushTrace:
    cost: int = 0
    rounds: int = 0
    within: bool = True


def reverse(graph: Graph, cands: DataFrame, p: PprParams, budget: float = float("inf"), resume: DataFrame | None = None) -> tuple[DataFrame, PushTrace]:
    """State (target, node, reserve, residue) of reverse pushes toward every target of ``cands`` (target, theta).

    Cost is the in-degree of each pushed node, summed over pushes.  When the next round would exceed
    ``budget`` the trace says so and the state is that of the last full round.
    """
    if graph.use_kernel(p.engine):
        return _reverse_kernel(graph, cands, p, budget, resume)
    return _reverse_frame(graph, cands, p, budget, resume)


def _reverse_kernel(graph: Graph, cands: DataFrame, p: PprParams, budget: float, resume: DataFrame | None) -> tuple[DataFrame, PushTrace]:
    adjacency = graph.csr
    rows = cands.select("target", "theta")
    if resume is not None:
        held = resume.groupBy("target").agg(F.collect_list(F.struct("node", "reserve", "residue")).alias("held"))
        rows = rows.join(held, "target", "left")

    spent = [0]  # of this task: the budget is for all its targets together

    def run(row):
        csr = adjacency.value
        state = None
        if row.get("held"):
            reserve, residue = np.zeros(len(csr.ids)), np.zeros(len(csr.ids))
            at = csr.place(np.array([h["node"] for h in row["held"]]))
            reserve[at] = [h["reserve"] for h in row["held"]]
            residue[at] = [h["residue"] for h in row["held"]]
            state = (reserve, residue)
        at = int(csr.place(np.array([row["target"]]))[0])
        reserve, residue, cost, rounds, within = kernels.reverse_push(csr, at, row["theta"], p.alpha, budget - spent[0], state, p.max_rounds)
        spent[0] = spent[0] + cost if within else float("inf")
        on = np.flatnonzero((reserve > 0) | (residue > 0))
        kinds = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64(), pa.int64(), pa.bool_()]
        names = ["target", "node", "reserve", "residue", "cost", "rounds", "within"]
        yield kernels.sparse_rows(names, kinds, [np.full(len(on), row["target"]), csr.ids[on], reserve[on], residue[on], [None] * len(on), [None] * len(on), [None] * len(on)])
        yield kernels.sparse_rows(names, kinds, [[row["target"]], [None], [None], [None], [cost], [rounds], [within]])

    # under a small budget one task takes all targets, so that it is not overshot by each of many
    tasks = rows.repartition(1 if budget < SMALL_BUDGET else max(1, graph.spark.sparkContext.defaultParallelism), "target")
    out = saved(tasks.mapInArrow(kernels.each_row(run), f"{STATE}, cost long, rounds long, within boolean"))
    t = out.where("cost is not null").agg(F.coalesce(F.sum("cost"), F.lit(0)), F.coalesce(F.max("rounds"), F.lit(0)), F.coalesce(F.min(F.col("within").cast("int")), F.lit(1))).first()
    within = bool(t[2]) and t[0] <= budget
    return out.where("cost is null").select("target", "node", "reserve", "residue"), PushTrace(t[0], t[1], within)


def ladder(graph: Graph, cands: DataFrame, rungs: list[tuple[int, float]], p: PprParams) -> tuple[DataFrame, list[tuple[int, int, int, bool]]]:
    """Pushes at each rung (walks, budget) in turn, until one is over its budget, by one task in one job.

    ``cands`` is (target, rough, own_tol).  Gives the state of the last rung within its budget (empty if none was) and
    (walks, cost, rounds, within) of each rung tried.  For budgets under ``SMALL_BUDGET``, which bound the task's work and
    with it the states it holds.
    """
    adjacency = graph.csr
    names = ["target", "node", "reserve", "residue", "walks", "cost", "rounds", "within"]
    kinds = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]

    def run(batches):
        rows = [row for batch in batches for row in batch.to_pylist()]
        csr = adjacency.value
        places = csr.place(np.array([row["target"] for row in rows], np.int64))
        held, before = [], 0
        for count, budget in rungs if rows else []:
            cost, rounds, within, got = 0, 0, True, []
            for k, row in enumerate(rows):
                theta = row["own_tol"] * row["own_tol"] * count / (p.theta_const * row["rough"])
                state = None
                if held and p.mode == "resume":
                    on, *values = held[k]
                    state = np.zeros(len(csr.ids)), np.zeros(len(csr.ids))
                    for whole, part in zip(state, values):
                        whole[on] = part
                reserve, residue, own, depth, within = kernels.reverse_push(csr, int(places[k]), theta, p.alpha, budget - before - cost, state, p.max_rounds)
                cost, rounds = cost + own, max(rounds, depth)
                if not within:
                    break
                on = np.flatnonzero((reserve > 0) | (residue > 0))
                got.append((on, reserve[on], residue[on]))
            yield kernels.sparse_rows(names, kinds, [[None], [None], [None], [None], [count], [cost], [rounds], [within]])
            if not within:
                break
            held = got
            before += cost if p.mode == "resume" else 0
        for row, (on, reserve, residue) in zip(rows, held):
            gone = [None] * len(on)
            yield kernels.sparse_rows(names, kinds, [np.full(len(on), row["target"]), csr.ids[on], reserve, residue, gone, gone, gone, gone])

    out = saved(cands.select("target", "rough", "own_tol").repartition(1).mapInArrow(run, f"{STATE}, walks long, cost long, rounds long, within boolean"))
    tried = out.where("walks is not null").select("walks", "cost", "rounds", "within").orderBy(F.desc("walks")).collect()
    return out.where("walks is null").select("target", "node", "reserve", "residue"), [tuple(row) for row in tried]


def _reverse_frame(graph: Graph, cands: DataFrame, p: PprParams, budget: float, resume: DataFrame | None) -> tuple[DataFrame, PushTrace]:
    limits = saved(cands.select("target", "theta"))
    count = limits.count()
    arcs = graph.arcs.select(F.col("dst").alias("node"), "src", "out_deg")
    in_deg = graph.nodes.select(F.col("id").alias("node"), "in_deg")
    state = resume if resume is not None else cands.select("target", F.col("target").alias("node"), F.lit(0.0).alias("reserve"), F.lit(1.0).alias("residue"))
    trace, held = PushTrace(), []
    while True:
        marked = join_bounded(state, limits, "target", "inner", count).withColumn("hot", F.col("residue") > F.col("theta"))
        cost = marked.where("hot").join(in_deg, "node").agg(F.count("*"), F.sum("in_deg")).first()
        if not cost[0]:
            return state.select("target", "node", "reserve", "residue"), trace
        if trace.cost + cost[1] > budget:
            trace.within = False
            return state.select("target", "node", "reserve", "residue"), trace
        if trace.rounds >= p.max_rounds:
            raise RuntimeError("a push did not end within max_rounds")
        trace.cost += cost[1]
        trace.rounds += 1
        state = reverse_round(marked, arcs, p.alpha)
        if trace.rounds % p.table_every:
            state = state.persist()
            held.append(state)
        else:
            state = saved(state)
            while held:
                held.pop().unpersist()


def reverse_round(marked: DataFrame, arcs: DataFrame, alpha: float) -> DataFrame:
    """One synchronous round; ``marked`` has ``hot``, ``arcs`` is (node, src, out_deg) by arc end."""
    settle = marked.select("node", "target", F.when(F.col("hot"), F.col("reserve") + alpha * F.col("residue")).otherwise(F.col("reserve")).alias("reserve"), F.when(F.col("hot"), 0.0).otherwise(F.col("residue")).alias("residue"))
    spread = marked.where("hot").join(arcs, "node").select(F.col("src").alias("node"), "target", F.lit(0.0).alias("reserve"), ((1 - alpha) * F.col("residue") / F.col("out_deg")).alias("residue"))
    return settle.unionByName(spread).groupBy("node", "target").agg(F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue")).select("target", "node", "reserve", "residue")


def reverse_single(graph: Graph, target: int, theta: float, p: PprParams) -> tuple[DataFrame, PushTrace]:
    graph.require(target)
    return reverse(graph, graph.spark.createDataFrame([(target, float(theta))], "target long, theta double"), p)


def reverse_all_targets(graph: Graph, source: int, tol: float, p: PprParams, max_nodes: int = 50_000) -> tuple[DataFrame, PushTrace]:
    """The absolute-tolerance baseline: a reverse push from every node, read at the source."""
    if graph.n > max_nodes:
        raise ValueError(f"a push from each of more than {max_nodes} nodes; raise max_nodes to insist")
    cands = graph.nodes.select(F.col("id").alias("target"), F.lit(float(tol)).alias("theta"))
    state, trace = reverse(graph, cands, p)
    return state.where((F.col("node") == source) & (F.col("reserve") > 0)).select(F.col("target").alias("node"), F.col("reserve").alias("est")), trace


def start_table(graph: Graph, source) -> DataFrame:
    """(node, weight) with weights that sum to one, of a node or a (node, weight) table."""
    if not isinstance(source, DataFrame):
        graph.require(source)
        return graph.spark.createDataFrame([(source, 1.0)], "node long, weight double")
    held = source.where("weight > 0").groupBy("node").agg(F.sum("weight").alias("weight"))
    total = held.agg(F.sum("weight")).first()[0]
    if not total:
        raise ValueError("no source has a positive weight")
    return held.select("node", (F.col("weight") / F.lit(total)).alias("weight"))


def start_vector(csr, starts: DataFrame) -> np.ndarray:
    t = starts.toArrow()
    v = np.zeros(len(csr.ids))
    v[csr.place(t.column("node").to_numpy())] = t.column("weight").to_numpy()
    return v


def forward(graph: Graph, source, rmax: float, p: PprParams) -> tuple[DataFrame, PushTrace]:
    """State (node, reserve, residue) of forward pushes; a node is hot while residue / out-degree > rmax."""
    starts = start_table(graph, source)
    if graph.use_kernel(p.engine):
        adjacency = graph.csr
        v = start_vector(adjacency.value, starts)

        def run(_):
            csr = adjacency.value
            reserve, residue, cost, rounds = kernels.forward_push(csr, v, rmax, p.alpha, p.max_rounds)
            on = np.flatnonzero((reserve > 0) | (residue > 0))
            names, kinds = ["node", "reserve", "residue", "cost", "rounds"], [pa.int64(), pa.float64(), pa.float64(), pa.int64(), pa.int64()]
            yield kernels.sparse_rows(names, kinds, [csr.ids[on], reserve[on], residue[on], [None] * len(on), [None] * len(on)])
            yield kernels.sparse_rows(names, kinds, [[None], [None], [None], [cost], [rounds]])

        out = saved(graph.spark.range(0, 1, 1, 1).mapInArrow(kernels.each_row(run), "node long, reserve double, residue double, cost long, rounds long"))
        t = out.where("cost is not null").first()
        return out.where("cost is null").select("node", "reserve", "residue"), PushTrace(t["cost"], t["rounds"])
    state = starts.select("node", F.lit(0.0).alias("reserve"), F.col("weight").alias("residue")).join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node")
    arcs = graph.arcs.select(F.col("src").alias("node"), "dst", "dst_deg")
    trace = PushTrace()
    while True:
        hot = F.col("residue") > F.lit(rmax) * F.col("deg")
        cost = state.where(hot).agg(F.count("*"), F.sum("deg")).first()
        if not cost[0]:
            return state.select("node", "reserve", "residue"), trace
        if trace.rounds >= p.max_rounds:
            raise RuntimeError("a push did not end within max_rounds")
        trace.cost += cost[1]
        trace.rounds += 1
        settle = state.select("node", "deg", F.when(hot, F.col("reserve") + p.alpha * F.col("residue")).otherwise(F.col("reserve")).alias("reserve"), F.when(hot, 0.0).otherwise(F.col("residue")).alias("residue"))
        spread = state.where(hot).join(arcs, "node").select(F.col("dst").alias("node"), F.col("dst_deg").alias("deg"), F.lit(0.0).alias("reserve"), ((1 - p.alpha) * F.col("residue") / F.col("deg")).alias("residue"))
        state = settle.unionByName(spread).groupBy("node").agg(F.max("deg").alias("deg"), F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue"))
        state = saved(state) if trace.rounds % p.table_every == 0 else state.persist()


def forward_absolute(graph: Graph, source, tol: float, p: PprParams) -> tuple[DataFrame, PushTrace]:
    """Forward push for an absolute tolerance: rmax = tol / dmax (undirected) or tol / m (directed)."""
    rmax = tol / (graph.m if graph.directed else graph.stats["dmax"])
    state, trace = forward(graph, source, rmax, p)
    return state.where("reserve > 0").select("node", F.col("reserve").alias("est")), trace


def forward_degree_norm(graph: Graph, source, tol_deg: float, p: PprParams) -> tuple[DataFrame, PushTrace]:
    """Forward push at rmax = tol_deg: error over degree is at most tol_deg on undirected graphs."""
    if graph.directed:
        raise ValueError("degree-normalised errors are bounded on undirected graphs only")
    state, trace = forward(graph, source, tol_deg, p)
    return state.where("reserve > 0").select("node", F.col("reserve").alias("est")), trace
