"""Entry points of the queries: absolute, degree-normalised, relative, Monte Carlo, PageRank, batches."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import PprParams, check_tol
from . import power, push, three_phase, walks
from .graph import Graph
from .three_phase import SolveReport


def absolute(graph: Graph, source, tol: float, p: PprParams) -> tuple[DataFrame, SolveReport]:
    """Every node within ``tol`` with probability 1 - 1/n at least."""
    return three_phase.run(graph, source, tol, p)


def degree_norm(graph: Graph, source, tol_deg: float, p: PprParams) -> tuple[DataFrame, SolveReport]:
    """Every node's error over its degree within ``tol_deg`` (undirected graphs)."""
    return three_phase.run(graph, source, tol_deg, p, degree_norm=True)


def degree_norm_via_absolute(graph: Graph, source, tol_deg: float, p: PprParams) -> tuple[DataFrame, SolveReport]:
    """The same guarantee from the absolute solver, at tol_deg times the smallest degree."""
    if graph.directed:
        raise ValueError("degree-normalised errors are defined on undirected graphs only")
    return three_phase.run(graph, source, tol_deg * graph.stats["dmin"], p)


def relative(graph: Graph, source, rel: float, floor: float, p: PprParams) -> tuple[DataFrame, SolveReport]:
    """Relative error ``rel`` for scores of ``floor`` and more, from the absolute solver."""
    check_tol(floor)
    return three_phase.run(graph, source, rel * floor, p)


def monte_carlo(graph: Graph, source, tol: float, p: PprParams) -> DataFrame:
    """Plain walks: ceil(ln(2 n^2) / (2 tol^2)) of them keep every node within ``tol`` (Hoeffding, union bound)."""
    return monte_carlo_walks(graph, source, monte_carlo_count(graph.n, check_tol(tol)), p)


def monte_carlo_count(n: int, tol: float) -> int:
    return math.ceil((math.log(2) + 2 * math.log(n)) / (2 * tol * tol))


def monte_carlo_walks(graph: Graph, source, count: int, p: PprParams) -> DataFrame:
    return walks.simulate(graph, source, 1, count, p).select("node", (F.col("cnt") / count).alias("est"))


def single_target(graph: Graph, target: int, tol: float, p: PprParams) -> DataFrame:
    """Scores of all nodes toward ``target``, each under its true value by ``tol`` at most."""
    state, _ = push.reverse_single(graph, target, check_tol(tol), p)
    return state.where("reserve > 0").select("node", F.col("reserve").alias("est"))


def uniform_sources(graph: Graph) -> DataFrame:
    return graph.nodes.select(F.col("id").alias("node"), F.lit(1.0).alias("weight"))


def pagerank(graph: Graph, tol: float, p: PprParams) -> tuple[DataFrame, SolveReport]:
    return three_phase.run(graph, uniform_sources(graph), tol, p)


def pagerank_exact(graph: Graph, p: PprParams, tail: float = 1e-12) -> DataFrame:
    return power.single_source(graph, uniform_sources(graph), p, tail)


def batch(graph: Graph, sources: list[int], tol: float, p: PprParams, degree_norm: bool = False) -> DataFrame:
    """(query, node, est) for a short list of sources."""
    parts = [three_phase.run(graph, s, tol, p, degree_norm)[0].select(F.lit(s).cast("long").alias("query"), "node", "est") for s in sources]
    return reduce(DataFrame.unionByName, parts)


def degree_sources(graph: Graph, count: int, seed: int = 1) -> list[int]:
    """``count`` nodes drawn with probability proportional to degree: the ends of hash-chosen arcs."""
    rows = graph.pairs.orderBy(F.md5(F.concat_ws(":", F.lit(seed), "src", "dst")), "src", "dst").limit(count).select("src").collect()
    return [r[0] for r in rows]


def recommend(graph: Graph, tol: float, p: PprParams) -> str:
    """three_phase or power: whichever has the smaller predicted operation count."""
    s = graph.stats
    spread = math.sqrt(s["m"]) if graph.directed else math.sqrt(s["dmax"])
    three = spread / tol * p.trials(s["n"]) ** 0.5 + p.phase1_walks(s["n"], tol) / p.alpha
    return "three_phase" if three < s["arcs"] * p.rounds_for(tol) else "power"
