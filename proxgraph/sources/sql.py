"""SQL surface: table functions for walk paths and pushes, and a query by edge view."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions import prng
from ..operators import solvers
from ..operators.graph import Graph
from ..params import PprParams
from ..session import ship


def register(spark: SparkSession, graph: Graph, prefix: str) -> None:
    """Views ``<prefix>_arcs`` and ``<prefix>_nodes``, and for graphs under the size check the functions
    ``<prefix>_walk(source, walks, alpha, seed)`` (walk, step, node) and
    ``<prefix>_push(target, theta, alpha)`` (node, reserve, residue)."""
    ship(spark)
    graph.register(prefix)
    adjacency = graph.csr

    @udtf(returnType="walk: bigint, step: int, node: bigint")
    class Walk:
        def eval(self, source: int, walks: int, alpha: float, seed: int) -> Iterator[tuple]:
            csr = adjacency.value
            limit = prng.stop_limit(float(alpha))
            for w in range(walks):
                key, at, step = prng.walk_key(seed, np.zeros(1, np.int64), np.array([w])), int(csr.place(np.array([source]))[0]), 0
                yield w, 0, int(csr.ids[at])
                while prng.draw(key, step, 0)[0] >= limit:
                    deg = csr.out_at[at + 1] - csr.out_at[at]
                    at = int(csr.out_to[csr.out_at[at] + prng.draw(key, step, 1)[0] % deg])
                    step += 1
                    yield w, step, int(csr.ids[at])

    @udtf(returnType="node: bigint, reserve: double, residue: double")
    class Push:
        def eval(self, target: int, theta: float, alpha: float) -> Iterator[tuple]:
            from ..operators import kernels

            csr = adjacency.value
            reserve, residue, *_ = kernels.reverse_push(csr, int(csr.place(np.array([target]))[0]), float(theta), float(alpha))
            for i in np.flatnonzero((reserve > 0) | (residue > 0)):
                yield int(csr.ids[i]), float(reserve[i]), float(residue[i])

    spark.udtf.register(f"{prefix}_walk", Walk)
    spark.udtf.register(f"{prefix}_push", Push)


def ppr(spark: SparkSession, view: str, source: int, tol: float, directed: bool = True, p: PprParams | None = None) -> DataFrame:
    """Scores within ``tol`` from a view or table of (src, dst)."""
    graph = Graph.from_edges(spark.table(view).select("src", "dst"), directed)
    return solvers.absolute(graph, source, tol, p or PprParams())[0].orderBy(F.desc("est"), "node")
