"""Uses of the scores: sweep cuts, top-k, feature rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..params import PprParams
from ..storage import join_bounded, saved
from . import power, push, solvers
from .graph import Graph


def sweep_profile(graph: Graph, scores: DataFrame) -> DataFrame:
    """(rank, node, vol, cut, conductance) of every prefix of the support, by est / degree descending.

    Scores are rounded to nine digits before ranking and ties go by id.  The running sums use one
    window over the support, which is under 2 / tol nodes for the solvers here.
    """
    deg = graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg"))
    order = Window.orderBy(F.desc("key"), "node")
    ranked = scores.where("est > 0").join(deg, "node").withColumn("key", F.round(F.col("est") / F.col("deg"), 9))
    ranked = saved(ranked.withColumn("rank", F.row_number().over(order)).select("node", "deg", "rank"))
    size = ranked.count()
    ends = join_bounded(graph.arcs.select("src", "dst"), ranked.select(F.col("node").alias("src"), F.col("rank").alias("a")), "src", "inner", size)
    ends = join_bounded(ends, ranked.select(F.col("node").alias("dst"), F.col("rank").alias("b")), "dst", "left", size)
    # an arc from rank a is cut from a on, until its other end b joins
    steps = ends.select(F.explode(F.when(F.col("b").isNull(), F.array(F.struct(F.col("a").alias("rank"), F.lit(1).alias("d")))).when(F.col("a") < F.col("b"), F.array(F.struct(F.col("a").alias("rank"), F.lit(1).alias("d")), F.struct(F.col("b").alias("rank"), F.lit(-1).alias("d")))).otherwise(F.array().cast("array<struct<rank:int,d:int>>"))).alias("s"))
    change = steps.groupBy(F.col("s.rank").alias("rank")).agg(F.sum("s.d").alias("change"))
    run = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    out = ranked.join(change, "rank", "left").select("rank", "node", F.sum("deg").over(run).alias("vol"), F.sum(F.coalesce("change", F.lit(0))).over(run).alias("cut"))
    total = graph.stats["arcs"]
    least = F.least(F.col("vol"), F.lit(total) - F.col("vol"))
    return out.withColumn("conductance", F.when(least > 0, F.col("cut") / least))


def best_cut(graph: Graph, scores: DataFrame) -> DataFrame:
    """The prefix of least conductance (the shortest of equals): size, vol, cut, conductance."""
    profile = sweep_profile(graph, scores).where("conductance is not null")
    return profile.agg(F.min_by(F.struct(F.col("rank").cast("long").alias("size"), "vol", "cut", "conductance"), F.struct(F.round("conductance", 9), "rank")).alias("b")).select("b.*")


def partition(graph: Graph, source: int, tol_deg: float, p: PprParams, scorer: str = "forward") -> DataFrame:
    """The sweep cut of a scorer's answer: forward push, the degree-normalised solver, or exact scores."""
    if scorer == "forward":
        scores = push.forward_degree_norm(graph, source, tol_deg, p)[0]
    elif scorer == "degree_norm":
        scores = solvers.degree_norm(graph, source, tol_deg, p)[0]
    elif scorer == "exact":
        scores = power.single_source(graph, source, p)
    else:
        raise ValueError("scorer must be forward, degree_norm or exact")
    return best_cut(graph, scores)


def topk(graph: Graph, scores: DataFrame, k: int, by: str = "est") -> DataFrame:
    """(rank, node, value): the k largest by est or est_over_d, rounded to nine digits, ties by id."""
    value = F.col("est")
    if by == "est_over_d":
        scores = scores.join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node")
        value = F.col("est") / F.col("deg")
    elif by != "est":
        raise ValueError("by must be est or est_over_d")
    first = scores.select("node", F.round(value, 9).alias("value")).orderBy(F.desc("value"), "node").limit(k)
    return first.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("value"), "node")).cast("long"))


def features(scores: DataFrame) -> DataFrame:
    """(query, features): a map of node to score for each query of (query, node, est)."""
    return scores.groupBy("query").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("node", "est")))).alias("features"))
