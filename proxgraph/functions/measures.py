"""Accuracy measures and structural checks, as one-row or per-node tables."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..params import PprParams
from ..storage import BROADCAST_ROWS


def _shuffled(graph, scores: DataFrame) -> DataFrame:
    """Scores of a kernel look like one row to the planner; those of many nodes are not to be broadcast."""
    return scores.hint("merge") if graph.n > BROADCAST_ROWS else scores


def differences(est: DataFrame, truth: DataFrame) -> DataFrame:
    """(node, est, truth, err) over the nodes of either; absent scores are zero."""
    both = est.select("node", F.col("est").alias("e")).join(truth.select("node", F.col("est").alias("t")), "node", "full")
    e, t = F.coalesce("e", F.lit(0.0)), F.coalesce("t", F.lit(0.0))
    return both.select("node", e.alias("est"), t.alias("truth"), F.abs(e - t).alias("err"))


def errors(graph, est: DataFrame, truth: DataFrame, floor: float = 0.01) -> DataFrame:
    """One row: max_abs, max_deg (error over out-degree), l1, max_rel over nodes with truth of ``floor`` and more."""
    d = differences(est, truth).join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node")
    return d.agg(F.max("err").alias("max_abs"), F.max(F.col("err") / F.col("deg")).alias("max_deg"), F.sum("err").alias("l1"), F.max(F.when(F.col("truth") >= floor, F.col("err") / F.col("truth"))).alias("max_rel"))


def mass(scores: DataFrame) -> DataFrame:
    return scores.agg(F.sum("est").alias("mass"))


def heavy_counts(graph, scores: DataFrame, tol: float, tol_deg: float) -> DataFrame:
    """One row: nodes over each tolerance, and the bounds 1/tol and S/tol_deg on them."""
    d = _shuffled(graph, scores).join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node")
    return d.agg(F.sum((F.col("est") > tol).cast("long")).alias("heavy"), F.lit(1 / tol).alias("heavy_bound"), F.sum((F.col("est") / F.col("deg") > tol_deg).cast("long")).alias("heavy_deg"), (F.sum(F.col("est") / F.col("deg")) / tol_deg).alias("heavy_deg_bound"))


def spread(graph, scores: DataFrame) -> DataFrame:
    """One row: S = sum est/degree, and sum est*degree."""
    d = _shuffled(graph, scores).join(graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg")), "node")
    return d.agg(F.sum(F.col("est") / F.col("deg")).alias("s_value"), F.sum(F.col("est") * F.col("deg")).alias("weighted_degree"))


def cost_value(graph, scores: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: A = sum over t of score(t) * sum over v of pairs(v, t) * in-degree(v); ``pairs`` is (query, node, est)."""
    into = pairs.join(graph.nodes.select(F.col("id").alias("query"), "in_deg"), "query").groupBy("node").agg(F.sum(F.col("est") * F.col("in_deg")).alias("est"))
    return pulled_value(scores, into)


def pulled_value(scores: DataFrame, into: DataFrame) -> DataFrame:
    """``cost_value`` from (node, est) that are already summed over all sources, each by its in-degree."""
    return scores.join(into.select("node", F.col("est").alias("pull")), "node").agg(F.sum(F.col("est") * F.col("pull")).alias("a_value"))


def symmetry_gap(graph, pairs: DataFrame) -> DataFrame:
    """One row: largest |score(u,v) d(u) - score(v,u) d(v)| (zero on undirected graphs)."""
    deg = graph.nodes.select("id", "out_deg")
    one = pairs.join(deg.withColumnRenamed("id", "query"), "query").select(F.col("query").alias("u"), F.col("node").alias("v"), (F.col("est") * F.col("out_deg")).alias("x"))
    other = one.select(F.col("u").alias("v"), F.col("v").alias("u"), F.col("x").alias("y"))
    return one.join(other, ["u", "v"], "full").agg(F.max(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))).alias("gap"))


def average_spread(graph, pairs: DataFrame) -> DataFrame:
    """One row: the mean of S with the source drawn by degree, and n / (2m), which it equals on undirected graphs."""
    from_all = pairs.join(graph.nodes.select(F.col("id").alias("query"), "out_deg"), "query").groupBy("node").agg(F.sum(F.col("est") * F.col("out_deg")).alias("est"))
    return mean_spread(graph, from_all)


def mean_spread(graph, from_all: DataFrame) -> DataFrame:
    """``average_spread`` from (node, est) that are already summed over all sources, each by its out-degree."""
    total = graph.stats["arcs"]
    d = from_all.join(graph.nodes.select(F.col("id").alias("node"), "out_deg"), "node")
    return d.agg(F.sum(F.col("est") / total / F.col("out_deg")).alias("mean_s"), F.lit(graph.n / total).alias("expected"))


def invariant_gap(graph, state: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: largest gap of score(v,t) = reserve(v,t) + sum over u of score(v,u) residue(u,t), for one target."""
    carried = pairs.join(state.select("node", "residue"), "node").groupBy("query").agg(F.sum(F.col("est") * F.col("residue")).alias("carried"))
    target = state.select("target").limit(1)
    true = pairs.join(target.withColumnRenamed("target", "node"), "node").select("query", F.col("est").alias("true"))
    d = carried.join(true, "query", "full").join(state.select(F.col("node").alias("query"), "reserve"), "query", "left")
    gap = F.abs(F.coalesce("true", F.lit(0.0)) - F.coalesce("reserve", F.lit(0.0)) - F.coalesce("carried", F.lit(0.0)))
    return d.agg(F.max(gap).alias("gap"))


def phase1_ok(rough: DataFrame, truth: DataFrame, tol: float) -> DataFrame:
    """One row: nodes that break the first phase's two-sided bounds (factor two from tol/4 up, additive below)."""
    both = rough.select("node", "rough").join(truth, "node", "full")
    r, t = F.coalesce("rough", F.lit(0.0)), F.coalesce("est", F.lit(0.0))
    bad = F.when(t >= tol / 4, (r < t / 2) | (r > 1.5 * t)).otherwise(r > t + tol / 4)
    return both.agg(F.sum(bad.cast("long")).alias("broken"))


def candidates_ok(cands: DataFrame, truth: DataFrame, tol: float) -> DataFrame:
    """One row: nodes over ``tol`` that are no candidates."""
    return truth.where(F.col("est") > tol).join(cands.select(F.col("target").alias("node")), "node", "left_anti").agg(F.count("*").alias("missed"))


def trial_moments(trials: DataFrame, truth: DataFrame) -> DataFrame:
    """(target, trials, mean, bias, variance) of the estimates of each trial."""
    t = truth.select(F.col("node").alias("target"), F.col("est").alias("true"))
    g = trials.groupBy("target").agg(F.count("*").alias("trials"), F.avg("est").alias("mean"), F.var_samp("est").alias("variance"))
    return g.join(t, "target", "left").select("target", "trials", "mean", (F.col("mean") - F.coalesce("true", F.lit(0.0))).alias("bias"), "variance")


def power_law_fit(scores: DataFrame) -> DataFrame:
    """One row: -slope of ln(score) over ln(rank), nodes, and the sum of squared scores."""
    ranked = scores.where("est > 0").select("node", F.round("est", 9).alias("est")).where("est > 0")
    ranked = ranked.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("est"), "node")))
    return ranked.agg((-F.regr_slope(F.log("est"), F.log("rank"))).alias("gamma"), F.count("*").alias("support"), F.sum(F.col("est") * F.col("est")).alias("sum_squares"))


def bounds(graph, scores: DataFrame, tol: float, tol_deg: float, gamma: float | None = None) -> DataFrame:
    """(name, value): the cost bounds without their logarithmic factors, for a source's scores."""
    s = graph.stats
    n, m, dmax = s["n"], s["m"], s["dmax"]
    r = spread(graph, scores).first()
    rows = {"lower": min(1 / tol, n), "monte_carlo": 1 / tol**2, "three_phase_directed": math.sqrt(m) / tol, "forward_directed": m / tol, "reverse_all": m / tol}
    if not graph.directed:
        rows |= {"three_phase_undirected": math.sqrt(dmax) / tol, "three_phase_source": math.sqrt(r["weighted_degree"]) / tol, "forward_undirected": dmax / tol, "degree_lower": r["s_value"] / tol_deg, "degree_three_phase": math.sqrt(r["s_value"]) / tol_deg, "degree_forward": 1 / tol_deg, "degree_average_lower": n / (m * tol_deg), "degree_average": math.sqrt(n / m) / tol_deg}
    if gamma is not None:
        rows["power_law"] = n ** (gamma - 0.5) / tol
    return graph.spark.createDataFrame([(k, float(v)) for k, v in sorted(rows.items())], "name string, value double")


def success_rate(worst: list[float], tol: float, n: int) -> dict:
    """Share of runs whose largest error is within ``tol``, and the guaranteed one."""
    return {"runs": len(worst), "rate": sum(e <= tol for e in worst) / max(1, len(worst)), "guaranteed": 1 - 1 / n}


def walk_moves_expected(p: PprParams) -> float:
    return (1 - p.alpha) / p.alpha
