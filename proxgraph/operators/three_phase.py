"""The three-phase solver: rough walks, adaptive reverse pushes, combined trials.

Phase I finds candidate targets and rough scores.  Phase II pushes backwards from each candidate,
deeper for larger rough scores, at ever smaller numbers of walks until the push would cost more than
the walks it saves.  Phase III walks again, completes every candidate's reserve at the source with the
residues at the walks' ends, and takes the median over independent trials.

One code path serves both error kinds: a node's own tolerance is ``tol`` (absolute) or ``tol * degree``
(degree-normalised, undirected).  For the second kind the published text of the algorithm is not at hand;
this is our own construction from the same variance bound.  Its first phase needs walks in proportion to
1 / (tol * smallest degree), so on graphs with leaves it does not reach the cost bound claimed for it.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..params import PprParams, check_tol
from ..storage import join_bounded, saved
from . import power, push, walks
from .graph import Graph


@dataclass
class Attempt:
    walks: int
    cost: int
    rounds: int
    accepted: bool


@dataclass
class SolveReport:
    """Counters of a solve.  Push cost: arcs touched.  Walk cost: node visits, 1 / alpha a walk by expectation."""

    n: int = 0
    m: int = 0
    phase1_walks: int = 0
    trials: int = 0
    walks: int = 0
    candidates: int = 0
    attempts: list[Attempt] = field(default_factory=list)
    alpha: float = 0.2
    fallback: bool = False
    resumed: bool = False
    touched_nodes: int = 0

    @property
    def push_cost(self) -> int:
        """Of the accepted push; in parts if it was resumed."""
        accepted = [a.cost for a in self.attempts if a.accepted]
        return sum(accepted) if self.resumed else (accepted or [0])[-1]

    @property
    def tried_cost(self) -> int:
        return sum(a.cost for a in self.attempts)

    @property
    def walk_cost(self) -> float:
        return (self.phase1_walks + self.trials * self.walks) / self.alpha

    @property
    def total_cost(self) -> float:
        return self.walk_cost + self.tried_cost


def rough_scores(graph: Graph, source, count: int, p: PprParams) -> DataFrame:
    """(node, cnt, rough) by ``count`` walks, numbered as trial 0."""
    got = walks.simulate(graph, source, 1, count, p)
    return got.select("node", "cnt", (F.col("cnt") / count).alias("rough"))


def candidates(rough: DataFrame, own_tol: Column) -> DataFrame:
    """(target, rough, own_tol) of the nodes whose rough score is over half their tolerance."""
    return rough.withColumn("own_tol", own_tol).where(F.col("rough") > F.col("own_tol") / 2).select(F.col("node").alias("target"), "rough", "own_tol")


def thresholds(cands: DataFrame, count: int, p: PprParams) -> DataFrame:
    """(target, theta) for ``count`` walks a trial; without ``adaptive`` one threshold for all, that of the largest rough score."""
    rough = F.col("rough")
    return _levelled(cands, p).select("target", (F.col("own_tol") * F.col("own_tol") * count / (p.theta_const * rough)).alias("theta"))


def _levelled(cands: DataFrame, p: PprParams) -> DataFrame:
    if p.adaptive:
        return cands
    return cands.withColumn("rough", F.lit(cands.agg(F.max("rough")).first()[0]))


def search(graph: Graph, cands: DataFrame, first: int, trials: int, p: PprParams, report: SolveReport) -> tuple[DataFrame, int]:
    """Halve the walks while the push at the halved thresholds costs no more than the walks; (state, walks).

    Budgets only fall, so with the kernel all attempts from the first small one on are one job.
    """
    top = cands.agg(F.max(F.col("rough") / (F.col("own_tol") * F.col("own_tol")))).first()[0]
    count, state = first, None
    if p.skip_noop:
        # thresholds of one or more push nothing: accepted at no cost
        while count > 1 and (count // 2) >= p.theta_const * top:
            count //= 2
            report.attempts.append(Attempt(count, 0, 0, True))
    spent = 0
    while count > 1:
        half = count // 2
        budget = trials * half / p.alpha
        if budget < push.SMALL_BUDGET and report.candidates <= push.LADDER_TARGETS and graph.use_kernel(p.engine) and (state is None or p.mode == "restart"):
            rungs = [(half >> k, trials * (half >> k) / p.alpha) for k in range(half.bit_length())]
            got, tried = push.ladder(graph, _levelled(cands, p), rungs, p)
            report.attempts.extend(Attempt(*t) for t in tried)
            accepted = [t[0] for t in tried if t[3]]
            if accepted:
                count, state = accepted[-1], got
            break
        resume = state if p.mode == "resume" else None
        base = spent if resume is not None else 0
        got, trace = push.reverse(graph, thresholds(cands, half, p), p, budget - base, resume)
        report.attempts.append(Attempt(half, trace.cost, trace.rounds, trace.within))
        if not trace.within:
            break
        count, state, spent = half, got, base + trace.cost
    if state is None:
        state, trace = push.reverse(graph, thresholds(cands, count, p), p)
        report.attempts.append(Attempt(count, trace.cost, trace.rounds, True))
    return state, count


def combine(graph: Graph, ends: DataFrame, state: DataFrame, cands: DataFrame, source, trials: int, count: int) -> DataFrame:
    """(trial, target, est): reserve at the source plus residues at the walks' ends; a row for every trial and candidate."""
    starts = push.start_table(graph, source)
    many = 1
    if isinstance(source, DataFrame):
        starts = saved(starts)
        many = starts.count()
    at_source = join_bounded(state, starts, "node", "inner", many).groupBy("target").agg(F.sum(F.col("reserve") * F.col("weight")).alias("settled"))
    gain = ends.join(state.where("residue > 0"), "node").groupBy("trial", "target").agg(F.sum(F.col("cnt") / count * F.col("residue")).alias("gain"))
    grid = cands.select("target").withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    out = grid.join(gain, ["trial", "target"], "left").join(at_source, "target", "left")
    return out.select("trial", "target", (F.coalesce("settled", F.lit(0.0)) + F.coalesce("gain", F.lit(0.0))).alias("est"))


def run(graph: Graph, source, tol: float, p: PprParams, degree_norm: bool = False, given: DataFrame | None = None) -> tuple[DataFrame, SolveReport]:
    """((node, est), report).  ``given`` (target, rough) replaces the first phase."""
    check_tol(tol)
    if degree_norm and graph.directed:
        raise ValueError("degree-normalised errors are defined on undirected graphs only")
    s = graph.stats
    report = SolveReport(n=s["n"], m=s["m"], alpha=p.alpha, trials=p.trials(s["n"]), resumed=p.mode == "resume")
    deg = graph.nodes.select(F.col("id").alias("node"), F.col("out_deg").alias("deg"))
    if given is None:
        report.phase1_walks = p.phase1_walks(s["n"], tol * s["dmin"] if degree_norm else tol)
        rough = rough_scores(graph, source, report.phase1_walks, p)
    else:
        rough = given.select(F.col("target").alias("node"), "rough")
    own = tol * F.col("deg") if degree_norm else F.lit(tol)
    cands = saved(candidates(rough.join(deg, "node") if degree_norm else rough, own))
    report.candidates = cands.count()
    empty = cands.select(F.col("target").alias("node"), F.lit(0.0).alias("est")).limit(0)
    if not report.candidates:
        return empty, report
    if p.force_walks:
        report.walks = p.force_walks
        state, trace = push.reverse(graph, thresholds(cands, report.walks, p), p)
        report.attempts.append(Attempt(report.walks, trace.cost, trace.rounds, True))
    else:
        state, report.walks = search(graph, cands, math.ceil(s["n"] / tol), report.trials, p, report)
    cap = s["n"] ** 2 if p.cost_cap == "n2" else p.cost_cap
    if cap is not None and report.total_cost > cap:
        report.fallback = True
        return power.single_source(graph, source, p).where(F.col("est") > tol / 4), report
    report.touched_nodes = state.select("node").distinct().count()
    # the third phase is independent of the first: another seed
    ends = walks.simulate(graph, source, report.trials, report.walks, p.with_(seed=p.seed + 1_000_003))
    trials = combine(graph, ends, state, cands, source, report.trials, report.walks)
    return trials.groupBy(F.col("target").alias("node")).agg(F.median("est").alias("est")), report


def trial_estimates(graph: Graph, source, tol: float, p: PprParams) -> DataFrame:
    """(trial, target, est) at a forced number of walks, for the estimator's measures."""
    count, s = p.force_walks, graph.stats
    cands = saved(candidates(rough_scores(graph, source, p.phase1_walks(s["n"], tol), p), F.lit(tol)))
    state, _ = push.reverse(graph, thresholds(cands, count, p), p)
    ends = walks.simulate(graph, source, p.trials(s["n"]), count, p.with_(seed=p.seed + 1_000_003))
    return combine(graph, ends, state, cands, source, p.trials(s["n"]), count)
