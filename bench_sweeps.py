"""Experiment sweeps: how cost and error move with tolerance, size, alpha, walks and thresholds."""

from __future__ import annotations

import math
import os
import time

from proxgraph.functions import measures
from proxgraph.operators import power, push, solvers
from proxgraph.params import PprParams
from proxgraph.sources.fixtures import FIXTURES


def _row(g, source, tol, p, truth) -> dict:
    began = time.time()
    est, r = solvers.absolute(g, source, tol, p)
    e = measures.errors(g, est, truth).first()
    return {"tol": tol, "alpha": p.alpha, "max_abs": e["max_abs"], "candidates": r.candidates, "walks": r.walks, "trials": r.trials, "push_cost": r.push_cost, "tried_cost": r.tried_cost, "walk_cost": r.walk_cost, "total_cost": r.total_cost, "attempts": len(r.attempts), "touched": r.touched_nodes, "seconds": round(time.time() - began, 2)}


def tolerance_sweep(spark, sf_dir: str, name: str, tols=(0.04, 0.02, 0.01, 0.005)) -> dict:
    """Cost over 1/tol for the three-phase solver, plain walks, forward push and the power method; log-log slopes."""
    g, p = FIXTURES[name].graph(spark, sf_dir), PprParams()
    s = g.median_node()
    truth = power.single_source(g, s, p).cache()
    rows = [_row(g, s, t, p, truth) for t in tols]
    for r in rows:
        _, trace = push.forward_absolute(g, s, r["tol"], p)
        r |= {"monte_carlo": solvers.monte_carlo_count(g.n, r["tol"]) / p.alpha, "forward": trace.cost, "power": g.stats["arcs"] * p.rounds_for(r["tol"])}
    slope = lambda k: math.log(rows[-1][k] / rows[0][k]) / math.log(tols[0] / tols[-1])
    return {"rows": rows, "slopes": {k: round(slope(k), 3) for k in ("total_cost", "monte_carlo", "forward") if rows[0][k]}}


def size_sweep(spark, sf_dir: str, name: str, tol: float = 0.01) -> list[dict]:
    """The same query on the table sizes at hand."""
    root, out = os.path.dirname(sf_dir.rstrip("/")), []
    for sf in ("sf0.001", "sf0.01", "sf0.1"):
        if os.path.isdir(f"{root}/{sf}"):
            g, p = FIXTURES[name].graph(spark, f"{root}/{sf}"), PprParams()
            s = g.median_node()
            out.append({"sf": sf, **g.stats, **_row(g, s, tol, p, power.single_source(g, s, p).cache())})
    return out


def alpha_sweep(spark, sf_dir: str, name: str, tol: float = 0.01) -> list[dict]:
    g = FIXTURES[name].graph(spark, sf_dir)
    s = g.median_node()
    return [_row(g, s, tol, p, power.single_source(g, s, p).cache()) for p in (PprParams(alpha=a) for a in (0.1, 0.2, 0.4))]


def balance_ablation(spark, sf_dir: str, name: str, tol: float = 0.005) -> list[dict]:
    """The chosen number of walks against fixed ones."""
    g, p = FIXTURES[name].graph(spark, sf_dir), PprParams()
    s = g.median_node()
    truth = power.single_source(g, s, p).cache()
    chosen = _row(g, s, tol, p, truth) | {"chosen": True}
    return [chosen, *(_row(g, s, tol, p.with_(force_walks=max(1, int(chosen["walks"] * f))), truth) | {"factor": f} for f in (0.125, 0.5, 2, 8))]


def adaptive_ablation(spark, sf_dir: str, name: str, tol: float = 0.005) -> list[dict]:
    """Thresholds by rough score against one threshold for all, and halving anew against resuming."""
    g, p = FIXTURES[name].graph(spark, sf_dir), PprParams()
    s = g.median_node()
    truth = power.single_source(g, s, p).cache()
    return [_row(g, s, tol, q, truth) | {"adaptive": q.adaptive, "mode": q.mode} for q in (p, p.with_(adaptive=False), p.with_(mode="resume"))]


def degree_sweep(spark, sf_dir: str, name: str, tols=(0.002, 0.0005)) -> list[dict]:
    """Degree-normalised solver against forward push at the same tolerance."""
    g, p = FIXTURES[name].graph(spark, sf_dir), PprParams()
    s = g.median_node()
    truth, out = power.single_source(g, s, p).cache(), []
    for t in tols:
        est, r = solvers.degree_norm(g, s, t, p)
        fwd, trace = push.forward_degree_norm(g, s, t, p)
        out.append({"tol_deg": t, "max_deg": measures.errors(g, est, truth).first()["max_deg"], "total_cost": r.total_cost, "push_cost": r.push_cost, "forward_cost": trace.cost, "forward_max_deg": measures.errors(g, fwd, truth).first()["max_deg"]})
    return out


def sweeps(spark, sf_dir: str) -> dict:
    return {
        "tolerance": {f: tolerance_sweep(spark, sf_dir, f) for f in ("part_next", "page_link")},
        "size": {f: size_sweep(spark, sf_dir, f) for f in ("part_next", "part_supp")},
        "alpha": alpha_sweep(spark, sf_dir, "page_link"),
        "balance": balance_ablation(spark, sf_dir, "part_supp"),
        "adaptive": {f: adaptive_ablation(spark, sf_dir, f) for f in ("part_supp", "doc_word")},
        "degree": {f: degree_sweep(spark, sf_dir, f) for f in ("part_supp", "page_link")},
    }
