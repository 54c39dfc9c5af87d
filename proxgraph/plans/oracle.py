"""DuckDB SQL of graph queries, put together from named table expressions."""

from __future__ import annotations

from ..functions import prng
from ..params import PprParams
from ..sources.fixtures import FIXTURES

ALPHA = 0.2


class Sql:
    """A WITH list that grows by ``add`` and ends with ``select``."""

    def __init__(self) -> None:
        self.parts: list[str] = []

    def add(self, name: str, body: str, columns: str = "", recursive: bool = False) -> "Sql":
        self.parts.append(f"{name}{columns} AS {'' if recursive else 'MATERIALIZED '}({body})")
        return self

    def select(self, body: str) -> str:
        return "WITH RECURSIVE " + ",\n".join(self.parts) + "\n" + body


def graph(name: str) -> Sql:
    """``g`` (src, dst, od, idx), ``nd`` (id, out_deg, in_deg), ``st`` (n, m, arcs, dmax, dmin), ``s`` (id: the median-degree node)."""
    f = FIXTURES[name]
    q = Sql().add("e", f.sql)
    both = "SELECT src, dst FROM e" if f.directed else "SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e"
    q.add("u", f"SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM ({both})")
    if name in DANGLING:
        q.add("u2", "SELECT * FROM u UNION SELECT dst, dst FROM u WHERE dst NOT IN (SELECT src FROM u)")
    base = "u2" if name in DANGLING else "u"
    q.add("g", f"SELECT src, dst, count(*) OVER (PARTITION BY src) AS od, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS idx FROM {base}")
    q.add("nd", "SELECT a.id, a.out_deg, coalesce(b.in_deg, 0) AS in_deg FROM (SELECT src AS id, count(*) AS out_deg FROM g GROUP BY 1) a LEFT JOIN (SELECT dst AS id, count(*) AS in_deg FROM g GROUP BY 1) b USING (id)")
    q.add("st", f"SELECT count(*) AS n, sum(out_deg)::BIGINT AS arcs, sum(out_deg)::BIGINT // {1 if f.directed else 2} AS m, max(out_deg) AS dmax, min(out_deg) AS dmin FROM nd")
    q.add("s", "SELECT id FROM nd WHERE out_deg >= (SELECT quantile_cont(out_deg, 0.5) FROM nd) ORDER BY out_deg, id LIMIT 1")
    return q


#: The step number that start draws are made with.
START_STEP = 1_000_003

#: Fixtures that may have nodes without out-arcs at some size.
DANGLING: frozenset = frozenset()


def start(q: Sql, kind: str) -> Sql:
    """``w0`` (node, weight): the median-degree node, all nodes, or customers by balance."""
    if kind == "median":
        return q.add("w0", "SELECT id AS node, 1.0::DOUBLE AS weight FROM s")
    if kind == "uniform":
        return q.add("w0", "SELECT id AS node, 1.0 / (SELECT n FROM st) AS weight FROM nd")
    return q.add("w0", "SELECT 4 * c_custkey AS node, c_acctbal / (SELECT sum(c_acctbal) FROM customer WHERE c_acctbal > 0 AND 4 * c_custkey IN (SELECT id FROM nd)) AS weight FROM customer WHERE c_acctbal > 0 AND 4 * c_custkey IN (SELECT id FROM nd)")


def power(q: Sql, rounds: int, name: str = "pw") -> Sql:
    """``pw`` (node, est) from ``w0``."""
    q.add(f"{name}_r", f"SELECT 0 AS k, node, weight AS mass FROM w0 UNION ALL SELECT k + 1, g.dst, sum({1 - ALPHA} * mass / od) FROM {name}_r JOIN g ON g.src = node WHERE k < {rounds} GROUP BY k + 1, g.dst", "(k, node, mass)", True)
    return q.add(name, f"SELECT node, sum({ALPHA} * mass) AS est FROM {name}_r GROUP BY node")


def power_target(q: Sql, rounds: int) -> Sql:
    """``pt`` (node, est): all nodes toward the median-degree one."""
    q.add("pt_r", f"SELECT 0 AS k, id AS node, 1.0::DOUBLE AS mass FROM s UNION ALL SELECT k + 1, g.src, sum({1 - ALPHA} * mass / od) FROM pt_r JOIN g ON g.dst = node WHERE k < {rounds} GROUP BY k + 1, g.src", "(k, node, mass)", True)
    return q.add("pt", f"SELECT node, sum({ALPHA} * mass) AS est FROM pt_r GROUP BY node")


def pairs(q: Sql, rounds: int) -> Sql:
    """``pp`` (query, node, est) for all pairs."""
    q.add("pp_r", f"SELECT 0 AS k, id AS query, id AS node, 1.0::DOUBLE AS mass FROM nd UNION ALL SELECT k + 1, query, g.dst, sum({1 - ALPHA} * mass / od) FROM pp_r JOIN g ON g.src = node WHERE k < {rounds} GROUP BY k + 1, query, g.dst", "(k, query, node, mass)", True)
    return q.add("pp", f"SELECT query, node, sum({ALPHA} * mass) AS est FROM pp_r GROUP BY 1, 2")


def reverse_push(q: Sql, cands: str, name: str = "rp", held: str | None = None) -> Sql:
    """``rp`` (target, node, reserve, residue) of synchronous rounds; ``cands`` selects (target, theta).

    ``held`` names a state of the same columns that the push goes on from.
    """
    q.add(f"{name}_c", cands)
    hot = "residue > theta"
    first = f"SELECT 0 AS k, target, target AS node, theta, 0.0::DOUBLE AS reserve, 1.0::DOUBLE AS residue, 1.0::DOUBLE AS mx FROM {name}_c"
    if held:
        first = f"SELECT 0 AS k, target, node, theta, reserve, residue, max(residue) OVER (PARTITION BY target) AS mx FROM {held} JOIN {name}_c USING (target)"
    body = (
        f"{first} UNION ALL "
        f"SELECT k, target, node, theta, reserve, residue, max(residue) OVER (PARTITION BY target) AS mx FROM (SELECT k, target, node, theta, sum(reserve) AS reserve, sum(residue) AS residue FROM ("
        f"SELECT r.k + 1 AS k, r.target, CASE WHEN c.leg = 0 THEN r.node ELSE g.src END AS node, r.theta, "
        f"CASE WHEN c.leg = 0 THEN r.reserve + CASE WHEN r.{hot} THEN {ALPHA} * r.residue ELSE 0 END ELSE 0 END AS reserve, "
        f"CASE WHEN c.leg = 0 THEN CASE WHEN r.{hot} THEN 0 ELSE r.residue END ELSE {1 - ALPHA} * r.residue / g.od END AS residue "
        f"FROM {name}_r r JOIN (SELECT 0 AS leg UNION ALL SELECT 1) c ON c.leg = 0 OR r.{hot} LEFT JOIN g ON c.leg = 1 AND g.dst = r.node "
        f"WHERE r.mx > r.theta AND (c.leg = 0 OR g.src IS NOT NULL)) GROUP BY k, target, node, theta)"
    )
    q.add(f"{name}_r", body, "(k, target, node, theta, reserve, residue, mx)", True)
    return q.add(name, f"SELECT target, node, reserve, residue FROM (SELECT *, max(k) OVER (PARTITION BY target) AS last FROM {name}_r) WHERE k = last")


def forward_push(q: Sql, rmax: str, name: str = "fp") -> Sql:
    """``fp`` (node, reserve, residue) of synchronous rounds from ``w0``."""
    hot = "r.residue > r.lim"
    body = (
        f"SELECT 0 AS k, node, 0.0::DOUBLE AS reserve, weight AS residue, ({rmax}) * out_deg AS lim, out_deg AS deg, max(CASE WHEN weight > ({rmax}) * out_deg THEN 1 ELSE 0 END) OVER () AS any_hot FROM w0 JOIN nd ON nd.id = node UNION ALL "
        f"SELECT k, node, reserve, residue, ({rmax}) * out_deg, out_deg, max(CASE WHEN residue > ({rmax}) * out_deg THEN 1 ELSE 0 END) OVER () FROM (SELECT k, node, sum(reserve) AS reserve, sum(residue) AS residue FROM ("
        f"SELECT r.k + 1 AS k, CASE WHEN c.leg = 0 THEN r.node ELSE g.dst END AS node, CASE WHEN c.leg = 0 THEN r.reserve + CASE WHEN {hot} THEN {ALPHA} * r.residue ELSE 0 END ELSE 0 END AS reserve, "
        f"CASE WHEN c.leg = 0 THEN CASE WHEN {hot} THEN 0 ELSE r.residue END ELSE {1 - ALPHA} * r.residue / r.deg END AS residue "
        f"FROM {name}_r r JOIN (SELECT 0 AS leg UNION ALL SELECT 1) c ON c.leg = 0 OR {hot} LEFT JOIN g ON c.leg = 1 AND g.src = r.node WHERE r.any_hot = 1) GROUP BY k, node) JOIN nd ON nd.id = node"
    )
    q.add(f"{name}_r", body, "(k, node, reserve, residue, lim, deg, any_hot)", True)
    return q.add(name, f"SELECT node, reserve, residue FROM {name}_r WHERE k = (SELECT max(k) FROM {name}_r)")


def walks(q: Sql, seed: int, trials: int | str, count: int | str, name: str = "wk", uniform: bool = False) -> Sql:
    """``wk`` (trial, node, cnt) of stopping walks from ``s``, or from nodes drawn alike, with the portable draws.

    ``trials`` and ``count`` are numbers or scalar subqueries.
    """
    p, limit = prng.P, prng.stop_limit(ALPHA)
    key = prng.mix31_sql(f"({prng.mix31_sql(f'({seed * 7919}::BIGINT + trial * 104729) % {p}')} + walk) % {p}")
    draw = lambda lane, step="step": prng.mix31_sql(f"(wkey + (2 * {step} + {lane}) * {prng._LANE}::BIGINT) % {p}")
    begin = f"SELECT trial, wkey, (SELECT id FROM s) AS node, 0::BIGINT AS step, false AS ended FROM {name}_k"
    q.add(f"{name}_k", f"SELECT trial, {key} AS wkey FROM (SELECT unnest(range({trials})) AS trial), (SELECT unnest(range({count})) AS walk)")
    if uniform:
        q.add(f"{name}_s", "SELECT id, row_number() OVER (ORDER BY id) - 1 AS slot FROM nd")
        begin = f"SELECT trial, wkey, id AS node, 0::BIGINT AS step, false AS ended FROM {name}_k JOIN {name}_s ON slot = {draw(0, START_STEP)} % (SELECT n FROM st)"
    body = (
        f"{begin} UNION ALL "
        f"SELECT trial, wkey, CASE WHEN stops THEN node ELSE g.dst END, step + 1, stops FROM (SELECT r.*, {draw(0)} < {limit} AS stops, {draw(1)} % nd.out_deg AS pick FROM {name}_r r JOIN nd ON nd.id = r.node WHERE NOT ended) x "
        f"LEFT JOIN g ON g.src = node AND g.idx = pick AND NOT stops"
    )
    q.add(f"{name}_r", body, "(trial, wkey, node, step, ended)", True)
    return q.add(name, f"SELECT trial, node, count(*) AS cnt FROM {name}_r WHERE ended GROUP BY 1, 2")


def three_phase(q: Sql, tol: float, seed: int, phase1: int, trials: int, count: int, degree_norm: bool = False) -> Sql:
    """``cand`` (target, rough, own_tol), ``tr`` (trial, target, est) and ``ans`` (node, est) at forced counts."""
    start(q, "median")
    _candidates(q, tol, seed, phase1, degree_norm, False)
    reverse_push(q, f"SELECT target, own_tol * own_tol * {count} / (6.0 * rough) AS theta FROM cand")
    return _answer(q, seed, trials, count, False)


def solver(q: Sql, tol: str, seed: int, p: PprParams, degree_norm: bool = False, uniform: bool = False) -> Sql:
    """``ans`` (node, est) and ``chosen`` (j, walks, cost) of the whole solver: all counts by its own formulas, and the search.

    The numbers of walks that halving can reach are a finite list, ``halves``; all are pushed side by side, each
    until its cost is over its budget, and the last before the first that went over is taken.  ``tol`` is a number or an expression over ``st``.
    """
    start(q, "uniform" if uniform else "median")
    q.add("tl", f"SELECT ({tol})::DOUBLE AS tol, ceil({p.median_const} * (ln(2) + 2 * ln(n)))::BIGINT AS trials, ceil({p.phase1_const} * (ln(2) + 3 * ln(n)) / (({tol})::DOUBLE * {'dmin' if degree_norm else 1}))::BIGINT AS phase1 FROM st")
    trials = "(SELECT trials FROM tl)"
    _candidates(q, "(SELECT tol FROM tl)", seed, "(SELECT phase1 FROM tl)", degree_norm, uniform)
    q.add("halves_r", "SELECT 0 AS j, ceil(n / tol)::BIGINT AS walks FROM st, tl UNION ALL SELECT j + 1, walks // 2 FROM halves_r WHERE walks > 1", "(j, walks)", True)
    q.add("halves", f"SELECT j, walks, CASE WHEN j = 0 THEN 1e300 ELSE {trials} * walks / {p.alpha} END::DOUBLE AS budget FROM halves_r")
    pushed = "sum(CASE WHEN residue > theta THEN in_deg ELSE 0 END) OVER (PARTITION BY j)"
    spread = (
        f"SELECT r.k + 1 AS k, r.j, r.target, CASE WHEN c.leg = 0 THEN r.node ELSE g.src END AS node, r.theta, r.budget, r.spent, "
        f"CASE WHEN c.leg = 0 THEN r.reserve + CASE WHEN r.residue > r.theta THEN {p.alpha} * r.residue ELSE 0 END ELSE 0 END AS reserve, "
        f"CASE WHEN c.leg = 0 THEN CASE WHEN r.residue > r.theta THEN 0 ELSE r.residue END ELSE {1 - p.alpha} * r.residue / g.od END AS residue "
        f"FROM sr_r r JOIN (SELECT 0 AS leg UNION ALL SELECT 1) c ON c.leg = 0 OR r.residue > r.theta LEFT JOIN g ON c.leg = 1 AND g.dst = r.node "
        f"WHERE r.most > r.theta AND r.spent <= r.budget AND (c.leg = 0 OR g.src IS NOT NULL)"
    )
    q.add("tries", f"SELECT j, target, own_tol * own_tol * walks / ({p.theta_const} * rough) AS theta, budget, 1.0::DOUBLE AS residue FROM cand, halves")
    body = (
        f"SELECT 0 AS k, j, target, target AS node, theta, budget, 0.0::DOUBLE AS reserve, residue, residue AS most, ({pushed})::DOUBLE AS spent FROM tries JOIN nd ON nd.id = target UNION ALL "
        f"SELECT k, j, target, node, theta, budget, reserve, residue, max(residue) OVER (PARTITION BY j, target), spent + {pushed} FROM ("
        f"SELECT k, j, target, node, theta, budget, spent, sum(reserve) AS reserve, sum(residue) AS residue FROM ({spread}) GROUP BY k, j, target, node, theta, budget, spent) JOIN nd ON nd.id = node"
    )
    q.add("sr_r", body, "(k, j, target, node, theta, budget, reserve, residue, most, spent)", True)
    q.add("costs", "SELECT j, max(spent) AS cost, max(spent) > max(budget) AS over FROM sr_r GROUP BY j")
    q.add("chosen", "SELECT h.j, h.walks, cost::BIGINT AS cost FROM halves h JOIN costs USING (j) WHERE h.j < coalesce((SELECT min(j) FROM costs WHERE over), 1000) ORDER BY h.j DESC LIMIT 1")
    q.add("rp", "SELECT target, node, reserve, residue FROM (SELECT *, max(k) OVER (PARTITION BY target) AS last FROM sr_r WHERE j = (SELECT j FROM chosen)) WHERE k = last")
    return _answer(q, seed, trials, "(SELECT coalesce(max(walks), 0) FROM chosen)", uniform)


def _candidates(q: Sql, tol: float | str, seed: int, count: int | str, degree_norm: bool, uniform: bool) -> None:
    walks(q, seed, 1, count, "w1", uniform)
    own = f"{tol}::DOUBLE * out_deg" if degree_norm else f"{tol}::DOUBLE"
    q.add("rough", f"SELECT node, cnt, cnt / {count}::DOUBLE AS rough, {own} AS own_tol FROM w1 JOIN nd ON nd.id = node")
    q.add("cand", "SELECT node AS target, rough, own_tol FROM rough WHERE rough > own_tol / 2")


def _answer(q: Sql, seed: int, trials: int | str, count: int | str, uniform: bool) -> Sql:
    """``tr`` and ``ans`` of the state ``rp``."""
    walks(q, seed + 1_000_003, trials, count, "w3", uniform)
    q.add("gain", f"SELECT trial, target, sum(cnt / {count}::DOUBLE * residue) AS gain FROM w3 JOIN rp USING (node) WHERE residue > 0 GROUP BY 1, 2")
    q.add("settled", "SELECT target, sum(reserve * weight) AS settled FROM rp JOIN w0 USING (node) GROUP BY 1")
    q.add("tr", f"SELECT t.trial, c.target, coalesce(settled, 0) + coalesce(gain, 0) AS est FROM cand c JOIN (SELECT unnest(range({trials})) AS trial) t ON true LEFT JOIN settled r ON r.target = c.target LEFT JOIN gain g2 ON g2.target = c.target AND g2.trial = t.trial")
    return q.add("ans", "SELECT target AS node, median(est) AS est FROM tr GROUP BY target")


def sweep(q: Sql, scores: str) -> Sql:
    """``sw`` (rank, node, vol, cut, conductance) of the prefixes of ``scores`` (node, est)."""
    q.add("rk", f"SELECT node, out_deg AS deg, row_number() OVER (ORDER BY round(est / out_deg, 9) DESC, node) AS rank FROM ({scores}) x JOIN nd ON nd.id = node WHERE est > 0")
    q.add("arc_ranks", "SELECT a.rank AS a, b.rank AS b FROM g JOIN rk a ON a.node = g.src LEFT JOIN rk b ON b.node = g.dst")
    q.add("chg", "SELECT rank, sum(d) AS d FROM (SELECT a AS rank, 1 AS d FROM arc_ranks WHERE b IS NULL OR a < b UNION ALL SELECT b, -1 FROM arc_ranks WHERE a < b) GROUP BY rank")
    return q.add("sw", "SELECT *, CASE WHEN least(vol, (SELECT arcs FROM st) - vol) > 0 THEN cut / least(vol, (SELECT arcs FROM st) - vol) END AS conductance FROM (SELECT rk.rank, node, sum(deg) OVER o AS vol, sum(coalesce(d, 0)) OVER o AS cut FROM rk LEFT JOIN chg USING (rank) WINDOW o AS (ORDER BY rk.rank ROWS UNBOUNDED PRECEDING))")
