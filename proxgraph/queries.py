"""Driver queries of the proximity engine and their DuckDB SQL.

Names are ``<method>_<fixture>``.  Floats are rounded to six digits; sources are the fixture's node of
median degree.  Queries that follow random draws use the portable generator, which the SQL replays.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import relational_queries
from .functions import measures
from .operators import apps, power, push, solvers, three_phase, walks
from .operators.graph import Graph
from .params import PprParams
from .plans import oracle
from .sources.fixtures import FIXTURES

P = PprParams()
DIRECTED = ("part_next", "user_next", "nation_trade", "role_turn", "knn10")
UNDIRECTED = ("cust_part", "part_supp", "page_link", "geo_tree", "doc_word")
EVERY = (*DIRECTED, *UNDIRECTED)
SMALL = ("nation_trade", "page_link")
TAIL, ROUNDS = 1e-4, P.rounds_for(1e-4)
#: Thresholds off round values, so that no tie decides a push.
THETA, RMAX, TOL, TOL_DEG = 0.00137, 0.000213, 0.02, 0.002
SEED, PHASE1, TRIALS, WALKS = 7, 4000, 21, 300

_GRAPHS: dict[tuple, Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The fixture's graph, built once for a session and a folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _GRAPHS:
        _GRAPHS[key] = FIXTURES[name].graph(spark, sf_dir)
    return _GRAPHS[key]


def _r(df: DataFrame, *columns: str) -> DataFrame:
    return df.select(*(F.round(c, 6).alias(c) if c in columns else F.col(c) for c in df.columns))


def _scores(df: DataFrame) -> DataFrame:
    return df.select("node", F.round("est", 6).alias("est"))


QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}


def _register(name: str, run: Callable, sql: Callable[[], str] | None = None) -> None:
    """``run`` takes (spark, sf_dir); ``sql`` gives the text."""
    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql()


def _each(method: str, names, run: Callable[[Graph], DataFrame], sql: Callable[[str], str] | None = None) -> None:
    for f in names:
        _register(f"{method}_{f}", lambda spark, sf_dir, f=f: run(graph(spark, sf_dir, f)), None if sql is None else partial(sql, f))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The absolute-tolerance solver on the page-link graph."""
    g = graph(spark, sf_dir, "page_link")
    return _scores(solvers.absolute(g, g.median_node(), TOL, P)[0])


# graphs

_each("graph_arcs", EVERY, lambda g: g.pairs.select("src", "dst"), lambda f: oracle.graph(f).select("SELECT src, dst FROM g"))
_each("graph_degrees", EVERY, lambda g: g.nodes, lambda f: oracle.graph(f).select("SELECT id, out_deg, in_deg FROM nd"))
_each(
    "graph_stats",
    EVERY,
    lambda g: g.nodes.agg(F.count("*").alias("n"), F.sum("out_deg").alias("arcs"), F.max("out_deg").alias("dmax"), F.min("out_deg").alias("dmin"), F.sum((F.col("in_deg") == 0).cast("long")).alias("no_in")).withColumn("m", F.lit(g.m).cast("long")),
    lambda f: oracle.graph(f).select("SELECT n, arcs, dmax, dmin, m, (SELECT count(*) FROM nd WHERE in_deg = 0) AS no_in FROM st"),
)
_each("degree_hist", EVERY, lambda g: g.nodes.groupBy(F.floor(F.log2("out_deg")).cast("long").alias("bin")).agg(F.count("*").alias("nodes")), lambda f: oracle.graph(f).select("SELECT floor(log2(out_deg))::BIGINT AS bin, count(*) AS nodes FROM nd GROUP BY 1"))
_each(
    "symmetric_check",
    UNDIRECTED,
    lambda g: g.pairs.select("src", "dst").join(g.pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_anti").agg(F.count("*").alias("one_way")),
    lambda f: oracle.graph(f).select("SELECT count(*) AS one_way FROM g a WHERE NOT EXISTS (SELECT 1 FROM g b WHERE b.src = a.dst AND b.dst = a.src)"),
)

# exact scores


def _power_sql(f: str, kind: str = "median") -> str:
    return oracle.power(oracle.start(oracle.graph(f), kind), ROUNDS).select("SELECT node, round(est, 6) AS est FROM pw")


_each("power", EVERY, lambda g: _scores(power.single_source(g, g.median_node(), P, TAIL)), _power_sql)
_each("power_frame", ("role_turn", "nation_trade", "page_link"), lambda g: _scores(power.single_source(g, g.median_node(), P.with_(engine="frame"), TAIL)), _power_sql)
_each("power_target", EVERY, lambda g: _scores(power.single_target(g, g.median_node(), P, TAIL)), lambda f: oracle.power_target(oracle.graph(f), ROUNDS).select("SELECT node, round(est, 6) AS est FROM pt"))
_each("power_all_pairs", SMALL, lambda g: _r(power.all_pairs(g, P, TAIL), "est"), lambda f: oracle.pairs(oracle.graph(f), ROUNDS).select("SELECT query, node, round(est, 6) AS est FROM pp"))
_each("pagerank_exact", EVERY, lambda g: _scores(solvers.pagerank_exact(g, P, TAIL)), partial(_power_sql, kind="uniform"))


def balance_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers by account balance, as nodes of the customer-part graph; negative balances have no weight."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select((4 * F.col("c_custkey")).alias("node"), F.col("c_acctbal").alias("weight"))
    return c.join(graph(spark, sf_dir, "cust_part").nodes.select(F.col("id").alias("node")), "node", "left_semi")


_register("ppr_dist_exact_cust_part", lambda spark, d: _scores(power.single_source(graph(spark, d, "cust_part"), balance_sources(spark, d), P, TAIL)), lambda: _power_sql("cust_part", "balance"))

# pushes

_PUSH = "SELECT node, round(reserve, 6) AS reserve, round(residue, 6) AS residue FROM "


def _state(df: DataFrame) -> DataFrame:
    return _r(df.select("node", "reserve", "residue"), "reserve", "residue")


def _rp_sql(f: str) -> str:
    return oracle.reverse_push(oracle.graph(f), f"SELECT id AS target, {THETA}::DOUBLE AS theta FROM s").select(_PUSH + "rp")


_each("reverse_push", EVERY, lambda g: _state(push.reverse_single(g, g.median_node(), THETA, P)[0]), _rp_sql)
_each("reverse_push_frame", ("role_turn", "nation_trade", "page_link"), lambda g: _state(push.reverse_single(g, g.median_node(), THETA, P.with_(engine="frame"))[0]), _rp_sql)


def _resumed(g: Graph) -> DataFrame:
    """A push to 4 theta that is then continued to theta."""
    target = g.median_node()
    cands = g.spark.createDataFrame([(target, 4 * THETA)], "target long, theta double")
    half, _ = push.reverse(g, cands, P)
    return _state(push.reverse(g, cands.withColumn("theta", F.lit(THETA)), P, resume=half)[0])


def _resumed_sql(f: str) -> str:
    half = oracle.reverse_push(oracle.graph(f), f"SELECT id AS target, {4 * THETA}::DOUBLE AS theta FROM s", "half")
    return oracle.reverse_push(half, f"SELECT id AS target, {THETA}::DOUBLE AS theta FROM s", "rp", "half").select(_PUSH + "rp")


_each("reverse_push_resumed", ("part_next", "page_link"), _resumed, _resumed_sql)
_each(
    "reverse_push_multi",
    ("part_supp", "page_link", "user_next"),
    lambda g: _r(push.reverse(g, g.nodes.orderBy(F.desc("out_deg"), "id").limit(8).select(F.col("id").alias("target"), (F.lit(0.01137) / F.sqrt("out_deg")).alias("theta")), P)[0], "reserve", "residue"),
    lambda f: oracle.reverse_push(oracle.graph(f), "SELECT id AS target, 0.01137 / sqrt(out_deg) AS theta FROM nd ORDER BY out_deg DESC, id LIMIT 8").select("SELECT target, node, round(reserve, 6) AS reserve, round(residue, 6) AS residue FROM rp"),
)
_each(
    "reverse_all_targets",
    ("nation_trade", "role_turn", "user_next", "page_link"),
    lambda g: _scores(push.reverse_all_targets(g, g.median_node(), 0.0213, P)[0]),
    lambda f: oracle.reverse_push(oracle.graph(f), "SELECT id AS target, 0.0213::DOUBLE AS theta FROM nd").select("SELECT target AS node, round(reserve, 6) AS est FROM rp WHERE node = (SELECT id FROM s) AND reserve > 0"),
)


def _fp(f: str) -> oracle.Sql:
    return oracle.forward_push(oracle.start(oracle.graph(f), "median"), f"{RMAX}")


_each("forward_push", EVERY, lambda g: _state(push.forward(g, g.median_node(), RMAX, P)[0]), lambda f: _fp(f).select(_PUSH + "fp"))
_each("forward_push_frame", ("role_turn", "nation_trade", "page_link"), lambda g: _state(push.forward(g, g.median_node(), RMAX, P.with_(engine="frame"))[0]), lambda f: _fp(f).select(_PUSH + "fp"))
_each(
    "forward_absolute",
    EVERY,
    lambda g: _scores(push.forward_absolute(g, g.median_node(), 0.0213, P)[0]),
    lambda f: oracle.forward_push(oracle.start(oracle.graph(f), "median"), f"0.0213 / (SELECT {'m' if FIXTURES[f].directed else 'dmax'} FROM st)").select("SELECT node, round(reserve, 6) AS est FROM fp WHERE reserve > 0"),
)
_each("forward_degree", UNDIRECTED, lambda g: _scores(push.forward_degree_norm(g, g.median_node(), RMAX, P)[0]), lambda f: _fp(f).select("SELECT node, round(reserve, 6) AS est FROM fp WHERE reserve > 0"))

# measures over exact scores and pushes

_ERR = "SELECT round(max(abs(coalesce(a.est, 0) - coalesce(b.est, 0))), 6) AS max_abs, round(max(abs(coalesce(a.est, 0) - coalesce(b.est, 0)) / out_deg), 6) AS max_deg, round(sum(abs(coalesce(a.est, 0) - coalesce(b.est, 0))), 6) AS l1, round(max(CASE WHEN b.est >= 0.01 THEN abs(coalesce(a.est, 0) - b.est) / b.est END), 6) AS max_rel FROM a FULL JOIN b USING (node) JOIN nd ON nd.id = node"


def _error_sql(f: str) -> str:
    return oracle.power(_fp(f), ROUNDS).add("a", "SELECT node, reserve AS est FROM fp WHERE reserve > 0").add("b", "SELECT * FROM pw").select(_ERR)


def _errors(g: Graph, est: DataFrame) -> DataFrame:
    return _r(measures.errors(g, est, power.single_source(g, g.median_node(), P, TAIL)), "max_abs", "max_deg", "l1", "max_rel")


_each("forward_error", EVERY, lambda g: _errors(g, push.forward(g, g.median_node(), RMAX, P)[0].select("node", F.col("reserve").alias("est"))), _error_sql)
_each(
    "reverse_error",
    EVERY,
    lambda g: measures.differences(solvers.single_target(g, g.median_node(), THETA, P), power.single_target(g, g.median_node(), P, TAIL)).agg(F.round(F.max("err"), 6).alias("max_abs")),
    lambda f: oracle.power_target(oracle.reverse_push(oracle.graph(f), f"SELECT id AS target, {THETA}::DOUBLE AS theta FROM s"), ROUNDS).select("SELECT round(max(abs(coalesce(reserve, 0) - coalesce(est, 0))), 6) AS max_abs FROM rp FULL JOIN pt USING (node)"),
)


def _pw(f: str) -> oracle.Sql:
    return oracle.power(oracle.start(oracle.graph(f), "median"), ROUNDS)


def _exact(g: Graph) -> DataFrame:
    return power.single_source(g, g.median_node(), P, TAIL)


def _from_all(g: Graph, weight: str) -> DataFrame:
    """Scores summed over every node as the source, times its degree."""
    return power.summed(g, g.nodes.select(F.col("id").alias("node"), F.col(weight).alias("weight")), P, TAIL)


_each("mass", EVERY, lambda g: _r(measures.mass(_exact(g)), "mass"), lambda f: _pw(f).select("SELECT round(sum(est), 6) AS mass FROM pw"))
_each(
    "heavy_counts",
    EVERY,
    lambda g: _r(measures.heavy_counts(g, _exact(g), 0.0071, 0.00073), "heavy_bound", "heavy_deg_bound"),
    lambda f: _pw(f).select("SELECT count(*) FILTER (est > 0.0071) AS heavy, round(1 / 0.0071, 6) AS heavy_bound, count(*) FILTER (est / out_deg > 0.00073) AS heavy_deg, round(sum(est / out_deg) / 0.00073, 6) AS heavy_deg_bound FROM pw JOIN nd ON nd.id = node"),
)
_each("spread", EVERY, lambda g: _r(measures.spread(g, _exact(g)), "s_value", "weighted_degree"), lambda f: _pw(f).select("SELECT round(sum(est / out_deg), 6) AS s_value, round(sum(est * out_deg), 6) AS weighted_degree FROM pw JOIN nd ON nd.id = node"))
_each(
    "power_law_fit",
    EVERY,
    lambda g: _r(measures.power_law_fit(_exact(g)), "gamma", "sum_squares"),
    lambda f: _pw(f).select("SELECT round(-regr_slope(ln(est), ln(k)), 6) AS gamma, count(*) AS support, round(sum(est * est), 6) AS sum_squares FROM (SELECT est, row_number() OVER (ORDER BY est DESC, node) AS k FROM (SELECT node, round(est, 9) AS est FROM pw) WHERE est > 0)"),
)
_each(
    "bounds",
    ("part_next", "part_supp", "page_link", "doc_word"),
    lambda g: _r(measures.bounds(g, _exact(g), TOL, TOL_DEG), "value"),
    lambda f: _pw(f).select(
        f"SELECT name, round(value, 6) AS value FROM (SELECT unnest(['lower', 'monte_carlo', 'three_phase_directed', 'forward_directed', 'reverse_all'{'' if FIXTURES[f].directed else ''', 'three_phase_undirected', 'three_phase_source', 'forward_undirected', 'degree_lower', 'degree_three_phase', 'degree_forward', 'degree_average_lower', 'degree_average' '''}]) AS name, "
        f"unnest([least(1 / {TOL}, n), 1 / ({TOL} * {TOL}), sqrt(m) / {TOL}, m / {TOL}, m / {TOL}{'' if FIXTURES[f].directed else f', sqrt(dmax) / {TOL}, sqrt(wd) / {TOL}, dmax / {TOL}, sv / {TOL_DEG}, sqrt(sv) / {TOL_DEG}, 1 / {TOL_DEG}, n / (m * {TOL_DEG}), sqrt(n::DOUBLE / m) / {TOL_DEG}'}]::DOUBLE[]) AS value FROM st, (SELECT sum(est / out_deg) AS sv, sum(est * out_deg) AS wd FROM pw JOIN nd ON nd.id = node))"
    ),
)
_each("symmetry_gap", ("page_link",), lambda g: _r(measures.symmetry_gap(g, power.all_pairs(g, P, TAIL)), "gap"), lambda f: oracle.pairs(oracle.graph(f), ROUNDS).select("SELECT round(max(abs(a.est * x.out_deg - coalesce(b.est, 0) * y.out_deg)), 6) AS gap FROM pp a JOIN nd x ON x.id = a.query JOIN nd y ON y.id = a.node LEFT JOIN pp b ON b.query = a.node AND b.node = a.query"))
_each("average_spread", ("page_link",), lambda g: _r(measures.mean_spread(g, _from_all(g, "out_deg")), "mean_s", "expected"), lambda f: oracle.pairs(oracle.graph(f), ROUNDS).select("SELECT round(sum(x.out_deg * est / y.out_deg) / max(arcs), 6) AS mean_s, round(max(n) / max(arcs), 6) AS expected FROM pp JOIN nd x ON x.id = query JOIN nd y ON y.id = node, st"))
_each("cost_value", SMALL, lambda g: _r(measures.pulled_value(_exact(g), _from_all(g, "in_deg")), "a_value"), lambda f: oracle.pairs(_pw(f), ROUNDS).select("SELECT round(sum(pw.est * pp.est * in_deg), 6) AS a_value FROM pw JOIN pp ON pp.node = pw.node JOIN nd ON nd.id = pp.query"))
_each(
    "invariant_gap",
    SMALL,
    lambda g: measures.invariant_gap(g, push.reverse_single(g, g.median_node(), THETA, P)[0], power.all_pairs(g, P, 1e-12)).select((F.col("gap") < 1e-9).alias("holds")),
    lambda f: oracle.pairs(oracle.reverse_push(oracle.graph(f), f"SELECT id AS target, {THETA}::DOUBLE AS theta FROM s"), P.rounds_for(1e-12)).select("SELECT max(abs(coalesce(t.est, 0) - coalesce(rp.reserve, 0) - c.x)) < 1e-9 AS holds FROM (SELECT query, sum(pp.est * residue) AS x FROM pp JOIN rp ON rp.node = pp.node GROUP BY 1) c LEFT JOIN pp t ON t.query = c.query AND t.node = (SELECT id FROM s) LEFT JOIN rp ON rp.node = c.query"),
)

# walks and solvers at fixed counts, replayed draw by draw

_WALK_ON = ("part_next", "nation_trade", "role_turn", "part_supp", "page_link", "doc_word")
_FIXED = P.with_(seed=SEED, force_phase1=PHASE1, force_trials=TRIALS, force_walks=WALKS)

_each("monte_carlo", _WALK_ON, lambda g: _scores(solvers.monte_carlo_walks(g, g.median_node(), PHASE1, P.with_(seed=SEED))), lambda f: oracle.walks(oracle.graph(f), SEED, 1, PHASE1).select(f"SELECT node, round(cnt / {PHASE1}.0, 6) AS est FROM wk"))
_each("monte_carlo_frame", ("role_turn", "page_link"), lambda g: _scores(solvers.monte_carlo_walks(g, g.median_node(), PHASE1, P.with_(seed=SEED, engine="frame"))), lambda f: oracle.walks(oracle.graph(f), SEED, 1, PHASE1).select(f"SELECT node, round(cnt / {PHASE1}.0, 6) AS est FROM wk"))


def _tp(f: str, tol: float, deg: bool = False) -> oracle.Sql:
    return oracle.three_phase(oracle.graph(f), tol, SEED, PHASE1, TRIALS, WALKS, deg)


_each("phase1_candidates", _WALK_ON, lambda g: _r(three_phase.candidates(three_phase.rough_scores(g, g.median_node(), PHASE1, _FIXED), F.lit(TOL)).select("target", "rough"), "rough"), lambda f: _tp(f, TOL).select("SELECT target, round(rough, 6) AS rough FROM cand"))
_each("phase3_trials", ("part_next", "part_supp", "page_link"), lambda g: _r(three_phase.trial_estimates(g, g.median_node(), TOL, _FIXED), "est"), lambda f: _tp(f, TOL).select("SELECT trial::INT AS trial, target, round(est, 6) AS est FROM tr"))
_each("absolute_fixed", _WALK_ON, lambda g: _scores(solvers.absolute(g, g.median_node(), TOL, _FIXED)[0]), lambda f: _tp(f, TOL).select("SELECT node, round(est, 6) AS est FROM ans"))
_each("degree_norm_fixed", ("part_supp", "page_link"), lambda g: _scores(solvers.degree_norm(g, g.median_node(), TOL_DEG, _FIXED)[0]), lambda f: _tp(f, TOL_DEG, True).select("SELECT node, round(est, 6) AS est FROM ans"))

# whole solvers at their own counts: scores, the walks a trial that the search ends with, and what its push cost.
# The portable generator is asked for by name, so that the SQL replays the draws at every size.

_OWN = P.with_(seed=SEED, rng="portable")


def _solved(got: tuple[DataFrame, three_phase.SolveReport]) -> DataFrame:
    est, report = got
    return _scores(est).withColumn("walks", F.lit(report.walks).cast("long")).withColumn("push_cost", F.lit(report.push_cost).cast("long"))


_ANSWER = "SELECT node, round(est, 6) AS est, walks, cost AS push_cost FROM ans, chosen"


def _own(f: str, tol: float | str, **kind) -> oracle.Sql:
    return oracle.solver(oracle.graph(f), str(tol), SEED, _OWN, **kind)


def _own_sql(tol: float | str, **kind) -> Callable[[str], str]:
    return lambda f: _own(f, tol, **kind).select(_ANSWER)


def _hub_sql(f: str) -> str:
    q = oracle.graph(f)
    q.parts[-1] = "s AS MATERIALIZED (SELECT id FROM nd ORDER BY out_deg DESC, id LIMIT 1)"
    return oracle.solver(q, str(TOL), SEED, _OWN).select(_ANSWER)


def _error_of(g: Graph, est: DataFrame) -> DataFrame:
    """The largest error, and whether the promise holds (exact scores lack ``TAIL`` at most)."""
    return measures.errors(g, est, _exact(g)).select(F.round("max_abs", 6).alias("max_abs"), (F.col("max_abs") <= TOL + TAIL).alias("within"))


def _error_of_sql(f: str) -> str:
    q = oracle.power(_own(f, TOL), ROUNDS)
    return q.select(f"SELECT round(max_abs, 6) AS max_abs, max_abs <= {TOL + TAIL} AS within FROM (SELECT max(abs(coalesce(ans.est, 0) - coalesce(pw.est, 0))) AS max_abs FROM pw FULL JOIN ans USING (node))")


_each("absolute", EVERY, lambda g: _solved(solvers.absolute(g, g.median_node(), TOL, _OWN)), _own_sql(TOL))
_each("absolute_error", ("part_next", "nation_trade", "knn10", "page_link"), lambda g: _error_of(g, solvers.absolute(g, g.median_node(), TOL, _OWN)[0]), _error_of_sql)
_each("absolute_hub", ("part_supp", "doc_word"), lambda g: _solved(solvers.absolute(g, g.hub(), TOL, _OWN)), _hub_sql)
_each("absolute_resume", ("part_supp",), lambda g: _solved(solvers.absolute(g, g.median_node(), TOL, _OWN.with_(mode="resume"))))
_each("degree_norm", UNDIRECTED, lambda g: _solved(solvers.degree_norm(g, g.median_node(), TOL_DEG, _OWN)), _own_sql(TOL_DEG, degree_norm=True))
_each("degree_via_absolute", ("part_supp", "cust_part"), lambda g: _solved(solvers.degree_norm_via_absolute(g, g.median_node(), TOL_DEG, _OWN)), _own_sql(f"{TOL_DEG}::DOUBLE * dmin"))
_each("relative", ("part_supp", "page_link"), lambda g: _solved(solvers.relative(g, g.median_node(), 0.5, 0.05, _OWN)), _own_sql(0.5 * 0.05))
_each("pagerank", ("part_next", "nation_trade", "part_supp", "page_link"), lambda g: _solved(solvers.pagerank(g, 0.005, _OWN)), _own_sql(0.005, uniform=True))
# the alias table of unlike weights has no SQL form
_register("ppr_dist_cust_part", lambda spark, d: _solved(solvers.absolute(graph(spark, d, "cust_part"), balance_sources(spark, d), 0.005, _OWN)))


def _batch_sql(f: str) -> str:
    """Three solves, each from a node that the same hash order of arcs gives."""
    one = []
    for k in range(3):
        q = oracle.graph(f)
        q.parts[-1] = f"s AS MATERIALIZED (SELECT src AS id FROM g ORDER BY md5(concat_ws(':', 1, src, dst)), src, dst LIMIT 1 OFFSET {k})"
        one.append("(" + oracle.solver(q, str(TOL_DEG), SEED, _OWN, degree_norm=True).select("SELECT s.id AS query, node, round(est, 6) AS est FROM ans, s") + ")")
    return "SELECT * FROM (" + " UNION ALL ".join(one) + ")"


_each("degree_average", ("page_link", "part_supp"), lambda g: _r(solvers.batch(g, solvers.degree_sources(g, 3), TOL_DEG, _OWN, True), "est"), _batch_sql)
_each(
    "monte_carlo_tol",
    ("part_next", "page_link"),
    lambda g: _scores(solvers.monte_carlo(g, g.median_node(), TOL, _OWN)),
    lambda f: oracle.walks(oracle.graph(f), SEED, 1, f"(SELECT ceil((ln(2) + 2 * ln(n)) / (2 * {TOL}::DOUBLE * {TOL}::DOUBLE))::BIGINT FROM st)").select("SELECT node, round(cnt / sum(cnt) OVER (), 6) AS est FROM wk"),
)

# uses

_CUT = "SELECT rank AS size, vol, cut, round(conductance, 6) AS conductance FROM sw WHERE conductance IS NOT NULL ORDER BY round(sw.conductance, 9), rank LIMIT 1"
_each("sweep_profile", UNDIRECTED, lambda g: _r(apps.sweep_profile(g, push.forward_degree_norm(g, g.median_node(), RMAX, P)[0]), "conductance"), lambda f: oracle.sweep(_fp(f), "SELECT node, reserve AS est FROM fp").select("SELECT rank, node, vol, cut, round(conductance, 6) AS conductance FROM sw"))
_each("sweep_best", UNDIRECTED, lambda g: _r(apps.partition(g, g.median_node(), RMAX, P), "conductance"), lambda f: oracle.sweep(_fp(f), "SELECT node, reserve AS est FROM fp").select(_CUT))
_each(
    "sweep_exact",
    ("page_link",),
    lambda g: _r(apps.partition(g, g.median_node(), RMAX, P, "exact"), "conductance"),
    lambda f: oracle.sweep(oracle.power(oracle.start(oracle.graph(f), "median"), P.rounds_for(1e-12)), "SELECT node, est FROM pw").select(_CUT),
)
_each("sweep_degree_norm", ("page_link",), lambda g: _r(apps.partition(g, g.median_node(), TOL_DEG, _OWN, "degree_norm"), "conductance"), lambda f: oracle.sweep(_own(f, TOL_DEG, degree_norm=True), "SELECT node, est FROM ans").select(_CUT))
_each("topk", EVERY, lambda g: apps.topk(g, _exact(g), 10), lambda f: _pw(f).select("SELECT row_number() OVER (ORDER BY round(est, 9) DESC, node) AS rank, node, round(est, 9) AS value FROM pw QUALIFY rank <= 10"))
_each("topk_norm", UNDIRECTED, lambda g: apps.topk(g, _exact(g), 10, "est_over_d"), lambda f: _pw(f).select("SELECT row_number() OVER (ORDER BY round(est / out_deg, 9) DESC, node) AS rank, node, round(est / out_deg, 9) AS value FROM pw JOIN nd ON nd.id = node QUALIFY rank <= 10"))
_register("alias_mass_cust_part", lambda spark, d: _alias_mass(spark, d), lambda: oracle.start(oracle.graph("cust_part"), "balance").select("SELECT node, round(weight, 6) AS weight FROM w0"))


def _alias_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the alias table gives each node: its own slot's share and those that point to it."""
    t = walks.alias_table(balance_sources(spark, sf_dir))
    n = t.count()
    both = t.select("node", (F.col("accept") / n).alias("w")).unionByName(t.select(F.col("alias").alias("node"), ((1 - F.col("accept")) / n).alias("w")))
    return both.groupBy("node").agg(F.round(F.sum("w"), 6).alias("weight"))


def queries() -> dict[str, Callable]:
    return {**QUERIES, **relational_queries.QUERIES}


def oracle_sql() -> dict[str, str]:
    return {**SQL, **relational_queries.SQL}
