"""Closed forms, push invariants, engines against each other, and the solvers' guarantees."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxgraph.functions import measures, prng
from proxgraph.operators import apps, power, push, solvers, three_phase, walks
from proxgraph.operators.graph import Graph, GraphError, apply_dangling_policy
from proxgraph.params import PprParams

P = PprParams()
A = P.alpha


def make(spark, pairs, directed=True, **options):
    return Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"), directed, **options)


def scores(df):
    return {r.node: r.est for r in df.collect()}


@pytest.fixture(scope="module")
def two_cycle(spark):
    return make(spark, [(0, 1), (1, 0)])


@pytest.fixture(scope="module")
def mixed(spark):
    """A directed graph with loops, repeated edges and uneven degrees."""
    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in zip(rng.integers(0, 60, 400), (rng.integers(0, 60, 400) ** 2) // 60, strict=True)]
    pairs += [(i, (i + 1) % 60) for i in range(60)]
    return make(spark, pairs)


@pytest.fixture(scope="module")
def social(spark):
    """An undirected graph with a hub, leaves and a second component."""
    rng = np.random.default_rng(4)
    pairs = [(0, i) for i in range(1, 50)] + [(int(a), int(b)) for a, b in rng.integers(1, 80, (150, 2)) if a != b]
    pairs += [(100, 101), (101, 102), (102, 100)]
    return make(spark, pairs, False)


def test_closed_forms(spark, two_cycle):
    assert scores(power.single_source(make(spark, [(5, 5)]), 5, P)) == pytest.approx({5: 1.0})
    assert scores(power.single_source(two_cycle, 0, P)) == pytest.approx({0: 1 / (2 - A), 1: (1 - A) / (2 - A)})
    k = 7
    ring = scores(power.single_source(make(spark, [(i, (i + 1) % k) for i in range(k)]), 0, P))
    assert ring == pytest.approx({j: A * (1 - A) ** j / (1 - (1 - A) ** k) for j in range(k)})
    full = scores(power.single_source(make(spark, [(i, j) for i in range(5) for j in range(i)], False), 2, P))
    assert len({round(v, 12) for n, v in full.items() if n != 2}) == 1 and sum(full.values()) == pytest.approx(1)
    three = scores(power.single_source(make(spark, [(0, 1), (1, 0), (1, 2), (2, 0)]), 0, P))
    assert three == pytest.approx({0: 0.471698, 1: 0.377358, 2: 0.150943}, abs=1e-6)


def test_unreachable_and_missing(spark, social):
    far = scores(power.single_source(social, 0, P))
    assert not set(far) & {100, 101, 102} and sum(far.values()) == pytest.approx(1)
    with pytest.raises(GraphError):
        power.single_source(social, 999, P).collect()
    with pytest.raises(GraphError):
        push.reverse_single(social, 999, 0.1, P)


def test_hygiene(spark):
    dead_end = spark.createDataFrame([(0, 1), (1, 0), (1, 2)], "src long, dst long")
    with pytest.raises(GraphError):
        Graph.from_edges(dead_end, True)
    assert {tuple(r) for r in apply_dangling_policy(dead_end, "self_loop").collect()} == {(0, 1), (1, 0), (1, 2), (2, 2)}
    assert {tuple(r) for r in apply_dangling_policy(dead_end, "drop").collect()} == {(0, 1), (1, 0)}
    with pytest.raises(GraphError):
        make(spark, [(0, None)])
    with pytest.raises(GraphError):
        make(spark, [(0, 1), (1, 1)], False)
    assert make(spark, [(0, 1), (0, 1), (1, 0), (1, 1)], False, self_loops="drop").m == 1
    for bad in ({"alpha": 0}, {"alpha": 1}, {"engine": "x"}, {"rng": "x"}, {"mode": "x"}):
        with pytest.raises(ValueError):
            PprParams(**bad)
    with pytest.raises(ValueError):
        solvers.absolute(make(spark, [(0, 1), (1, 0)]), 0, 0.0, P)


@pytest.mark.parametrize("name", ["mixed", "social"])
def test_engines_agree(request, name):
    g, frame = request.getfixturevalue(name), P.with_(engine="frame")
    for one, two in (
        (power.single_source(g, 3, P, 1e-4), power.single_source(g, 3, frame, 1e-4)),
        (power.single_target(g, 3, P, 1e-3), power.single_target(g, 3, frame, 1e-3)),
        (solvers.monte_carlo_walks(g, 3, 500, P), solvers.monte_carlo_walks(g, 3, 500, frame)),
        (push.forward(g, 3, 0.003, P)[0].select("node", F.col("residue").alias("est")), push.forward(g, 3, 0.003, frame)[0].select("node", F.col("residue").alias("est"))),
        (push.reverse_single(g, 3, 0.03, P)[0].select("node", F.col("residue").alias("est")), push.reverse_single(g, 3, 0.03, frame)[0].select("node", F.col("residue").alias("est"))),
    ):
        assert {k: v for k, v in scores(one).items() if v > 0} == pytest.approx({k: v for k, v in scores(two).items() if v > 0}, abs=1e-12)


def test_reverse_push_rounds(two_cycle):
    """The two-cycle by hand: four rounds to theta = 0.5."""
    state, trace = push.reverse_single(two_cycle, 1, 0.5, P)
    rows = {r.node: (r.reserve, r.residue) for r in state.collect()}
    assert rows[0] == pytest.approx((0.2624, 0.0)) and rows[1] == pytest.approx((0.328, 0.4096))
    assert (trace.cost, trace.rounds) == (4, 4)


@pytest.mark.parametrize("name", ["mixed", "social"])
def test_push_invariants(request, name):
    g = request.getfixturevalue(name)
    truth, theta = scores(power.single_target(g, 3, P)), 0.0071
    state = push.reverse_single(g, 3, theta, P)[0]
    rows = state.collect()
    assert all(r.residue <= theta for r in rows)
    for r in rows:
        assert -1e-12 <= truth.get(r.node, 0) - r.reserve <= theta + 1e-12
    assert measures.invariant_gap(g, state, power.all_pairs(g, P)).first()[0] < 1e-9
    resumed, _ = push.reverse(g, g.spark.createDataFrame([(3, theta)], "target long, theta double"), P, resume=push.reverse_single(g, 3, 8 * theta, P)[0])
    assert all(r.residue <= theta and -1e-12 <= truth.get(r.node, 0) - r.reserve <= theta + 1e-12 for r in resumed.collect())
    state, _ = push.forward(g, 3, 0.0013, P)
    total = state.agg(F.sum("reserve"), F.sum("residue")).first()
    assert total[0] + total[1] == pytest.approx(1)
    e = measures.errors(g, state.select("node", F.col("reserve").alias("est")), power.single_source(g, 3, P)).first()
    assert e.l1 <= g.stats["arcs"] * 0.0013 + 1e-9
    if not g.directed:
        assert e.max_deg <= 0.0013 + 1e-12


def test_push_budget(mixed):
    cands = mixed.spark.createDataFrame([(3, 0.001), (4, 0.001)], "target long, theta double")
    for p in (P, P.with_(engine="frame")):
        _, full = push.reverse(mixed, cands, p)
        assert full.within and push.reverse(mixed, cands, p, full.cost)[1].within
        assert not push.reverse(mixed, cands, p, full.cost - 1)[1].within
    assert push.reverse(mixed, cands, P)[1].cost == push.reverse(mixed, cands, P.with_(engine="frame"))[1].cost


def test_portable_draws_are_even():
    u = prng.draw(prng.walk_key(3, np.arange(40) % 7, np.arange(40_000).reshape(40, 1000).ravel()[:40]), 0, 0)
    assert len(np.unique(u)) == 40
    many = prng.draw(prng.walk_key(1, np.zeros(200_000, np.int64), np.arange(200_000)), 5, 1) / prng.P
    hist = np.histogram(many, 50, (0, 1))[0]
    assert ((hist - 4000) ** 2 / 4000).sum() < 90
    assert abs(np.corrcoef(many[:-1], many[1:])[0, 1]) < 0.01


@pytest.mark.parametrize("rng", ["portable", "wide"])
def test_walks_follow_the_scores(mixed, rng):
    n = 200_000
    got = scores(solvers.monte_carlo_walks(mixed, 3, n, P.with_(rng=rng)))
    truth = scores(power.single_source(mixed, 3, P))
    chi = sum((got.get(k, 0) - t) ** 2 / t * n for k, t in truth.items() if t * n > 5)
    assert chi < len(truth) + 5 * math.sqrt(2 * len(truth))


def test_wide_draws_are_those_of_spark(spark):
    rows = [(t, w, s) for t in (0, 5) for w in (0, 1, 1 << 40) for s in (0, 3, 1_000_003)]
    df = spark.createDataFrame(rows, "trial int, walk long, step int")
    for seed in (1, 7 + 1_000_003):
        for lane in (0, 1):
            got = {(r.trial, r.walk, r.step): r.u for r in df.withColumn("u", prng.wide_draw_col(seed, F.col("trial"), F.col("walk"), F.col("step"), lane)).collect()}
            want = {(t, w, s): int(prng.wide_draw(prng.wide_key(seed, np.array([t]), np.array([w])), s, lane)[0]) for t, w, s in rows}
            assert got == want


def test_wide_walks_of_both_engines(social):
    for start in (0, solvers.uniform_sources(social)):
        one, two = ({(r.trial, r.node): r.cnt for r in walks.simulate(social, start, 2, 60, PprParams(alpha=0.7, rng="wide", engine=e)).collect()} for e in ("kernel", "frame"))
        assert one == two and sum(one.values()) == 120


def test_generator_by_number_of_walks():
    assert P.generator(1 << 20) == "portable" and P.generator((1 << 20) + 1) == "wide"
    assert P.with_(rng="portable").generator(1 << 30) == "portable" and P.with_(rng="wide").generator(1) == "wide"
    with pytest.raises(ValueError):
        P.with_(rng="narrow")


def test_equal_weights_need_no_driver_table(spark, monkeypatch):
    monkeypatch.setattr(walks, "MAX_ALIAS", 10)
    even = spark.range(500).select((F.col("id") * 3).alias("node"), F.lit(0.5).alias("weight"))
    rows = walks.alias_table(even).orderBy("slot").collect()
    assert [(r.slot, r.node, r.accept, r.alias) for r in rows] == [(i, 3 * i, 1.0, 3 * i) for i in range(500)]
    with pytest.raises(ValueError):
        walks.alias_table(even.withColumn("weight", F.col("node") + 1.0))
    with pytest.raises(ValueError):
        walks.alias_table(even.withColumn("weight", F.lit(0.0)))


def test_walks_do_not_depend_on_layout(mixed):
    old = mixed.spark.conf.get("spark.sql.shuffle.partitions")
    answers = []
    for parts in ("1", "4", "16"):
        mixed.spark.conf.set("spark.sql.shuffle.partitions", parts)
        answers.append(scores(solvers.monte_carlo_walks(mixed, 3, 3000, P)))
    mixed.spark.conf.set("spark.sql.shuffle.partitions", old)
    assert answers[0] == answers[1] == answers[2]


def test_alias_arrays():
    rng = np.random.default_rng(0)
    for n in (1, 2, 7, 100):
        w = rng.random(n) ** 3
        accept, alias = walks.alias_arrays(w)
        got = accept.copy()
        np.add.at(got, alias, 1 - accept)
        assert got / n == pytest.approx(w / w.sum())


def test_source_distribution(social):
    sources = social.spark.createDataFrame([(0, 3.0), (5, 1.0), (6, -2.0), (5, 1.0)], "node long, weight double")
    exact = scores(power.single_source(social, sources, P))
    one, two = scores(power.single_source(social, 0, P)), scores(power.single_source(social, 5, P))
    assert exact == pytest.approx({k: 0.6 * one.get(k, 0) + 0.4 * two.get(k, 0) for k in exact})
    est, report = solvers.absolute(social, sources, 0.01, P)
    assert measures.errors(social, est, power.single_source(social, sources, P)).first().max_abs <= 0.01
    for engine in ("kernel", "frame"):
        got = scores(walks.simulate(social, sources, 1, 400, P.with_(engine=engine)).select("node", F.col("cnt").alias("est")))
        assert sum(got.values()) == 400
        if engine == "kernel":
            first = got
    assert got == first


@pytest.mark.parametrize("tol", [0.02, 0.005])
@pytest.mark.parametrize("name", ["mixed", "social"])
def test_absolute_guarantee(request, name, tol):
    g = request.getfixturevalue(name)
    truth = power.single_source(g, 3, P)
    worst = []
    for seed in range(4):
        est, report = solvers.absolute(g, 3, tol, P.with_(seed=seed, mode="resume" if seed % 2 else "restart"))
        worst.append(measures.errors(g, est, truth).first().max_abs)
        assert report.candidates < 2 / tol and report.walks >= 1
        accepted = [a for a in report.attempts if a.accepted]
        assert all(a.cost <= report.trials * a.walks / A for a in accepted[:-1])
        rejected = [a for a in report.attempts if not a.accepted]
        assert len(rejected) <= 1 and all(a is report.attempts[-1] for a in rejected)
    assert measures.success_rate(worst, tol, g.n)["rate"] == 1


def test_degree_normalised_guarantee(social, mixed):
    truth = power.single_source(social, 3, P)
    for tol in (0.002, 0.0005):
        est, report = solvers.degree_norm(social, 3, tol, P)
        assert measures.errors(social, est, truth).first().max_deg <= tol
    with pytest.raises(ValueError):
        solvers.degree_norm(mixed, 3, 0.01, P)
    with pytest.raises(ValueError):
        push.forward_degree_norm(mixed, 3, 0.01, P)


def test_estimator_moments(mixed):
    """Unbiased trials whose variance is under theta * score / walks, and so under tol^2 / 3."""
    tol, truth = 0.02, power.single_source(mixed, 3, P)
    p = P.with_(force_walks=40, force_trials=400)
    trials = three_phase.trial_estimates(mixed, 3, tol, p)
    rough = three_phase.candidates(three_phase.rough_scores(mixed, 3, p.phase1_walks(mixed.n, tol), p), F.lit(tol))
    theta = {r.target: r.theta for r in three_phase.thresholds(rough, 40, p).collect()}
    true = scores(truth)
    rows = measures.trial_moments(trials, truth).collect()
    assert rows and {r.target for r in rows} == set(theta)
    for r in rows:
        bound = theta[r.target] * true[r.target] / 40
        assert r.trials == 400 and r.variance <= 1.3 * bound and bound <= tol * tol / 3 * 1.001
        assert abs(r.bias) <= 4 * math.sqrt(max(r.variance, 1e-18) / 400) + 1e-12


def test_first_phase_bounds(mixed):
    tol, truth = 0.01, power.single_source(mixed, 3, P)
    for seed in range(3):
        p = P.with_(seed=seed, phase1_const=48)
        rough = three_phase.rough_scores(mixed, 3, p.phase1_walks(mixed.n, tol), p)
        assert measures.phase1_ok(rough, truth, tol).first()[0] == 0
        cands = three_phase.candidates(rough, F.lit(tol))
        assert measures.candidates_ok(cands, truth, tol).first()[0] == 0


def test_structure(social):
    pairs = power.all_pairs(social, P)
    assert measures.symmetry_gap(social, pairs).first()[0] < 1e-9
    r = measures.average_spread(social, pairs).first()
    assert r.mean_s == pytest.approx(r.expected)
    truth = power.single_source(social, 3, P)
    assert measures.cost_value(social, truth, pairs).first()[0] == pytest.approx(measures.spread(social, truth).first().weighted_degree)
    h = measures.heavy_counts(social, truth, 0.01, 0.001).first()
    assert h.heavy <= h.heavy_bound and h.heavy_deg <= h.heavy_deg_bound


def test_balance_is_near_the_best(social):
    """The chosen number of walks costs at most a small multiple of the best fixed one."""
    tol = 0.005
    _, chosen = solvers.absolute(social, 3, tol, P)
    costs = []
    for walks_ in (chosen.walks // 8, chosen.walks // 2, chosen.walks, chosen.walks * 2, chosen.walks * 8):
        if walks_ >= 1:
            _, r = solvers.absolute(social, 3, tol, P.with_(force_walks=walks_))
            costs.append(r.trials * r.walks / A + r.push_cost)
    assert chosen.trials * chosen.walks / A + chosen.tried_cost <= 8 * min(costs)


def test_cost_grows_slower_than_plain_walks(mixed):
    three, plain = [], []
    for tol in (0.02, 0.005):
        _, r = solvers.absolute(mixed, 3, tol, P)
        three.append(r.total_cost)
        plain.append(solvers.monte_carlo_count(mixed.n, tol))
    slope = lambda c: math.log(c[1] / c[0]) / math.log(4)
    assert slope(plain) == pytest.approx(2, abs=0.01) and slope(three) < 1.6


def test_fallback(mixed):
    est, report = solvers.absolute(mixed, 3, 0.02, P.with_(cost_cap=10))
    assert report.fallback and measures.errors(mixed, est, power.single_source(mixed, 3, P)).first().max_abs <= 0.02


def test_other_solvers(social, mixed):
    truth = power.single_source(social, 3, P)
    assert measures.errors(social, solvers.monte_carlo(social, 3, 0.02, P), truth).first().max_abs <= 0.02
    assert measures.errors(social, push.forward_absolute(social, 3, 0.01, P)[0], truth).first().max_abs <= 0.01
    assert measures.errors(mixed, push.forward_absolute(mixed, 3, 0.5, P)[0], power.single_source(mixed, 3, P)).first().l1 <= 0.5
    assert measures.errors(social, push.reverse_all_targets(social, 3, 0.01, P)[0], truth).first().max_abs <= 0.01
    est, _ = solvers.relative(social, 3, 0.5, 0.05, P)
    assert measures.errors(social, est, truth, 0.05).first().max_rel <= 0.5
    est, _ = solvers.pagerank(mixed, 0.01, P)
    assert measures.errors(mixed, est, solvers.pagerank_exact(mixed, P)).first().max_abs <= 0.01
    est, _ = solvers.degree_norm_via_absolute(social, 3, 0.01, P)
    assert measures.errors(social, est, truth).first().max_deg <= 0.01
    assert solvers.recommend(mixed, 0.3, P) in ("three_phase", "power")
    assert {r.query for r in solvers.batch(social, [3, 5], 0.02, P).select("query").distinct().collect()} == {3, 5}
    assert len(solvers.degree_sources(social, 5)) == 5


def test_sweep_against_brute_force(social, spark):
    truth = power.single_source(social, 3, P)
    deg = {r.id: r.out_deg for r in social.nodes.collect()}
    order = [n for n, v in sorted(scores(truth).items(), key=lambda x: (-round(x[1] / deg[x[0]], 9), x[0]))]
    arcs = [(r.src, r.dst) for r in social.arcs.collect()]
    inside, best = set(), None
    for r, n in zip(apps.sweep_profile(social, truth).orderBy("rank").collect(), order, strict=True):
        inside.add(n)
        cut = sum(a in inside and b not in inside for a, b in arcs)
        vol = sum(deg[x] for x in inside)
        assert (r.node, r.vol, r.cut) == (n, vol, cut)
        low = min(vol, len(arcs) - vol)
        if low > 0 and (best is None or cut / low < best[0]):
            best = (cut / low, len(inside))
    got = apps.best_cut(social, truth).first()
    assert (got.conductance, got.size) == pytest.approx(best)


def test_sweep_finds_the_planted_cut(spark):
    k5 = [(i, j) for i in range(5) for j in range(i)]
    g = make(spark, k5 + [(a + 10, b + 10) for a, b in k5] + [(0, 10)], False)
    for scorer in ("forward", "degree_norm", "exact"):
        r = apps.partition(g, 1, 0.0007, P, scorer).first()
        assert (r["size"], r.cut, r.vol) == (5, 1, 21), scorer


def test_apps(social):
    truth = power.single_source(social, 3, P)
    top = apps.topk(social, truth, 5).orderBy("rank").collect()
    assert [r.rank for r in top] == [1, 2, 3, 4, 5] and top[0].value >= top[4].value
    f = apps.features(power.multi_source(social, social.spark.createDataFrame([(3,), (5,)], "node long"), P)).collect()
    assert {r.query for r in f} == {3, 5} and all(sum(r.features.values()) == pytest.approx(1, abs=1e-6) for r in f)


def test_graph_helpers(social):
    sub = social.subgraph(social.spark.createDataFrame([(i,) for i in (100, 101, 102)], "id long"))
    assert (sub.n, sub.m) == (3, 3)
    kept = social.sample_edges(0.5, 1)
    assert 0 < kept.count() < social.stats["arcs"]
    assert kept.exceptAll(kept.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).count() == 0
    assert social.hub() == 0 and social.median_node() is not None
    social.register("s")
    assert social.spark.sql("select count(*) from s_nodes").first()[0] == social.n


def test_one_exchange_per_push_round(mixed):
    state = mixed.spark.createDataFrame([(3, 3, 0.0, 1.0)], push.STATE).repartition(4, "node").withColumn("hot", F.lit(True))
    arcs = mixed.arcs.select(F.col("dst").alias("node"), "src", "out_deg")
    plan = push.reverse_round(state, arcs, A)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan
    shuffles = plan.count("Exchange hashpartitioning")
    assert shuffles <= 3  # both sides of the join with the arcs at most, and the sum


@pytest.mark.parametrize("mode", ["restart", "resume"])
def test_search_in_one_job_is_the_search_by_attempts(social, monkeypatch, mode):
    p = P.with_(seed=5, mode=mode)
    whole, one = solvers.absolute(social, 3, 0.01, p)
    monkeypatch.setattr(push, "LADDER_TARGETS", 0)
    parts, many = solvers.absolute(social, 3, 0.01, p)
    assert one.attempts == many.attempts and one.walks == many.walks and one.push_cost == many.push_cost
    a, b = ({r.node: r.est for r in x.collect()} for x in (whole, parts))
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-12 for k in a)
