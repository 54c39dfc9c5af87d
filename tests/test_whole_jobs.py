"""Operators do their job over whole texts and tables: small inputs against brute force."""

import random
from collections import Counter
from datetime import datetime, timedelta
from itertools import combinations

import numpy as np
import pytest

from proxgraph import queries, relational_queries
from proxgraph.functions import measures
from proxgraph.operators import graph as graphs
from proxgraph.operators import kernels, power, push, relational, solvers
from proxgraph.sources.fixtures import FIXTURES, nearest
from proxgraph.storage import saved


def test_doc_word_reads_whole_texts(spark, tmp_path):
    texts = {1: "head " + "x" * 500 + " Tail deep", 2: "tail", 3: "", 4: None, 5: " ".join(f"w{i}" for i in range(300))}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    pairs = {(d, w) for d, t in texts.items() for w in (t or "").lower().split(" ") if w}
    number = {w: i for i, w in enumerate(sorted({w for _, w in pairs}), 1)}
    got = FIXTURES["doc_word"].build(spark, str(tmp_path)).collect()
    assert sorted((r.src, r.dst) for r in got) == sorted((4 * d, 4 * number[w] + 1) for d, w in pairs)


def _shared(edges):
    held = {}
    for c, p in edges:
        held.setdefault(c, set()).add(p)
    met = Counter(x for ps in held.values() for x in combinations(sorted(ps), 2))
    return sorted((*x, n) for x, n in met.items() if n > 1)


def test_common_neighbours_of_all_parts(spark, tmp_path):
    rng = random.Random(3)
    lines = [(o, rng.randrange(60)) for o in range(40) for _ in range(6)]
    spark.createDataFrame([(o, o % 7) for o in range(40)], "o_orderkey long, o_custkey long").write.parquet(str(tmp_path / "orders.parquet"))
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    want = _shared({(o % 7, p) for o, p in lines})
    assert any(p >= 20 for p, *_ in want)
    assert sorted(map(tuple, relational_queries.rel_common_neighbours(spark, str(tmp_path)).collect())) == want


def test_common_neighbours_in_blocks(spark):
    edges = [(0, p) for p in range(50)] + [(1, p) for p in range(0, 50, 3)] + [(2, 7), (2, 9), (2, 9)]
    got = relational.common_neighbours(spark.createDataFrame(edges, "c long, p long"), "c", "p", "q", block=4)
    assert sorted(map(tuple, got.collect())) == _shared(edges)


def test_nearest_in_blocks(spark):
    rng = np.random.default_rng(4)
    vectors = [[float(x) for x in rng.integers(-2, 3, 4)] for _ in range(60)]
    vectors = [v if any(v) else [1.0, 0.0, 0.0, 0.0] for v in vectors]
    df = spark.createDataFrame(list(enumerate(vectors)), "vec_id long, embedding array<float>")
    unit = np.array(vectors) / np.linalg.norm(vectors, axis=1, keepdims=True)
    sim = np.round(unit @ unit.T, 9)
    want = {(i, j) for i in range(60) for j in sorted((j for j in range(60) if j != i), key=lambda j: (-sim[i, j], j))[:5]}
    for block in (7, 25, 1000):
        assert sorted((r.src, r.dst) for r in nearest(df, 5, block=block).collect()) == sorted(want), block
    assert nearest(df.limit(1), 5).count() == 0 and nearest(df.limit(0), 5).count() == 0


def test_sessions_are_whole_and_not_held_by_the_driver(spark, tmp_path):
    begin, rng = datetime(2024, 3, 1), random.Random(5)
    rows = [(k, begin + timedelta(seconds=rng.randrange(400_000)), k % 7, "click", 1.0, "{}") for k in range(600)]
    rows.append((600, begin + timedelta(seconds=400_001), 99, "click", 1.0, "{}"))  # still open when the input ends
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(str(tmp_path / "events.parquet"))
    want, last = [], {}
    for user, ts in sorted((r[2], r[1]) for r in rows):
        if user not in last or ts - last[user][0] >= timedelta(minutes=30):
            want.append([user, ts, 0])
        last[user] = (ts,)
        want[-1][2] += 1
    got = relational_queries.stream_sessions(spark, str(tmp_path))
    assert got.inputFiles()  # a table, not rows in the driver's memory
    micros = lambda t: (t - datetime(1970, 1, 1)) // timedelta(microseconds=1)
    assert sorted(map(tuple, got.collect())) == sorted((u, micros(t), n) for u, t, n in want)


@pytest.mark.parametrize("pages", [30, 5200])
def test_measures_over_all_sources_of_any_graph(spark, tmp_path, pages):
    rows = [(k, "u", f'<a href="/{k % 11}"><a href="/{k * k % 13}">') for k in range(pages)]
    spark.createDataFrame(rows, "page_id long, url string, html string").repartition(2).write.parquet(str(tmp_path / "pages.parquet"))
    mean = queries.QUERIES["average_spread_page_link"](spark, str(tmp_path)).first()
    cost = queries.QUERIES["cost_value_page_link"](spark, str(tmp_path)).first()
    g = queries.graph(spark, str(tmp_path), "page_link")
    assert mean.expected == round(g.n / g.stats["arcs"], 6) and cost.a_value > 0
    if pages == 30:
        every = power.all_pairs(g, queries.P, queries.TAIL)
        assert mean.mean_s == pytest.approx(measures.average_spread(g, every).first().mean_s, abs=1e-6)
        assert cost.a_value == pytest.approx(measures.cost_value(g, queries._exact(g), every).first().a_value, abs=1e-6)


@pytest.mark.parametrize("directed", [False, True])
def test_stored_adjacency_takes_graphs_that_are_too_large_to_broadcast(spark, monkeypatch, directed):
    rng = np.random.default_rng(1)
    arcs = {(int(a), int(b) + (0 if directed else 1000)) for a, b in rng.integers(0, 300, (2000, 2))} | ({(i, (i + 1) % 300) for i in range(300)} if directed else set())
    edges = spark.createDataFrame(sorted(arcs), "src long, dst long").repartition(5)
    small = graphs.Graph.from_edges(edges, directed)
    held, node, p = small.csr.value, small.median_node(), queries.P
    runs = (lambda g: power.single_source(g, node, p), lambda g: power.single_target(g, node, p), lambda g: solvers.monte_carlo_walks(g, node, 1000, p), lambda g: push.reverse_single(g, node, 1e-4, p)[0].select("node", "reserve"))
    want = [sorted(map(tuple, run(small).collect())) for run in runs]
    monkeypatch.setattr(graphs, "KERNEL_ARCS", 10)
    monkeypatch.setattr(graphs, "STORE_BATCH", 300)
    large = graphs.Graph.from_edges(edges, directed)
    assert large.use_kernel("auto")
    stored = large.csr.value
    for name in ("ids", "out_at", "out_to", "in_at", "in_from"):
        assert np.array_equal(getattr(held, name), getattr(stored, name)), name
    for run, rows in zip(runs, want):
        got = sorted(map(tuple, run(large).collect()))
        assert [r[0] for r in got] == [r[0] for r in rows] and np.allclose(got, rows, atol=1e-14)
    monkeypatch.setattr(graphs, "STORE_NODES", 10)
    assert not graphs.Graph.from_edges(edges, directed).use_kernel("auto")


def test_power_in_chunks_of_arcs(monkeypatch):
    rng = np.random.default_rng(2)
    out_deg = rng.integers(1, 9, 50)
    at = np.concatenate(([0], np.cumsum(out_deg)))
    to = rng.integers(0, 50, at[-1])
    src = np.repeat(np.arange(50), out_deg)
    order = np.lexsort((src, to))
    csr = graphs.Csr(np.arange(50), at, to, np.concatenate(([0], np.cumsum(np.bincount(to, minlength=50)))), src[order])
    whole = kernels.power(csr, np.eye(50)[3], 0.2, 30), kernels.reverse_power(csr, 3, 0.2, 30)
    monkeypatch.setattr(kernels, "CHUNK_ARCS", 7)
    assert np.allclose(kernels.power(csr, np.eye(50)[3], 0.2, 30), whole[0], atol=1e-15)
    assert np.allclose(kernels.reverse_power(csr, 3, 0.2, 30), whole[1], atol=1e-15)
    step = np.zeros((50, 50))
    np.add.at(step, (src, to), 1 / out_deg[src])
    exact = 0.2 * sum(np.linalg.matrix_power(0.8 * step, k) for k in range(31))
    assert np.allclose(whole[0], exact[3]) and np.allclose(whole[1], exact[:, 3])


def test_saved_tables_leave_no_shuffle_files(spark):
    def files():
        return spark._jvm.org.apache.spark.SparkEnv.get().shuffleManager().shuffleBlockResolver().getStoredShuffles().size()

    before = files()
    kept = saved(spark.range(10_000).repartition(8, "id").groupBy("id").count())
    assert files() <= before
    assert kept.count() == 10_000


def test_arcs_are_numbered_behind_one_shuffle(spark, monkeypatch):
    """Repeated rows, and a node with more arcs than the builder holds; a plan of one shuffle and one sort, without windows."""
    rng = random.Random(5)
    edges = [(0, rng.randrange(500)) for _ in range(900)] + [(rng.randrange(40), rng.randrange(60)) for _ in range(700)] + [(41, 3)] * 9
    near = {}
    for a, b in sorted(set(edges)):
        near.setdefault(a, []).append(b)
    want = [(a, b, i, len(bs)) for a, bs in sorted(near.items()) for i, b in enumerate(bs)]
    placed = graphs._placed(spark.createDataFrame(edges, "src long, dst long"))
    assert sorted(tuple(r) for r in placed.collect()) == want
    plan = placed._jdf.queryExecution().sparkPlan().toString()
    assert plan.count("Exchange ") == 1 and plan.count("Sort ") == 1 and "Aggregate" not in plan and "Window" not in plan
    monkeypatch.setattr(graphs, "HELD_ARCS", 50)
    a, b = (np.array(x) for x in zip(*sorted(edges), strict=True))
    for size in (7, 64, 5000):
        batches = [graphs.pa.RecordBatch.from_arrays([graphs.pa.array(x[k : k + size]) for x in (a, b)], names=["src", "dst"]) for k in range(0, len(a), size)]
        assert [tuple(r.values()) for got in graphs._numbered(iter(batches)) for r in got.to_pylist()] == want


def test_arcs_travel_as_packed_runs(spark, monkeypatch):
    """Runs, pieces and a node that takes several pieces; far ids; the shuffle has far fewer rows than arcs."""
    rng = random.Random(6)
    far = 1 << 61
    edges = [(7, -9 - 4 * k) for k in range(3000)] + [(rng.randrange(400), -9 - 4 * rng.randrange(3000)) for _ in range(5000)] + [(far, -far), (far, -far - 5)] * 3
    both = set(edges) | {(b, a) for a, b in edges}
    near = {}
    for a, b in sorted(both):
        near.setdefault(a, []).append(b)
    want = [(a, b, i, len(bs)) for a, bs in sorted(near.items()) for i, b in enumerate(bs)]
    for name, value in (("RUN_ARCS", 700), ("PIECE_ARCS", 512), ("SAMPLE_EVERY", 4), ("BATCH_ARCS", 100)):
        monkeypatch.setattr(graphs, name, value)
    table = spark.createDataFrame(edges, "src long, dst long").repartition(3)
    placed = graphs._placed(table, True)
    assert sorted(tuple(r) for r in placed.collect()) == want
    plan = placed._jdf.queryExecution().sparkPlan().toString()
    assert "piece" in plan and plan.count("Exchange ") == 1
    for bad, kind in (([(None, 1)], "null"), ([(3, 3)], "self-loop")):
        with pytest.raises(graphs.GraphError, match=kind):
            graphs.Graph.from_edges(table.union(spark.createDataFrame(bad, "src long, dst long")), False)
    looped = table.union(spark.createDataFrame([(3, 3)], "src long, dst long"))
    assert graphs.Graph.from_edges(looped, False, self_loops="drop").pairs.count() == len(want)
    empty = graphs._placed(spark.createDataFrame([], "src long, dst long"), True)
    assert empty.count() == 0


def test_large_vocabularies_are_not_joined_by_shuffle(spark, tmp_path):
    """Words are numbered by hashes in array files, whatever their number: texts are not shuffled, and no word is lost."""
    rng = random.Random(8)
    texts = [(d, " ".join(rng.choice(["Ä", "b\n", "x\ty", "É", f"w{rng.randrange(900)}", "", "Z"]) for _ in range(60))) for d in range(200)]
    spark.createDataFrame(texts, "doc_id long, text string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    pairs = {(d, w) for d, t in texts for w in t.lower().split(" ") if w}
    number = {w: i for i, w in enumerate(sorted({w for _, w in pairs}, key=str.encode), 1)}
    got = FIXTURES["doc_word"].build(spark, str(tmp_path))
    assert "Exchange" not in got._jdf.queryExecution().sparkPlan().toString() and "Join" not in got._jdf.queryExecution().sparkPlan().toString()
    assert sorted((r.src, r.dst) for r in got.collect()) == sorted((4 * d, 4 * number[w] + 1) for d, w in pairs)


def test_scores_of_many_nodes_are_not_broadcast(spark, monkeypatch):
    edges = spark.createDataFrame([(i, 1000 + i % 7) for i in range(60)] + [(i, 1000 + i % 5) for i in range(60)], "src long, dst long")
    g = graphs.Graph.from_edges(edges, False)
    scores = power.single_source(g, 3, queries.P)
    want = measures.spread(g, scores).collect()
    monkeypatch.setattr(measures, "BROADCAST_ROWS", 10)
    got = measures.spread(g, scores)
    assert "BroadcastHashJoin" not in got._jdf.queryExecution().sparkPlan().toString()
    assert np.allclose(got.collect(), want)
