"""Readers, the adjacency store, the SQL surface, streams against batch, plans."""

import pytest
from pyspark.sql import functions as F

from proxgraph.operators import power, relational, solvers
from proxgraph.operators.graph import Graph
from proxgraph.params import PprParams
from proxgraph.sources import io, sql
from proxgraph.streaming import edges as streams

PAIRS = [(i, (i * 7 + 3) % 50) for i in range(50)] + [(i, (i + 1) % 50) for i in range(50)]


@pytest.fixture(scope="module")
def graph(spark):
    return Graph.from_edges(spark.createDataFrame(PAIRS, "src long, dst long"), True)


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json", "text", "edgelist"])
def test_formats(spark, tmp_path, fmt):
    df = spark.createDataFrame(PAIRS, "src long, dst long")
    path = str(tmp_path / "e")
    if fmt in ("text", "edgelist"):
        path = str(tmp_path / "e.txt")
        with open(path, "w") as f:
            f.write("# a comment\n\n" + "\n".join(f"{a}\t {b}" for a, b in PAIRS))
    else:
        df.write.format(fmt).save(path)
    if fmt == "edgelist":
        io.register(spark)
        got = spark.read.format("edgelist").option("split", "40").load(path)
    else:
        got = io.read_edges(spark, path, fmt)
    assert sorted(map(tuple, got.collect())) == sorted(PAIRS)


def test_adjacency_store(spark, graph, tmp_path):
    path = str(tmp_path / "adj")
    io.write_adjacency(graph, path, 8)
    back = io.read_adjacency(spark, path, True)
    assert {tuple(r) for r in back.arcs.collect()} == {tuple(r) for r in graph.arcs.collect()}
    near = io.neighbours(spark, path, spark.createDataFrame([(3,), (11,)], "id long"), 8)
    assert {(r.src, r.dst) for r in near.collect()} == {p for p in PAIRS if p[0] in (3, 11)}
    scores = power.single_source(back, 3, PprParams())
    io.write_scores(scores, str(tmp_path / "s"))
    io.write_scores(scores, str(tmp_path / "s"))
    assert spark.read.parquet(str(tmp_path / "s")).agg(F.sum("est")).first()[0] == pytest.approx(1)


def test_sql_surface(spark, graph):
    sql.register(spark, graph, "g")
    walks = spark.sql("select walk, max_by(node, step) as node from g_walk(3, 500, 0.2D, 1) group by walk")
    ends = {r.node: r.n for r in walks.groupBy("node").agg(F.count("*").alias("n")).collect()}
    assert ends == {r.node: round(r.est * 500) for r in solvers.monte_carlo_walks(graph, 3, 500, PprParams()).collect()}
    assert spark.sql("select max(residue) from g_push(3, 0.01D, 0.2D)").first()[0] <= 0.01
    spark.createDataFrame(PAIRS, "src long, dst long").createOrReplaceTempView("pairs_view")
    top = sql.ppr(spark, "pairs_view", 3, 0.02).first()
    assert top.node == 3


def test_range_lookup_and_prefix_sum(spark):
    df = spark.range(100).select("id", (F.col("id") % 7 + 1).alias("w"))
    run = relational.cumulative(df, "w", ["id"], F.floor(F.col("id") / 9)).collect()
    total = 0
    for r in sorted(run, key=lambda r: r.id):
        total += r.w
        assert r.running == total


def test_stream_refresh(spark, tmp_path):
    spark.createDataFrame(PAIRS[:60], "src long, dst long").coalesce(1).write.parquet(str(tmp_path / "in"))
    spark.createDataFrame(PAIRS[60:], "src long, dst long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    s = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    seen = []
    streams.refresh(s, lambda e: e.agg(F.count("*").alias("n")), seen).awaitTermination()
    assert len(seen) == 2 and seen[-1].first().n == len(set(PAIRS))


def test_entry_contract():
    import __spark_entry__ as entry

    names, texts = entry.queries(), entry.oracle_sql()
    assert set(texts) <= set(names) and len(names) > 150


def test_entry_without_the_operators(tmp_path):
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/proxgraph", tmp_path / "proxgraph", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert not any(n.startswith('op') for n in q) and 'pipeline' not in q and len(q) > 100"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
