"""Training-data operators do their job over whole texts: cases that a cut would lose."""

import pytest

from proxgraph.llm import license_scan, line_dedup, queries


def test_license_expression_of_any_length():
    far = " OR ".join([f"LicenseRef-{i}" for i in range(60)])
    automaton = license_scan.build_automaton()
    labels = lambda text: license_scan.scan_text(text.encode(), automaton)[5]
    assert labels(f"// SPDX-License-Identifier: {far} OR MIT\ncode") == "mit,other"
    assert labels(f"// SPDX-License-Identifier: ({far} OR GPL-2.0-only) AND MIT\ncode") == "gpl,mit,other"
    cut_in_a_name = "MIT" + " " * 493 + "OR Apache-2.0"  # 500 characters end after the operator
    assert labels(f"SPDX-License-Identifier: {cut_in_a_name}") == "apache,mit"


def test_license_tags_on_one_line():
    automaton = license_scan.build_automaton()
    text = "SPDX-License-Identifier: MIT then prose " + "x " * 300 + "SPDX-License-Identifier: Apache-2.0 more\nSPDX-License-Identifier:\n* none"
    assert license_scan.scan_text(text.encode(), automaton)[5] == "apache,mit"


PASSAGE = " ".join(f"p{i}" for i in range(50))


@pytest.fixture
def passages(spark):
    short = PASSAGE.rsplit(" ", 1)[0]
    rows = [(3, f"e\n{PASSAGE}\nf\n{PASSAGE}"), (1, f"a\n{PASSAGE}\nb\n{short}"), (2, f"c\n{short}\nd"), (4, f"g\n {PASSAGE}"), (None, PASSAGE), (5, None)]
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_line_dedup_of_single_long_lines(passages):
    got = {r.doc_id: (r.text, r.n_removed_lines) for r in line_dedup.dedup_lines(passages, min_words=50).collect()}
    short = PASSAGE.rsplit(" ", 1)[0]
    assert got == {1: (f"a\n{PASSAGE}\nb\n{short}", 0), 2: (f"c\n{short}\nd", 0), 3: ("e\nf", 2), 4: (f"g\n {PASSAGE}", 0), None: (PASSAGE, 0), 5: (None, 0)}


def test_line_dedup_query_and_stage_take_single_long_lines(spark, passages, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    passages.selectExpr("doc_id", "text", "cast(length(text) as long) as n_chars").write.parquet(str(tmp_path / "documents.parquet"))
    assert {r.doc_id: r.n_removed_lines for r in queries.op2_line_dedup(spark, str(tmp_path)).collect()}[3] == 2
    left = corpus_pipeline.dedup_lines(spark, spark.read.parquet(str(tmp_path / "documents.parquet")), str(tmp_path))
    assert {r.doc_id: (r.text, r.n_chars) for r in left.collect()}[3] == ("e\nf", 3)
