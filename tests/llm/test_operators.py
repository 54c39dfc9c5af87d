"""Operators against brute force, and their edge cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter
from fnmatch import fnmatchcase  # noqa: F401

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxgraph.llm.queries import VOCABULARY
from proxgraph.llm import common, context_mixing, decontaminate, host_quality, jaccard_join, license_scan, line_dedup, mixing, substring_dedup, url_filter, word_pieces

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
#: Extra columns whose names the operators use inside.
EXTRA = ("id", "body", "rank", "fp", "copies", "kept", "gone", "node", "line", "token")


def _words(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


@pytest.fixture(scope="module")
def corpus():
    """Texts with exact and near copies, shared passages, repeated lines, short, empty, null and very long ones."""
    rng = random.Random(5)
    base = _words(rng, 300)
    passage = _words(rng, 60)
    rows = [(i, "\n".join(_words(rng, rng.randint(5, 30)) for _ in range(rng.randint(1, 8))), "en", f"s{i % 5}") for i in range(40)]
    rows += [(100 + i, base, "en", "s0") for i in range(5)]
    for i in range(12):
        w = base.split()
        for _ in range(rng.randint(1, 8)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        rows.append((200 + i, " ".join(w), "fr", "s1"))
    rows += [(300 + i, f"{_words(rng, 40)}\n{passage}\n{_words(rng, 30)}", "de", "s2") for i in range(6)]
    rows += [(400, "", "en", "s3"), (401, None, "en", None), (402, " \n\t ", None, "s3"), (403, "a", "en", "s3"), (404, "A", "en", "s3"), (405, "one two three four", "es", "s4"), (406, "One two three four", "es", "s4")]
    rows += [(500, "\n".join(f"same line {i % 7}" for i in range(3000)), "en", "s4"), (501, _words(rng, 20000, 5000), "en", "s4")]
    rows += [(7, rows[7][1], "en", "s2"), (None, base, "en", "s0"), (None, None, None, None)]
    rng.shuffle(rows)
    return [(*r, len(r[1] or "")) for r in rows]


def _frame(spark, rows):
    df = spark.createDataFrame(rows, SCHEMA)
    return df.select("*", *(F.lit("x").alias(c) for c in EXTRA))


@pytest.fixture(scope="module")
def docs(spark, corpus):
    return _frame(spark, corpus).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return _frame(spark, [])


def _ws(text):
    return (text or "").encode().split()


_ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def _lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_context_mixing(docs, corpus, empty):
    got = context_mixing.score_documents(docs).collect()
    assert len(got) == len(corpus)
    trained = Counter()
    for d, text, *_ in corpus:
        if not context_mixing.is_held_out(d):
            trained.update([*(_lower(text).encode().split()), b""])
    n, v = sum(trained.values()), len(trained)
    want = Counter()
    for d, text, *_ in corpus:
        w = [*(_lower(text).encode().split()), b""]
        base = sum(math.log10((trained[x] + 1) / (n + v + 1)) for x in w)
        want[(d, d is not None and zlib.crc32(str(d).encode()) % 7 == 2, len(w), sum(trained[x] > 0 for x in w), n, round(base, 5))] += 1
    assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 5)) for r in got) == want
    assert all(r.score < 0 for r in got)
    assert context_mixing.score_documents(empty).count() == 0


def test_context_mixing_is_a_distribution():
    """Codes are complete, and a bit's two values have a total probability of one."""
    rng = np.random.default_rng(0)
    for n in (2, 3, 10, 500):
        _, length = context_mixing.huffman(rng.integers(1, 1000, n))
        assert (0.5**length).sum() == 1
    mixer = context_mixing.Mixer(3, 4, 4)
    for _ in range(5):
        x, gate, bit = rng.normal(0, 4, (200, 3)).astype(np.float32), rng.integers(0, 4, 200), rng.integers(0, 2, 200)
        both = 2.0 ** -mixer.code(x, gate, gate, bit, None) + 2.0 ** -mixer.code(x, gate, gate, 1 - bit, None)
        assert np.abs(both - 1).max() < 1e-4
        mixer.code(x, gate, gate, bit, np.ones(200, np.float32))
    speller = context_mixing.Speller([b"alpha", b"beta", b"gamma"])
    first = [bytes([b]) for b in range(256) if b != 32]
    one = speller.cost(first)
    assert (2.0**-one).sum() < 1


def test_context_mixing_learns(spark):
    rng = random.Random(1)
    rows = [(i, " ".join(rng.choices(["alpha", "beta", "gamma", "delta"], weights=[8, 4, 2, 1], k=80)), "en", "s", 0) for i in range(120)]
    got = context_mixing.score_documents(_frame(spark, rows)).where("held_out").agg(F.sum("score"), F.sum("n_tokens")).first()
    assert -got[0] / got[1] / context_mixing.LOG2_TO_LOG10 < 2.2  # the source has 1.6 bits a token; untrained bytes would take 48


def _chains(rng, follow, n):
    """Texts in which each word has two words that may follow."""
    out = []
    for _ in range(n):
        w = [rng.choice(sorted(follow))]
        while len(w) < 60:
            w.append(rng.choice(follow[w[-1]]))
        out.append(w)
    return out


def test_context_mixing_knows_the_order_of_words(spark):
    """Held-out texts score higher than their own words in another order, and the layout of the rows plays no part."""
    rng = random.Random(3)
    words = [f"w{i}" for i in range(60)]
    texts = _chains(rng, {w: rng.sample(words, 2) for w in words}, 300)
    held = [i for i in range(10_000) if context_mixing.is_held_out(i)]
    learned = [i for i in range(10_000) if not context_mixing.is_held_out(i)]
    rows = [(learned[k], " ".join(w)) for k, w in enumerate(texts[:260])]
    rows += [(held[2 * k], " ".join(w)) for k, w in enumerate(texts[260:])]
    rows += [(held[2 * k + 1], " ".join(rng.sample(w, len(w)))) for k, w in enumerate(texts[260:])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.score for r in context_mixing.score_documents(df.repartition(2)).collect()}
    better = [got[held[2 * k]] > got[held[2 * k + 1]] for k in range(40)]
    assert sum(better) == 40
    again = {r.doc_id: r.score for r in context_mixing.score_documents(df.repartition(7)).collect()}
    assert again == got


def test_context_mixing_sets_repeated_texts_apart(spark):
    """Many shards, one of them split for a large group of copies; texts that occur twice are far more likely than others."""
    rng = random.Random(4)
    rows = [(i, _words(rng, 80, 3000)) for i in range(400)]
    twice = [1000 + i for i in range(40) if not context_mixing.is_held_out(i)][:20]  # of learned documents
    rows += [(i, rows[i - 1000][1]) for i in twice]
    crowd = _words(rng, 80, 3000)
    rows += [(2000 + i, crowd) for i in range(200)]
    rows += [(5, rows[5][1]), (None, rows[6][1]), (None, None), (3000, ""), (3001, " \n")]
    got = context_mixing.score_documents(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), shard_bytes=20_000).collect()
    assert len(got) == len(rows) and all(r.score is not None for r in got)
    rate = {r.doc_id: r.score / r.n_tokens for r in got if r.doc_id is not None and r.n_tokens > 1}
    others = sorted(rate[i] for i in range(40, 400))
    assert min(rate[i] for i in twice) > others[-1] and min(rate[2000 + i] for i in range(200)) > others[-1]
    assert len({r.score for r in got if r.doc_id == 5}) == 1


def test_context_mixing_counts_the_whole_corpus(spark):
    """Small parts, some for words that need more than one, give nearly the scores of a single part: no count is of a sample."""
    rng = random.Random(8)
    words = [f"w{i}" for i in range(150)]
    texts = _chains(rng, {w: rng.sample(words, 3) for w in words}, 900)
    # a word before all others, the same pair and the same three words in every text
    rows = [(i, " ".join(["the " + x for x in w[:30]] + w[30:] + ["one two three"] * 5)) for i, w in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    small, whole = ({r.doc_id: r.score for r in context_mixing.score_documents(x, shard_bytes=size).collect()} for x, size in ((df.repartition(3), 4_000), (df, 64 << 20)))
    held = [i for i, _ in rows if context_mixing.is_held_out(i)]
    gap = [small[i] / whole[i] for i in held]
    assert 0.95 < sum(gap) / len(gap) < 1.1
    again = {r.doc_id: r.score for r in context_mixing.score_documents(df.repartition(5), shard_bytes=4_000).collect()}
    assert again == small


def test_substring_dedup(docs, corpus, empty):
    got = substring_dedup.dedup_substrings(docs).collect()
    first = {}
    for d, text, *_ in corpus:
        w = _ws(text)
        for i in range(len(w) - 49):
            k = tuple(w[i : i + 50])
            if d is not None:
                first[k] = min(d, first.get(k, d))
    want = Counter()
    for d, text, *_ in corpus:
        w = _ws(text)
        gone = [False] * len(w)
        for i in range(len(w) - 49):
            if d is not None and first[tuple(w[i : i + 50])] < d:
                gone[i : i + 50] = [True] * 50
        want[(d, len(w), sum(gone), b" ".join(x for x, g in zip(w, gone) if not g).decode())] += 1
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.kept) for r in got) == want
    assert any(0 < r.n_removed < r.n_words for r in got)
    assert substring_dedup.dedup_substrings(empty).count() == 0


def _line_brute(corpus, m):
    seen, out = {}, {}
    texts = sorted({(d, t) for d, t, *_ in corpus if d is not None and t is not None}, key=lambda x: x[0])
    for d, text in texts:
        lines = text.split("\n")
        idx = [i for i, x in enumerate(lines) if re.search(r"[^\x20\x09-\x0D]", x)]
        gone = set()
        for a in range(len(idx) - m + 1):
            k = tuple(lines[i] for i in idx[a : a + m])
            if k in seen:
                gone |= set(idx[a : a + m])
            seen.setdefault(k, (d, a))
        out[(d, text)] = ("\n".join(x for i, x in enumerate(lines) if i not in gone), len(idx), len(gone))
    return out


@pytest.mark.parametrize("m", [1, 2, 3, 5])
def test_line_dedup(docs, corpus, m):
    want = _line_brute(corpus, m)
    full = Counter()
    for d, t, *_ in corpus:
        n = len([x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)])
        full[(d, *want.get((d, t), (t, n, 0)))] += 1
    got = line_dedup.dedup_lines(docs, m)
    assert Counter((r.doc_id, r.text, r.n_lines, r.n_removed_lines) for r in got.collect()) == full
    assert set(EXTRA) <= set(got.columns)


def test_line_dedup_empty_and_longest(docs, empty, spark):
    assert line_dedup.dedup_lines(empty).count() == 0
    rows = [(1, "a\nb\nc\nd\ne", "", "", 0), (2, "x\na\nb\nc\nd\ny", "", "", 0)]
    got = {(r.id, r.place): r.lines for r in line_dedup.longest_repeats(_frame(spark, rows)).collect()}
    assert got == {(1, 0): 4, (1, 1): 2, (1, 2): 2, (1, 3): 1, (2, 1): 4, (2, 2): 2, (2, 3): 2, (2, 4): 1}


def test_host_quality_counts(docs, corpus, empty):
    want = Counter()
    for d, text, *_ in corpus:
        text = text or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", text)
        g = Counter(zip(w, w[1:], w[2:]))
        rep = {p for i in range(len(w) - 2) if g[tuple(w[i : i + 3])] > 1 for p in (i, i + 1, i + 2)}
        seen, dup = set(), 0
        for x in text.split("\n"):
            if re.search(r"[^\x20\x09-\x0D]", x):
                dup += x in seen
                seen.add(x)
        want[(d, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(rep), len(w) < 50 or 100 * len(rep) > 50 * len(w))] += 1
    got = host_quality.judge(docs).collect()
    assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got) == want
    assert not any(r.kept and r.base_failed for r in got)
    assert host_quality.judge(empty).count() == 0
    assert host_quality.filter_documents(docs).count() == sum(r.kept for r in got)


def test_host_verdicts(spark):
    good = " ".join(f"word{i}" for i in range(60))
    rows = [(i, "bad", "en", "junk", 3) for i in range(95)] + [(i, good, "en", "junk", 3) for i in range(95, 97)]
    rows += [(i, good, "en", f"h{i % 9}", 3) for i in range(200, 500)]
    got = host_quality.judge(_frame(spark, rows))
    assert {r[0] for r in got.where("source = 'junk'").select("host_verdict").distinct().collect()} == {"blocked"}
    assert got.where("kept").count() == 300


def test_decontaminate(spark, docs, corpus, empty):
    texts = {d: t for d, t, *_ in corpus}
    items = [("7", " ".join(texts[300].split()[42:58])), ("12", "ONE, two! three"), ("3", " ".join(texts[500].split()[:14])), ("9", None), ("10", " .. "), (None, "w1 w2"), ("12", "ONE, two! three"), ("8", "unseen words only")]
    bench = spark.createDataFrame(items, "item_id string, text string").withColumn("id", F.lit(1)).withColumn("key", F.lit(1))
    windows = {}
    for i, t in items:
        w = _ALNUM.findall(_lower(t))
        for k in range(len(w) - min(10, len(w)) + 1) if w and i is not None else ():
            windows.setdefault(tuple(w[k : k + min(10, len(w))]), set()).add(i)
    want = Counter()
    for d, t, *_ in corpus:
        w, hit, found = _ALNUM.findall(_lower(t)), set(), set()
        for size in {len(k) for k in windows}:
            for i in range(len(w) - size + 1):
                if x := windows.get(tuple(w[i : i + size])):
                    hit |= set(range(i, i + size))
                    found |= x
        want[(d, len(w), len(hit), tuple(sorted(found)), bool(hit))] += 1
    for bound in (50_000, 1):  # the broadcast set, and the shuffled join beyond its bound
        old, decontaminate.MAX_BROADCAST_WINDOWS = decontaminate.MAX_BROADCAST_WINDOWS, bound
        got = decontaminate.decontaminate(docs, bench).collect()
        decontaminate.MAX_BROADCAST_WINDOWS = old
        assert Counter((r.doc_id, r.n_words, r.n_hit, tuple(r["items"]), r.contaminated) for r in got) == want
    kept = decontaminate.drop_contaminated(docs, bench)
    assert kept.count() == sum(n for k, n in want.items() if not k[4]) and set(EXTRA) <= set(kept.columns)
    cut = {r.doc_id: r.clean_words for r in decontaminate.cut_spans(docs, bench).where("doc_id is not null").collect()}
    assert all(len(cut[k[0]]) == k[1] - k[2] for k in want if k[0] is not None)
    assert decontaminate.decontaminate(empty, bench).count() == 0
    assert decontaminate.decontaminate(docs, bench.limit(0)).where("contaminated").count() == 0


def test_glob_automaton():
    rng = random.Random(3)
    globs = [*(g for _, g in url_filter.GLOBS), "*", "", "a", "?", "a*b", "**a**", "a?b*", "*" + "abcdefghij" * 9, *("".join(rng.choices("ab*?", k=rng.randint(1, 9))) for _ in range(60))]
    texts = ["", "a", "ab", "b/login", "abcdefghij" * 10, *("".join(rng.choices("ab/.", k=rng.randint(0, 30))) for _ in range(300))]
    raw = np.frombuffer("".join(texts).encode(), np.uint8)
    offs = np.concatenate(([0], np.cumsum([len(t) for t in texts])))
    got = url_filter.GlobAutomaton(globs).match(raw, offs)
    for j, g in enumerate(globs):
        pattern = re.compile("".join(".*" if c == "*" else "." if c == "?" else re.escape(c) for c in g), re.S)
        assert [bool(pattern.fullmatch(t)) for t in texts] == got[:, j].tolist(), g


def test_url_rules(spark):
    rows = [(1, "https://a.Example.COM/en/7/x#f"), (2, "http://example.com/en/9"), (3, "http://x.net/de/1?u"), (4, "http://sub.example.net/de/8"), (5, "http://q.org/es/?utm_source=f"), (6, "http://q.io/a?utm_source=f"), (7, None), (8, "no scheme"), (9, "http://notcom/en/"), (10, "http://com?x"), (None, "x://h#/y")]
    df = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit(1)).withColumn("globs", F.lit(2))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(df).collect()}
    assert got[1] == ("a.example.com", "/en/7/x", "example.com/en/7", "allow")
    assert got[2][2:] == ("com/en/", "block") and got[3][2:] == ("net/de/", "allow") and got[4][2:] == ("example.net/de/8", "block") and got[5][2:] == ("org/es/", "block")
    assert got[6] == ("q.io", "/a", None, "block") and got[7] == ("", "", None, "allow") and got[8] == ("", "", None, "allow")
    assert got[9][2] is None and got[10] == ("com", "", None, "allow") and got[None] == ("h", "", None, "allow")
    assert url_filter.filter_urls(df.limit(0)).count() == 0


def test_url_globs_take_signs_literally(spark):
    long = "http://x.io/" + "a/" * 50_000 + "?utm_source=f"
    urls = ["http://x.io/docs/utm_source=x.html", "http://x.io/a?utm_source=x", "http://x.io/help/sessionid=explained", "http://x.io/?sessionid=1", long, long]
    got = [r.verdict for r in url_filter.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")).orderBy("page_id").collect()]
    assert got == ["allow", "block", "allow", "block", "block", "block"]
    automaton = url_filter.GlobAutomaton(["a?c", r"a\?c", r"*\*", "*\\\\"])
    raw = [b"abc", b"a?c", b"x*", b"x\\"]
    hits = automaton.match(np.frombuffer(b"".join(raw), np.uint8), np.concatenate(([0], np.cumsum([len(x) for x in raw]))))
    assert hits.tolist() == [[True, False, False, False], [True, True, False, False], [False, False, True, False], [False, False, False, True]]


def test_license_expressions():
    e = license_scan.evaluate
    assert e("MIT OR GPL-3.0-only") == (frozenset({"mit", "gpl"}), True)
    assert e("MIT AND GPL-3.0-only") == (frozenset({"mit", "gpl"}), False)
    assert e("MIT OR BSD-2-Clause AND GPL-2.0") == (frozenset({"mit", "bsd", "gpl"}), True)
    assert e("(MIT OR BSD-2-Clause) AND GPL-2.0") == (frozenset({"mit", "bsd", "gpl"}), False)
    assert e("GPL-2.0-only WITH Classpath-exception-2.0 OR Apache-2.0")[1]
    assert e("MIT and more text") == e("MIT") == e("MIT or so, as said") and e("see the file") is None
    assert e("MIT AND LicenseRef-own-1")[0] == {"mit", "other"}
    for bad in ("", "AND MIT", "MIT OR", "(MIT", "MIT)", "()"):
        assert e(bad) is None, bad


def test_license_scan(spark, docs, empty):
    rows = [
        (1, "Released under the MIT License. mit-license! Apache  LICENSE", "mit,apache", 3, 3, 7),
        (2, "the GNU General Public License, version 3", "gpl", 1, 2, 2),
        (3, "mitlicense apache", "", 0, None, None),
        (4, "# SPDX-License-Identifier: (MIT OR Apache-2.0) AND BSD-3-Clause\ncode", "", 0, None, None),
        (5, None, "", 0, None, None),
        (6, "", "", 0, None, None),
    ]
    got = {r.doc_id: r for r in license_scan.scan_licenses(spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string").withColumn("id", F.lit(0)).withColumn("labels", F.lit(0))).collect()}
    for i, _, labels, n, first, last in rows:
        r = got[i]
        assert (r.base_labels, r.n_base, r.first_word, r.last_word) == (",".join(sorted(filter(None, labels.split(",")))), n, first, last), i
        assert 0 <= r.score <= 1 and set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))
    assert got[4].labels == "apache,bsd,mit" and got[4].permissive and got[4].score > 0.9
    long = "mit license " * 40_000 + "SPDX-License-Identifier: Apache-2.0\n" * 2_000
    r = license_scan.scan_licenses(spark.createDataFrame([(1, long), (1, long)], "doc_id long, text string")).collect()
    assert len(r) == 2 and r[0] == r[1] and (r[0].n_base, r[0].last_word, r[0].labels) == (40_000, 79_998, "apache,mit")
    assert license_scan.scan_licenses(docs).count() == docs.count() and license_scan.scan_licenses(empty).count() == 0


def test_license_phrases_against_brute_force():
    rng = random.Random(8)
    parts = ["mit", "license", "apache", "general", "public", "gnu", "lesser", "cc", "by", "nc", "sa", "x", "MIT License", "all rights reserved"]
    automaton = license_scan.build_automaton()
    for _ in range(200):
        text = "".join(rng.choice(parts) + rng.choice(" -.\n") for _ in range(rng.randint(0, 40)))
        words = re.findall(r"[0-9a-z]+", text.lower())
        places = lambda p: [i for i in range(len(words)) if words[i : i + len(p.split())] == p.split()]
        base = {p: places(p) for p in license_scan.BASE_PHRASES}
        every = sorted(i for v in base.values() for i in v)
        held = {license_scan.BASE_PHRASES[p] for p, v in base.items() if v}
        more = {label for p, (label, _) in license_scan.NOTICES.items() if places(p)}
        got = license_scan.scan_text(text.encode(), automaton)
        assert got[:6] == (len(words), len(every), every[0] if every else None, every[-1] if every else None, ",".join(sorted(held)), ",".join(sorted(held | more)))


def test_piece_counter_is_greedy():
    rng = random.Random(2)
    for _ in range(60):
        pieces = {"".join(rng.choices("abc", k=rng.randint(1, 6))).encode() for _ in range(rng.randint(1, 25))}
        counter = word_pieces.PieceCounter(sorted(pieces))
        for _ in range(60):
            word = "".join(rng.choices("abcd" if rng.random() < 0.1 else "abc", k=rng.randint(1, 20))).encode()
            assert counter.count(word) == _greedy(word, pieces, pieces), (pieces, word)
            last = {p for p in pieces if p[0] != 97}
            assert word_pieces.PieceCounter(pieces, last).count(word) == _greedy(word, pieces, last), (pieces, last, word)


def test_word_pieces(docs, corpus, empty):
    got = word_pieces.count_pieces(docs, [b"w", b"1", b"2", b"12", b"line", b"same", *(str(i).encode() for i in range(10))])
    rows = {(r.doc_id, r.n_units) for r in got.collect()}
    assert {(d, len(re.findall(rb"[0-9a-z\x80-\xff]+|[^\s]", _lower(t).encode()))) for d, t, *_ in corpus} == rows
    assert word_pieces.count_pieces(empty, [b"a"]).count() == 0


def _greedy(word, inside, last):
    """Pieces of a word by the longest match; a piece that ends the word is one of ``last``."""
    at = n = 0
    while at < len(word):
        if word[at:] in last:
            return n + 1
        size = next((k for k in range(len(word) - at - 1, 0, -1) if word[at : at + k] in inside), 0)
        if not size:
            return 0
        at, n = at + size, n + 1
    return n


def test_vocabulary_with_word_ends(spark, docs, corpus):
    inside, last = word_pieces.read_vocabulary(VOCABULARY)
    counter = word_pieces.PieceCounter(inside, last)
    assert all(counter.count(bytes([b])) == 1 for b in range(256))
    assert [counter.count(w) for w in (b"the", b"conductance", b"const", b"ceil")] == [1, 3, 2, 2]
    inside, last = set(inside), set(last)
    want = Counter()
    for d, t, *_ in corpus:
        units = re.findall(rb"[0-9a-z\x80-\xff]+|[^\s]", _lower(t).encode())
        counts = [_greedy(u, inside, last) for u in units]
        want[(d, len(units), sum(counts) + counts.count(0), counts.count(0))] += 1
    got = word_pieces.count_pieces(docs.withColumn("n_tokens", F.lit("x")).withColumn("n_units", F.lit("x")), VOCABULARY)
    assert Counter((r.doc_id, r.n_units, r.n_tokens, r.n_unknown) for r in got.collect()) == want


def test_jaccard_join(docs, corpus, empty):
    sets = {}
    for d, text, *_ in corpus:
        w = _lower(text).encode().split()
        sets.setdefault(d, []).append(frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset())
    nodes = [(d, s) for d, l in sets.items() if d is not None for s in l if s]
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (d, s) in enumerate(nodes):
        for e, t in nodes[:i]:
            if 100 * len(s & t) >= 80 * len(s | t):
                a, b = find(d), find(e)
                root[max(a, b)] = min(a, b)
    want = Counter((d, len(s), None if d is None else find(d)) for d, l in sets.items() for s in l)
    got = jaccard_join.near_duplicates(docs)
    assert Counter((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()) == want
    assert jaccard_join.near_duplicates(empty).count() == 0


def _linked_roots(texts, threshold):
    """Smallest index that each text reaches, by all pairs."""
    sets = [frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) for w in (t.split() for t in texts)]
    root = list(range(len(sets)))
    for i, s in enumerate(sets):
        for j in range(i):
            if 100 * len(s & sets[j]) >= threshold * len(s | sets[j]):
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if r == old else r for r in root]
    return root


@pytest.mark.parametrize("threshold", [60, 80, 100])
def test_jaccard_families_lose_no_link(spark, threshold):
    """Families of near copies around the threshold, some without their base, under tokens that most texts have."""
    rng = random.Random(threshold)
    common = _words(rng, 30)
    texts = []
    for family in range(4):
        base = _words(rng, 45 + 20 * family, 10**6).split()
        for _ in range(40):
            w = list(base)
            for _ in range(rng.randint(0, 6)):
                at = rng.randrange(len(w))
                w[at : at + rng.randint(0, 2)] = [f"y{rng.randrange(4)}"] * rng.randint(0, 2)
            texts.append(f"{common} {' '.join(w)}" if rng.random() < 0.8 else " ".join(w))
    texts += [_words(rng, k) for k in (1, 2, 4, 5, 6, 7, 8)] * 2
    rng.shuffle(texts)
    got = jaccard_join.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5), threshold)
    assert [r.component_id for r in got.orderBy("doc_id").collect()] == _linked_roots(texts, threshold)


@pytest.mark.parametrize("bits", [40, 9])
def test_jaccard_keys_and_copies(spark, monkeypatch, bits):
    """Copies in other tasks, repeated rows, and tokens that share a key lose no link; a text's tokens go through the shuffle once."""
    monkeypatch.setattr(jaccard_join, "KEY_BITS", bits)
    monkeypatch.setattr(jaccard_join, "HELD_TOKENS", 300)
    v = np.sort(np.random.default_rng(bits).integers(0, 1 << (bits + jaccard_join.TEXT_BITS), 500, np.uint64))
    key, name = jaccard_join._unpack(jaccard_join._pack(7, v))
    assert (key == (v >> np.uint64(jaccard_join.TEXT_BITS))).all() and (name - 7 == (v & np.uint64((1 << jaccard_join.TEXT_BITS) - 1))).all()
    rng = random.Random(bits)
    texts = []
    for _ in range(30):
        base = _words(rng, 60, 10**6).split()
        texts.append(" ".join(base))
        for at in (20, 21, 40):
            texts.append(" ".join(base[:at] + ["z"] + base[at + 1 :]))
        texts += texts[-2:]
    rows = list(enumerate(texts)) + [(5, texts[5]), (5, texts[5])]
    held = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    got = {r.doc_id: r.component_id for r in jaccard_join.near_duplicates(held).collect()}
    assert [got[i] for i in range(len(texts))] == _linked_roots(texts, 80)


def test_jaccard_opens_few_groups_of_a_large_family(spark, monkeypatch):
    """Copies of one text with several edits share most tokens but are not linked: the matrix must not open a group for each pair."""
    rng = random.Random(3)
    base = _words(rng, 150, 10**6).split()
    texts = []
    for i in range(200):
        w = list(base)
        for at in rng.sample(range(150), 3):
            w[at] = f"e{i}x{at}"
        texts.append(" ".join(w))
    texts += [_words(rng, 40, 10**6) for _ in range(300)]
    asked = []

    def saved(df):
        out = common.saved(df)
        if out.columns[:2] == ["token", "a"]:
            asked.append(out.count())
        return out

    monkeypatch.setattr(jaccard_join, "saved", saved)
    got = jaccard_join.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3))
    assert [r.component_id for r in got.orderBy("doc_id").collect()] == _linked_roots(texts, 80)
    assert asked and asked[0] < 2000


def test_collided_fingerprints_take_the_second():
    a, b = np.arange(5, dtype=np.uint64), np.arange(6, dtype=np.uint64)
    held = frozenset({jaccard_join.fingerprint(a)})
    assert jaccard_join.text_key(a, held) == jaccard_join.fingerprint(a, 1) != jaccard_join.fingerprint(a)
    assert jaccard_join.text_key(b, held) == jaccard_join.fingerprint(b)


def test_keep_first_of_repeated_rows_and_ids(spark):
    near = " ".join(f"a{i}" for i in range(60))
    rows = [(1, near, "p"), (1, near, "q"), (1, near + " z", "p"), (2, near, "p"), (3, "alone here", "p"), (3, "alone here", "p"), (None, near, "p"), (None, near, "p"), (4, None, "p"), (4, " ", "p")]
    got = Counter((r.doc_id, r.text) for r in jaccard_join.keep_first(spark.createDataFrame(rows, "doc_id long, text string, root string")).collect())
    first = got.pop((1, near), 0) + got.pop((1, near + " z"), 0)
    assert first == 1 and got == {(3, "alone here"): 1, (None, near): 2, (4, None): 1, (4, " "): 1}


def test_mixing_fill():
    assert mixing.fill(100, [("a", 1, 10), ("b", 1, 1000), ("c", 2, 1000)]) == {"a": 10, "b": 30, "c": 60}
    assert mixing.fill(100, [("a", 1, 10), ("b", 1, 20)]) == {"a": 10, "b": 20}
    assert mixing.fill(100, [("a", 0, 10), ("b", 1, 500)]) == {"a": 0, "b": 100}
    assert mixing.fill(0, []) == {}


def test_mixing_shortage_goes_to_siblings_first():
    leaves = [("d1", "en", "a", 10), ("d1", "en", "b", 1000), ("d2", "en", "c", 1000)]
    got = mixing.budgets(leaves, 200, {}, 1.0)
    assert got == {("d1", "en", "a"): 10, ("d1", "en", "b"): 90, ("d2", "en", "c"): 100}


def test_mixing_fill_of_many_children():
    """Water level by search against the dealt amounts."""
    rng = random.Random(6)
    kids = [(str(i), rng.choice([0, 1, 2, 5]), rng.randint(0, 50)) for i in range(20_000)]
    got = mixing.fill(150_000, kids)
    level = max(got[n] / w for n, w, c in kids if w and got[n] < c - 1e-6)
    assert abs(sum(got.values()) - 150_000) < 1e-3
    assert all(abs(got[n] - min(c, level * w)) < 1e-6 for n, w, c in kids)


def _mixed(docs, **options):
    return sorted((r.doc_id is None, r.doc_id or 0, r.source, r.n_tokens, r.copies) for r in mixing.mix(docs, **options).collect())


def test_mixing(spark, docs, corpus, empty):
    options = {"budget_share": 0.5, "weights": {("s", "en", "s0"): 3.0}, "max_epochs": 2.0}
    rows = mixing.mix(docs, **options).collect()
    assert len(rows) == len(corpus) and {r.domain for r in rows} == {"s", "none"}
    leaves = {}
    for r in rows:
        leaves.setdefault((r.domain, r.lang, r.source), []).append(r)
    want = mixing.budgets([(*p, sum(r.n_tokens for r in held)) for p, held in leaves.items()], 0.5 * sum(r.n_tokens for r in rows), options["weights"], 2.0)
    for path, held in leaves.items():
        assert {r.leaf_take for r in held} == {want[path]} and {r.leaf_tokens for r in held} == {sum(r.n_tokens for r in held)}
        taken = sum(r.copies * r.n_tokens for r in held)
        assert taken <= held[0].leaf_take, path
        assert all(r.copies == 0 for r in held if r.n_tokens == 0)
        epochs = held[0].leaf_take // max(1, held[0].leaf_tokens)
        assert all(epochs <= r.copies <= epochs + 1 for r in held if r.n_tokens)
        # the prefix stops only at a document that doesn't fit
        left = [r.n_tokens for r in held if r.n_tokens and r.copies == epochs]
        assert not left or held[0].leaf_take - taken < max(left) or taken == held[0].leaf_take
    assert mixing.mix(empty).count() == 0 and mixing.select_documents(empty).count() == 0
    chosen = mixing.select_documents(docs, **options)
    assert set(docs.columns) <= set(chosen.columns) and chosen.where("copies < 1").count() == 0
    assert sorted(r.copies for r in chosen.collect()) == sorted(r.copies for r in rows if r.copies)


def test_mixing_of_repeated_ids_and_rows_keeps_budgets(spark):
    """The same choice for every layout, and no budget is broken, however rows repeat."""
    rng = random.Random(2)
    rows = [(i % 7, _words(rng, rng.randint(1, 12)), "en", "a") for i in range(300)] + [(9, "same words here", "en", "a")] * 200 + [(None, _words(rng, 5), "en", "b") for _ in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    want = _mixed(df, budget_share=0.3)
    for parts in (1, 5, 9):
        assert _mixed(df.repartition(parts), budget_share=0.3) == want
    chosen = mixing.select_documents(df, budget_share=0.3)
    total = sum(len(t.split()) for _, t, *_ in rows)
    taken = sum(len(r.text.split()) * r.copies for r in chosen.collect())
    assert 0.28 * total < taken <= 0.3 * total
    assert chosen.where("doc_id is null").count() > 0


def test_keep_first_and_pipeline_stages(spark, docs, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    docs.select(*SCHEMA_COLUMNS).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, " ".join(docs.where("doc_id = 300").first().text.split()[:20]))], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, rows, str(tmp_path))
        assert out.columns == rows.columns, name
        rows = corpus_pipeline.saved(out)
    assert rows.where("doc_id = 300").count() == 0
    assert rows.where("doc_id between 100 and 105 or doc_id between 200 and 220").count() == 1
    ids = {r.doc_id for r in rows.select("doc_id").collect()}
    final = corpus_pipeline.run(spark, str(tmp_path))
    assert {r.doc_id for r in final.select("doc_id").collect()} <= ids
    digest = hashlib.sha256(b"".join(sorted(str(r.doc_id).encode() for r in final.collect()))).hexdigest()
    again = hashlib.sha256(b"".join(sorted(str(r.doc_id).encode() for r in corpus_pipeline.run(spark, str(tmp_path)).collect()))).hexdigest()
    assert digest == again


SCHEMA_COLUMNS = [c.split()[0] for c in SCHEMA.split(", ")]


def test_symbols_are_found_by_the_first_bits_of_their_hashes():
    """Words that share their first 20 bits, unknown ones beside them, and a vocabulary that was sent to another process."""
    import pickle

    from proxgraph.llm import context_mixing

    words = context_mixing.Vocabulary([f"w{i}".encode() for i in range(5000)] + [b""], np.arange(5001)[::-1] + 1, 3)
    near = words.hashes[:2500] ^ np.uint64(1)
    words.hashes = np.sort(np.concatenate([words.hashes[:2500], near, words.hashes[2500:2501]]))
    asked = np.concatenate([words.hashes, words.hashes ^ np.uint64(2), words.hashes + np.uint64(1 << 50), np.array([0, 2**64 - 1], np.uint64)])
    at = np.minimum(np.searchsorted(words.hashes, asked), len(words.hashes) - 1)
    want = np.where(words.hashes[at] == asked, words.symbol[at], words.escape)
    assert words.begin is None
    assert np.array_equal(words.symbols(asked), want)
    assert words.most >= 2 and np.array_equal(pickle.loads(pickle.dumps(words)).symbols(asked), want)
