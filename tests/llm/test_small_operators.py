"""Odd rows of the operators that SQL checks at scale: nulls, empties, repeats, clashing names, empty tables."""

import hashlib
import re

import duckdb
import pytest
from pyspark.sql import functions as F

from graphloop.llm import fingerprint, kneser_ney, language_id, line_dedup, mixing, near_dup, quality_rules, registry, suffix_dedup, url_filter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [(1, None, None), (2, "", "a"), (3, "a\n\nb", "a"), (3, "a\n\nb", "a"), (None, "a", None), (4, " \t ", "b"), (5, "x" * 70 + "é漢\U0001f600" * 30 + "\nend", "b")]


def frame(spark, rows=ODD, schema="doc_id long, text string, source string"):
    return spark.createDataFrame(rows, schema)


# Line dedup


def test_lines(spark):
    rows = [(k, f"Common line \nown {k}\n\n  COMMON LINE\nrare") for k in range(12)] + [(100, None), (101, ""), (102, "common line"), (102, "common line"), (None, "Common line\nx")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_lines", F.lit("clash"))
    out = {(r.doc_id, r.text): r for r in line_dedup.dedup_lines(df, threshold=13).collect()}
    assert out[(0, "own 0\n\nrare")].n_dropped == 2 and out[(0, "own 0\n\nrare")].n_lines == 5
    assert out[(100, "")].n_lines == 1 and out[(100, "")].n_dropped == 0
    assert out[(102, "")].n_dropped == 1
    assert out[(None, "x")].n_dropped == 1
    assert line_dedup.dedup_lines(df.where("false")).count() == 0
    assert {r.n_dropped for r in line_dedup.dedup_lines(df, threshold=99).collect()} == {0}


def test_lines_fold_ascii_only(spark):
    rows = [(k, "\x0béCOLE a\x0c") for k in range(5)] + [(k + 5, "École a") for k in range(5)] + [(k + 10, "École A") for k in range(5)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    dropped = {r.doc_id: r.n_dropped for r in line_dedup.dedup_lines(df, threshold=10).collect()}
    assert [dropped[k] for k in (0, 5, 10)] == [0, 1, 1]


def test_runs_are_compacted(spark):
    runs = line_dedup.LineRuns(threshold=3, fanout=2)
    for k in range(5):
        runs.add(spark.createDataFrame([(1, 1), (2, k)], "h1 long, h2 long"))
    assert [len(level) for level in runs.levels] == [1, 0, 1]
    assert [tuple(r) for r in runs.frequent().collect()] == [(1, 1)]
    with pytest.raises(ValueError):
        line_dedup.LineRuns(threshold=0)


# Mixing


def plain_targets(sizes, weights, epochs):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[k % len(weights)] for k, s in enumerate(order)}
    total, capped = sum(sizes.values()), set()
    while True:
        room = total - sum(epochs * sizes[s] for s in capped)
        free = [s for s in order if s not in capped]
        share = {s: room * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] >= epochs * sizes[s]}
        if not over:
            return {s: float(epochs * sizes[s]) if s in capped else share[s] for s in order}
        capped |= over


def test_targets_and_shares(spark):
    rows = [(k, "w " * (k % 7 + 1), s) for k, s in enumerate((["big"] * 300 + ["mid"] * 60 + [None] * 9 + ["tiny"] * 3) * 2)]
    out = mixing.mix(frame(spark, rows)).collect()
    sizes = {}
    for _, text, s in rows:
        sizes[s] = sizes.get(s, 0) + len(text.split())
    expected = plain_targets(sizes, [5, 2, 1], 3)
    taken = {}
    for r in out:
        assert r.source_size == sizes[r.source] and abs(r.target - expected[r.source]) < 1e-6
        assert 0 <= r.taken <= 3 * r.size and r.taken == r.copies * r.size
        taken[r.source] = taken.get(r.source, 0) + r.taken
    assert sum(taken.values()) <= sum(sizes.values())
    assert all(abs(taken[s] - expected[s]) <= 14 for s in sizes)
    again = mixing.mix(frame(spark, rows).repartition(5)).collect()
    assert sorted((r.id, r.copies) for r in out) == sorted((r.id, r.copies) for r in again)


def test_mix_odd_rows(spark):
    out = mixing.digest(mixing.mix(frame(spark).withColumn("size", F.lit("clash")))).collect()
    assert len(out) == len(ODD)
    assert {r.doc_id: r.size for r in out} == {1: 0, 2: 0, 3: 2, None: 1, 4: 0, 5: 2}
    assert mixing.mix(frame(spark, [])).count() == 0
    with pytest.raises(ValueError):
        mixing.mix(frame(spark), max_epochs=0)


# Fingerprints


def test_fingerprints_odd_rows(spark):
    rows = fingerprint.digest(fingerprint.compare_with_edits(frame(spark))).collect()
    assert len(rows) == len(ODD)
    by_text = {}
    for r in rows:
        by_text.setdefault((r.doc_id), set()).add(r.fingerprint)
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    assert len(by_text[3]) == 1 and by_text[1] == by_text[2]
    order = sorted([(d, t or "") for d, t, _ in ODD], key=lambda x: (x[0] is None, -(x[0] or 0), x[1]))
    edits = set()
    for k, (doc, text) in enumerate(order):
        following = order[(k + 1) % len(order)][1]
        half = len(text) // 2
        edits.add((doc, len(text), hashlib.sha256((text[: len(text) - half] + following[:half]).encode()).hexdigest()))
    assert {(r.doc_id, r.n_chars, r.edited_sha256) for r in rows} == edits


def test_next_over_many_ranges(spark, monkeypatch):
    monkeypatch.setattr(fingerprint, "ROWS_A_RANGE", 3)
    ids = [k * k for k in range(40)]
    df = spark.createDataFrame([(i, f"t{i}") for i in ids], "id long, text string")
    out = {r.id: r.next_text for r in fingerprint.with_next(df, "id", ["text"]).collect()}
    assert out == {i: f"t{ids[k - 1]}" for k, i in enumerate(ids)}
    one = fingerprint.with_next(df.where("id = 0"), "id", ["text"]).first()
    assert one.next_text == "t0"
    assert fingerprint.with_next(df.where("false"), "id", ["text"]).count() == 0


def test_next_over_clustered_and_extreme_ids(spark, monkeypatch):
    monkeypatch.setattr(fingerprint, "ROWS_A_RANGE", 2)
    ids = sorted({-(2**63), 2**63 - 1, 0, *range(5_000_000, 5_000_060)})
    df = spark.createDataFrame([(i, f"t{i}") for i in ids] + [(None, "none")], "id long, text string")
    out = {r.id: r.next_text for r in fingerprint.with_next(df, "id", ["text"]).collect()}
    assert out[ids[0]] == "none" and out[None] == f"t{ids[-1]}"
    assert all(out[i] == f"t{before}" for before, i in zip(ids[:-1], ids[1:], strict=True))


def test_edits_are_located(spark):
    lines = [f"line {k}" for k in range(50)]
    changed = list(lines)
    changed[3], changed[40] = "other", "another"
    old = fingerprint.fingerprints(spark.createDataFrame([(1, "\n".join(lines)), (2, "same")], "doc_id long, text string"))
    new = fingerprint.fingerprints(spark.createDataFrame([(1, "\n".join([*changed, "more"])), (2, "same")], "doc_id long, text string"))
    assert sorted(tuple(r) for r in fingerprint.locate_edits(old, new).collect()) == [(1, 0, 3), (1, 2, 40), (1, 3, 50)]


# Quality rules


def plain_repeats(words):
    n, seen = len(words), {}
    for i in range(n - 7):
        seen.setdefault(tuple(words[i : i + 8]), []).append(i)
    return len({p for at in seen.values() if len(at) > 1 for i in at for p in range(i, i + 8)})


def test_measures_equal_a_plain_version():
    import random

    rng = random.Random(2)
    texts = ["", None, "a " * 30, "A B\nA B\n\n|x| #1!", "\u2028x y", "z" * 500]
    texts += [" ".join(rng.choice("abc") for _ in range(rng.randrange(1, 80))) for _ in range(60)]
    for text in texts:
        got = dict(zip(quality_rules.MEASURES, quality_rules.measure_text(text), strict=True))
        words = WORD.findall(text or "")
        lines = [x for x in (text or "").split("\n") if WORD.search(x)]
        assert got["n_words"] == len(words) and got["word_chars"] == sum(map(len, words))
        assert got["n_symbols"] == sum(c in "#*$%&|<>" for c in text or "")
        assert got["n_repeat_words"] == plain_repeats(words)
        assert got["n_dup_lines"] == len(lines) - len(set(lines))


def test_ledger_policies_and_ablation(spark):
    good = "A plain sentence of words that goes on for long enough to be kept by all rules of the strict policy here."
    rows = [(1, good, "a"), (2, "short", "a"), (3, good.upper(), "b"), (4, "go " * 40, "b"), (5, None, None), (6, good, "a")]
    judged = quality_rules.ledger(frame(spark, rows).withColumn("failed", F.lit("clash")))
    kept = {r.doc_id for r in judged.where(quality_rules.passes(quality_rules.STRICT)).collect()}
    assert kept == {1, 6}
    table = {(r.policy, r.rule): r for r in quality_rules.ablation(judged).collect()}
    assert table[("strict", "shouting")].n_only == 1 and table[("strict", "shouting")].n_kept == 2
    assert table[("base", "few_words")].n_failed == 2 and table[("base", "few_words")].n_docs == 6
    assert quality_rules.digest(frame(spark, [])).count() == 0


# URL filter

RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("block", "example.com", ""), ("allow", "b.org", "/x"), ("block", "b.org", "/x")]


def test_urls(spark):
    rules = [url_filter.UrlRule(*r) for r in RULES]
    cases = {
        "http://A.example.COM/en/71?q#f": ("a.example.com", "/en/71", "example.com/en/7", "allow"),
        "http://example.com": ("example.com", "", "example.com", "block"),
        "x://other.com/en/": ("other.com", "/en/", "com/en/", "block"),
        "x://other.com/en": ("other.com", "/en", None, "allow"),
        "http://notexample.net/en/": ("notexample.net", "/en/", None, "allow"),
        "http://b.org/x": ("b.org", "/x", "b.org/x", "allow"),
        "http://h?x=/en/": ("h", "", None, "allow"),
        "no scheme": ("", "", None, "allow"),
        "": ("", "", None, "allow"),
        None: ("", "", None, "allow"),
    }
    df = spark.createDataFrame([(k, u, "clash") for k, u in enumerate(cases)], "page_id long, url string, host string")
    out = {r.url: (r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(df, rules).collect()}
    assert out == cases
    assert url_filter.filter_urls(df.where("false"), rules).count() == 0
    with pytest.raises(ValueError):
        url_filter.UrlTrie([url_filter.UrlRule("deny", "a")])


def test_the_rules_of_the_query_are_those_of_the_contract(spark, tmp_path):
    contract = {("com", "/en/"): "block", ("example.com", "/en/7"): "allow", ("net", "/de/"): "allow", ("example.net", "/de/8"): "block", ("org", "/es/"): "block"}
    assert {(r.host, r.path): r.action for r in registry.URL_RULES} == contract
    rows = [(k, f"http://www.{host}{path}x") for k, (host, path) in enumerate(contract)] + [(9, "http://example.net/de/7")]
    spark.createDataFrame(rows, "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    mine = {r.page_id: (r.rule, r.verdict) for r in registry.op7_url_filter(spark, str(tmp_path)).collect()}
    assert mine == {k: (host + path, action) for k, ((host, path), action) in enumerate(contract.items())} | {9: ("net/de/", "allow")}
    db = duckdb.connect()
    db.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet/*.parquet'")
    assert {r[0]: (r[3], r[4]) for r in db.execute(registry.oracle_sql()["op7_url_filter"]).fetchall()} == mine


# Columns of the user's own, named like anything an operator may use within


def test_other_columns_pass_through(spark):
    names = ["_row", "row", "drop", "_drop", "kept", "_kept", "judged", "_judged", "measured", "_m", "Start", "range"]
    df = spark.createDataFrame([(1, "a b\nc", "http://x.com/en/", *names), (2, None, None, *names)], ["doc_id", "text", "url", *names])
    for out in (line_dedup.dedup_lines(df, threshold=2), url_filter.filter_urls(df, []), quality_rules.ledger(df), language_id.identify(df, None)):
        assert [tuple(r) for r in out.select(*names).collect()] == [tuple(names)] * 2
    upper = df.withColumn("HOST", F.lit("mine")).withColumn("N_Lines", F.lit("mine")).withColumn("Score", F.lit("mine")).withColumn("Failed", F.lit("mine"))
    for out in (line_dedup.dedup_lines(upper), url_filter.filter_urls(upper, []), quality_rules.ledger(upper), language_id.identify(upper, None)):
        assert out.count() == 2
    odd = df.withColumn("source", F.lit("s"))
    assert mixing.mix(odd).count() == 2 and fingerprint.fingerprints(odd).count() == 2
    assert near_dup.near_duplicates(odd).count() == 2 and suffix_dedup.dedup_passages(odd).count() == 2
    assert kneser_ney.classify(odd.withColumn("lang", F.lit("en")), df.selectExpr("doc_id AS id")).count() == 2


def test_hot_lines_are_found_by_broadcast_and_by_join(spark, monkeypatch):
    rows = [(k, f"everywhere\nsometimes {k % 7}\nown {k}") for k in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    expected = {k: f"own {k}" for k, _ in rows}
    for share in (1, 8, 100_000):
        monkeypatch.setattr(line_dedup, "HOT_SHARE", share)
        assert {r.doc_id: r.text for r in line_dedup.dedup_lines(df).collect()} == expected


def test_late_copies_meet_in_no_task(spark, monkeypatch):
    monkeypatch.setattr(mixing, "ROWS_A_BUCKET", 50)
    rows = [(k, "w " * (k % 5 + 1), "big" if k % 20 else "tiny") for k in range(3000)]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    taken = {}
    for r in out:
        taken[r.source] = taken.get(r.source, 0) + r.taken
    targets = {r.source: r.target for r in out}
    assert all(abs(taken[s] - targets[s]) <= 10 for s in targets)


def test_rules_of_many_lengths_share_a_node():
    trie = url_filter.UrlTrie([url_filter.UrlRule("block", "a.com", "/x"), url_filter.UrlRule("allow", "a.com", "/xyz"), url_filter.UrlRule("block", "com", "/xyzzy")])
    assert [trie.match("a.com", p)[0] for p in ("/x", "/xy", "/xyz", "/xyzzy", "/w", "")] == ["a.com/x", "a.com/x", "a.com/xyz", "a.com/xyz", None, None]
    assert trie.match("b.com", "/xyzzy/1") == ("com/xyzzy", "block")


def test_likeness_follows_the_branches(spark):
    import random

    rng = random.Random(3)
    lines = [" ".join(rng.choice("lorem ipsum dolor sit amet elit sed do eiusmod".split()) + str(rng.randrange(99)) for _ in range(30)) for _ in range(60)]
    inserted = [*lines[:20], lines[20].replace(" ", " word ", 1), *lines[21:]]
    cases = {1: lines, 2: inserted, 3: lines[:30] + [x[::-1] for x in lines[30:]], 4: [x[::-1] for x in lines], 5: ["new line", *lines]}
    df = spark.createDataFrame([(k, "\n".join(x)) for k, x in cases.items()], "id long, text string")
    base = fingerprint.with_tree(df.where("id = 1"), F.col("text"))
    other = fingerprint.with_tree(df, F.col("text"), "o_").withColumnRenamed("id", "other").drop("text")
    found = {r.other: r.near for r in base.crossJoin(other).select("other", fingerprint.likeness("", "o_").alias("near")).collect()}
    assert found[1] == 1.0 and 0.98 < found[2] < 1.0 and 0.4 < found[3] < 0.6 and found[4] < 0.1
    assert found[5] > 0.95  # all sections shift by a line, and their spans are still found
