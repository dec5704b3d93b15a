import random
from collections import Counter

import pytest

from graphloop.llm import suffix_dedup


def brute_force(rows, length):
    raws = [(text or "").encode() for _, text in rows]
    counts = Counter(r[i : i + length] for r in raws for i in range(len(r) - length + 1))
    out = []
    for (doc, _), r in zip(rows, raws, strict=True):
        gone = bytearray(len(r))
        for i in range(len(r) - length + 1):
            if counts[r[i : i + length]] > 1:
                gone[i : i + length] = b"\x01" * length
        kept = bytes(b for b, g in zip(r, gone, strict=True) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        out.append((doc, len(r), sum(gone), spans, kept))
    return sorted(out, key=repr)


def run(spark, rows, **options):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = suffix_dedup.dedup_passages(df, **options).collect()
    return sorted(((r.id, r.n_bytes, sum(s.stop - s.start for s in r.spans), len(r.spans), bytes(r.kept)) for r in found), key=repr)


def texts(seed, alphabet, n, most):
    rng = random.Random(seed)
    passages = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(10, most // 2))) for _ in range(8)]
    made = []
    for _ in range(n):
        parts = [rng.choice(passages) if rng.random() < 0.3 else "".join(rng.choice(alphabet) for _ in range(rng.randrange(1, most // 3))) for _ in range(rng.randrange(1, 6))]
        made.append("".join(parts))
        if rng.random() < 0.2:
            text = list(rng.choice(made))
            if text:
                text[rng.randrange(len(text))] = rng.choice(alphabet)
            made.append("".join(text))
    return made


@pytest.mark.parametrize("seed", [1, 2])
def test_equals_brute_force(spark, seed, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SEGMENT", 300)
    monkeypatch.setattr(suffix_dedup, "CHUNK", 3000)
    made = texts(seed, "abcdefghij éß" if seed == 1 else "ab", 60, 240)
    rows = list(enumerate(made)) + [(900, None), (901, ""), (902, "a" * 130), (903, "xyz" * 40), (904, "short")]
    assert run(spark, rows, length=24, gram=7) == brute_force(rows, 24)


def test_production_parameters(spark):
    made = texts(7, "abcdefghijklmnopqrstuvwxyz \n", 50, 2400)
    rows = list(enumerate(made + made[:3]))
    assert run(spark, rows) == brute_force(rows, 200)


def test_repeated_rows_and_empty(spark):
    rows = [(1, "q" * 10 + "0123456789" * 21), (1, "q" * 10 + "0123456789" * 21), (None, "x" * 10)]
    assert run(spark, rows) == brute_force(rows, 200)
    assert run(spark, []) == []


def test_merge_keeps_order_and_prefixes():
    rng = random.Random(5)
    for n_runs in (1, 2, 3, 5, 8):
        runs = [sorted("".join(rng.choice("ab") for _ in range(rng.randrange(1, 9))).encode() for _ in range(rng.randrange(0, 20))) for _ in range(n_runs)]

        def coded(run):
            before = b""
            for s in run:
                yield s, suffix_dedup._common(before, s, 0)
                before = s

        got = list(suffix_dedup.merge_runs([coded(r) for r in runs]))
        assert [s for _, s, _ in got] == sorted(s for r in runs for s in r)
        assert all(got[i][2] == suffix_dedup._common(got[i - 1][1], got[i][1], 0) for i in range(1, len(got)))


def test_a_shared_start_does_not_make_one_range(spark):
    """Suffixes that begin alike for 24 bytes and more are still dealt to several ranges."""
    rng = random.Random(31)
    head = "".join(rng.choice("abcdefgh") for _ in range(150))
    tails = ["".join(rng.choice("abcdefgh ") for _ in range(120)) for _ in range(60)]
    rows = [(k, head + tails[k % 60]) for k in range(180)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    texts = df.selectExpr("xxhash64(text) AS dk", "hash(text) AS chk", "text").distinct()
    found = suffix_dedup.repeated_anchors(suffix_dedup.find_anchors(texts, 200, 40))
    sample = suffix_dedup.splitters(texts, found, found.count(), 40)
    assert len(suffix_dedup.cut_ranges(sample["suffix"], 8)) == 7 or len(set(sample["suffix"])) < 7
    assert run(spark, rows) == brute_force(rows, 200)
