import random
import re

import pytest

from graphloop.llm import near_dup


def brute_force(rows, width, percent):
    sets = []
    for _, text in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
        grams = {tuple(words[i : i + width]) for i in range(len(words) - width + 1)}
        sets.append(grams if len(words) >= width else {tuple(words)} if words else set())
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j]:
                common = len(sets[i] & sets[j])
                if 100 * common >= percent * (len(sets[i]) + len(sets[j]) - common):
                    up[find(i)] = find(j)
    least = {}
    for i, (doc, _) in enumerate(rows):
        if doc is not None:
            least[find(i)] = min(doc, least.get(find(i), doc))
    return sorted((rows[i][0], len(sets[i]), least.get(find(i))) for i in range(len(rows)))


def corpus(seed, groups, singles):
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(3000)]
    rows = []

    def add(text):
        rows.append((len(rows), text))

    for size, edits in groups:
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(40, 200))]
        for _ in range(size):
            words = list(base)
            for _ in range(rng.randrange(edits + 1)):
                words[rng.randrange(len(words))] = rng.choice(vocabulary)
            add(" ".join(words))
    for _ in range(singles):
        add(" ".join(rng.choice(vocabulary) for _ in range(rng.randrange(1, 120))))
    for text in ("", None, " \n ", "One", "one", "two words", "Two  Words", "a b c", "A B C d"):
        add(text)
    rng.shuffle(rows)
    return rows


def check(spark, rows, width, percent, **options):
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumnRenamed("doc_id", "doc_id")
    found = near_dup.near_duplicates(df, width=width, percent=percent, **options).collect()
    got = sorted(((r.id, r.n_shingles, r.component) for r in found), key=lambda r: r[0])
    assert got == brute_force(rows, width, percent)
    assert all(r.kept == (r.id == r.component) for r in found)


@pytest.mark.parametrize("seed", [1, 2])
def test_equals_brute_force(spark, seed):
    check(spark, corpus(seed, [(12, 2), (5, 1), (3, 0), (8, 6), (2, 1)] * 3, 60), 3, 85)


def test_large_group_in_blocks(spark):
    check(spark, corpus(4, [(150, 4), (40, 0), (60, 9)], 30), 3, 85, leaf=8, depth=2, block=16)


def test_nulls_repeats_and_empty(spark):
    df = spark.createDataFrame([(None, "a b c d"), (None, "a b c d"), (7, "a b c d"), (7, "a b c d"), (8, None)], "doc_id long, text string")
    got = sorted(map(str, near_dup.near_duplicates(df, width=3, percent=85).select("id", "component", "kept").collect()))
    assert got == sorted(["Row(id=None, component=7, kept=False)"] * 2 + ["Row(id=7, component=7, kept=True)"] * 2 + ["Row(id=8, component=8, kept=True)"])
    assert near_dup.near_duplicates(df.where("false")).count() == 0


@pytest.mark.parametrize("percent, trees", [(80, 5), (85, 4)])
def test_trees_keep_the_promise_at_the_deepest_level(percent, trees):
    assert near_dup.tree_count(percent) == trees
    assert near_dup.miss_probability(percent, trees, 2, 4) < 0.0001 < near_dup.miss_probability(percent, trees - 1, 2, 4)


def test_derived_trees_are_used(spark, monkeypatch):
    used, plain = [], near_dup.candidates
    monkeypatch.setattr(near_dup, "candidates", lambda sets, percent, trees, **more: used.append(trees) or plain(sets, percent, trees, **more))
    near_dup.near_duplicates(spark.createDataFrame([(1, "a b c")], "doc_id long, text string"))
    assert used == [5]


def test_cells_never_rule_out_a_link():
    rng = near_dup.np.random.Generator(near_dup.np.random.PCG64(1))
    for size in (1, 5, 60, 4000):
        a = rng.integers(0, 2**63, size, dtype=near_dup.np.uint64)
        b = near_dup.np.concatenate([a[: size // 2 + 1], rng.integers(0, 2**63, size // 2, dtype=near_dup.np.uint64)])
        assert near_dup.np.minimum(near_dup.cells(a), near_dup.cells(b)).sum() >= len(near_dup.np.intersect1d(a, b))


def test_pairs_at_the_threshold_are_found(spark):
    """Many lone pairs whose similarity is from 80 to 86 hundredths: none is lost."""
    rng = random.Random(21)
    rows, pairs = [], 0
    for k in range(300):
        words = [f"{rng.randrange(10**6)}" for _ in range(200)]
        other = list(words)
        for at in rng.sample(range(10, 190), 6):
            other[at] = "x"
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(other))]
    found = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=3, percent=80).collect()
    got = {r.id: r.component for r in found}
    for (i, a), (j, b) in zip(rows[::2], rows[1::2], strict=True):
        x, y = ({tuple(t.split()[n : n + 3]) for n in range(198)} for t in (a, b))
        linked = 100 * len(x & y) >= 80 * len(x | y)
        pairs += linked
        assert (got[j] == i) == linked
    assert pairs > 200


def test_group_of_thousands_with_apart_members(spark):
    """A chain of 1,500 near copies: the first and the last are nothing alike, and most are apart from the hub."""
    rng = random.Random(22)
    words = [f"{rng.randrange(10**6)}" for _ in range(80)]
    rows = []
    for k in range(1500):
        rows.append((k, " ".join(words)))
        words[(7 * k) % 80] = f"{rng.randrange(10**6)}"
    out = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=3, percent=85, leaf=4, depth=1, block=64).collect()
    assert {r.component for r in out} == {0}


def test_connected_nodes_do_not_branch(spark, monkeypatch):
    """Near copies of one text are connected after a level; the links of texts that chain through crowded nodes are kept."""
    rng = random.Random(23)
    base = [f"{rng.randrange(10**6)}" for _ in range(300)]
    copies = [(k, " ".join([*base, str(k)])) for k in range(400)]
    written, plain = [], near_dup.stored
    monkeypatch.setattr(near_dup, "stored", lambda df: written.append(plain(df)) or written[-1])
    out = near_dup.near_duplicates(spark.createDataFrame(copies, "doc_id long, text string")).collect()
    assert {r.component for r in out} == {0}
    levels = [df.count() for df in written if "size" in df.columns and "sig" in df.columns]
    assert 0 < levels[0] <= 400 * 5 * 2 and sum(levels[1:]) < levels[0]
    monkeypatch.undo()
    check(spark, corpus(24, [(200, 1), (80, 8), (30, 16)], 20), 3, 85, leaf=4)


def test_sets_apart_do_not_keep_crowded_nodes_branching(spark, monkeypatch):
    """Copies of one text and a few texts half like it: their nodes end at once, where all of a node went on to every level before."""
    rng = random.Random(25)
    base = [f"{rng.randrange(10**6)}" for _ in range(120)]
    rows = [(k, " ".join([*base, str(k)])) for k in range(600)]
    rows += [(600 + k, " ".join(base[:80] + [f"{rng.randrange(10**6)}" for _ in range(20)])) for k in range(30)]
    rows += [(630, " ".join(base[:80] + rows[629][1].split()[80:] + ["end"]))]
    written, plain = [], near_dup.stored
    monkeypatch.setattr(near_dup, "stored", lambda df: written.append(plain(df)) or written[-1])
    check(spark, rows, 3, 85, block=64)
    crowded = [df.where("size > 32").count() for df in written if "size" in df.columns and "sig" in df.columns]
    assert crowded[0] > 600 and sum(crowded[1:]) <= 2 * crowded[0]


def test_unlike_sets_of_a_crowded_node_are_no_candidates(spark, monkeypatch):
    """Texts that share a passage, none alike: they meet in crowded nodes to the last level, where all were candidates of one hub before."""
    rng = random.Random(26)
    base = [f"{rng.randrange(10**6)}" for _ in range(60)]
    rows = [(k, " ".join(base + [f"{rng.randrange(10**6)}" for _ in range(50)])) for k in range(300)]
    groups, plain = [], near_dup.confirmed
    monkeypatch.setattr(near_dup, "confirmed", lambda texts, *more: groups.append(texts.count()) or plain(texts, *more))
    check(spark, rows, 3, 85)
    assert groups[0] < 100


@pytest.mark.parametrize("way", ["all", "guests", "hub"])
def test_links_of_blocks(spark, way):
    """Blocks of each way connect what they promise: all that is alike, guests with what is like them, everything to the hub."""
    rng = near_dup.np.random.Generator(near_dup.np.random.PCG64(3))
    sigs = {kind: rng.integers(0, 2**16, 64, dtype="uint16").tobytes() for kind in "abc"}
    rows = [(7, 0, int(k == 0), k, 100, sigs[kind], 1 if k == 1 else k) for k, kind in enumerate("aabbca")]
    df = spark.createDataFrame(rows, "node long, block int, guest int, rid long, n long, sig binary, label long")
    got = {(r.src, r.dst) for r in near_dup._link_blocks(df, 85, way).collect()}
    linked = {"all": {(0, 1), (0, 5), (2, 3)}, "guests": {(0, 1), (0, 5)}, "hub": {(0, 1), (0, 2), (0, 3), (0, 4), (0, 5)}}[way]
    assert got == linked
