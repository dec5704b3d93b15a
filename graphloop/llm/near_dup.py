"""Near-duplicate documents by a chosen-path set similarity join over MinHash values.

1. Every text becomes its set of word shingles, a 128-bit name of the set and a signature of
   minwise tokens. Texts with equal sets collapse into one node of the join, whatever their
   number, by a combinable minimum.
2. Trees: in each of several independent trees a set walks from the root along ``branches``
   minwise tokens chosen by the node, so two sets meet below a node where a chosen token
   agrees. Nodes are expanded level by level. Small ones, and those of one block, are compared
   exhaustively on their signatures, with a margin below the threshold; so are larger ones whose
   sets are connected but for at most a block of them. The others branch again, and what is left
   at the last level is so alike that all of it is taken as candidates of one hub.
3. Candidates form provisional groups. Within a group links are confirmed on full sets: in one
   task up to ``block`` members; beyond that in blocks, each with the group's hub, after which
   the members that are not yet one with the hub are compared, in blocks too, with all blocks: a
   task never holds more than two blocks. Comparisons stop where two members are known to be
   connected, so no group emits its pairs, and pairs are passed over only where a count of
   shingles by hash proves that they share too few.
4. Confirmed links are contracted to components.

A pair at the threshold is missed with probability below 0.0001 as a candidate of nodes: by
all trees down to the deepest level, or by the margin on signatures. The number of trees is
derived from that (``tree_count``). Every reported link is exact, and confirmation misses none.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloop.algorithms.components import contract
from graphloop.llm.shingles import shingle_sets
from graphloop.materialize import stored

COORDINATES = 64
_RNG = np.random.Generator(np.random.PCG64(5))
_SEEDS = _RNG.integers(0, 2**32, COORDINATES, dtype=np.uint32)
_ODD = _RNG.integers(0, 2**31, COORDINATES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_ROWS = 512
MISS = 0.0001
CELLS = 512
BRANCHES = 2


def signature(shingles: np.ndarray) -> np.ndarray:
    """16 bits of each of the ``COORDINATES`` minwise values of a non-empty set."""
    low = (shingles ^ (shingles >> np.uint64(32))).astype(np.uint32)
    least = np.full(COORDINATES, 0xFFFFFFFF, dtype=np.uint32)
    for at in range(0, len(low), _ROWS):
        x = (low[at : at + _ROWS, None] ^ _SEEDS) * _ODD
        x ^= x >> np.uint32(15)
        np.minimum(least, x.min(axis=0), out=least)
    return least.astype(np.uint16)


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """100 * size of the intersection >= percent * size of the union, on sorted sets."""
    small, large = sorted((len(a), len(b)))
    if 100 * small < percent * large:
        return False
    both = np.concatenate([a, b])
    both.sort(kind="stable")
    common = int((both[1:] == both[:-1]).sum())
    return 100 * common >= percent * (small + large - common)


def cells(shingles: np.ndarray) -> np.ndarray:
    """How many shingles fall into each of ``CELLS`` cells: two sets share at most the sum of the smaller counts."""
    counts = np.bincount((shingles >> np.uint64(40)).astype(np.int64) % CELLS, minlength=CELLS)
    return np.minimum(counts, 2**31 - 1).astype(np.int32)


def describe(df: DataFrame, width: int) -> DataFrame:
    """(id, row_hash, n, s1, s2, sig) for rows (id, row_hash, text)."""
    schema = f"id {dict(df.dtypes)['id']}, row_hash long, n long, s1 long, s2 long, sig binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, s1, s2, sigs = [], [], [], []
            for found in shingle_sets(batch.column(2).to_pylist(), width):
                n.append(len(found))
                if len(found):
                    name = hashlib.blake2b(found.tobytes(), digest_size=16).digest()
                    s1.append(int.from_bytes(name[:8], "little", signed=True))
                    s2.append(int.from_bytes(name[8:], "little", signed=True))
                    sigs.append(signature(found).tobytes())
                else:
                    s1.append(None), s2.append(None), sigs.append(None)
            longs = (pa.array(values, pa.int64()) for values in (n, s1, s2))
            columns = [batch.column(0), batch.column(1), *longs, pa.array(sigs, pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "row_hash", "n", "s1", "s2", "sig"])

    return df.mapInArrow(run, schema)


def _token(coordinate: Column) -> Column:
    return F.substring(F.col("sig"), coordinate * 2 + 1, F.lit(2))


def _children(branches: int) -> Column:
    """The nodes below ``node`` to which a set goes."""
    first = F.pmod(F.xxhash64("node"), F.lit(COORDINATES)).cast("int")
    stride = (F.pmod(F.xxhash64(F.lit("stride"), "node"), F.lit(COORDINATES // 2)) * 2 + 1).cast("int")
    chosen = [F.pmod(first + stride * k, F.lit(COORDINATES)) for k in range(branches)]
    return F.array(*(F.xxhash64("node", c, _token(c)) for c in chosen))


def _runs(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Tables that hold whole groups of rows that lie together by ``keys``."""
    rest: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        rest.append(batch)
        whole = pa.Table.from_batches(rest)
        changed = np.zeros(whole.num_rows, dtype=bool)
        for key in keys:
            values = whole.column(key).to_numpy()
            changed[1:] |= values[1:] != values[:-1]
        last = np.flatnonzero(changed)
        if len(last):
            yield whole.slice(0, int(last[-1]))
            rest = whole.slice(int(last[-1])).combine_chunks().to_batches()
    if rest:
        yield pa.Table.from_batches(rest)


def _least_agreement(percent: int) -> int:
    """How many of the minwise values two sets at the threshold share at least, but for 4.2 standard deviations."""
    share = percent / 100
    return int(COORDINATES * max(0.0, share - 4.2 * (share * (1 - share) / COORDINATES) ** 0.5))


def miss_probability(percent: int, trees: int, branches: int, depth: int) -> float:
    """How likely a pair at the threshold fails the margin on signatures, or meets in no node of the deepest level.

    Trees read one signature, so their misses depend on how many of its values agree and are
    multiplied for each such number. Nodes are taken to choose their values independently.
    """
    share, least, missed = percent / 100, _least_agreement(percent), 0.0
    for agree in range(COORDINATES + 1):
        chance = comb(COORDINATES, agree) * share**agree * (1 - share) ** (COORDINATES - agree)
        apart = 0.0
        for _ in range(depth):
            apart = (1 - agree / COORDINATES * (1 - apart)) ** branches
        missed += chance * (1.0 if agree < least else apart**trees)
    return missed


def tree_count(percent: int, branches: int = BRANCHES, depth: int = 4) -> int:
    """The fewest trees by which a pair at the threshold is missed with probability below ``MISS``."""
    for trees in range(1, COORDINATES + 1):
        if miss_probability(percent, trees, branches, depth) < MISS:
            return trees
    raise ValueError(f"{COORDINATES} trees miss too many pairs at {percent}%; give their number")


def _compare_small(members: DataFrame, percent: int, leaf: int) -> DataFrame:
    """Candidate links (src, dst) within nodes of at most ``leaf`` sets, by signatures."""
    least = _least_agreement(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _runs(batches, ["node"]):
            node, rid, n = (rows.column(c).to_numpy() for c in ("node", "rid", "n"))
            sig = np.frombuffer(b"".join(rows.column("sig").to_pylist()), dtype=np.uint16).reshape(-1, COORDINATES)
            for d in range(1, leaf):
                at = np.flatnonzero(node[d:] == node[:-d])
                if not len(at):
                    break
                a, b = n[at], n[at + d]
                at = at[100 * np.minimum(a, b) >= percent * np.maximum(a, b)]
                at = at[(sig[at] == sig[at + d]).sum(axis=1) >= least]
                yield pa.RecordBatch.from_arrays([pa.array(rid[at]), pa.array(rid[at + d])], names=["src", "dst"])

    dealt = members.select("node", "rid", "n", "sig").repartition("node").sortWithinPartitions("node", "rid")
    return dealt.mapInArrow(run, "src long, dst long").distinct()


def _spanning(n: np.ndarray, sig: np.ndarray, label: np.ndarray, asking: int, percent: int) -> Iterator[tuple[int, int]]:
    """Links (i, j) by signature that connect what is alike among the first ``asking`` rows and all, none between rows connected already."""
    least, known = _least_agreement(percent), np.unique(label, return_inverse=True)[1]
    for i in range(asking):
        others = i + 1 + np.flatnonzero(known[i + 1 :] != known[i])
        others = others[100 * np.minimum(n[others], n[i]) >= percent * np.maximum(n[others], n[i])]
        others = others[(sig[others] == sig[i]).sum(axis=1) >= least]
        if len(others):
            groups, at = np.unique(known[others], return_index=True)
            yield from ((i, j) for j in others[at].tolist())
            known[np.isin(known, groups)] = known[i]


def _link_blocks(rows: DataFrame, percent: int, way: str) -> DataFrame:
    """Candidate links (src, dst) within blocks of rows (node, block, guest, rid, n, sig, label).

    Way "all" compares all rows, "guests" the guests of a block with all; "hub" takes everything as
    alike the first guest, one row for each label.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _runs(batches, ["node", "block"]):
            node, block, guest, rid, n, label = (table.column(c).to_numpy() for c in ("node", "block", "guest", "rid", "n", "label"))
            sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), dtype=np.uint16).reshape(-1, COORDINATES)
            cuts = (np.flatnonzero((node[1:] != node[:-1]) | (block[1:] != block[:-1])) + 1).tolist()
            src, dst = [], []
            for a, b in zip([0, *cuts], [*cuts, len(node)], strict=True):
                if way == "hub":
                    found = ((0, j) for j in np.unique(label[a:b], return_index=True)[1].tolist() if j)
                else:
                    asking = int(guest[a:b].sum()) if way == "guests" else b - a
                    found = _spanning(n[a:b], sig[a:b], label[a:b], asking, percent)
                for i, j in found:
                    src.append(rid[a + i])
                    dst.append(rid[a + j])
            yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

    dealt = rows.select("node", "block", "guest", "rid", "n", "sig", "label").repartition("node", "block")
    return dealt.sortWithinPartitions("node", "block", F.desc("guest"), "rid").mapInArrow(run, "src long, dst long").distinct()


def _in_blocks(members: DataFrame, guests: DataFrame, block: int) -> DataFrame:
    """Nodes dealt to blocks of about ``block`` sets, each of which has all ``guests`` of its node; rows (node, rid, n, sig, label, size)."""
    columns = ["node", "rid", "n", "sig", "label"]
    n_blocks = F.ceil(F.col("size") / block).cast("int")
    own = members.select(*columns, F.pmod(F.xxhash64("rid"), n_blocks).cast("int").alias("block"), F.lit(0).alias("guest"))
    return own.unionByName(guests.select(*columns, F.explode(F.sequence(F.lit(0), n_blocks - 1)).alias("block"), F.lit(1).alias("guest")))


def _hubs(members: DataFrame) -> DataFrame:
    """The first set of each node."""
    return members.groupBy("node").agg(F.min(F.struct("rid", "n", "sig", "label", "size")).alias("hub")).select("node", "hub.*")


def _mostly_one(members: DataFrame) -> DataFrame:
    """Nodes of several labels, with the label of most of their sets (main) and how many sets have others (apart)."""
    tally = members.groupBy("node", "label").agg(F.count(F.lit(1)).alias("k")).groupBy("node")
    tally = tally.agg(F.max(F.struct("k", "label")).alias("most"), F.sum("k").alias("k"))
    return tally.select("node", F.col("most.label").alias("main"), (F.col("k") - F.col("most.k")).alias("apart")).where("apart > 0")


def candidates(
    sets: DataFrame, percent: int, trees: int, branches: int = BRANCHES, leaf: int = 32, depth: int = 4, block: int = 512
) -> DataFrame:
    """Candidate links (src, dst) between rows (rid, n, sig), at least one path of them for each candidate pair.

    Crowded nodes, of more than ``leaf`` sets, are compared in blocks of about ``block``, where their
    hub joins each block, and ``label`` names what such links have connected in any tree. Nodes of one block
    end there. In larger ones all but at most ``block`` sets may have one label; those apart then
    join each block and are compared with all, so these nodes end too: they send each set once and at most
    as many copies of those apart. Only the others branch.
    Tables of nodes are written before they are joined, so that adaptive plans split crowded nodes.
    """
    tops = F.explode(F.array(*(F.xxhash64(F.lit(f"tree {t}")) for t in range(trees))))
    members = sets.select("rid", "n", "sig", F.col("rid").alias("label"), tops.alias("node"))
    links = crowded = None
    for _ in range(depth):
        members = members.select("rid", "n", "sig", "label", F.explode(_children(branches)).alias("node"))
        nodes = members.groupBy("node").agg(F.count(F.lit(1)).alias("size"), F.min("label").alias("least"), F.max("label").alias("most"))
        sizes = stored(nodes.where("least < most").select("node", "size"))
        members = stored(members.join(sizes, "node"))
        small = _compare_small(members.where(F.col("size") <= leaf), percent, leaf)
        links = small if links is None else links.unionByName(small)
        members = members.where(F.col("size") > leaf)
        if members.isEmpty():
            break
        found = stored(_link_blocks(_in_blocks(members, _hubs(members.where(F.col("size") > block)), block), percent, "all"))
        links = links.unionByName(found)
        members = members.where(F.col("size") > block)
        if members.isEmpty():
            break
        crowded = found if crowded is None else crowded.unionByName(found)
        labels = contract(crowded)[0].select(F.col("node").alias("rid"), "component")
        members = stored(members.join(labels, "rid", "left").withColumn("label", F.coalesce("component", "rid")).drop("component"))
        members = members.join(stored(_mostly_one(members)), "node")
        few = members.where(F.col("apart") <= block)
        found = stored(_link_blocks(_in_blocks(few.where("label = main"), few.where("label <> main"), block), percent, "guests"))
        links, crowded = links.unionByName(found), crowded.unionByName(found)
        members = members.where(F.col("apart") > block)
        if members.isEmpty():
            break
    else:
        links = links.unionByName(_link_blocks(_in_blocks(members, _hubs(members), block), percent, "hub"))
    return links


class _Groups:
    """Union-find over labels."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        path = []
        while (above := self.up.get(x, x)) != x:
            path.append(x)
            x = above
        for y in path:
            self.up[y] = x
        return x

    def join(self, a: int, b: int) -> None:
        self.up[self.find(a)] = self.find(b)


def _confirm(rows: DataFrame, width: int, percent: int) -> DataFrame:
    """Exact links that connect what is alike among rows (grp, block, asked, probe, rid, label, text).

    In a block without probes all rows are compared, in one with probes only probes with the
    others. Rows with one label are connected already. A row is first held against the first
    member of each group, then, while they are apart, against the others; pairs that cannot
    share enough by their sizes and cells are passed over.
    """

    def links(rids, labels, probes, sets) -> Iterator[tuple[int, int]]:
        known, asked = _Groups(), bool(probes.any())
        counts = np.array([cells(x) for x in sets])
        sizes = np.array([len(x) for x in sets])
        clusters: dict[int, list[int]] = {}
        order = np.argsort(probes, kind="stable").tolist()
        for i in order:
            mine = known.find(labels[i])
            if not asked or probes[i]:
                both = sizes + sizes[i]
                near = np.flatnonzero(100 * np.minimum(sizes, sizes[i]) >= percent * np.maximum(sizes, sizes[i]))
                shared = np.minimum(counts[near], counts[i]).sum(axis=1)
                alike = np.zeros(len(sets), dtype=bool)
                alike[near] = (100 + percent) * shared >= percent * both[near]
                for other in sorted(clusters, key=lambda c: -len(clusters[c])):
                    if other == known.find(mine) or other not in clusters:
                        continue
                    for j in clusters[other]:
                        if alike[j] and similar(sets[i], sets[j], percent):
                            yield rids[i], rids[j]
                            known.join(mine, other)
                            top = known.find(other)
                            merged = clusters.pop(other) + clusters.pop(mine, [])
                            clusters[top] = merged
                            mine = top
                            break
            if not (asked and probes[i]):
                clusters.setdefault(known.find(mine), []).append(i)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _runs(batches, ["grp", "block", "asked"]):
            keys = [table.column(c).to_numpy() for c in ("grp", "block", "asked")]
            cuts = np.flatnonzero(np.any([k[1:] != k[:-1] for k in keys], axis=0)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(keys[0])], strict=True):
                part = table.slice(a, b - a)
                sets = list(shingle_sets(part.column("text").to_pylist(), width))
                rids, labels = part.column("rid").to_pylist(), part.column("label").to_pylist()
                found = list(links(rids, labels, part.column("probe").to_numpy(), sets))
                if found:
                    src, dst = zip(*found, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

    dealt = rows.select("grp", "block", "asked", "probe", "rid", "label", "text").repartition("grp", "block", "asked")
    return dealt.sortWithinPartitions("grp", "block", "asked", "rid").mapInArrow(run, "src long, dst long")


def confirmed(texts: DataFrame, width: int, percent: int, block: int = 512) -> DataFrame:
    """Exact links among provisional groups; rows (rid, grp, hub, size, text), written before."""

    def blocks(n: Column) -> Column:
        return F.ceil(n / (block // 2)).cast("int")

    def spread(k: Column) -> Column:
        return F.explode(F.sequence(F.lit(0), k - 1))

    n_blocks = F.when(F.col("size") <= block, F.lit(1)).otherwise(blocks(F.col("size")))
    rows = texts.withColumn("n_blocks", n_blocks).withColumn("probe", F.lit(0)).withColumn("asked", F.lit(0)).withColumn("label", F.col("rid"))
    own = rows.withColumn("block", F.pmod(F.xxhash64("rid"), F.col("n_blocks")).cast("int"))
    large = rows.where(F.col("n_blocks") > 1)
    hubs = large.where(F.col("rid") == F.col("hub")).withColumn("block", spread(F.col("n_blocks")))
    first = stored(_confirm(own.unionByName(hubs), width, percent))
    if large.isEmpty():
        return first
    roots, _ = contract(first)
    # Ids and labels only: texts join what is still to be compared.
    labelled = large.select("rid", "grp", "hub", "n_blocks").join(roots.select(F.col("node").alias("rid"), "component"), "rid", "left")
    labelled = stored(labelled.withColumn("label", F.coalesce("component", "rid")).drop("component"))
    heads = labelled.where(F.col("rid") == F.col("hub")).select("grp", F.col("label").alias("head"))
    apart = stored(labelled.join(F.broadcast(heads) if heads.count() < 100_000 else heads, "grp").where(F.col("label") != F.col("head")).select("rid", "grp", "label", "n_blocks"))
    if apart.isEmpty():
        return first
    asking = apart.groupBy("grp").agg(blocks(F.count(F.lit(1))).alias("n_asked"))
    bodies = texts.select("rid", "text")
    asked = apart.join(asking, "grp").withColumn("asked", F.pmod(F.xxhash64(F.lit("asked"), "rid"), F.col("n_asked")).cast("int"))
    asked = asked.join(bodies, "rid").withColumn("probe", F.lit(1)).withColumn("block", spread(F.col("n_blocks")))
    held = labelled.join(asking, "grp").withColumn("block", F.pmod(F.xxhash64("rid"), F.col("n_blocks")).cast("int"))
    held = held.join(bodies, "rid").withColumn("probe", F.lit(0)).withColumn("asked", spread(F.col("n_asked")))
    columns = ["grp", "block", "asked", "probe", "rid", "label", "text"]
    return first.unionByName(_confirm(held.select(columns).unionByName(asked.select(columns)), width, percent))


def near_duplicates(
    df: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, trees: int | None = None, leaf: int = 32, depth: int = 4, block: int = 512
) -> DataFrame:
    """(id, n_shingles, component, kept): documents linked at a similarity of ``percent`` / 100.

    ``component`` is the smallest id reachable by links, the document's own where it has none,
    and ``kept`` marks the document with that id. Null texts and texts without words have an
    empty set and are linked with nothing. Rows with the same id are one document as far as
    ``kept`` goes; a null id is never the smallest unless all ids of a component are null.
    An empty table gives an empty result, and other columns of ``df`` do not matter.
    ``trees`` is derived from ``percent`` and ``depth`` if not given.
    """
    trees = tree_count(percent, depth=depth) if trees is None else trees
    base = df.select(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col)).alias("row_hash"), F.col(text_col).alias("text"))
    marked = stored(describe(base, width))
    pick = F.min(F.struct(F.col("id").isNull().alias("unknown"), "id", "row_hash")).alias("pick")
    sets = marked.where("n > 0").groupBy("s1", "s2").agg(pick, F.first("n").alias("n"), F.first("sig").alias("sig"))
    sets = sets.select("s1", "s2", "n", "sig", F.col("pick.id").alias("first"), "pick.row_hash")
    sets = stored(sets.withColumn("rid", F.monotonically_increasing_id()))
    links = stored(candidates(sets, percent, trees, leaf=leaf, depth=depth, block=block))
    groups, _ = contract(links)
    hubs = groups.select(F.col("component").alias("rid"), F.col("component").alias("grp")).distinct()
    groups = hubs.unionByName(groups.select(F.col("node").alias("rid"), F.col("component").alias("grp")))
    sizes = groups.groupBy("grp").agg(F.count(F.lit(1)).alias("size"))
    wanted = groups.join(sizes, "grp").join(sets.select("rid", "first", "row_hash"), "rid").withColumn("hub", F.col("grp"))
    same = base["id"].eqNullSafe(wanted["first"]) & (base["row_hash"] == wanted["row_hash"])
    texts = stored(base.join(wanted, same).select("rid", "grp", "hub", "size", "text"))
    roots, _ = contract(confirmed(texts, width, percent, block))
    named = sets.select("s1", "s2", "rid", "first").join(roots.withColumnRenamed("node", "rid"), "rid", "left")
    named = named.withColumn("root", F.coalesce("component", "rid"))
    least = stored(named.groupBy("root").agg(F.min("first").alias("component_id")))
    named = named.join(least, "root").select("s1", "s2", "component_id")
    out = marked.select("id", "n", "s1", "s2").join(named, ["s1", "s2"], "left")
    component = F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("id"))
    return out.select("id", F.col("n").alias("n_shingles"), component.alias("component"), F.col("id").eqNullSafe(component).alias("kept"))


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns."""
    return found.select(F.col("id").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), "kept")
