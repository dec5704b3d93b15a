"""Document fingerprints: a Merkle tree over paragraphs and sections.

Leaves are spans of ``LEAST`` to ``SPAN`` code points that end with a blank, if there is one, and
never cross a line end, so spans fall into step again after an insertion; a paragraph is
a line, a section ``FANOUT`` paragraphs, and the root covers the sections. Equal roots mean
equal texts; where roots differ, unequal sections, then paragraphs, then spans locate the edit.
Likeness goes down the tree too: the spans of sections that agree count without being opened.

Only built-in functions are used. The text is cut in one pass by a bounded pattern, so a very
long line costs time in proportion to its length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphloop.llm.text import sha256_hex
from graphloop.materialize import stored

LEAST, SPAN = 12, 48
FANOUT = 16
LEAF_HEX, SECTION_HEX = 10, 16
ROWS_A_RANGE = 2_000
BYTES_A_RANGE = 8_000_000
CUTS = 1 << 20


def paragraphs(text: Column) -> Column:
    """Digests of the lines of a text."""
    return F.transform(F.split(text, "\n", -1), sha256_hex)


def sections(paragraph_digests: Column) -> Column:
    """Digests of runs of ``FANOUT`` paragraphs."""
    first = F.sequence(F.lit(0), F.floor((F.size(paragraph_digests) - 1) / FANOUT).cast("int"))
    return F.transform(first, lambda k: sha256_hex(F.array_join(F.slice(paragraph_digests, k * FANOUT + 1, FANOUT), "")))


def root(section_digests: Column) -> Column:
    return sha256_hex(F.array_join(section_digests, ""))


def leaves(text: Column) -> Column:
    """Short hashes of the spans of each section, in order."""
    lines = F.split(text, "\n", -1)
    first = F.sequence(F.lit(0), F.floor((F.size(lines) - 1) / FANOUT).cast("int"))
    pattern = F.lit(rf"[^\n]{{{LEAST},{SPAN}}}? |[^\n]{{1,{SPAN}}}\n?|\n")

    def of(part: Column) -> Column:
        spans = F.regexp_extract_all(part, pattern, F.lit(0))
        return F.transform(spans, lambda x: F.substring(F.md5(x.cast("binary")), 1, LEAF_HEX))

    return F.transform(first, lambda k: of(F.array_join(F.slice(lines, k * FANOUT + 1, FANOUT), "\n")))


def with_tree(df: DataFrame, text: Column, prefix: str = "") -> DataFrame:
    """Adds <prefix>root, <prefix>leaves and the levels between them."""
    p, s, r, x = (prefix + name for name in ("paragraphs", "sections", "root", "leaves"))
    df = df.withColumn(p, paragraphs(text))
    df = df.withColumn(s, sections(F.col(p)))
    return df.withColumn(r, root(F.col(s))).withColumn(x, leaves(text))


def likeness(a: str, b: str) -> Column:
    """Of the trees whose columns have the prefixes ``a`` and ``b``: 1 for equal roots, else below 1.

    Sections that agree, place by place, bring all their spans; the others are opened, and of their
    distinct spans those in common count. The sum is taken against all of the larger tree's.
    """
    n = F.greatest(F.size(f"{a}sections"), F.size(f"{b}sections"))
    places = F.sequence(F.lit(0), n - 1)
    agree = F.filter(places, lambda k: F.get(f"{a}sections", k).eqNullSafe(F.get(f"{b}sections", k)))
    differ = F.filter(places, lambda k: ~F.get(f"{a}sections", k).eqNullSafe(F.get(f"{b}sections", k)))

    def opened(prefix: str) -> Column:
        none = F.array().cast("array<string>")
        return F.array_distinct(F.flatten(F.transform(differ, lambda k: F.coalesce(F.get(f"{prefix}leaves", k), none))))

    closed = F.aggregate(agree, F.lit(0), lambda total, k: total + F.size(F.get(f"{a}leaves", k)))
    x, y = opened(a), opened(b)
    common, most = F.size(F.array_intersect(x, y)), F.greatest(F.size(x), F.size(y))
    whole = closed + most + F.when(common == most, 1).otherwise(0)
    part = (closed + common).cast("double") / F.greatest(whole, F.lit(1)).cast("double")
    return F.when(F.col(f"{a}root") == F.col(f"{b}root"), F.lit(1.0)).otherwise(part)


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, root, sections, paragraphs, leaves) of each row; null texts count as empty.

    Repeated rows each get a row; an empty table gives an empty result; other columns of
    ``df`` are left out, so their names cannot clash.
    """
    base = df.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return with_tree(base, F.col("text")).select("id", "root", "sections", "paragraphs", "leaves")


def locate_edits(old: DataFrame, new: DataFrame) -> DataFrame:
    """(id, section, paragraph) of every paragraph that differs between two fingerprint tables.

    Rows are matched by id; a paragraph that only one side has counts as different. Branches
    with equal section digests are not opened.
    """
    a, b = old.alias("a"), new.alias("b")
    pairs = a.join(b, F.col("a.id").eqNullSafe(F.col("b.id"))).where(F.col("a.root") != F.col("b.root"))
    n = F.greatest(F.size("a.sections"), F.size("b.sections"))
    opened = F.filter(F.sequence(F.lit(0), n - 1), lambda k: ~F.get("a.sections", k).eqNullSafe(F.get("b.sections", k)))
    found = pairs.select(
        F.col("a.id").alias("id"), F.explode(opened).alias("section"), F.col("a.paragraphs").alias("pa"), F.col("b.paragraphs").alias("pb")
    )
    inside = F.sequence(F.col("section") * FANOUT, F.col("section") * FANOUT + FANOUT - 1)
    differs = F.filter(inside, lambda k: ~F.get("pa", k).eqNullSafe(F.get("pb", k)))
    return found.select("id", "section", F.explode(differs).alias("paragraph"))


def with_next(df: DataFrame, id_col: str, columns: list[str]) -> DataFrame:
    """Adds next_<column>: the value in the next row by descending id, after the last the first.

    Rows go once, by ranges of ids of equal width for about ``ROWS_A_RANGE`` rows each; a range
    that holds far more, as where ids lie in clusters, is cut again in proportion. Only the
    first row of each range crosses over, by a join of as many rows as there are ranges.
    Null ids come last; ties go by the columns themselves.
    """
    wide = sum((F.coalesce(F.octet_length(c), F.lit(0)) for c in columns), F.lit(0))
    span = df.agg(F.min(id_col).alias("lo"), F.max(id_col).alias("hi"), F.count(F.lit(1)).alias("n"), F.sum(wide).alias("bytes")).first()
    if not span["n"]:
        return df.select("*", *(F.lit(None).cast(df.schema[c].dataType).alias(f"next_{c}") for c in columns))
    lo, hi = span["lo"] or 0, span["hi"] or 0
    ranges = max(1, span["n"] // ROWS_A_RANGE, span["bytes"] // BYTES_A_RANGE)
    width = max(1, -(-(hi - lo + 1) // ranges))
    # In doubles nothing overflows, and order is kept even where neighbours round to one value.
    spot = (F.lit(float(hi)) - F.col(id_col).cast("double")) / F.lit(float(width))
    cell = F.coalesce(F.floor(spot).cast("long"), F.lit(ranges + 1).cast("long"))
    crowded = df.select(cell.alias("_cell")).groupBy("_cell").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > 4 * ROWS_A_RANGE)
    crowded = stored(crowded.select("_cell", F.least(F.ceil(F.col("_n") / ROWS_A_RANGE), F.lit(CUTS)).cast("long").alias("_parts")))
    dealt = df.withColumn("_cell", cell)
    if crowded.isEmpty():
        dealt = dealt.withColumn("_range", F.col("_cell") * CUTS).drop("_cell")
    else:  # at most one crowded cell for each 4 * ROWS_A_RANGE rows
        part = F.least(F.floor((spot - F.col("_cell")) * F.col("_parts")), F.col("_parts") - 1)
        dealt = dealt.join(F.broadcast(crowded), "_cell", "left").withColumn("_range", F.col("_cell") * CUTS + F.coalesce(part, F.lit(0))).drop("_cell", "_parts")
    placed = dealt
    order = [F.col(id_col).desc_nulls_last(), *(F.col(c) for c in columns)]
    inside = Window.partitionBy("_range").orderBy(*order)
    dealt = dealt.withColumn("_after", F.lead(F.struct(*columns)).over(inside))

    ids = placed.select("_range", F.col(id_col).alias("_id")).groupBy("_range").agg(F.max("_id").alias("_id"))
    firsts = (
        placed.join(F.broadcast(ids) if ranges < 1_000_000 else ids, ["_range"])
        .where(F.col(id_col).eqNullSafe(F.col("_id")))
        .groupBy("_range")
        .agg(F.min(F.struct(*columns)).alias("_head"))
    )
    firsts = stored(firsts)
    ring = Window.partitionBy(F.lit(0)).orderBy("_range")
    whole = ring.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    links = firsts.select("_range").withColumn("_to", F.coalesce(F.lead("_range").over(ring), F.first("_range").over(whole)))
    follow = links.join(firsts.select(F.col("_range").alias("_to"), "_head"), "_to").select(F.col("_range").alias("_from"), "_head")
    # Both sides lie by range already: the rows are not dealt out again.
    ends = (F.col("_range") == F.col("_from")) & F.col("_after").isNull()
    rows = dealt.join(follow, ends, "left").withColumn("_after", F.coalesce("_after", "_head"))
    return rows.select(*df.columns, *(F.col(f"_after.{c}").alias(f"next_{c}") for c in columns))


def compare_with_edits(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of each text, of its edited text and of the next text, with their likeness.

    The edited text is the text with its last half (rounded down) replaced by as much of the
    start of the next row's text. Null texts count as empty; a table of one row follows itself.
    """
    base = df.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows = with_next(base, "id", ["text"]).withColumn("n_chars", F.length("text").cast("long"))
    half = F.floor(F.col("n_chars") / 2).cast("int")
    start = F.substring(F.col("text"), F.lit(1), F.col("n_chars").cast("int") - half)
    rows = rows.withColumn("edited", F.concat(start, F.substring(F.col("next_text"), F.lit(1), half)))
    for prefix, text in (("", "text"), ("edited_", "edited"), ("next_", "next_text")):
        rows = with_tree(rows, F.col(text), prefix)
    near = {f"near_{name}": likeness("", f"{name}_") for name in ("edited", "next")}
    return rows.withColumns(near)


def as_text(prefix: str = "") -> Column:
    """A fingerprint as one string: the root, then of each section a colon, the start of its digest, a dot and its leaves."""
    parts = F.zip_with(f"{prefix}sections", f"{prefix}leaves", lambda d, x: F.concat(F.lit(":"), F.substring(d, 1, SECTION_HEX), F.lit("."), F.array_join(x, "")))
    return F.concat(F.col(f"{prefix}root"), F.array_join(parts, ""))


def digest(compared: DataFrame) -> DataFrame:
    """The contract's columns."""
    return compared.select(
        F.col("id").alias("doc_id"),
        "n_chars",
        sha256_hex(F.col("edited")).alias("edited_sha256"),
        as_text().alias("fingerprint"),
        as_text("edited_").alias("edited_fingerprint"),
        "near_edited",
        "near_next",
    )
