"""DuckDB SQL with the results of the text queries, where SQL can express them."""

from __future__ import annotations

SEPARATORS = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
FOLD = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

_MIX = f"""
WITH base AS (
  SELECT doc_id AS id, source, len({WORDS})::BIGINT AS size, md5('mix:' || coalesce(doc_id::VARCHAR, 'null')) AS turn
  FROM documents),
ranked AS (
  SELECT source, source_size, rank, [5, 2, 1][((rank - 1) % 3 + 1)::INT] AS weight, 3 * source_size AS cap
  FROM (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS rank
        FROM base GROUP BY source)),
level AS (
  SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER before, 0))::BIGINT AS room,
         (sum(weight) OVER () - coalesce(sum(weight) OVER before, 0))::BIGINT AS weights
  FROM ranked WINDOW before AS (ORDER BY cap::DOUBLE / weight, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
marked AS (SELECT *, cap::DOUBLE * weights <= weight::DOUBLE * room AS capped FROM level),
targets AS (
  SELECT source, source_size, rank, CASE WHEN capped THEN cap::DOUBLE ELSE (weight * (SELECT arg_max(room, weights) FROM marked WHERE NOT capped))::DOUBLE
           / (SELECT max(weights) FROM marked WHERE NOT capped)::DOUBLE END AS target
  FROM marked),
known AS (SELECT b.*, t.source_size, t.rank, t.target FROM base b JOIN targets t ON b.source IS NOT DISTINCT FROM t.source),
queued AS (
  SELECT *, sum(size) OVER (PARTITION BY rank ORDER BY turn, id, size ROWS UNBOUNDED PRECEDING) AS upto FROM known WHERE size > 0),
copies AS (SELECT q.*, epoch, (epoch * source_size + upto)::DOUBLE / target AS finish FROM queued q, range(3) e(epoch)),
served AS (
  SELECT id, count(*) AS copies FROM (
    SELECT id, sum(size) OVER (ORDER BY finish, rank, turn, id, size, epoch ROWS UNBOUNDED PRECEDING) AS total FROM copies)
  WHERE total <= (SELECT sum(size) FROM base) GROUP BY id)
SELECT k.id AS doc_id, k.size, k.source_size, k.target, (coalesce(s.copies, 0) * k.size)::BIGINT AS taken
FROM known k LEFT JOIN served s USING (id)
"""


def _tree(text: str) -> str:
    """Struct of root, section digests and leaves by section of a text."""
    return f"""(SELECT {{'root': sha256(array_to_string(sections, '')), 'sections': sections, 'leaves': leaves}} FROM (
      SELECT list_transform(places, lambda k: sha256(array_to_string(list_transform(lines[(k * 16 + 1):(k * 16 + 16)], lambda x: sha256(x)), ''))) AS sections,
        list_transform(places, lambda k: list_transform(regexp_extract_all(array_to_string(lines[(k * 16 + 1):(k * 16 + 16)], chr(10)),
          '[^\\n]{{12,48}}? |[^\\n]{{1,48}}\\n?|\\n'), lambda s: substring(md5(s), 1, 10))) AS leaves
      FROM (SELECT lines, range(0, ((len(lines) - 1) // 16 + 1)::BIGINT) AS places FROM (SELECT string_split({text}, chr(10)) AS lines))))"""


def _likeness(a: str, b: str) -> str:
    def opened(t: str) -> str:
        return f"list_distinct(flatten(list_transform(list_filter(range(0, places), lambda k: {a}.sections[k + 1] IS DISTINCT FROM {b}.sections[k + 1]), lambda k: coalesce({t}.leaves[k + 1], []))))"

    return f"""(SELECT CASE WHEN {a}.root = {b}.root THEN 1.0::DOUBLE ELSE (closed + len(list_intersect(x, y)))::DOUBLE
        / greatest(closed + greatest(len(x), len(y)) + CASE WHEN len(list_intersect(x, y)) = greatest(len(x), len(y)) THEN 1 ELSE 0 END, 1)::DOUBLE END
      FROM (SELECT {opened(a)} AS x, {opened(b)} AS y,
          coalesce(list_sum(list_transform(list_filter(range(0, places), lambda k: {a}.sections[k + 1] IS NOT DISTINCT FROM {b}.sections[k + 1]), lambda k: len({a}.leaves[k + 1]))), 0) AS closed
        FROM (SELECT greatest(len({a}.sections), len({b}.sections))::BIGINT AS places)))"""


def _shown(t: str) -> str:
    return f"{t}.root || array_to_string(list_transform(range(0, len({t}.sections)::BIGINT), lambda k: ':' || substring({t}.sections[k + 1], 1, 16) || '.' || array_to_string({t}.leaves[k + 1], '')), '')"


_FINGERPRINTS = f"""
WITH base AS (SELECT doc_id, coalesce(text, '') AS text, length(coalesce(text, ''))::BIGINT AS n_chars FROM documents),
followed AS (
  SELECT *, coalesce(lead(text) OVER w, first_value(text) OVER (ORDER BY doc_id DESC NULLS LAST)) AS next_text
  FROM base WINDOW w AS (ORDER BY doc_id DESC NULLS LAST)),
edits AS (
  SELECT *, substring(text, 1, n_chars - n_chars // 2) || substring(next_text, 1, n_chars // 2) AS edited FROM followed),
trees AS (
  SELECT doc_id, n_chars, edited, {_tree('text')} AS t, {_tree('edited')} AS e, {_tree('next_text')} AS n FROM edits)
SELECT doc_id, n_chars, sha256(edited) AS edited_sha256,
       {_shown('t')} AS fingerprint,
       {_shown('e')} AS edited_fingerprint,
       {_likeness('t', 'e')} AS near_edited, {_likeness('t', 'n')} AS near_next
FROM trees
"""

_URLS = f"""
WITH parts AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substring(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
split AS (
  SELECT page_id, {FOLD.format("regexp_extract(rest, '^[^/?#]*')")} AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path
  FROM parts),
rules(rule_host, rule_path, action) AS (
  VALUES ('com', '/en/', 'block'), ('example.com', '/en/7', 'allow'), ('net', '/de/', 'allow'), ('example.net', '/de/8', 'block'),
         ('org', '/es/', 'block')),
hits AS (
  SELECT page_id, arg_max(rule_host || rule_path, length(rule_host || rule_path)) AS rule,
         arg_max(action, length(rule_host || rule_path)) AS action
  FROM split JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
  GROUP BY page_id)
SELECT page_id, host, path, rule, coalesce(action, 'allow') AS verdict FROM split LEFT JOIN hits USING (page_id)
"""

_LINES = f"""
WITH lines AS (
  SELECT doc_id, line, pos, {FOLD.format(f"trim(line, {SEPARATORS})")} AS key
  FROM (SELECT doc_id, unnest(l) AS line, generate_subscripts(l, 1) AS pos
        FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents))),
frequent AS (SELECT key FROM lines WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT doc_id) >= 10),
marked AS (SELECT l.*, f.key IS NOT NULL AS dropped FROM lines l LEFT JOIN frequent f USING (key))
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (dropped)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT dropped), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

_QUALITY = rf"""
WITH base AS (SELECT doc_id, coalesce(text, '') AS text, {WORDS} AS w FROM documents),
words AS (
  SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS pos FROM base),
windows AS (
  SELECT doc_id, pos, word, lag(word) OVER o AS before, string_agg(word, ' ') OVER (o ROWS BETWEEN CURRENT ROW AND 7 FOLLOWING) AS grams,
         lead(word, 7) OVER o IS NOT NULL AS whole
  FROM words WINDOW o AS (PARTITION BY doc_id ORDER BY pos)),
counted AS (
  SELECT doc_id, pos, word = before AS adjacent, (whole AND count(*) OVER (PARTITION BY doc_id, whole, grams) > 1)::INT AS twice FROM windows),
covered AS (
  SELECT doc_id, adjacent, max(twice) OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN 7 PRECEDING AND CURRENT ROW) AS covered FROM counted),
repeats AS (
  SELECT doc_id, sum(covered)::BIGINT AS n_repeat_words, count(*) FILTER (adjacent)::BIGINT AS n_adjacent FROM covered GROUP BY doc_id),
lines AS (
  SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) - count(DISTINCT line))::BIGINT AS n_dup_lines
  FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM base)
  WHERE trim(line, {SEPARATORS}) <> '' GROUP BY doc_id),
measured AS (
  SELECT b.doc_id, len(w)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
         length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines,
         coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines, coalesce(n_adjacent, 0) AS n_adjacent,
         length(regexp_replace(text, '[^\p{{L}}]', '', 'g')) AS n_letters, length(regexp_replace(text, '[^\p{{Lu}}]', '', 'g')) AS n_upper,
         length(regexp_replace(text, '[^!]', '', 'g')) AS n_exclaim
  FROM base b LEFT JOIN repeats USING (doc_id) LEFT JOIN lines USING (doc_id)),
judged AS (
  SELECT *, ((n_words < 20)::BIGINT * 1 + (100 * n_repeat_words > 30 * n_words)::BIGINT * 2 + (100 * n_symbols > 10 * n_words)::BIGINT * 4
    + (100 * n_upper > 30 * n_letters)::BIGINT * 8 + (100 * n_exclaim > 20 * n_words)::BIGINT * 16 + (100 * n_dup_lines > 30 * n_lines)::BIGINT * 32
    + (100 * n_adjacent > 20 * n_words)::BIGINT * 64 + (word_chars < 2 * n_words OR word_chars > 20 * n_words)::BIGINT * 128
    + (10 * n_letters < 6 * word_chars)::BIGINT * 256)::BIGINT AS failed
  FROM measured)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failed & 3) <> 0 AS base_failed, failed = 0 AS kept, failed FROM judged
"""

_NEAR = rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all({FOLD.format("coalesce(text, '')")}, '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS MATERIALIZED (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS s
  FROM words),
sized AS MATERIALIZED (SELECT doc_id, len(s)::BIGINT AS n, md5(array_to_string(list_sort(s), chr(10))) AS name FROM sets),
firsts AS MATERIALIZED (SELECT name, min(doc_id) AS doc_id, any_value(n) AS n FROM sized WHERE n > 0 GROUP BY name),
grams AS MATERIALIZED (SELECT doc_id, n, unnest(s) AS gram FROM firsts JOIN sets USING (doc_id)),
links AS MATERIALIZED (
  SELECT a.doc_id AS x, b.doc_id AS y FROM grams a JOIN grams b ON a.gram = b.gram AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
parts(doc_id, component) USING KEY (doc_id) AS (
  SELECT doc_id, doc_id FROM firsts
  UNION SELECT l.y, min(p.component) FROM parts p JOIN links l ON p.doc_id = l.x JOIN recurring.parts r ON r.doc_id = l.y
  GROUP BY l.y, r.component HAVING min(p.component) < r.component)
SELECT d.doc_id, d.n AS n_shingles, coalesce(p.component, d.doc_id) AS component_id, d.doc_id = coalesce(p.component, d.doc_id) AS kept
FROM sized d LEFT JOIN firsts f ON d.name = f.name AND d.n > 0 LEFT JOIN parts p ON p.doc_id = f.doc_id
"""

SQL = {
    "op2_mix_sources": _MIX,
    "op3_document_fingerprints": _FINGERPRINTS,
    "op4_quality_rules": _QUALITY,
    "op5_minhash_near_dedup": _NEAR,
    "op7_url_filter": _URLS,
    "op10_line_dedup": _LINES,
}
