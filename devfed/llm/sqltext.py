"""DuckDB SQL of the operators that SQL can express, for comparison."""

from __future__ import annotations

from . import lmscore, neardup, quality, substring, urlfilter

WORD = r"[^\x20\x09-\x0D]+"
_FOLDED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _grams(lengths: list[int]) -> str:
    """Columns with the n words from each place on, joined by a space (no word holds one); null where a text ends before."""
    return ", ".join("word" + "".join(f" || ' ' || lead(word, {k}) OVER o" for k in range(1, n)) + f" AS g{n}" for n in lengths)


def quality_rules() -> str:
    lengths = sorted({quality.BASE_WINDOW, *quality.WINDOW_LIMITS})
    rules = " AND ".join(f"100 * coalesce(c{n}, 0) <= {limit} * word_chars" for n, limit in quality.WINDOW_LIMITS.items())
    sums = ", ".join(f"sum(CASE WHEN n = {n} THEN chars END) AS c{n}" for n in quality.WINDOW_LIMITS)
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{WORD}') AS w FROM documents),
f AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols FROM d),
lines AS (SELECT doc_id, line, length(array_to_string(regexp_extract_all(line, '{WORD}'), '')) AS chars, count(*) AS c FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '{WORD}') GROUP BY doc_id, line),
l AS (SELECT doc_id, CAST(sum(c - 1) AS BIGINT) AS n_dup_lines, sum((c - 1) * chars) AS dup_line_chars FROM lines GROUP BY doc_id),
words AS MATERIALIZED (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
grams AS MATERIALIZED (SELECT doc_id, i, {_grams(lengths)} FROM words WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
windows AS ({" UNION ALL ".join(f"SELECT doc_id, {n} AS n, i, count(*) OVER (PARTITION BY doc_id, g{n}) AS c FROM grams WHERE g{n} IS NOT NULL" for n in lengths)}),
covered AS (SELECT DISTINCT doc_id, n, unnest(range(i, i + n)) AS i FROM windows WHERE c > 1),
spans AS (SELECT c.doc_id, c.n, count(*) AS n_covered, sum(length(word)) AS chars FROM covered c JOIN words w ON c.doc_id = w.doc_id AND c.i = w.i GROUP BY ALL),
g AS (SELECT doc_id, CAST(sum(CASE WHEN n = {quality.BASE_WINDOW} THEN n_covered END) AS BIGINT) AS n_repeat_words, {sums} FROM spans GROUP BY doc_id),
j AS (SELECT f.*, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(dup_line_chars, 0) AS dup_line_chars, coalesce(n_repeat_words, 0) AS n_repeat_words, {", ".join(f"c{n}" for n in quality.WINDOW_LIMITS)}
  FROM f LEFT JOIN l ON f.doc_id = l.doc_id LEFT JOIN g ON f.doc_id = g.doc_id)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND good AS kept
FROM (SELECT *, n_words < {quality.LEAST_WORDS} OR 100 * n_repeat_words > {quality.BASE_LIMIT} * n_words AS base_failed, 100 * dup_line_chars <= {quality.LINE_LIMIT} * word_chars AND {rules} AS good FROM j)"""


def substring_dedup() -> str:
    n = substring.WINDOW
    return f"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS w FROM documents),
words AS MATERIALIZED (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
grams AS (SELECT doc_id, i, {_grams([n])} FROM words WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
windows AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY g{n}) AS first_doc FROM grams WHERE g{n} IS NOT NULL),
removed AS (SELECT DISTINCT doc_id, unnest(range(i, i + {n})) AS i FROM windows WHERE first_doc < doc_id),
kept AS (SELECT w.doc_id, string_agg(w.word, ' ' ORDER BY w.i) AS kept, count(*) AS n FROM words w ANTI JOIN removed r ON w.doc_id = r.doc_id AND w.i = r.i GROUP BY w.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN kept ON d.doc_id = kept.doc_id"""


def near_dedup() -> str:
    n = neardup.SHINGLE
    return f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_FOLDED}, '{WORD}') AS w FROM documents),
shingles AS MATERIALIZED (
  SELECT DISTINCT doc_id, w[i:i + {n - 1}] AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - {n - 2})) AS i FROM d WHERE len(w) >= {n})
  UNION ALL SELECT doc_id, w FROM d WHERE len(w) BETWEEN 1 AND {n - 1}),
sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
meets AS MATERIALIZED (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS m FROM shingles a JOIN shingles b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
links AS MATERIALIZED (SELECT a, b FROM meets JOIN sizes x ON a = x.doc_id JOIN sizes y ON b = y.doc_id WHERE 100 * m >= {neardup.PERCENT} * (x.n + y.n - m)),
both_ways AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT reach.a, e.b FROM reach JOIN both_ways e ON reach.b = e.a)
SELECT d.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, component_id, component_id = d.doc_id AS kept
FROM d LEFT JOIN sizes ON d.doc_id = sizes.doc_id JOIN (SELECT a, min(b) AS component_id FROM reach GROUP BY a) c ON c.a = d.doc_id"""


def url_filter() -> str:
    host = lambda u: f"translate(regexp_extract(coalesce({u}, ''), '(?s)^.*?://([^/?#]*)', 1), '{urlfilter.UPPER}', '{urlfilter.LOWER}')"
    rules = ", ".join(f"('{r.text}', '{r.host}', '{r.path}', {str(r.block).upper()})" for r in urlfilter.RULES)
    d, ctes = urlfilter.DAMPING, []
    for name, (a, b) in (("good", ("src", "dst")), ("bad", ("dst", "src"))):
        ctes.append(f"{name}_out AS MATERIALIZED (SELECT {a} AS h, sum(n) AS total FROM edges GROUP BY {a})")
        passed = f"m.fresh * {d} * e.n // (100 * o.total)"
        # whole parts of a page's mass run out, and the recursion with them
        ctes.append(
            f"{name}_steps AS (SELECT 0 AS step, host, CAST({name} AS HUGEINT) * {urlfilter.PAGE} * {100 - d} // 100 AS fresh FROM seeds WHERE {name} > 0 "
            f"UNION ALL SELECT step + 1, e.{b}, CAST(sum({passed}) AS HUGEINT) FROM {name}_steps m JOIN edges e ON e.{a} = m.host JOIN {name}_out o ON o.h = m.host GROUP BY step, e.{b} HAVING sum({passed}) > 0)"
        )
        ctes.append(f"{name} AS (SELECT host, CAST(sum(fresh) AS HUGEINT) AS mass FROM {name}_steps GROUP BY host)")
    link = r"""(?i)<a\b[^>]*?\bhref\s*=\s*["'']?\s*([a-z][a-z0-9+.-]*://[^/?#"''\s>]*)"""
    return f"""
WITH RECURSIVE p AS MATERIALIZED (SELECT page_id, {host("url")} AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path, coalesce(html, '') AS html FROM pages),
rules AS (SELECT * FROM (VALUES {rules}) t(rule, h, start, block)),
judged AS MATERIALIZED (SELECT p.page_id, p.host, p.path, arg_max(rule, length(rule)) AS rule, arg_max(block, length(rule)) AS block
  FROM p LEFT JOIN rules ON (p.host = h OR ends_with(p.host, '.' || h)) AND starts_with(p.path, start) GROUP BY p.page_id, p.host, p.path),
seeds AS MATERIALIZED (SELECT host, count_if(NOT block) AS good, count_if(block) AS bad FROM judged WHERE block IS NOT NULL AND host <> '' GROUP BY host),
links AS (SELECT host AS src, unnest(regexp_extract_all(html, '{link}', 1)) AS link FROM p),
edges AS MATERIALIZED (SELECT src, dst, count(*) AS n FROM (SELECT src, {host("link")} AS dst FROM links) WHERE src <> '' AND dst <> '' AND src <> dst GROUP BY src, dst),
{", ".join(ctes)}
SELECT j.page_id, j.host, j.path, j.rule, CASE WHEN coalesce(block, coalesce(b.mass, 0) * greatest(all_good, 1) > coalesce(g.mass, 0) * greatest(all_bad, 1)) THEN 'block' ELSE 'allow' END AS verdict
FROM judged j CROSS JOIN (SELECT coalesce(sum(good), 0) AS all_good, coalesce(sum(bad), 0) AS all_bad FROM seeds) LEFT JOIN good g ON g.host = j.host LEFT JOIN bad b ON b.host = j.host"""


def lm_scoring() -> str:
    """A space, which no word holds, is the start mark as a history and the end mark as a word."""
    weight = lmscore.LAMBDA

    def loss(n: str, left: str) -> str:
        single = f"(c.{n} - {left} * own_word + 1.0e0) / (n_{n} - {left} * events + vocabulary)"
        known = f"h.{n} - {left} * own_history"
        return f"-ln(CASE WHEN {known} > 0 THEN {weight}e0 * (p.{n} - {left} * own_pair) / CAST({known} AS DOUBLE) + {1 - weight!r}e0 * {single} ELSE {single} END)"

    return f"""
WITH d AS MATERIALIZED (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS w, CASE WHEN doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) THEN 1 ELSE 0 END AS member FROM documents),
e AS MATERIALIZED (SELECT doc_id, member, unnest(list_prepend(' ', w)) AS v, unnest(list_append(w, ' ')) AS w FROM d WHERE len(w) > 0),
c AS MATERIALIZED (SELECT w, count(*) AS whole, sum(member) AS chosen FROM e GROUP BY w),
h AS MATERIALIZED (SELECT v, count(*) AS whole, sum(member) AS chosen FROM e GROUP BY v),
p AS MATERIALIZED (SELECT v, w, count(*) AS whole, sum(member) AS chosen FROM e GROUP BY v, w),
totals AS (SELECT sum(whole) AS n_whole, sum(chosen) AS n_chosen, count(*) AS vocabulary FROM c),
x AS (SELECT *, count(*) OVER (PARTITION BY doc_id, v, w) AS own_pair, count(*) OVER (PARTITION BY doc_id, v) AS own_history, count(*) OVER (PARTITION BY doc_id, w) AS own_word, count(*) OVER (PARTITION BY doc_id) AS events FROM e),
l AS (SELECT doc_id, avg({loss("chosen", "member")}) AS target_loss, avg({loss("whole", "1")}) AS background_loss
  FROM x JOIN c ON x.w = c.w JOIN h ON x.v = h.v JOIN p ON x.v = p.v AND x.w = p.w CROSS JOIN totals GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, round(target_loss, 6) + 0.0e0 AS target_loss, round(background_loss, 6) + 0.0e0 AS background_loss, round(target_loss - background_loss, 6) + 0.0e0 AS score FROM d LEFT JOIN l ON d.doc_id = l.doc_id"""
