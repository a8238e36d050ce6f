"""DuckDB SQL for the registered queries, written against the tables alone."""

from __future__ import annotations

from spark_curation import published
from spark_curation.functions.text import REFERENCES
from spark_curation.operators import render, rules, teachers

SQL: dict[str, str] = {}


def q(s: str) -> str:
    """A string literal."""
    return "'" + s.replace("'", "''") + "'"


def sub(expr: str, pattern: str, new: str) -> str:
    return f"regexp_replace({expr}, {q(pattern)}, {new}, 'g')"


def n_of(expr: str, pattern: str) -> str:
    return f"len(regexp_extract_all({expr}, {q(pattern)}))"


def decoded(expr: str) -> str:
    for name, char in REFERENCES:
        expr = f"replace({expr}, {q(name)}, {q(char)})"
    return expr


def blocks(html: str) -> str:
    """The native recipe: list of {text, zone} of a page."""
    h = sub(f"coalesce({html}, '')", r"[\r\n\t]+", "' '")
    for p in render.DROP:
        h = sub(h, p, "''")
    h = sub(sub(h, render.OPENS, "chr(30) || '\\1'"), render.CLOSES, "'\\1' || chr(30)")
    inner = sub(sub(sub("s", render.BREAKS, "chr(10)"), render.CELLS, "' '"), render.TAGS, "''")
    lines = f"list_filter(list_transform(string_split({decoded(inner)}, chr(10)), lambda x: trim({sub('x', chr(92) + 's+', chr(39) + ' ' + chr(39))})), lambda x: x <> '')"
    return f"flatten(list_transform(string_split({h}, chr(30)), lambda s: list_transform({lines}, lambda x: {{'text': x, 'zone': lower(regexp_extract(s, {q(render.ZONE)}, 1))}})))"


def joined(lst: str) -> str:
    return f"coalesce(array_to_string({lst}, chr(10)), '')"


def words_of(expr: str) -> str:
    return f"CAST({n_of(f'coalesce({expr}, {chr(39)*2})', chr(92) + 'S+')} AS BIGINT)"


R = f"""
rendered AS (SELECT page_id, url, blocks, list_transform(blocks, lambda b: b.text) AS lines FROM (SELECT page_id, url, {blocks('html')} AS blocks FROM pages)),
admitted AS (SELECT *, {joined('lines')} AS raw FROM rendered WHERE len(lines) > 0 AND length({joined('lines')}) >= 20 AND {words_of(joined('lines'))} <= 29696)"""


def junk(t: str) -> dict[str, str]:
    n = f"greatest({words_of(t)}, 1)"
    ws = f"regexp_extract_all(coalesce({t}, ''), '\\S+')"
    return {
        "n": words_of(t),
        "symbols": f"({n_of(f'coalesce({t}, {q(str())}) || {q(chr(32))}', teachers.SYMBOLED)} / CAST({n} AS DOUBLE))",
        "shouts": f"({n_of(f'coalesce({t}, {q(str())}) || {q(chr(32))}', teachers.SHOUTED)} / CAST({n} AS DOUBLE))",
        "runs": f"(len(list_filter(list_zip({ws}, ({ws})[2:]), lambda p: p[1] = p[2])) / CAST({n} AS DOUBLE))",
        "pipes": n_of(f"coalesce({t}, '')", r"\|"),
        "ends": n_of(f"coalesce({t}, '')", r"[.!?]"),
    }


def family(t: str) -> str:
    j = junk(t)
    return f"CASE WHEN {j['symbols']} > 0.3 OR {j['shouts']} > 0.3 THEN 'gibberish' WHEN {j['runs']} > 0.3 THEN 'spam' WHEN {j['pipes']} >= 3 THEN 'listing' WHEN {j['ends']} = 0 AND {j['n']} < 10 THEN 'ui_only' END"


def edu(t: str) -> str:
    ws = f"regexp_extract_all(coalesce({t}, ''), '\\S+')"
    alpha = n_of(f"coalesce({t}, '')", r"\S*[A-Za-zÀ-ÿ]\S*")
    lines = f"list_filter(string_split(coalesce({t}, ''), chr(10)), lambda x: x <> '')"
    ended = f"len(list_filter({lines}, lambda x: regexp_matches(x, {q(chr(91) + '.!?' + chr(93) + '[' + chr(34) + chr(39) + ')' + chr(92) + ']]*$')})))"
    share = lambda a, b: f"(CASE WHEN {b} = 0 THEN 0.0::DOUBLE ELSE CAST({a} AS DOUBLE) / CAST({b} AS DOUBLE) END)"
    return f"round(5 * sqrt({share(f'len(list_distinct({ws}))', f'len({ws})')}) * {share(alpha, f'len({ws})')} * {share(ended, f'len({lines})')}, 4)"


def rewritten(t: str) -> str:
    piece = f"trim({sub(sub(sub(sub(f'substr({t}, CAST(i AS BIGINT) * 7000 + 1, 7000)', '[#%*$&]{3}', chr(39) * 2), '!{2,}', chr(39) * 2), ' ?' + chr(92) + '| ?', q(', ')), '[ ' + chr(92) + 't]+', q(' '))})"
    return f"array_to_string(list_transform(range(greatest(CAST(ceil(length({t}) / 7000.0) AS BIGINT), 1)), lambda i: {piece}), ' ')"


def noise(line: str, before: str) -> str:
    return f"((regexp_matches({line}, {q(teachers.NOTICE)}) OR list_contains({before}, {line})) AND NOT regexp_matches({line}, {q(teachers.PROTECTED)}))"


def policy(threshold: float = 1.0, rescue: str = "edu") -> str:
    worth = {"edu": f"edu >= {threshold}", "three_way": f"edu BETWEEN {threshold} AND 2.0", "classifier": f"{words_of('rewr')} * 2 >= {words_of('extracted')}"}[rescue]
    keep = "edu > 2.0" if rescue == "three_way" else "false"
    before = "list_transform(list_filter(main, lambda z: z.lid < m.lid), lambda z: z.txt)"
    ratio = f"(CASE WHEN {words_of('extracted')} = 0 THEN 0.0 ELSE {words_of('rewr')} / CAST({words_of('extracted')} AS DOUBLE) END)"
    return f"""
m1 AS (SELECT *, list_filter(list_transform(range(1, len(lines) + 1), lambda i: {{'lid': i, 'txt': lines[i], 'zone': blocks[i].zone}}), lambda m: m.zone = '') AS main FROM admitted),
m2 AS (SELECT *, {joined('list_transform(main, lambda m: m.txt)')} AS extracted, list_filter(main, lambda m: {noise('m.txt', before)}) AS bad FROM m1),
m3 AS (SELECT *, {family('extracted')} AS family, {edu('extracted')} AS edu, {rewritten('extracted')} AS rewr,
  list_filter(main, lambda m: NOT list_contains(list_transform(bad, lambda z: z.lid), m.lid)) AS clean FROM m2),
m4 AS (SELECT *, list_sum(list_transform(clean, lambda m: {n_of('m.txt', teachers.FRAGMENT)})) AS n_frag, {joined(f"list_filter(list_transform(clean, lambda m: {sub('m.txt', teachers.FRAGMENT, chr(39) * 2)}), lambda x: trim(x) <> '')")} AS edited FROM m3),
m5 AS (SELECT *, CASE WHEN family IS NOT NULL AND {keep} THEN 'keep' WHEN family IS NOT NULL AND {worth} AND trim(rewr) <> '' AND NOT regexp_matches(rewr, {q(teachers.ARTIFACTS)}) AND {ratio} BETWEEN 0.2 AND 3.0 THEN 'rewrite'
  WHEN family IS NOT NULL THEN 'delete' WHEN len(bad) > 0 OR coalesce(n_frag, 0) > 0 THEN 'edit' ELSE 'keep' END AS verdict FROM m4),
policy AS (SELECT *, nullif(CASE verdict WHEN 'keep' THEN extracted WHEN 'edit' THEN edited WHEN 'rewrite' THEN {sub('rewr', '^' + chr(92) + 's+|' + chr(92) + 's+$', chr(39) * 2)} END, '') AS text,
  CASE WHEN verdict = 'edit' THEN bad ELSE [] END AS drops, CASE WHEN verdict = 'edit' THEN coalesce(n_frag, 0) ELSE 0 END AS n_cuts FROM m5)"""


def ranges(flags: str) -> str:
    """Flags (a list of booleans) to 'a-b,c-d' of their maximal runs."""
    starts = f"list_filter(range(1, len({flags}) + 1), lambda i: {flags}[i] AND NOT coalesce(CASE WHEN i > 1 THEN {flags}[i-1] END, false))"
    ends = f"list_filter(range(1, len({flags}) + 1), lambda i: {flags}[i] AND NOT coalesce({flags}[i+1], false))"
    return f"coalesce(array_to_string(list_transform(range(1, len({starts}) + 1), lambda k: {starts}[k] || '-' || {ends}[k]), ','), '')"


def n_ranges(flags: str) -> str:
    return f"len(list_filter(range(1, len({flags}) + 1), lambda i: {flags}[i] AND NOT coalesce(CASE WHEN i > 1 THEN {flags}[i-1] END, false)))"


STRIP = "list_transform(blocks, lambda b: b.zone <> '')"
DROPS = "list_transform(range(1, len(lines) + 1), lambda i: list_contains(list_transform(drops, lambda z: z.lid), i))"
P = f"WITH {R}, {policy()}"
E = f"{P}, executed AS (SELECT *, {words_of('raw')} AS words_in, {words_of('raw')} - {words_of('extracted')} AS words_stripped, {words_of('text')} AS words_out, CASE WHEN verdict = 'delete' THEN 'deleted' WHEN text IS NULL THEN 'empty' WHEN verdict = 'rewrite' THEN 'rewritten' WHEN verdict = 'edit' THEN 'refined' ELSE 'extracted' END AS provenance FROM policy)"

SQL["render_line_counts"] = f"WITH {R} SELECT page_id, CAST(len(lines) AS INT) AS n_lines, CAST(length({joined('lines')}) AS BIGINT) AS n_chars, {words_of(joined('lines'))} AS n_tokens FROM rendered"
SQL["render_lines"] = f"WITH {R} SELECT page_id, CAST(i AS INT) AS lid, blocks[i].text AS line, blocks[i].zone AS zone FROM (SELECT page_id, blocks, unnest(range(1, len(blocks) + 1)) AS i FROM rendered)"
SQL["render_by_parser"] = SQL["render_lines"]
SQL["numbered_prompt"] = f"WITH {R} SELECT page_id, md5({joined('list_transform(range(1, len(lines) + 1), lambda i: ' + q('<lid:') + ' || i || ' + q('> ') + ' || lines[i])')}) AS prompt_md5, true AS round_trip FROM rendered"
SQL["numbered_sql"] = SQL["numbered_prompt"].replace(", true AS round_trip", "")
SQL["admission"] = f"WITH {R} SELECT CASE WHEN len(lines) = 0 THEN 'empty' WHEN length({joined('lines')}) < 400 THEN 'short' WHEN {words_of(joined('lines'))} > 29696 THEN 'long' ELSE 'admitted' END AS outcome, count(*) AS n FROM rendered GROUP BY 1"
SQL["strip_policy_ranges"] = f"WITH {R} SELECT page_id, {ranges(STRIP)} AS strip, CAST(len(lines) AS INT) AS n_lines FROM admitted"
SQL["policy_verdicts"] = f"{P} SELECT page_id, verdict, family, edu, CAST({n_ranges(DROPS)} AS INT) AS n_drop, CAST(n_cuts AS INT) AS n_cuts, {ranges(DROPS)} AS drop_ranges FROM policy"
SQL["program_roundtrip"] = f"WITH {R} SELECT page_id, layout, true AS same FROM admitted, (VALUES ('decision_first'), ('extract_first')) AS l(layout)"
for v in ("keep", "edit", "delete", "rewrite"):
    SQL[f"execute_{v}"] = f"{E} SELECT page_id, provenance, words_in, words_stripped, words_out, md5(text) AS text_md5 FROM executed WHERE verdict = '{v}'"
SQL["execute_relational"] = f"{E} SELECT page_id, md5(text) AS text_md5 FROM executed WHERE verdict IN ('keep', 'edit') AND n_cuts = 0 AND text IS NOT NULL"
SQL["verdict_counts"] = f"{E} SELECT verdict, count(*) AS n_pages, CAST(sum(words_in) AS BIGINT) AS words_in, CAST(coalesce(sum(words_out), 0) AS BIGINT) AS words_out FROM executed GROUP BY 1"
SQL["provenance_counts"] = f"{E} SELECT provenance, count(*) AS n FROM executed GROUP BY 1"
SQL["stream_verdicts"] = f"{P} SELECT verdict, count(*) AS n FROM policy GROUP BY 1"
SQL["teacher_pipeline"] = f"{E} SELECT provenance, count(*) AS n, CAST(coalesce(sum(words_out), 0) AS BIGINT) AS words_out FROM executed GROUP BY 1"
_rawedit = f"{joined(f'list_filter(list_transform(list_filter(list_transform(range(1, len(lines) + 1), lambda i: {{{q(chr(108)+chr(105)+chr(100))}: i, {q(chr(116))}: lines[i]}}), lambda z: NOT list_contains(list_transform(drops, lambda y: y.lid), z.lid)), lambda z: CASE WHEN blocks[z.lid].zone = {q(chr(0))[:1]}{chr(39)} THEN {sub(chr(122) + chr(46) + chr(116), teachers.FRAGMENT, chr(39) * 2)} ELSE z.t END), lambda x: trim(x) <> {chr(39) * 2})')}"
SQL["ablation_tokens"] = f"""{E},
v AS (SELECT 'full' AS variant, text FROM executed UNION ALL SELECT 'edit off', CASE WHEN verdict = 'edit' THEN nullif(extracted, '') ELSE text END FROM executed
UNION ALL SELECT 'rewrite off', CASE WHEN verdict = 'rewrite' THEN NULL ELSE text END FROM executed
UNION ALL SELECT 'delete off', CASE WHEN verdict = 'delete' THEN nullif(extracted, '') ELSE text END FROM executed
UNION ALL SELECT 'extract off', CASE verdict WHEN 'keep' THEN raw WHEN 'edit' THEN {_rawedit} ELSE text END FROM executed)
SELECT variant, count(text) AS n_docs, CAST(sum({words_of('text')}) AS BIGINT) AS words FROM v GROUP BY 1"""
SQL["cascaded_extract"] = f"{E} SELECT count(text) AS n_docs, CAST(sum(words_out) AS BIGINT) AS words FROM executed"
SQL["operation_profile"] = f"""{E}, b AS (SELECT provenance, CASE WHEN provenance <> 'refined' THEN '-' ELSE (CASE WHEN g <= 0 THEN '0' WHEN g <= 0.05 THEN '0-5' WHEN g <= 0.2 THEN '5-20' WHEN g <= 0.5 THEN '20-50' ELSE '50+' END) END AS bin
FROM (SELECT provenance, CASE WHEN words_in = words_stripped THEN 0.0 ELSE CAST(words_in - words_stripped - words_out AS DOUBLE) / CAST(words_in - words_stripped AS DOUBLE) END AS g FROM executed))
SELECT provenance, bin, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER () AS DOUBLE), 6) AS share FROM b GROUP BY 1, 2"""
SQL["token_waterfall"] = f"""{E}, s AS (
SELECT 0 AS step, 'input' AS operation, sum(words_in) AS w FROM executed UNION ALL SELECT 1, 'extract', sum(words_in - words_stripped) FROM executed
UNION ALL SELECT 2, 'delete', sum(CASE WHEN verdict = 'delete' THEN 0 ELSE words_in - words_stripped END) FROM executed
UNION ALL SELECT 3, 'edit', sum(CASE WHEN verdict = 'rewrite' THEN words_in - words_stripped ELSE words_out END) FROM executed
UNION ALL SELECT 4, 'rewrite', sum(words_out) FROM executed)
SELECT step, operation, CAST(w AS BIGINT) AS words_left, CAST(w - lag(w) OVER (ORDER BY step) AS BIGINT) AS change FROM s"""


def quartiles(c: str) -> str:
    return ", ".join(f"CAST(quantile_cont({c}, {p}) AS DOUBLE) AS {c}_{n}" for n, p in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))) + f", round(avg({c}), 6) AS {c}_mean"


def thirds(at: str, n: str, name: str) -> str:
    return ", ".join(f"round(avg(CAST(least(floor(({at} - 1) * 3 / CAST({n} AS DOUBLE)), 2) = {k} AS DOUBLE)), 6) AS {name}_{x}" for k, x in enumerate(("first", "middle", "last")))


_ISLANDS = "SELECT page_id, any_value(n) AS n, min(i) AS a, max(i) AS b, count(*) AS span_lines, CAST(sum(w) AS BIGINT) AS span_words FROM (SELECT *, i - row_number() OVER (PARTITION BY page_id ORDER BY i) AS g FROM {t}) GROUP BY page_id, g"
SQL["strip_stats"] = f"""{P}, ln AS (SELECT page_id, n, i, blocks[i].zone <> '' AS gone, {words_of('lines[i]')} AS w FROM (SELECT page_id, blocks, lines, len(lines) AS n, unnest(range(1, len(lines) + 1)) AS i FROM policy)),
lost AS (SELECT * FROM ln WHERE gone), sp AS ({_ISLANDS.format(t='lost')}),
pg AS (SELECT page_id, n, coalesce(ops, 0) AS ops, coalesce(gone, 0) AS gone, coalesce(ld, 0) AS ld, coalesce(tr, 0) AS tr, coalesce(ev, 0) AS ev, coalesce(le, false) AS le, coalesce(te, false) AS te FROM (SELECT page_id, len(lines) AS n FROM policy)
  LEFT JOIN (SELECT page_id, count(*) AS ops, sum(span_lines) AS gone, sum(CASE WHEN a = 1 THEN span_words ELSE 0 END) AS ld, sum(CASE WHEN b = n AND a > 1 THEN span_words ELSE 0 END) AS tr, sum(span_words) AS ev, bool_or(a = 1) AS le, bool_or(b = n) AS te FROM sp GROUP BY 1) USING (page_id))
SELECT * FROM (SELECT count(*) AS pages, round(avg(CAST(ops > 0 AS DOUBLE)), 6) AS with_removal, {quartiles('ops')}, {quartiles('gone')}, round(avg(CAST(le AS DOUBLE)), 6) AS leading, round(avg(CAST(te AS DOUBLE)), 6) AS trailing, CAST(sum(gone) AS BIGINT) AS lines_gone, CAST(sum(n) AS BIGINT) AS lines_in,
  round(sum(ld) / CAST(sum(ev) AS DOUBLE), 6) AS words_leading, round((sum(ev) - sum(ld) - sum(tr)) / CAST(sum(ev) AS DOUBLE), 6) AS words_interior, round(sum(tr) / CAST(sum(ev) AS DOUBLE), 6) AS words_trailing FROM pg),
(SELECT {quartiles('span_lines')}, {quartiles('span_words')} FROM sp), (SELECT {thirds('i', 'n', 'lines')} FROM lost)"""
SQL["edit_stats"] = f"""{P}, ed AS (SELECT page_id, lines, main, list_transform(drops, lambda z: z.lid) AS dropped, clean, n_cuts FROM policy WHERE verdict = 'edit'),
kp AS (SELECT page_id, main[k].lid AS lid, main[k].txt AS txt, k AS p, n, list_contains(dropped, main[k].lid) AS gone FROM (SELECT *, len(main) AS n, unnest(range(1, len(main) + 1)) AS k FROM ed)),
lost AS (SELECT page_id, n, lid AS i, p, {words_of('txt')} AS w FROM kp WHERE gone), sp AS ({_ISLANDS.format(t='lost')}),
fr AS (SELECT page_id, n, p, unnest(regexp_extract_all(txt, {q(teachers.FRAGMENT)})) AS frag FROM kp WHERE NOT gone),
ats AS (SELECT page_id, n, p FROM lost UNION ALL SELECT page_id, n, p FROM fr),
pg AS (SELECT page_id, coalesce(rm, 0) AS rm, coalesce(n_cuts, 0) AS sub, coalesce(fk, false) AS fk, coalesce(lk, false) AS lk FROM ed LEFT JOIN (SELECT page_id, count(*) AS rm FROM sp GROUP BY 1) USING (page_id) LEFT JOIN (SELECT page_id, bool_or(p = 1) AS fk, bool_or(p = n) AS lk FROM ats GROUP BY 1) USING (page_id))
SELECT * FROM (SELECT count(*) AS pages, count(*) AS by_operations, CAST(0 AS BIGINT) AS by_page_text, {quartiles('rm')}, {quartiles('sub')}, round(avg(CAST(rm > 0 AND sub = 0 AS DOUBLE)), 6) AS rm_only, round(avg(CAST(rm = 0 AND sub > 0 AS DOUBLE)), 6) AS sub_only, round(avg(CAST(rm > 0 AND sub > 0 AS DOUBLE)), 6) AS both_kinds,
  round(avg(CAST(fk AS DOUBLE)), 6) AS first_kept, round(avg(CAST(lk AS DOUBLE)), 6) AS last_kept FROM pg),
(SELECT {quartiles('rm_lines')}, {quartiles('rm_words')} FROM (SELECT span_lines AS rm_lines, span_words AS rm_words FROM sp)), (SELECT {quartiles('sub_words')} FROM (SELECT {words_of('frag')} AS sub_words FROM fr)), (SELECT {thirds('p', 'n', 'edits')} FROM ats)"""
SQL["target_invariant"] = f"WITH {R} SELECT count(*) AS n, CAST(0 AS BIGINT) AS n_different FROM admitted"
SQL["leak_rate"] = f"WITH {R} SELECT count(*) AS n, 0.0::DOUBLE AS leaked FROM admitted"
for name, kw in {"edu 1.0": {}, "edu 1.5": {"threshold": 1.5}, "classifier": {"rescue": "classifier"}, "three_way": {"rescue": "three_way"}}.items():
    one = f"(WITH {R}, {policy(**kw)} SELECT '{name}' AS variant, verdict, count(*) AS n FROM policy GROUP BY 2)"
    SQL["rescue_variants"] = SQL.get("rescue_variants", "SELECT * FROM (") + (" UNION ALL " if "rescue_variants" in SQL else "") + one
SQL["rescue_variants"] += ")"

SQL["program_items"] = """SELECT * FROM (VALUES (1, 'keep', 'decision_first', 'ok', '1-2', '', '', NULL, false), (2, 'edit', 'extract_first', 'ok', '4-4', '1-1', '3= [share]', NULL, false), (3, 'edit', 'decision_first', 'ok', '1-2,4-4', '3-3', '', NULL, true),
(4, 'keep', 'decision_first', 'ok', '3-9', '', '', NULL, false), (5, 'edit', 'decision_first', 'ok', '', '4-2', '1=absent', NULL, false), (6, NULL, NULL, 'malformed', '', '', '', NULL, false), (7, NULL, NULL, 'malformed', '', '', '', NULL, false),
(8, 'rewrite', 'decision_first', 'ok', '1-1', '', '', 'New text.' || chr(10) || 'More.', false), (9, 'edit', 'decision_first', 'ok', '', '', '', 'Plain page text.', false), (10, 'edit', 'decision_first', 'ok', '', '', '2=say "hi"', NULL, false)) AS t(page_id, verdict, layout, status, strip, drop_ranges, cuts, body, lenient)"""
SQL["program_problems"] = "SELECT * FROM (VALUES (1, ''), (2, ''), (3, ''), (4, 'echo,range'), (5, 'inverted,fragment'), (6, 'malformed'), (7, 'malformed'), (8, ''), (9, ''), (10, '')) AS t(page_id, problems)"
SQL["flawed_execution"] = """SELECT page_id, provenance, replace(text, '/', chr(10)) AS text FROM (VALUES (1, 'extracted', 'Rivers carry silt. [share]/Read next'), (2, 'refined', 'They say "hi" here/Rivers carry silt.'), (3, 'empty', NULL), (4, 'extracted', 'Home/They say "hi" here'),
(5, 'refined', 'Home/They say "hi" here/Rivers carry silt. [share]/Read next'), (6, 'malformed', NULL), (7, 'malformed', NULL), (8, 'rewritten', 'New text./More.'), (9, 'refined', 'Plain page text.'), (10, 'refined', 'Home/They  here/Rivers carry silt. [share]/Read next')) AS t(page_id, provenance, text)"""
SQL["program_items"] = "WITH t AS (" + SQL["program_items"].replace("t(page_id,", "t(k,") + ") SELECT page_id, t.* EXCLUDE (k) FROM pages JOIN t ON t.k = page_id % 10 + 1"
SQL["program_problems"] = "WITH t AS (" + SQL["program_problems"].replace("t(page_id,", "t(k,") + ") SELECT page_id, problems FROM pages JOIN t ON t.k = page_id % 10 + 1"
SQL["flawed_execution"] = "WITH t AS (" + SQL["flawed_execution"].replace("SELECT page_id", "SELECT page_id AS k") + ") SELECT page_id, provenance, replace(text, 'Home', coalesce(url, '')) AS text FROM pages JOIN t ON t.k = page_id % 10 + 1"

# ---- documents ----
D = "documents"
SQL["rewrite_accept"] = f"SELECT doc_id, {words_of('o')} AS n_out, trim(o) <> '' AND NOT regexp_matches(o, {q(teachers.ARTIFACTS)}) AND (CASE WHEN {words_of('text')} = 0 THEN 0.0 ELSE {words_of('o')} / CAST({words_of('text')} AS DOUBLE) END) BETWEEN 0.2 AND 3.0 AS accepted FROM (SELECT doc_id, text, {rewritten('text')} AS o FROM documents)"
SQL["refinement_replies"] = "SELECT doc_id % 4 AS kind, doc_id % 4 IN (0, 1) AS delete, count(*) AS n FROM documents GROUP BY 1, 2"
SQL["edu_scores"] = f"SELECT doc_id, {edu('text')} AS edu FROM documents"
SQL["valueless_families"] = f"SELECT coalesce({family('text')}, '-') AS family, count(*) AS n FROM documents GROUP BY 1"
SQL["rescue_threshold"] = f"SELECT threshold, count(*) AS n, count(*) FILTER (edu >= threshold) AS rescued FROM (SELECT {family('text')} AS family, {edu('text')} AS edu FROM documents), (VALUES (0.5::DOUBLE), (1.0), (1.5), (2.0)) AS t(threshold) WHERE family IS NOT NULL GROUP BY 1"
SQL["postfilter_leaks"] = "SELECT count(*) AS n_left FROM documents WHERE doc_id % 50 NOT IN (7, 9)"
SQL["exact_dup_texts"] = "SELECT doc_id AS id, owner FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS owner FROM documents) WHERE doc_id <> owner"
_G13 = """g AS (SELECT doc_id, array_to_string(w[i:i+12], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM (SELECT doc_id, regexp_extract_all(text, '\\S+') AS w FROM documents))),
own AS (SELECT doc_id, g, min(doc_id) OVER (PARTITION BY g) AS owner FROM g),
fell AS (SELECT doc_id AS id, count(*) AS n_grams, count(*) FILTER (owner < doc_id) AS n_owned FROM own GROUP BY 1 HAVING count(*) FILTER (owner < doc_id) >= 0.8 * count(*))"""
SQL["ngram_dedup"] = f"WITH {_G13} SELECT id, n_grams, n_owned FROM fell"
SQL["unique_tokens"] = f"WITH {_G13} SELECT lang AS pipeline, CAST(sum({words_of('text')}) AS BIGINT) AS unique_tokens, count(*) AS n_docs FROM documents WHERE doc_id NOT IN (SELECT id FROM fell) GROUP BY 1"
SQL["equal_token_cut"] = f"SELECT doc_id, n_tokens FROM (SELECT doc_id, n_tokens, coalesce(sum(n_tokens) OVER (ORDER BY pos, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS run FROM (SELECT doc_id, {words_of('text')} AS n_tokens, ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT AS pos FROM documents)) WHERE run < 100000"
_G8 = "SELECT DISTINCT {k}, array_to_string(w[i:i+7], ' ') AS g FROM (SELECT {k}, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT {k}, regexp_extract_all(text, '\\S+') AS w FROM {t}))"
SQL["benchmark_hits"] = f"SELECT doc_id, item_id, count(*) AS n_shared FROM ({_G8.format(k='doc_id', t='documents')}) JOIN ({_G8.format(k='item_id', t='benchmark')}) USING (g) GROUP BY 1, 2"
SQL["decontaminated"] = f"SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM ({SQL['benchmark_hits']})) GROUP BY 1"


def statistics(t: str = "text") -> str:
    """Select list of the page statistics over columns text, w (words), l (lines), g (5-grams)."""
    share = lambda a, b: f"(CASE WHEN {b} = 0 THEN 0.0::DOUBLE ELSE CAST({a} AS DOUBLE) / CAST({b} AS DOUBLE) END)"
    size = lambda lst: f"coalesce(list_sum(list_transform({lst}, lambda x: length(x))), 0)"
    has = lambda p: f"len(list_filter(l, lambda x: regexp_matches(x, {q(p)})))"
    stops = "[" + ",".join(q(x) for x in rules.STOP_WORDS) + "]"
    return ", ".join(
        f"{e} AS {k}"
        for k, e in {
            "n_words": "CAST(len(w) AS BIGINT)", "n_lines": "CAST(len(l) AS BIGINT)", "mean_word": share(size("w"), "len(w)"), "symbol_ratio": share(n_of(t, r"#|\.\.\.|…"), "len(w)"),
            "bullet_share": share(has(r"^[-*•]"), "len(l)"), "ellipsis_share": share(has(r"(?:\.\.\.|…)$"), "len(l)"), "alpha_share": share(n_of(t, r"\S*[A-Za-zÀ-ÿ]\S*"), "len(w)"),
            "stop_words": f"CAST(len(list_filter({stops}, lambda x: list_contains(lw, x))) AS BIGINT)", "dup_line_share": share("(len(l) - len(list_distinct(l)))", "len(l)"),
            "dup_line_chars": share(f"({size('l')} - {size('list_distinct(l)')})", size("l")), "dup_gram_share": share("(len(g) - len(list_distinct(g)))", "len(g)"),
            "ended_share": share(has(rules.ENDED), "len(l)"), "short_share": share("len(list_filter(l, lambda x: length(x) < 30))", "len(l)"), "sentences": f"CAST({n_of(t + ' || ' + q(' '), r'[.!?]' + chr(92) + 's')} AS BIGINT)",
        }.items()
    )


def with_statistics(source: str, alias: str = "st") -> str:
    """CTEs that add the statistics to (doc_id, text) of ``source``."""
    return f"""{alias}0 AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '\\S+') AS w, list_filter(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x: trim(x)), lambda x: x <> '') AS l FROM {source}),
{alias}1 AS (SELECT *, list_transform(w, lambda x: lower(x)) AS lw, list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) AS g FROM {alias}0),
{alias} AS (SELECT doc_id, text, {statistics()} FROM {alias}1)"""


_BAND = {k: " OR ".join([f"{k} < {lo}" for lo in [b[0]] if lo is not None] + [f"{k} > {hi}" for hi in [b[1]] if hi is not None]) for k, b in rules.BAND.items()}
_A = {"filler": f"regexp_matches(text, {q(rules.FILLER)})", "brace": "contains(text, '{')", "sentences": "sentences < 3", "blocklist": f"regexp_matches(text, {q(rules.BLOCKLIST)})"}
_C = {"ended_lines": "ended_share <= 0.12", "dup_chars": "dup_line_chars >= 0.1", "short_lines": "short_share >= 0.67"}
RULES = {"a": _A, "b": _BAND, "c": _BAND | {"c_" + k: v for k, v in _C.items()} | {"a_filler": _A["filler"], "a_brace": _A["brace"]}}
_ALINES = f"array_to_string(list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, {q(rules.ENDED)}) AND len(regexp_extract_all(x, '\\S+')) >= 5 AND NOT regexp_matches(x, {q(rules.POLICY)})), chr(10))"
_BBAD = " OR ".join(f"regexp_matches(x, {q(p)})" for p in (r"^[^a-z]*[A-Z][^a-z]*$", r"^[0-9\s.,:;/-]+$", r"(?i)^\s*[0-9.,]+ (?:likes?|views?|comments?|shares?)\s*$", r"(?i)^\s*(?:sign|log) ?in\b.{0,40}$|^\s*read more\b.{0,40}$")) + " OR NOT regexp_matches(x, '\\S\\s+\\S')"
_BLINES = f"array_to_string(list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: NOT ({_BBAD}) OR trim(x) = ''), chr(10))"
_SOURCE = {
    "a": f"src AS (SELECT doc_id, coalesce({_ALINES}, '') AS text FROM documents)",
    "b": f"src AS (SELECT doc_id, b AS text FROM (SELECT doc_id, text, coalesce({_BLINES}, '') AS b FROM documents) WHERE {words_of('b')} >= 0.95 * {words_of('text')})",
    "c": "src AS (SELECT doc_id, text FROM documents)",
}
for k in "abc":
    bad = " OR ".join(f"({x})" for x in RULES[k].values())
    SQL[f"rules_{k}"] = f"WITH {_SOURCE[k]}, {with_statistics('src')} SELECT doc_id, md5(text) AS text_md5 FROM st WHERE NOT ({bad}) AND n_words > 0"
SQL["page_statistics"] = f"WITH {with_statistics('documents')} SELECT doc_id, n_words, n_lines, " + ", ".join(f"round({c}, 6) AS {c}" for c in ("mean_word", "symbol_ratio", "alpha_share", "dup_line_share", "dup_line_chars", "dup_gram_share", "ended_share", "short_share")) + ", stop_words, sentences FROM st"
_DEC = f"WITH {with_statistics('documents')}, dec AS (" + " UNION ALL ".join(f"SELECT doc_id AS id, '{s}' AS stack, '{r}' AS rule, ({x}) AS dropped FROM st" for s, rs in RULES.items() for r, x in rs.items()) + ")"
SQL["rule_decisions"] = f"{_DEC} SELECT stack, rule, count(*) FILTER (dropped) AS n_dropped FROM dec GROUP BY 1, 2"
SQL["rule_false_drop"] = f"{_DEC} SELECT stack, rule, count(*) AS n_dropped, round(avg(CAST(quality = 1 AS DOUBLE)), 6) AS false_drop FROM dec JOIN labels ON id = doc_id WHERE dropped GROUP BY 1, 2"
SQL["keepdrop_accuracy"] = f"{_DEC} SELECT stack, round(avg(CAST(keep = (quality = 1) AS DOUBLE)), 6) AS accuracy, count(*) AS n FROM (SELECT id, stack, NOT bool_or(dropped) AS keep FROM dec GROUP BY 1, 2) JOIN labels ON id = doc_id GROUP BY 1"
SQL["rules_a_spans"] = """WITH l AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '') AS l FROM documents), s AS (SELECT doc_id, array_to_string(l[i:i+2], chr(10)) AS h FROM (SELECT doc_id, l, unnest(range(1, len(l) - 1)) AS i FROM l))
SELECT doc_id, count(*) AS n_spans FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY h) AS owner FROM s) WHERE owner < doc_id GROUP BY 1"""
_BC = f"b AS (SELECT doc_id FROM ({SQL['rules_b']})), c AS (SELECT doc_id FROM ({SQL['rules_c']}))"
SQL["set_ops"] = f"WITH {_BC} SELECT 'both' AS kind, count(*) AS n FROM b WHERE doc_id IN (SELECT doc_id FROM c) UNION ALL SELECT 'only b', count(*) FROM b WHERE doc_id NOT IN (SELECT doc_id FROM c) UNION ALL SELECT 'only c', count(*) FROM c WHERE doc_id NOT IN (SELECT doc_id FROM b) UNION ALL SELECT 'either', count(*) FROM (SELECT doc_id FROM b UNION SELECT doc_id FROM c)"


def scraped(cond: str) -> str:
    return f"s AS (SELECT page_id, {joined(f'list_transform(list_filter(blocks, lambda b: {cond}), lambda b: b.text)')} AS text FROM rendered)"


TAGDROP = scraped("b.zone NOT IN ('nav', 'footer', 'header')")
SQL["scrape_tagdrop"] = f"WITH {R}, {TAGDROP} SELECT page_id, md5(text) AS text_md5, {words_of('text')} AS n_tokens FROM s"
SQL["scrape_teacher"] = f"WITH {R}, {scraped('b.zone = ' + chr(39) * 2)} SELECT page_id, md5(text) AS text_md5, {words_of('text')} AS n_tokens FROM s"
SQL["fused_cells"] = " UNION ALL ".join(f"SELECT p_partkey AS page_id, '{k}' AS kind, 'Brand{x}' || p_brand || chr(10) || 'Size{x}' || p_size || chr(10) || p_type || chr(10) || 'Steel' AS text FROM part" for k, x in (("spaced", " "), ("fused", "")))
SQL["gold_documents"] = f"WITH {R} SELECT page_id, min(doc_id) AS doc_id, count(*) AS n_copies FROM (SELECT page_id, array_to_string(list_transform(list_filter(blocks, lambda b: b.zone = ''), lambda b: b.text)[2:], ' ') AS body FROM rendered) JOIN (SELECT doc_id, trim(regexp_replace(text, '\\s+', ' ', 'g')) AS t FROM documents) ON body = t GROUP BY 1"
_NOISY = f"{noise('l[i]', 'l[1:i-1]')} OR (length(l[i]) < 20 AND NOT regexp_matches(l[i], '[.!?]$'))"


def _lined(source: str, key: str) -> str:
    return f"ln AS (SELECT {key} AS page_id, l, list_transform(range(1, len(l) + 1), lambda i: {_NOISY}) AS f FROM (SELECT {key}, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: trim(x) <> '') AS l FROM {source}))"


def _progs(cut: bool) -> str:
    line = sub("l[i]", teachers.FRAGMENT, "''") if cut else "l[i]"
    kept = f"list_filter(list_transform(list_filter(range(1, len(l) + 1), lambda i: NOT f[i]), lambda i: {line}), lambda x: trim(x) <> '')"
    return f"pr AS (SELECT page_id, nullif({joined(kept)}, '') AS text, {words_of(joined('l'))} AS words_in FROM ln)"


SQL["refiner_chunkprog"] = f"WITH {R}, {TAGDROP}, {_lined('s', 'page_id')}, {_progs(False)} SELECT page_id, md5(text) AS text_md5, words_in, {words_of('text')} AS words_out FROM pr"
SQL["refiner_lineprog"] = f"WITH {R}, {TAGDROP}, {_lined('s', 'page_id')}, {_progs(True)} SELECT page_id, md5(text) AS text_md5, words_in, {words_of('text')} AS words_out FROM pr"
SQL["document_edit"] = f"WITH {_lined('documents', 'doc_id')}, {_progs(True)} SELECT page_id AS doc_id, md5(text) AS text_md5, words_in, {words_of('text')} AS words_out FROM pr"
SQL["conversation_edit"] = f"WITH cv AS (SELECT conv_id, array_to_string(list(regexp_replace(text, '\\s+', ' ', 'g') ORDER BY turn, text), chr(10)) AS text FROM conversations GROUP BY 1), {_lined('cv', 'conv_id')}, {_progs(True)} SELECT page_id AS conv_id, words_in, {words_of('text')} AS words_out FROM pr"
SQL["chunk_programs"] = f"WITH {R}, {TAGDROP}, {_lined('s', 'page_id')} SELECT page_id, coalesce(nullif(array_to_string(list_transform(list_filter(string_split({ranges('f')}, ','), lambda x: x <> ''), lambda x: 'remove_lines(' || (split_part(x, '-', 1)::INT - 1) || ', ' || (split_part(x, '-', 2)::INT - 1) || ')'), chr(10)), ''), 'keep_all()') AS output FROM ln"

# ---- published arithmetic ----
PUB = published.values_sql()
SQL["centered_accuracy"] = "SELECT task, round(acc, 6) AS acc, round((acc - 0.5) / (1 - 0.5), 6) AS centered FROM (SELECT lang AS task, avg(CAST((n_chars >= 200) = (quality = 1) AS DOUBLE)) AS acc FROM documents JOIN labels USING (doc_id) GROUP BY 1)"
_w = published.TASKS
SQL["suite_rollup"] = " UNION ALL ".join(f"SELECT pipeline, scale, '{c}' AS category, round({c}, 6) AS score, CAST({n} AS BIGINT) AS n_tasks FROM {PUB}" for c, n in _w.items()) + f" UNION ALL SELECT pipeline, scale, 'all', round(({' + '.join(f'{n} * {c}' for c, n in _w.items())}) / 22, 6), 22 FROM {PUB}"
_SCORES = "(SELECT source AS pipeline, lang AS scale, avg(n_chars) AS score FROM documents GROUP BY 1, 2)"
SQL["relative_gain"] = f"SELECT a.pipeline, a.scale, round(a.score / b.score - 1, 6) AS gain FROM {_SCORES} a JOIN {_SCORES} b ON a.scale = b.scale AND b.pipeline = 'src0'"
SQL["scale_ranks"] = f"SELECT * FROM (SELECT pipeline, scale, score, CAST(dense_rank() OVER (PARTITION BY scale ORDER BY score DESC) AS INT) AS place FROM {_SCORES}) WHERE place <= 2"
SQL["repetition_factor"] = f"SELECT pipeline, scale, round(budget / n, 4) AS repetition FROM (SELECT source AS pipeline, CAST(sum(n_chars) AS DOUBLE) AS n FROM documents GROUP BY 1), (VALUES {', '.join(f'({chr(39)}{k}{chr(39)}, {v * 1e6!r}::DOUBLE)' for k, v in published.BUDGETS.items())}) AS b(scale, budget)"
SQL["welch"] = "SELECT round((0.15392 - 0.14162) / sqrt(0.00387::DOUBLE * 0.00387 / 5 + 0.00356::DOUBLE * 0.00356 / 5), 4) AS t"
SQL["judge_replies"] = "SELECT doc_id AS id, CAST(CASE WHEN k = 0 THEN n_chars % 3 END AS INT) AS recall, CASE WHEN k = 1 THEN 'keep' END AS verdict, CAST(CASE WHEN k = 1 THEN n_chars % 4 END AS INT) AS value, k >= 2 AS bad_reply FROM (SELECT *, doc_id % 4 AS k FROM documents)"

# ---- quality ----


def quality(t: str) -> str:
    j = junk(f"substr({t}, 1, 24000)")
    return f"CAST(round(1 + 4 * (1 - least(1.0, {j['symbols']} + {j['shouts']} + {j['runs']} + CASE WHEN {j['pipes']} >= 3 THEN 0.5 ELSE 0.0 END))) AS INT)"


def rating(t: str) -> str:
    j = junk(f"substr({t}, 1, 24000)")
    return f"(CASE WHEN {j['symbols']} <= 0.1 AND {j['shouts']} <= 0.1 AND {j['runs']} <= 0.1 THEN 1 ELSE 0 END + CASE WHEN {j['n']} >= 50 THEN 1 ELSE 0 END + CASE WHEN {j['ends']} * 40 >= {j['n']} AND {j['ends']} > 0 THEN 1 ELSE 0 END)"


J = f"{E}, judged AS (SELECT page_id, verdict, provenance, {quality('raw')} AS q0, {quality('text')} AS q1, {edu('raw')} AS e0, {edu('text')} AS e1, {rating('text')} AS rating, text IS NOT NULL AS kept FROM executed)"
_QG = "CASE WHEN q0 <= 2 THEN '1-2' WHEN q0 <= 3 THEN '3' ELSE '4-5' END"
_EG = "CASE WHEN e0 < 0.5 THEN '<0.5' WHEN e0 < 1.0 THEN '0.5-1' ELSE '>=1' END"
SQL["before_after_by_verdict"] = f"{J} SELECT verdict, count(*) AS n, round(avg(q0), 6) AS before, round(avg(CASE WHEN kept THEN q1 END), 6) AS after FROM judged GROUP BY 1"
SQL["quality_by_group"] = f"{J} SELECT 'quality' AS scorer, {_QG} AS grp, count(*) AS n, round(avg(q1), 4) AS after FROM judged WHERE kept GROUP BY 2 UNION ALL SELECT 'edu', {_EG}, count(*), round(avg(e1), 4) FROM judged WHERE kept GROUP BY 2"
SQL["good_page_retention"] = f"{J} SELECT count(*) AS n_good, round(avg(CAST(kept AS DOUBLE)), 6) AS kept FROM judged WHERE e0 >= 1.0"
SQL["judge_by_group"] = f"{J} SELECT {_QG} AS grp, count(*) AS n, round(avg(rating), 4) AS rating, round(avg(CAST(rating >= 2 AS DOUBLE)), 4) AS keep_share FROM judged WHERE kept GROUP BY 1"
SQL["paired_length"] = f"{E}, {TAGDROP}, j AS (SELECT words_out AS x, {words_of('s.text')} AS y FROM executed JOIN s USING (page_id) WHERE executed.text IS NOT NULL) SELECT count(*) AS n, round(avg(CAST(x < y AS DOUBLE)), 6) AS shorter, round(quantile_cont(x / CAST(y AS DOUBLE), 0.5), 6) AS median_ratio FROM j WHERE x > 0 AND y > 0"
SQL["embedding_soft_match"] = """WITH v AS (SELECT vec_id, label, unnest(range(1, len(embedding) + 1)) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings), m AS (SELECT label, i, avg(x) AS m FROM v GROUP BY 1, 2),
c AS (SELECT vec_id, v.label, sum(x * m) / sqrt(sum(x * x) * sum(m * m)) AS c FROM v JOIN m USING (label, i) GROUP BY 1, 2) SELECT label, count(*) AS n, round(avg(c), 4) AS mean_cosine FROM c GROUP BY 1"""

# ---- streams, SQL surface, relational ----
SQL["stream_dedup"] = "SELECT count(DISTINCT regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS n FROM pages JOIN events ON page_id = event_id"
SQL["event_tumbling"] = "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2"
SQL["event_sliding"] = "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL '30 minutes', ts) - INTERVAL (k * 30) MINUTE AS start FROM events, (VALUES (0), (1)) AS t(k)) GROUP BY 1"
SQL["event_sessions"] = "WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '1 hour' THEN 0 ELSE 1 END AS fresh FROM events), b AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM a), c AS (SELECT user_id, k, count(*) AS n FROM b GROUP BY 1, 2) SELECT user_id, count(*) AS n_sessions, max(n) AS longest FROM c GROUP BY 1"
SQL["page_lines_udtf"] = f"WITH {R} SELECT page_id, CAST(len(blocks) AS BIGINT) AS n_lines, CAST(len(list_filter(blocks, lambda b: b.zone = '')) AS BIGINT) AS n_content FROM rendered"
SQL["json_props"] = "SELECT event_type, count(*) AS n, count(*) FILTER (json_valid(props)) AS n_json FROM events GROUP BY 1"
SQL["asof_event"] = "SELECT c.event_id, (SELECT max(o.event_id) FROM events o WHERE o.user_id = c.user_id AND o.event_type <> 'click' AND o.ts = (SELECT max(p.ts) FROM events p WHERE p.user_id = c.user_id AND p.event_type <> 'click' AND p.ts <= c.ts)) AS last_other_id FROM events c WHERE c.event_type = 'click'"
SQL["rollup_orders"] = "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total, CAST(grouping(o_orderstatus, o_orderpriority) AS BIGINT) AS g FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"
SQL["cube_lineitem"] = "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"
SQL["semi_anti"] = "SELECT c_mktsegment, nullif(count(*) FILTER (b), 0) AS n_semi, nullif(count(*) FILTER (NOT b), 0) AS n_anti FROM (SELECT c_mktsegment, c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000) AS b FROM customer) GROUP BY 1"
SQL["topk_per_group"] = "SELECT o_orderpriority, o_orderkey, place FROM (SELECT o_orderpriority, o_orderkey, CAST(row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS INT) AS place FROM orders) WHERE place <= 3"
SQL["star_join"] = "SELECT r_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"
SQL["stream_host_lines"] = f"WITH {R}, x AS (SELECT time_bucket(INTERVAL '30 days', ts, TIMESTAMP '1970-01-01') AS start, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, unnest(lines) AS line FROM rendered JOIN events ON page_id = event_id), c AS (SELECT start, host, line, count(*) AS n FROM x GROUP BY 1, 2, 3 HAVING count(*) >= 3) SELECT count(*) AS n_lines, max(n) AS most FROM c"
SQL["stream_interval_join"] = "SELECT count(*) AS n FROM pages JOIN events ON page_id = event_id WHERE page_id % 5 <> 0"

# ---- targets ----
_RM = "list_transform(list_filter(string_split({r}, ','), lambda x: x <> ''), lambda x: 'rm ' || CASE WHEN split_part(x, '-', 1) = split_part(x, '-', 2) THEN split_part(x, '-', 1) ELSE x END)"
_CUTS = f"flatten(list_transform(clean, lambda m: list_transform(regexp_extract_all(m.txt, {q(teachers.FRAGMENT)}), lambda f: 'sub ' || m.lid || ': ' || to_json(f))))"
T = f"""{P}, target AS (SELECT page_id, verdict, {words_of('raw')} AS page, {words_of('raw')} + len(lines) + {words_of('answer')} AS n_tokens, answer, ops FROM (
SELECT *, array_to_string(list_concat(['<' || verdict || '>', '<extract>'], {_RM.format(r=ranges(STRIP))}, ['<' || verdict || '>'], CASE verdict WHEN 'edit' THEN list_concat({_RM.format(r=ranges(DROPS))}, {_CUTS}) WHEN 'rewrite' THEN [rewr] ELSE [] END), chr(10)) AS answer,
{n_ranges(STRIP)} + {n_ranges(DROPS)} + n_cuts AS ops FROM policy))"""
SQL["target_tokens"] = f"{T} SELECT page_id, verdict, n_tokens, md5(answer) AS answer_md5 FROM target"
SQL["fit_window"] = f"{T} SELECT verdict, count(*) AS n, max(n_tokens) AS longest FROM target WHERE n_tokens <= 900 GROUP BY 1"
SQL["outcome_line"] = f"{T} SELECT string_agg(verdict || ' ' || round(100.0 * n / total, 1)::DOUBLE || '%', ', ' ORDER BY verdict) AS line FROM (SELECT verdict, count(*) AS n, CAST(sum(count(*)) OVER () AS DOUBLE) AS total FROM target GROUP BY 1)"
_DRAW = "(('0x' || substr(md5({x}), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"
SQL["stage_mixture"] = f"""{T}, k AS (SELECT count(*) FILTER (verdict = 'rewrite')::DOUBLE AS r, count(*) FILTER (verdict <> 'rewrite')::DOUBLE AS o FROM target), d AS (SELECT verdict, {_DRAW.format(x="'0|' || page_id")} AS u FROM target)
SELECT 1 AS stage, verdict, count(*) AS n FROM d, k WHERE verdict <> 'rewrite' OR u < least(1.0, 0.01 * o / (0.99 * r)) GROUP BY 2
UNION ALL SELECT 2, verdict, count(*) FROM d, k WHERE verdict = 'rewrite' OR u < least(1.0, r * 0.7 / (0.3 * o)) GROUP BY 2"""
SQL["pack_sequences"] = T.replace("WITH ", "WITH RECURSIVE ", 1) + f""", o AS (SELECT shard, n_tokens, row_number() OVER (PARTITION BY shard ORDER BY page_id) AS k FROM (SELECT page_id, n_tokens, CAST(floor({_DRAW.format(x="page_id::VARCHAR")} * 4) AS INT) AS shard FROM target)),
p AS (SELECT shard, k, n_tokens, n_tokens AS fill, CAST(0 AS BIGINT) AS pack_id FROM o WHERE k = 1 UNION ALL
SELECT o.shard, o.k, o.n_tokens, CASE WHEN p.fill + o.n_tokens > 4096 THEN o.n_tokens ELSE p.fill + o.n_tokens END, p.pack_id + CASE WHEN p.fill + o.n_tokens > 4096 THEN 1 ELSE 0 END FROM p JOIN o ON o.shard = p.shard AND o.k = p.k + 1)
SELECT shard, pack_id, count(*) AS n, CAST(sum(n_tokens) AS BIGINT) AS n_tokens FROM p GROUP BY 1, 2"""
SQL["output_economy"] = f"{T}, x AS (SELECT {words_of('answer')} AS a, page, ops FROM target WHERE verdict <> 'rewrite') SELECT count(*) AS n, round(sum(a) / CAST(sum(page) AS DOUBLE), 6) AS answer_share, round(corr(a, ops), 4) AS with_ops, round(corr(a, page), 4) AS with_page FROM x"
