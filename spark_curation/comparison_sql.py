"""DuckDB SQL for the comparisons of pipelines, written against the tables alone."""

from __future__ import annotations

from spark_curation.operators import scrapers, teachers
from spark_curation.oracles import E, R, RULES, T, TAGDROP, _SOURCE, _lined, _progs, edu, family, policy, q, quality, rating, rewritten, scraped, sub, with_statistics, words_of

SQL: dict[str, str] = {}
_WS = "regexp_extract_all(lower({t}), '\\S+')"
_U = "(('0x' || substr(md5({x}), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def _bad(k: str) -> str:
    return " OR ".join(f"({x})" for x in RULES[k].values())


def ruled(k: str, source: str, alias: str) -> str:
    """CTEs of a rule stack over (page_id, text) of ``source``; the result is ``alias``."""
    src = _SOURCE[k].replace("src AS", f"{alias}s AS").replace("FROM documents", f"FROM (SELECT page_id AS doc_id, text FROM {source})")
    return f"{src}, {with_statistics(f'{alias}s', f'{alias}t')}, {alias} AS (SELECT doc_id AS page_id, text FROM {alias}t WHERE NOT ({_bad(k)}) AND n_words > 0 AND text <> '')"


def lineprog(source: str, alias: str, cut: bool = True) -> str:
    return f"{_lined(source, 'page_id').replace('ln AS', f'{alias}l AS', 1)}, {_progs(cut).replace('pr AS', f'{alias}p AS', 1).replace('FROM ln', f'FROM {alias}l')}, {alias} AS (SELECT page_id, text FROM {alias}p WHERE text <> '')"


def routed(source: str, key: str, alias: str) -> str:
    """CTEs of the chunk router; ``alias`` has a row for each chunk, ``alias``_out one for each document."""
    grown = "CASE WHEN a.open = '' THEN b.open ELSE a.open || chr(10) || b.open END"
    step = f"CASE WHEN length({grown}) >= 1500 THEN {{'done': list_append(a.done, {grown}), 'open': ''}} ELSE {{'done': a.done, 'open': {grown}}} END"
    cleaned = f"array_to_string(list_filter(list_transform(string_split(chunk, chr(10)), lambda x: {sub('x', teachers.FRAGMENT, chr(39) * 2)}), lambda x: NOT regexp_matches(x, {q(teachers.NOTICE)}) AND trim(x) <> ''), chr(10))"
    return f"""{alias}0 AS (SELECT {key} AS page_id, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: trim(x) <> '') AS l FROM {source}),
{alias}1 AS (SELECT page_id, list_reduce(list_transform(l, lambda x: {{'done': CAST([] AS VARCHAR[]), 'open': x}}), lambda a, b: {step}, {{'done': CAST([] AS VARCHAR[]), 'open': ''}}) AS acc FROM {alias}0 WHERE len(l) > 0),
{alias}2 AS (SELECT page_id, CASE WHEN acc.open = '' THEN acc.done ELSE list_append(acc.done, acc.open) END AS c FROM {alias}1),
{alias}3 AS (SELECT page_id, i, c[i] AS chunk FROM (SELECT page_id, c, unnest(range(1, len(c) + 1)) AS i FROM {alias}2)),
{alias}4 AS (SELECT *, {family('chunk')} AS fam, regexp_matches(chunk, {q(teachers.FRAGMENT)}) OR regexp_matches(chunk, {q(teachers.NOTICE)}) AS noisy FROM {alias}3),
{alias} AS (SELECT *, CASE WHEN fam IN ('spam', 'listing', 'ui_only') THEN 'drop' WHEN fam = 'gibberish' THEN 'guided' WHEN noisy THEN 'clean' ELSE 'keep' END AS route FROM {alias}4),
{alias}_out AS (SELECT page_id, nullif(coalesce(string_agg(o, chr(10) ORDER BY i), ''), '') AS text, count(*) AS n_chunks, count(*) FILTER (route = 'drop') AS n_dropped, count(*) FILTER (route = 'clean') AS n_cleaned, count(*) FILTER (route = 'guided') AS n_guided
  FROM (SELECT *, CASE route WHEN 'keep' THEN chunk WHEN 'clean' THEN {cleaned} WHEN 'guided' THEN {rewritten('chunk')} END AS o FROM {alias}) GROUP BY page_id)"""


SQL["chunk_route"] = f"WITH {routed('documents', 'doc_id', 'ch')} SELECT page_id AS doc_id, n_chunks, n_dropped, n_cleaned, n_guided, {words_of('text')} AS words_out FROM ch_out"

#: All texts of all pipelines as ``corpus``, and what deduplication leaves as ``uniq``.
CORPUS = f"""{E}, {TAGDROP}, s1 AS (SELECT page_id, text FROM s WHERE text <> ''), {ruled('a', 's', 'ra')}, {ruled('b', 's', 'rb')}, {ruled('c', 's', 'rc')}, {lineprog('s', 'lc', False)}, {lineprog('s', 'lp')}, {routed('s', 'page_id', 'ch')},
corpus0 AS (SELECT 'raw' AS pipeline, page_id, text FROM s UNION ALL SELECT 'rules_a', page_id, text FROM ra UNION ALL SELECT 'rules_b', page_id, text FROM rb UNION ALL SELECT 'rules_c', page_id, text FROM rc
UNION ALL SELECT 'refiner_chunkprog', page_id, text FROM lc UNION ALL SELECT 'refiner_lineprog', page_id, text FROM lp UNION ALL SELECT 'orchestrated', page_id, text FROM ch_out WHERE text <> '' UNION ALL SELECT 'unified', page_id, text FROM executed WHERE text IS NOT NULL),
corpus AS MATERIALIZED (SELECT *, {words_of('text')} AS n_tokens FROM corpus0)"""
_DEDUP = """
g13 AS (SELECT pipeline, page_id, array_to_string(w[i:i+12], ' ') AS g FROM (SELECT pipeline, page_id, w, unnest(range(1, len(w) - 11)) AS i FROM (SELECT pipeline, page_id, regexp_extract_all(text, '\\S+') AS w FROM corpus))),
own13 AS (SELECT pipeline, page_id, min(page_id) OVER (PARTITION BY pipeline, g) AS owner FROM g13),
fell AS (SELECT pipeline, page_id FROM own13 GROUP BY 1, 2 HAVING count(*) FILTER (owner < page_id) >= 0.8 * count(*)),
uniq AS MATERIALIZED (SELECT * FROM corpus ANTI JOIN fell USING (pipeline, page_id))"""
U = f"{CORPUS}, {_DEDUP}"
SQL["main_unique_tokens"] = f"{U} SELECT pipeline, CAST(sum(n_tokens) AS BIGINT) AS unique_tokens, count(*) AS n_docs FROM uniq GROUP BY 1"


def run_of(source: str) -> str:
    pos = "('0x' || substr(md5(page_id::VARCHAR), 1, 8))::BIGINT"
    return f"(SELECT *, coalesce(sum(n_tokens) OVER (PARTITION BY pipeline ORDER BY {pos}, page_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS run FROM {source})"


_SCALES = """tot AS (SELECT pipeline, CAST(sum(n_tokens) AS DOUBLE) AS t FROM uniq GROUP BY 1), unit AS (SELECT t AS u FROM tot WHERE pipeline = 'unified'),
scaled AS MATERIALIZED (SELECT r.pipeline, scale, page_id, text, n_tokens, greatest(1.0, f * u / t) AS rep FROM """ + run_of("uniq") + """ r JOIN tot USING (pipeline), unit, (VALUES ('S', 1.0::DOUBLE), ('M', 4.0), ('L', 7.5)) AS x(scale, f) WHERE run < f * u)"""
SQL["main_repetition"] = f"{U}, {_SCALES} SELECT pipeline, scale, CAST(sum(n_tokens) AS BIGINT) AS n_read, round(max(rep), 4) AS repetition FROM scaled GROUP BY 1, 2"


def offered(source: str, alias: str) -> str:
    """CTE of four candidates for each (task, id, last, tail) of ``source``."""
    ranked = f"(SELECT task, id, last, tail, b, row_number() OVER (PARTITION BY task, b ORDER BY id) - 1 AS r, count(*) OVER (PARTITION BY task, b) AS n FROM (SELECT *, CAST(floor({_U.format(x=repr('bucket|') + ' || id')} * 4) AS INT) AS b FROM {source}))"
    return f"{alias} AS (SELECT x.task, x.id, c.choice, list_concat([x.last], y.tail) AS ws FROM {ranked} x, (VALUES (0), (1), (2), (3)) AS c(choice) JOIN {ranked} y ON x.task = y.task AND x.b = y.b AND y.r = (x.r + c.choice) % x.n)"


_SPLIT = "SELECT {task} AS task, id, w[len(w) // 2] AS last, w[len(w) // 2 + 1:] AS tail FROM ({rows}) WHERE len(w) >= 8"
_HELD = _U.format(x="'held|' || doc_id") + " < 0.1"
_CONT = f"co0 AS ({_SPLIT.format(task=repr('continue'), rows='SELECT item_id AS id, ' + _WS.format(t='text') + ' AS w FROM benchmark')}), {offered('co0', 'co')}"
_CONT_DOC = _SPLIT.format(task="'continue_' || lang", rows="SELECT doc_id AS id, lang, " + _WS.format(t="text") + " AS w FROM documents WHERE " + _HELD)
_B4 = f"CAST(floor({_U.format(x=repr('bucket|') + ' || doc_id')} * 4) AS INT)"
TASKS = f"""{_CONT},
la0 AS ({_CONT_DOC}), {offered('la0', 'la')},
od0 AS (SELECT item_id AS id, {_WS.format(t='text')} AS w FROM benchmark), od AS (SELECT 'order' AS task, id, 0 AS choice, w AS ws FROM od0 WHERE len(w) >= 8 UNION ALL
  SELECT 'order', id, 1, list_transform(list_sort(list_transform(range(1, len(w) + 1), lambda i: {{'k': md5((i - 1) || '|' || w[i]), 'x': w[i]}})), lambda p: p.x) FROM od0 WHERE len(w) >= 8),
rp1 AS (SELECT conv_id, max(text) FILTER (k = 1) AS a, max(text) FILTER (k = 2) AS b FROM (SELECT conv_id, text, row_number() OVER (PARTITION BY conv_id ORDER BY turn, text) AS k FROM conversations) GROUP BY 1),
rp0 AS (SELECT 'reply' AS task, conv_id AS id, {_WS.format(t='a')}[-1] AS last, {_WS.format(t='b')} AS tail FROM rp1 WHERE a IS NOT NULL AND b IS NOT NULL AND len({_WS.format(t='a')}) > 0 AND len({_WS.format(t='b')}) > 0), {offered('rp0', 'rp')},
rk0 AS (SELECT doc_id, lang, quality, {_WS.format(t='text')} AS ws, {_B4} AS b FROM documents JOIN labels USING (doc_id)), rk1 AS (SELECT *, row_number() OVER (PARTITION BY lang, b, quality ORDER BY doc_id) - 1 AS r, count(*) OVER (PARTITION BY lang, b, quality) AS n FROM rk0 WHERE len(ws) >= 2),
rk2 AS (SELECT z.doc_id AS id, z.ws AS bad, g.ws AS good FROM rk1 z JOIN rk1 g ON z.quality = 0 AND g.quality = 1 AND z.lang = g.lang AND z.b = g.b AND g.r = z.r % g.n),
asked AS MATERIALIZED (SELECT task, id, choice, ws[i] AS w1, ws[i + 1] AS w2 FROM (SELECT task, id, choice, ws, unnest(range(1, len(ws))) AS i FROM (SELECT * FROM co UNION ALL SELECT * FROM la UNION ALL SELECT * FROM od UNION ALL SELECT * FROM rp UNION ALL SELECT 'rank', id, 0, good FROM rk2 UNION ALL SELECT 'rank', id, 1, bad FROM rk2)))"""


def evaluated(source: str, by: list[str], weight: str = "1.0", tasks: str = "asked") -> str:
    """CTEs ending in ``ev`` (by..., task, n, acc, chance) of the corpora in ``source``."""
    k = ", ".join(by)
    kk = f"{k}, " if by else ""
    groups = f"SELECT DISTINCT {k} FROM {source}" if by else "SELECT 1 AS one"
    return f"""gr AS ({groups}), need AS (SELECT DISTINCT w1 FROM {tasks}),
bi AS MATERIALIZED (SELECT {kk}w1, w2, sum(wt) AS c2 FROM (SELECT {kk}wt, w[i] AS w1, w[i + 1] AS w2 FROM (SELECT {kk}{weight} AS wt, w, unnest(range(1, len(w))) AS i FROM (SELECT *, {_WS.format(t='text')} AS w FROM {source}))) WHERE w1 IN (SELECT w1 FROM need) GROUP BY ALL),
mo AS MATERIALIZED (SELECT *, sum(c2) OVER (PARTITION BY {kk}w1) AS c1 FROM bi),
sc AS (SELECT {kk}task, id, choice, round(avg(ln((coalesce(c2, 0) + 0.1) / (coalesce(c1, 0) + 10000.0))), 6) AS score FROM (SELECT * FROM {tasks}, gr) LEFT JOIN mo USING ({kk}w1, w2) GROUP BY ALL),
be AS (SELECT {kk}task, id, max({{'score': score, 'choice': choice}}) AS best, count(*) AS k FROM sc GROUP BY ALL),
ev AS (SELECT {kk}task, count(*) AS n, round(avg(CAST(best.choice = 0 AS DOUBLE)), 6) AS acc, round(avg(1.0 / k), 6) AS chance FROM be GROUP BY ALL)"""


_CAT = "CASE task WHEN 'continue' THEN 'reading' WHEN 'reply' THEN 'commonsense' WHEN 'rank' THEN 'quality' ELSE 'language' END"


def means(by: list[str]) -> str:
    k = ", ".join(by)
    c = "(acc - chance) / (1 - chance)"
    return f"SELECT {k}, {_CAT} AS category, round(avg({c}), 4) AS score, count(*) AS n_tasks FROM ev GROUP BY ALL UNION ALL SELECT {k}, 'suite', round(avg({c}), 4), count(*) FROM ev GROUP BY ALL"


SQL["main_suite"] = f"{U}, {_SCALES}, {TASKS}, {evaluated('scaled', ['pipeline', 'scale'], 'rep')} {means(['pipeline', 'scale'])}"
SQL["main_ranks"] = f"""WITH m AS (SELECT pipeline, scale, score FROM ({SQL['main_suite']}) WHERE category = 'suite'), r AS (SELECT *, CAST(dense_rank() OVER (PARTITION BY scale ORDER BY score DESC) AS INT) AS place FROM m)
SELECT scale, place, pipeline, score, round(score - base, 4) AS over_rules_b FROM r JOIN (SELECT scale, score AS base FROM m WHERE pipeline = 'rules_b') USING (scale) WHERE place <= 2"""
SQL["proxy_suite"] = f"WITH {TASKS}, known AS (SELECT * FROM documents WHERE NOT ({_HELD})), {evaluated('known', [])} SELECT * FROM ev"
SQL["proxy_bigrams"] = f"SELECT w1, w2, c2, CAST(sum(c2) OVER (PARTITION BY w1) AS BIGINT) AS c1 FROM (SELECT w[i] AS w1, w[i + 1] AS w2, count(*) AS c2 FROM (SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT {_WS.format(t='text')} AS w FROM documents)) GROUP BY 1, 2)"
_G8 = "SELECT DISTINCT {k}, array_to_string(w[i:i+7], ' ') AS g FROM (SELECT {k}, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT {k}, regexp_extract_all(text, '\\S+') AS w FROM {t}))"
SQL["decontaminated_suite"] = f"""WITH {_CONT}, asked AS (SELECT task, id, choice, ws[i] AS w1, ws[i + 1] AS w2 FROM (SELECT task, id, choice, ws, unnest(range(1, len(ws))) AS i FROM co)),
hit AS (SELECT DISTINCT doc_id FROM ({_G8.format(k='doc_id', t='documents')}) JOIN ({_G8.format(k='item_id', t='benchmark')}) USING (g)),
both_ AS (SELECT 'all' AS corpus, text FROM documents UNION ALL SELECT 'clean', text FROM documents ANTI JOIN hit USING (doc_id)), {evaluated('both_', ['corpus'])} SELECT corpus, n, acc, chance FROM ev"""

# ---- scrapers ----
_MARKED = f"regexp_replace(regexp_replace(html, '(?i)<a\\b[^>]*>', chr(2), 'g'), '(?i)</a>', chr(3), 'g')"


def density() -> str:
    """CTEs of the density scraper; the result is ``de``."""
    from spark_curation.oracles import blocks

    stops = "[" + ",".join(q(x) for x in scrapers.STOPS) + "]"
    share = f"(CASE WHEN len(regexp_extract_all(t, '\\S+')) = 0 THEN 0.0 ELSE len(list_filter(regexp_extract_all(lower(t), '\\S+'), lambda w: list_contains({stops}, w))) / CAST(len(regexp_extract_all(t, '\\S+')) AS DOUBLE) END)"
    linked = "coalesce(list_sum(list_transform(regexp_extract_all(x, chr(2) || '[^' || chr(3) || ']*'), lambda y: length(y) - length(regexp_replace(y, '[^' || chr(2) || ']', '', 'g')))), 0)"
    return f"""d0 AS (SELECT page_id, unnest(range(1, len(b) + 1)) AS i, b FROM (SELECT page_id, {blocks(_MARKED)} AS b FROM pages)),
d1 AS (SELECT page_id, i, b[i].text AS x, b[i].zone AS zone FROM d0),
d2 AS (SELECT page_id, i, zone, trim(translate(x, chr(2) || chr(3), '')) AS t, {linked} / CAST(greatest(length(translate(x, chr(2) || chr(3), '')), 1) AS DOUBLE) AS links FROM d1 WHERE trim(translate(x, chr(2) || chr(3), '')) <> ''),
d3 AS (SELECT page_id, i, t, CASE WHEN zone <> '' OR links > {scrapers.LINKED} THEN 'bad' WHEN length(t) < {scrapers.SHORT} THEN 'short' WHEN s >= {scrapers.STOP_HIGH} AND length(t) > {scrapers.LONG} THEN 'good' WHEN s >= {scrapers.STOP_LOW} THEN 'near' ELSE 'bad' END AS c FROM (SELECT *, {share} AS s FROM d2)),
d4 AS (SELECT *, coalesce(last_value(CASE WHEN c IN ('good', 'bad') THEN c END IGNORE NULLS) OVER (PARTITION BY page_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 'bad') AS l,
  coalesce(first_value(CASE WHEN c IN ('good', 'bad') THEN c END IGNORE NULLS) OVER (PARTITION BY page_id ORDER BY i ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 'bad') AS r FROM d3),
de AS (SELECT p.page_id, coalesce(string_agg(t, chr(10) ORDER BY i), '') AS text FROM pages p LEFT JOIN (SELECT * FROM d4 WHERE c = 'good' OR (c = 'near' AND (l = 'good' OR r = 'good')) OR (c = 'short' AND l = 'good' AND r = 'good')) k USING (page_id) GROUP BY 1)"""


SQL["scrape_density"] = f"WITH {density()} SELECT page_id, md5(text) AS text_md5, {words_of('text')} AS n_tokens FROM de"
#: The pages have one article each, so the best subtree is its lines.
_TREE = scraped("b.zone = ''").replace("s AS", "te AS", 1)
SQL["scrape_maintree"] = f"WITH {R}, {_TREE} SELECT page_id, md5(text) AS text_md5, {words_of('text')} AS n_tokens FROM te"
_SCRAPED = f"{density()}, {_TREE}"
_CASCADES = f"WITH {R}, {TAGDROP}, {_SCRAPED}, {ruled('b', 's', 'k1')}, {ruled('b', 'te', 'k2')}, {ruled('b', 'de', 'k3')}, {lineprog('s', 'k4')}, {lineprog('te', 'k5')}, {lineprog('de', 'k6')}"
_MANY = [("tagdrop", "b", "k1"), ("maintree", "b", "k2"), ("teacher", "b", "k2"), ("density", "b", "k3"), ("tagdrop", "lineprog", "k4"), ("maintree", "lineprog", "k5"), ("teacher", "lineprog", "k5"), ("density", "lineprog", "k6")]
SQL["cascade_tokens"] = f"{_CASCADES} " + " UNION ALL ".join(f"SELECT '{a}' AS scraper, '{b}' AS cleaner, count(*) AS n_docs, CAST(sum({words_of('text')}) AS BIGINT) AS words FROM {t} HAVING count(*) > 0" for a, b, t in _MANY)
SQL["scraper_suite"] = f"{_CASCADES}, many AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT '{a} {b}' AS pipeline, text FROM {t}" for a, b, t in _MANY if b == "b" or a == "teacher") + f"), {TASKS}, {evaluated('many', ['pipeline'])} {means(['pipeline'])}"
_GRADES = "list_distinct(list_filter(string_split({x}, chr(10)), lambda z: z <> ''))"
SQL["extraction_judge"] = f"""WITH {R}, {TAGDROP}, {_SCRAPED}, f AS (SELECT 'tagdrop' AS scraper, page_id, text FROM s UNION ALL SELECT 'maintree', page_id, text FROM te UNION ALL SELECT 'teacher', page_id, text FROM te UNION ALL SELECT 'density', page_id, text FROM de),
l AS (SELECT scraper, list_filter(string_split(te.text, chr(10)), lambda z: z <> '') AS g, list_filter(string_split(f.text, chr(10)), lambda z: z <> '') AS f FROM te JOIN f USING (page_id)),
n AS (SELECT scraper, g, f, len(list_distinct(list_intersect(f, g))) AS b, len(list_distinct(g)) AS ng, len(list_distinct(f)) AS nf FROM l),
o AS (SELECT scraper, CASE WHEN ng > 0 AND b / ng::DOUBLE >= 0.99 THEN 2 WHEN ng > 0 AND b / ng::DOUBLE >= 0.5 THEN 1 ELSE 0 END AS recall, CASE WHEN nf > 0 AND b / nf::DOUBLE >= 0.99 THEN 2 WHEN nf > 0 AND b / nf::DOUBLE >= 0.5 THEN 1 ELSE 0 END AS precision,
  CASE WHEN list_filter(g, lambda x: list_contains(f, x)) = list_filter(f, lambda x: list_contains(g, x)) THEN 2 WHEN b > 0 THEN 1 ELSE 0 END AS integrity FROM n)
SELECT scraper, round(avg(recall), 4) AS recall, round(avg(precision), 4) AS precision, round(avg(integrity), 4) AS integrity, round(avg((recall + precision + integrity) / 3.0), 4) AS mean_grade FROM o GROUP BY 1"""


def bag_f1(a: str, b: str) -> str:
    """CTEs ending in ``f1``: bag-of-words measures of (page_id, text) of ``a`` against ``b``."""
    bag = "(SELECT page_id, w, count(*) AS {c} FROM (SELECT page_id, unnest(regexp_extract_all(text, '\\S+')) AS w FROM {t}) GROUP BY 1, 2)"
    return f"""jn AS (SELECT page_id, coalesce(x, 0) AS x, coalesce(y, 0) AS y FROM {bag.format(c='x', t=a)} FULL JOIN {bag.format(c='y', t=b)} USING (page_id, w)),
f1 AS (SELECT page_id, CASE WHEN sum(x) = 0 THEN 0.0 ELSE sum(least(x, y)) / CAST(sum(x) AS DOUBLE) END AS p, CASE WHEN sum(y) = 0 THEN 0.0 ELSE sum(least(x, y)) / CAST(sum(y) AS DOUBLE) END AS r, 2 * sum(least(x, y)) / CAST(sum(x) + sum(y) AS DOUBLE) AS f FROM jn GROUP BY 1)"""


SQL["scraper_f1"] = " UNION ALL ".join(f"(WITH {R}, {TAGDROP}, {_SCRAPED}, {bag_f1(t, 'te')} SELECT '{n}' AS scraper, round(avg(p), 4) AS precision, round(avg(r), 4) AS recall, round(avg(f), 4) AS f1 FROM f1)" for n, t in (("tagdrop", "s"), ("maintree", "te"), ("density", "de"), ("teacher", "te")))

# ---- variants of the executor and of the data ----
_rawedit = f"coalesce(array_to_string(list_filter(list_transform(list_filter(range(1, len(lines) + 1), lambda i: NOT list_contains(list_transform(drops, lambda y: y.lid), i)), lambda i: CASE WHEN blocks[i].zone = '' THEN {sub('lines[i]', teachers.FRAGMENT, chr(39) * 2)} ELSE lines[i] END), lambda x: trim(x) <> ''), chr(10)), '')"
SQL["ablation_suite"] = f"""{E}, va AS MATERIALIZED (SELECT * FROM (SELECT 'full' AS variant, text FROM executed UNION ALL SELECT 'edit off', CASE WHEN verdict = 'edit' THEN nullif(extracted, '') ELSE text END FROM executed
UNION ALL SELECT 'rewrite off', CASE WHEN verdict = 'rewrite' THEN NULL ELSE text END FROM executed UNION ALL SELECT 'delete off', CASE WHEN verdict = 'delete' THEN nullif(extracted, '') ELSE text END FROM executed
UNION ALL SELECT 'extract off', CASE verdict WHEN 'keep' THEN raw WHEN 'edit' THEN {_rawedit} ELSE text END FROM executed) WHERE text IS NOT NULL), {TASKS}, {evaluated('va', ['variant'])} {means(['variant'])}"""
_VARIANTS = " UNION ALL ".join(f"(WITH {R}, {policy(**kw)} SELECT '{n}' AS variant, page_id, verdict, text FROM policy WHERE text IS NOT NULL)" for n, kw in {"edu 1.0": {}, "edu 1.5": {"threshold": 1.5}, "classifier": {"rescue": "classifier"}, "three_way": {"rescue": "three_way"}}.items())
_DRAWN = _U.format(x="'share|' || page_id")
SQL["selection_leaderboard"] = f"""WITH v0 AS MATERIALIZED ({_VARIANTS}), vs AS MATERIALIZED (SELECT variant, share, page_id, text FROM v0, (VALUES (0.1::DOUBLE), (0.3), (1.0)) AS t(share) WHERE verdict <> 'rewrite' OR {_DRAWN} < share), {TASKS}, {evaluated('vs', ['variant', 'share'])},
m AS (SELECT variant, share, score FROM ({means(['variant', 'share'])}) WHERE category = 'suite'), n AS (SELECT variant, share, count(*) AS n_docs, CAST(sum({words_of('text')}) AS BIGINT) AS words FROM vs GROUP BY 1, 2)
SELECT *, CAST(dense_rank() OVER (ORDER BY score DESC) AS INT) AS place FROM n JOIN m USING (variant, share)"""
SQL["share_sweep"] = f"""{T}, k AS (SELECT count(*) FILTER (verdict = 'rewrite')::DOUBLE AS r, count(*) FILTER (verdict <> 'rewrite')::DOUBLE AS o FROM target), d AS (SELECT verdict, n_tokens, {_U.format(x="'0|' || page_id")} AS u FROM target)
SELECT share, verdict, count(*) AS n, CAST(sum(n_tokens) AS BIGINT) AS n_tokens FROM d, k, (VALUES (0.1::DOUBLE), (0.2), (0.3), (0.5)) AS x(share) WHERE verdict = 'rewrite' OR u < least(1.0, r * (1 - share) / (share * o)) GROUP BY 1, 2"""
_DRAW_SEED = _U.format(x="'seed' || seed || '|' || page_id")
_RUNS = f"""{U}, ea AS MATERIALIZED (SELECT pipeline, seed, text FROM uniq, (VALUES (0), (1), (2), (3), (4)) AS x(seed) WHERE pipeline IN ('unified', 'refiner_lineprog') AND {_DRAW_SEED} < 0.5), {TASKS}, {evaluated('ea', ['pipeline', 'seed'])},
runs AS (SELECT pipeline, seed, round(avg((acc - chance) / (1 - chance)), 6) AS score FROM ev GROUP BY 1, 2)"""
SQL["seed_variance"] = f"{_RUNS} SELECT pipeline, count(*) AS n, round(avg(score), 4) AS mean, round(stddev_samp(score), 4) AS sd, round(min(score), 4) AS least, round(max(score), 4) AS most FROM runs GROUP BY 1"
SQL["seed_welch"] = f"{_RUNS}, z AS (SELECT pipeline, avg(score) AS m, stddev_samp(score) AS sd FROM runs GROUP BY 1) SELECT round((a.m - b.m) / sqrt(a.sd * a.sd / 5 + b.sd * b.sd / 5), 2) AS t FROM z a, z b WHERE a.pipeline = 'unified' AND b.pipeline = 'refiner_lineprog'"

# ---- measures of every pipeline's texts ----
_J = f"""{CORPUS}, pg AS (SELECT page_id, {quality('raw')} AS q0, {edu('raw')} AS e0, {words_of('raw')} AS w0 FROM admitted), ps AS (SELECT DISTINCT pipeline FROM corpus),
cs AS (SELECT pipeline, page_id, {edu('text')} AS e1, {quality('text')} AS q1, {rating('text')} AS rating, n_tokens AS w1 FROM corpus WHERE text <> ''), ju AS MATERIALIZED (SELECT * FROM (SELECT * FROM pg, ps) LEFT JOIN cs USING (pipeline, page_id))"""
SQL["profile_by_pipeline"] = f"""{_J}, b AS (SELECT pipeline, CASE WHEN w1 IS NULL THEN 'dropped' WHEN g <= 0 THEN '0' WHEN g <= 0.05 THEN '0-5' WHEN g <= 0.2 THEN '5-20' WHEN g <= 0.5 THEN '20-50' ELSE '50+' END AS bin FROM (SELECT *, (w0 - w1) / CAST(w0 AS DOUBLE) AS g FROM ju))
SELECT pipeline, bin, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER (PARTITION BY pipeline) AS DOUBLE), 6) AS share FROM b GROUP BY 1, 2"""
_GRP = {"quality": "CASE WHEN q0 <= 2 THEN '1-2' WHEN q0 <= 3 THEN '3' ELSE '4-5' END", "edu": "CASE WHEN e0 < 0.5 THEN '<0.5' WHEN e0 < 1.0 THEN '0.5-1' ELSE '>=1' END"}
SQL["groups_by_pipeline"] = f"{_J} " + " UNION ALL ".join(
    f"SELECT pipeline, '{k}' AS scorer, {g} AS grp, count(*) AS n, count(w1) AS n_kept, round(count(*) / CAST(sum(count(*)) OVER (PARTITION BY pipeline) AS DOUBLE), 6) AS share, round(avg({a}), 4) AS after, round(avg(rating), 4) AS rating, round(avg(CASE WHEN rating IS NOT NULL THEN CAST(rating >= 2 AS DOUBLE) END), 4) AS keep_share FROM ju GROUP BY pipeline, {g}"
    for (k, g), a in zip(_GRP.items(), ("q1", "e1"), strict=True)
)
SQL["groups_by_pipeline"] = SQL["groups_by_pipeline"].replace("avg(rating)", "avg(CASE WHEN w1 IS NOT NULL THEN rating END)").replace("CASE WHEN rating IS NOT NULL", "CASE WHEN w1 IS NOT NULL")
SQL["retention_by_pipeline"] = f"{_J}, r AS (SELECT pipeline, count(*) AS n_good, round(avg(CAST(w1 IS NOT NULL AS DOUBLE)), 6) AS kept FROM ju WHERE e0 >= 1.0 GROUP BY 1) SELECT pipeline, n_good, kept, round(kept - (SELECT kept FROM r WHERE pipeline = 'rules_b'), 6) AS over_rules_b FROM r"
for n in (3, 5):
    SQL[f"distinct_{n}grams"] = f"""{U}, le AS (SELECT min(t) AS t FROM (SELECT sum(n_tokens) AS t FROM uniq GROUP BY pipeline)), cu AS (SELECT pipeline, regexp_extract_all(text, '\\S+') AS w FROM {run_of('uniq')}, le WHERE run < t)
SELECT pipeline, count(DISTINCT g) AS n_distinct, count(*) AS n_total, round(count(DISTINCT g) / CAST(count(*) AS DOUBLE), 6) AS share FROM (SELECT pipeline, array_to_string(w[i:i+{n - 1}], ' ') AS g FROM (SELECT pipeline, w, unnest(range(1, len(w) - {n - 2})) AS i FROM cu)) GROUP BY 1"""
SQL["length_profile"] = f"{CORPUS} SELECT pipeline, count(*) AS n, CAST(quantile_cont(n_tokens, 0.5) AS DOUBLE) AS median_tokens, round(avg(CAST(n_tokens < 100 AS DOUBLE)), 6) AS under_100 FROM corpus GROUP BY 1"
SQL["length_histogram"] = f"{CORPUS} SELECT pipeline, CASE WHEN n_tokens > 0 THEN CAST(2 ** floor(log2(n_tokens)) AS BIGINT) ELSE 0 END AS from_tokens, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER (PARTITION BY pipeline) AS DOUBLE), 6) AS share FROM corpus GROUP BY 1, 2"
SQL["curated_pool"] = f"{U} SELECT provenance, count(*) AS n, CAST(sum(n_tokens) AS BIGINT) AS n_tokens FROM uniq JOIN executed USING (page_id) WHERE pipeline = 'unified' GROUP BY 1"
SQL["rendered_once"] = f"WITH {R} SELECT count(*) AS n_pages, CAST(sum(len(lines)) AS BIGINT) AS n_lines, CAST(sum({words_of('raw')}) AS BIGINT) AS n_tokens FROM admitted"

