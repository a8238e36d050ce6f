"""DuckDB SQL for the queries of ``surfaces``, written against the tables alone."""

from __future__ import annotations

from spark_curation.comparison_sql import TAGDROP
from spark_curation.operators import rulebook, rules, teachers
from spark_curation.oracles import E, P, R, edu, family, n_of, policy, q, quality, rewritten, words_of

SQL: dict[str, str] = {}


def protected(x: str) -> str:
    return "(" + " OR ".join(f"regexp_matches({x}, {q(p)})" for p in rulebook.PROTECTED.values()) + ")"


def noise(x: str) -> str:
    return f"(CASE WHEN {protected(x)} THEN NULL " + " ".join(f"WHEN regexp_matches({x}, {q(p)}) THEN '{k}'" for k, p in rulebook.NOISE.items()) + " END)"


_WORTHLESS = f"coalesce({family('text')}, CASE WHEN {n_of('coalesce(text, ' + chr(39) * 2 + ')', rulebook.CALLS)} >= {rulebook.LEAST_CALLS} AND {words_of('text')} <= {rulebook.MOST_WORDS} THEN 'promotion' END)"
SQL["rulebook_lines"] = f"SELECT coalesce({noise('line')}, '-') AS family, count(*) AS n, count(*) FILTER ({protected('line')}) AS n_protected FROM (SELECT unnest(string_split(coalesce(text, ''), chr(10))) AS line FROM documents) WHERE trim(line) <> '' GROUP BY 1"
SQL["rulebook_families"] = f"SELECT coalesce({_WORTHLESS}, '-') AS family, count(*) AS n FROM documents GROUP BY 1"
_SENT = f"regexp_extract_all(line, {q(rulebook.SENTENCE)})"
_LEFT = f"nullif(trim(array_to_string(list_filter({_SENT}, lambda s: {noise('trim(s)')} IS NULL), '')), '')"
SQL["rulebook_apply"] = f"""WITH l AS (SELECT doc_id, i, line FROM (SELECT doc_id, unnest(range(1, len(ls) + 1)) AS i, unnest(ls) AS line FROM (SELECT doc_id, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: trim(x) <> '') AS ls FROM documents))),
c AS (SELECT *, CASE WHEN {protected('line')} THEN line WHEN len({_SENT}) > 1 THEN {_LEFT} WHEN {noise('line')} IS NULL THEN line END AS cl FROM l),
a AS (SELECT doc_id, string_agg(cl, chr(10) ORDER BY i) AS cleaned, count(*) - count(cl) AS gone, count(*) FILTER (cl <> line) AS changed FROM c GROUP BY 1)
SELECT doc_id, family, md5(CASE WHEN family IS NULL THEN nullif(cleaned, '') END) AS cleaned_md5, CAST(coalesce(gone, 0) AS INT) AS lines_gone, CAST(coalesce(changed, 0) AS INT) AS lines_changed FROM (SELECT doc_id, {_WORTHLESS} AS family FROM documents) LEFT JOIN a USING (doc_id)"""
SQL["rules_a_removed"] = """WITH l AS (SELECT doc_id, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: trim(x) <> '') AS l FROM documents), s AS (SELECT doc_id, i, array_to_string(l[i:i+2], chr(10)) AS h FROM (SELECT doc_id, l, unnest(range(1, len(l) - 1)) AS i FROM l)),
g AS (SELECT DISTINCT doc_id, unnest([i, i + 1, i + 2]) AS i FROM (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY h) AS owner FROM s) WHERE owner < doc_id), gg AS (SELECT doc_id, list(i) AS gone FROM g GROUP BY 1),
k AS (SELECT doc_id, l, list_filter(range(1, len(l) + 1), lambda i: NOT list_contains(coalesce(gone, []), i)) AS keep FROM l LEFT JOIN gg USING (doc_id))
SELECT doc_id, md5(coalesce(array_to_string(list_transform(keep, lambda i: l[i]), chr(10)), '')) AS text_md5, CAST(len(l) - len(keep) AS INT) AS n_gone FROM k"""
SQL["rules_b_gate"] = f"SELECT count(*) AS n_pages, count(DISTINCT url) AS n_urls FROM pages WHERE NOT regexp_matches(url, {q(rules.BLOCKED_URL)}) AND lower(regexp_extract(html, '(?i)<html[^>]*\\blang=\"?([a-z]+)', 1)) = 'en'"
SQL["lines_absent"] = f"WITH {R}, {TAGDROP} SELECT page_id, CAST(len(list_filter(blocks, lambda b: b.zone IN ('nav', 'footer', 'header') AND NOT list_contains(string_split(text, chr(10)), b.text))) AS INT) AS n_absent, CAST(len(lines) AS INT) AS n_lines FROM rendered JOIN s USING (page_id)"
_W = "regexp_extract_all(coalesce(text, ''), '\\S+')"
SQL["head_tail"] = f"SELECT doc_id, {words_of('t')} AS n, md5(t) AS text_md5 FROM (SELECT doc_id, CASE WHEN len({_W}) > 100 THEN array_to_string(list_concat({_W}[1:50], {_W}[-50:]), ' ') ELSE text END AS t FROM documents)"
SQL["refining_cap"] = f"SELECT {words_of(rewritten('text'))} <= {words_of('text')} + 256 AS ok, count(*) AS n FROM documents GROUP BY 1"
SQL["page_edit_audit"] = f"{E} SELECT count(*) AS n, 1.0::DOUBLE AS pure_deletion, round(avg(CAST(regexp_extract_all(text, '\\S+') <> regexp_extract_all(extracted, '\\S+') AS DOUBLE)), 6) AS changed FROM executed WHERE verdict = 'edit' AND text IS NOT NULL"
_RW = f"(SELECT {words_of('text')} AS a, {words_of('o')} AS b, trim(o) <> '' AND NOT regexp_matches(o, {q(teachers.ARTIFACTS)}) AS fine FROM (SELECT text, {rewritten('text')} AS o FROM documents))"
SQL["rewrite_lengths"] = f"SELECT count(*) AS n, round(avg(b / nullif(CAST(a AS DOUBLE), 0)), 6) AS mean_ratio, count(*) FILTER (fine AND (CASE WHEN a = 0 THEN 0.0 ELSE b / CAST(a AS DOUBLE) END) BETWEEN 0.2 AND 3.0) AS n_accepted FROM {_RW}"

_LED = "(SELECT CASE o_orderstatus WHEN 'F' THEN 'once' WHEN 'O' THEN 'per pool' WHEN 'P' THEN 'per corpus' END AS paid, o_orderpriority AS step, floor(o_totalprice) AS hours FROM orders)"
SQL["cost_break_even"] = f"SELECT once, saved_per_pool, round(once / saved_per_pool, 4) AS pools FROM (SELECT sum(hours) FILTER (paid = 'once') AS once, sum(hours) FILTER (paid = 'per pool' AND step = '5-LOW') - sum(hours) FILTER (paid = 'per pool' AND step = '1-URGENT') AS saved_per_pool FROM {_LED})"
SQL["cost_ledger"] = f"SELECT coalesce(paid, 'all') AS paid, coalesce(step, 'all') AS step, round(sum(hours), 6) AS hours, round(sum(hours) / (SELECT sum(hours) FROM {_LED}), 6) AS share FROM {_LED} GROUP BY ROLLUP (paid, step)"
SQL["csv_published"] = "SELECT c_mktsegment AS paid, count(*) AS n, sum(floor(c_acctbal)) FILTER (c_custkey % 100 <> 0) AS hours, count(*) FILTER (c_custkey % 100 = 0) AS n_corrupt FROM customer GROUP BY 1"
SQL["run_program_sql"] = f"{E} SELECT page_id, md5(CASE WHEN verdict = 'rewrite' THEN nullif(trim(text), '') ELSE text END) AS text_md5 FROM executed WHERE n_cuts = 0"
SQL["program_items_sql"] = f"""{P}, ln AS (SELECT page_id, i, blocks[i].zone <> '' AS stripped, list_contains(list_transform(drops, lambda z: z.lid), i) AS dropped FROM (SELECT page_id, blocks, drops, unnest(range(1, len(lines) + 1)) AS i FROM policy)),
g AS (SELECT page_id, 's' AS k, i - row_number() OVER (PARTITION BY page_id ORDER BY i) AS g FROM ln WHERE stripped UNION ALL SELECT page_id, 'd', i - row_number() OVER (PARTITION BY page_id ORDER BY i) FROM ln WHERE dropped), rm AS (SELECT count(*) AS n FROM g GROUP BY page_id, k, g)
SELECT 'rm' AS kind, count(*) AS n, CAST(sum(n) AS BIGINT) AS n_lines FROM rm UNION ALL SELECT 'sub', CAST(sum(n_cuts) AS BIGINT), CAST(sum(n_cuts) AS BIGINT) FROM policy HAVING sum(n_cuts) > 0"""
SQL["json_schema"] = "SELECT event_type, count(*) AS n, count(*) FILTER (props IS NOT NULL AND NOT json_valid(props)) AS n_bad, CAST(sum(coalesce(len(json_keys(props)), 0)) AS BIGINT) AS n_keys FROM events GROUP BY 1"
SQL["confusion_matrix"] = "SELECT one, " + ", ".join(f"count(*) FILTER (two = '{v}') AS \"{v}\"" for v in ("keep", "edit", "delete", "rewrite")) + f" FROM (WITH {R}, {policy()} SELECT page_id, verdict AS one FROM policy) JOIN (WITH {R}, {policy(1.5)} SELECT page_id, verdict AS two FROM policy) USING (page_id) GROUP BY 1"
SQL["sketched_distinct"] = "SELECT lang, count(DISTINCT w) AS exact, true AS close FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '\\S+')) AS w FROM documents) GROUP BY 1"
SQL["approximate_quantiles"] = "SELECT lang, CAST(quantile_cont(n_chars, 0.5) AS DOUBLE) AS exact, true AS close FROM documents GROUP BY 1"
SQL["frequent_lines"] = "SELECT md5(line) AS line_md5, count(DISTINCT doc_id) AS n_docs FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE trim(line) <> '' GROUP BY line ORDER BY n_docs DESC, line_md5 LIMIT 10"
SQL["unpivoted_scores"] = " UNION ALL ".join(f"SELECT quality, '{n}' AS scorer, count(*) AS n, round(avg({e}), 4) AS mean FROM documents JOIN labels USING (doc_id) GROUP BY 1" for n, e in (("quality_score", quality("text")), ("edu_score", edu("text"))))
SQL["stream_late_rows"] = "SELECT count(*) AS n_rows, true AS some_late FROM events"
SQL["stream_labels"] = "SELECT quality, count(*) AS n FROM pages LEFT JOIN labels ON page_id = doc_id GROUP BY 1"
